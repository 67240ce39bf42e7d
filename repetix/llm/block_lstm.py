"""HTML extraction: a bidirectional LSTM in NumPy labels the leaf blocks of a page.

A block is what stands between block tags. Its vector has the sum of hashed embeddings of its
tag path (names, classes, ids and roles), the mean of those of its hashed words, and a few
measures of length, links and punctuation. Two LSTMs read a page's blocks forwards and
backwards, so each decision sees the whole page. The labeller is trained on labelled pages made
at random in many layouts, so it depends on no table.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import checked
from .html_blocks import Block, PageMaker, blocks_of

PATHS, WORDS, PATH_DIM, WORD_DIM, MEASURES, HIDDEN = 2048, 512, 16, 6, 10, 20
INPUT = PATH_DIM + WORD_DIM + MEASURES
PAGES_AT_ONCE = 64
REMEMBERED = 100_000
#: Longer words are hashed anew each time, so that what is remembered has a bound in bytes.
REMEMBERED_LENGTH = 256

Encoded = tuple[list[np.ndarray], list[np.ndarray], np.ndarray]


class Encoder:
    """Blocks of a page as slots of path elements, slots of words with counts, and measures."""

    def __init__(self):
        self.slots: dict[str, int] = {}
        self.paths: dict[tuple[str, ...], np.ndarray] = {}

    def slot(self, word: str) -> int:
        found = self.slots.get(word)
        if found is None:
            found = zlib.crc32(word.lower().encode("utf-8", "surrogatepass")) % WORDS
            if len(word) <= REMEMBERED_LENGTH:
                if len(self.slots) > REMEMBERED:
                    self.slots.clear()
                self.slots[word] = found
        return found

    def path(self, path: tuple[str, ...]) -> np.ndarray:
        found = self.paths.get(path)
        if found is None:
            if len(self.paths) > REMEMBERED:
                self.paths.clear()
            near = [zlib.crc32(e.encode("utf-8", "surrogatepass")) % (PATHS // 2) for e in dict.fromkeys(path) if e not in ("html", "body")]
            leaf = [PATHS // 2 + s for s in near[-1:]]
            found = self.paths[path] = np.array(near + leaf, np.int64)
        return found

    def page(self, blocks: list[Block]) -> Encoded:
        n = len(blocks)
        measures = np.zeros((n, MEASURES), np.float32)
        words = []
        for i, b in enumerate(blocks):
            split = b.text.split(" ")
            words.append(np.bincount(np.fromiter(map(self.slot, split), np.int64, len(split)), minlength=WORDS))
            chars, count = len(b.text), len(split)
            measures[i] = (
                math.log1p(chars) / 6, math.log1p(count) / 4, min(1.0, b.linked / chars), min(1.0, 10 * (b.text.count(",") + b.text.count(".")) / chars),
                b.text[-1] in ".!?", i / n, (n - i) / n, min(1.0, i / 10), min(1.0, (n - i) / 10), "©" in b.text[:20],
            )
        return [self.path(b.path) for b in blocks], words, measures


class BlockLabeller:
    """The two LSTMs and their training."""

    def __init__(self, weights: dict[str, np.ndarray] | None = None, seed: int = 5):
        rng = np.random.default_rng(seed)

        def normal(*shape: int) -> np.ndarray:
            return (rng.standard_normal(shape) / math.sqrt(shape[0])).astype(np.float32)

        self.w = weights or {
            "path": (rng.standard_normal((PATHS, PATH_DIM)) * 0.3).astype(np.float32), "word": (rng.standard_normal((WORDS, WORD_DIM)) * 0.1).astype(np.float32),
            "fx": normal(INPUT, 4 * HIDDEN), "fh": normal(HIDDEN, 4 * HIDDEN), "fb": np.zeros(4 * HIDDEN, np.float32),
            "bx": normal(INPUT, 4 * HIDDEN), "bh": normal(HIDDEN, 4 * HIDDEN), "bb": np.zeros(4 * HIDDEN, np.float32),
            "out": normal(2 * HIDDEN + INPUT, 1), "bias": np.zeros(1, np.float32),
        }

    def inputs(self, pages: list[Encoded]) -> tuple[np.ndarray, np.ndarray]:
        """(time, page, INPUT) and lengths; pages are padded at the end."""
        lengths = np.array([len(p[2]) for p in pages])
        x = np.zeros((int(lengths.max()), len(pages), INPUT), np.float32)
        for j, (paths, words, measures) in enumerate(pages):
            for i, slots in enumerate(paths):
                x[i, j, :PATH_DIM] = self.w["path"][slots].sum(0)
            counts = np.stack(words).astype(np.float32)
            x[: len(words), j, PATH_DIM : PATH_DIM + WORD_DIM] = counts @ self.w["word"] / counts.sum(1, keepdims=True)
            x[: len(words), j, PATH_DIM + WORD_DIM :] = measures
        return x, lengths

    def _run(self, x: np.ndarray, live: np.ndarray, name: str, keep: bool):
        time, pages, _ = x.shape
        h = c = np.zeros((pages, HIDDEN), np.float32)
        from_x = x @ self.w[f"{name}x"] + self.w[f"{name}b"]
        out, saved = np.zeros((time, pages, HIDDEN), np.float32), []
        for t in range(time):
            z = from_x[t] + h @ self.w[f"{name}h"]
            gates = 1 / (1 + np.exp(-np.clip(z[:, : 3 * HIDDEN], -30, 30)))
            i, f, o, g = gates[:, :HIDDEN], gates[:, HIDDEN : 2 * HIDDEN], gates[:, 2 * HIDDEN :], np.tanh(z[:, 3 * HIDDEN :])
            new_c = f * c + i * g
            tanh_c = np.tanh(new_c)
            new_h = o * tanh_c
            if keep:
                saved.append((i, f, o, g, c, tanh_c, h))
            on = live[t][:, None]
            h, c = np.where(on, new_h, h), np.where(on, new_c, c)
            out[t] = h
        return out, saved

    def _back(self, x: np.ndarray, live: np.ndarray, name: str, saved: list, grad_out: np.ndarray, grads: dict) -> np.ndarray:
        wh = self.w[f"{name}h"]
        grad_z = np.zeros((*x.shape[:2], 4 * HIDDEN), np.float32)
        dh = dc = np.zeros((x.shape[1], HIDDEN), np.float32)
        for t in range(len(x) - 1, -1, -1):
            i, f, o, g, c, tanh_c, h = saved[t]
            on = live[t][:, None]
            dh = dh + grad_out[t]
            dnew = np.where(on, dc, 0) + np.where(on, dh, 0) * o * (1 - tanh_c**2)
            dz = np.concatenate([dnew * g * i * (1 - i), dnew * c * f * (1 - f), np.where(on, dh, 0) * tanh_c * o * (1 - o), dnew * i * (1 - g**2)], 1)
            grad_z[t] = dz
            grads[f"{name}h"] += h.T @ dz
            dh, dc = np.where(on, dz @ wh.T, dh), np.where(on, dnew * f, dc)
        flat = grad_z.reshape(-1, 4 * HIDDEN)
        grads[f"{name}x"] += x.reshape(-1, INPUT).T @ flat
        grads[f"{name}b"] += flat.sum(0)
        return grad_z @ self.w[f"{name}x"].T

    @staticmethod
    def _turned(a: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """Each page's blocks in reverse, padding left at the end."""
        t = np.arange(len(a))[:, None]
        at = np.where(t < lengths, lengths - 1 - t, t)
        return np.take_along_axis(a, at[:, :, None], 0)

    def forward(self, pages: list[Encoded], keep: bool = False):
        x, lengths = self.inputs(pages)
        live = np.arange(len(x))[:, None] < lengths
        forwards, saved_f = self._run(x, live, "f", keep)
        turned = self._turned(x, lengths)
        backwards, saved_b = self._run(turned, live, "b", keep)
        both = np.concatenate([forwards, self._turned(backwards, lengths), x], 2)
        score = (both @ self.w["out"])[:, :, 0] + self.w["bias"]
        return score, (x, turned, lengths, live, both, saved_f, saved_b)

    def train(self, pages: list[Encoded], labels: list[np.ndarray], epochs: int = 12, batch: int = 16, rate: float = 0.012, seed: int = 3) -> BlockLabeller:
        rng = np.random.default_rng(seed)
        first = {k: np.zeros_like(v) for k, v in self.w.items()}
        second = {k: np.zeros_like(v) for k, v in self.w.items()}
        step = 0
        by_length = np.argsort([len(p[2]) for p in pages], kind="stable")
        lots = [by_length[i : i + batch] for i in range(0, len(pages), batch)]
        for epoch in range(epochs):
            for lot in rng.permutation(len(lots)):
                chosen = [self._masked(pages[i], rng) for i in lots[lot]]
                score, (x, turned, lengths, live, both, saved_f, saved_b) = self.forward(chosen, keep=True)
                target = np.zeros(score.shape, np.float32)
                for j, i in enumerate(lots[lot]):
                    target[: len(labels[i]), j] = labels[i]
                grads = {k: np.zeros_like(v) for k, v in self.w.items()}
                dscore = np.where(live, 1 / (1 + np.exp(-np.clip(score, -30, 30))) - target, 0)[:, :, None].astype(np.float32) / live.sum()
                grads["out"] += both.reshape(-1, both.shape[2]).T @ dscore.reshape(-1, 1)
                grads["bias"] += dscore.sum()
                dboth = dscore @ self.w["out"].T
                dx = dboth[:, :, 2 * HIDDEN :] + self._back(x, live, "f", saved_f, dboth[:, :, :HIDDEN], grads)
                back = self._back(turned, live, "b", saved_b, self._turned(dboth[:, :, HIDDEN : 2 * HIDDEN], lengths), grads)
                dx = dx + self._turned(back, lengths)
                for j, (paths, words, _) in enumerate(chosen):
                    n = len(paths)
                    np.add.at(grads["path"], np.concatenate(paths), np.repeat(dx[:n, j, :PATH_DIM], [len(p) for p in paths], 0))
                    counts = np.stack(words).astype(np.float32)
                    grads["word"] += (counts / counts.sum(1, keepdims=True)).T @ dx[:n, j, PATH_DIM : PATH_DIM + WORD_DIM]
                step += 1
                pace = rate * min(1, 3 * (1 - epoch / epochs))
                norm = math.sqrt(sum(float((g**2).sum()) for g in grads.values()))
                for k, g in grads.items():
                    g = g / max(1.0, norm)
                    first[k] = 0.9 * first[k] + 0.1 * g
                    second[k] = 0.99 * second[k] + 0.01 * g * g
                    self.w[k] -= (pace * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.99**step)) + 1e-6)).astype(np.float32)
        return self

    @staticmethod
    def _masked(page: Encoded, rng: np.random.Generator) -> Encoded:
        """Some path elements are hidden in training, so that context has to make up for them."""
        return [s[rng.random(len(s)) > 0.03] for s in page[0]], page[1], page[2]

    def labels(self, pages: list[Encoded]) -> list[np.ndarray]:
        """True for each block of the article; pages are run in lots of like length."""
        out: list[np.ndarray] = [np.zeros(0, bool)] * len(pages)
        order = [i for i in np.argsort([len(p[2]) for p in pages], kind="stable") if len(pages[i][2])]
        for at in range(0, len(order), PAGES_AT_ONCE):
            lot = order[at : at + PAGES_AT_ONCE]
            score, _ = self.forward([pages[i] for i in lot])
            for j, i in enumerate(lot):
                out[i] = score[: len(pages[i][2]), j] > 0
        return out


def trained(pages: int = 900, seed: int = 11) -> BlockLabeller:
    maker, encoder = PageMaker(seed), Encoder()
    made = [b for b in (blocks_of(maker.page()) for _ in range(pages)) if b]
    return BlockLabeller().train([encoder.page(b) for b in made], [np.array([x.label for x in b], np.float32) for b in made])


def extract_text(pages: DataFrame, labeller: BlockLabeller | None = None, keep: tuple[str, ...] = ("page_id", "url"), html_col: str = "html") -> DataFrame:
    """The columns in `keep` and text, n_chars: the article's blocks of every page, joined by line ends.

    A null or empty page, or one without a block of the article, has an empty text. Pages of any
    length are read whole; a tag cut off at the end is dropped. An empty table gives no rows.
    """
    sent = pages.sparkSession.sparkContext.broadcast((labeller or trained()).w)
    kept = checked(pages, *dict.fromkeys([*keep, html_col]))
    names = [c for c in kept.columns if c in keep]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, model = Encoder(), BlockLabeller(sent.value)
        for batch in batches:
            for at in range(0, batch.num_rows, 4 * PAGES_AT_ONCE):
                part = batch.slice(at, 4 * PAGES_AT_ONCE)
                blocks = [blocks_of(p.as_py()) for p in part.column(html_col)]
                flags = model.labels([encoder.page(b) for b in blocks])
                texts = ["\n".join(b.text for b, y in zip(page, ys, strict=True) if y) for page, ys in zip(blocks, flags, strict=True)]
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in names), pa.array(texts, pa.string())], names=[*names, "text"])

    types = dict(kept.dtypes)
    out = kept.mapInArrow(run, ", ".join([*(f"`{c}` {types[c]}" for c in names), "text string"]))
    return out.withColumn("n_chars", F.length("text").cast("long"))


def op9_block_lstm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_text(spark.read.parquet(f"{sf_dir}/pages.parquet"))
