"""BPE encoding and decoding with contiguous rank arrays.

A word is one array of part boundaries beside one array of ranks of adjacent parts. The
least rank is found by scanning, its boundary deleted, and the two neighbouring ranks are
looked up anew; words are short, so the scans beat any heap. A word of over LONG_WORD bytes,
such as a line without blanks, has its array in short blocks, so that the work grows with its
length times a logarithm. Vocabulary, merges, special tokens and normalisation come from a
public tokenizer file.
"""

from __future__ import annotations

import functools
import hashlib
import heapq
import json
import re
import unicodedata
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from .common import checked

#: Words remembered by a worker; beyond it the memory starts anew, which changes no result.
REMEMBERED = 300_000
#: The same for the bytes of the words and of what is remembered of them.
REMEMBERED_BYTES = 128 << 20
#: Words of more bytes have their rank array in blocks.
LONG_WORD = 128

# White space as the tokenizer file's \s has it, and its split pattern.
SPACE = r"\t\n\v\f\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[{letter}]+|[{number}]|[{other}]+"
# Code points that Unicode assigned after the versions that the library was built with. Its letter and number
# classes lack the first two; its canonical order and composition take the third for starters that join with nothing; it
# lowers the last (first, last, offset), newer than some interpreters.
LATE_LETTERS = (
    "\u0558\u058b\u058c\u088f\u0c5c\u0cdc\u208f\u209d-\u209f\ua7ce\ua7cf\ua7d2\ua7d4\ua7dd\ua7e2\ua7f1\uab6c\uab6d\U000107bb-\U000107bf"
    "\U00010940-\U00010959\U00010ec5-\U00010ec7\U00010ed9-\U00010eee\U00011b0a\U00011db0-\U00011ddb\U00011df1\U00016ea0-\U00016eb8\U00016ebb-\U00016ed3"
    "\U00016ff2\U00016ff3\U000187f8-\U000187ff\U00018cd6-\U00018cda\U00018d09-\U00018d20\U00018d80-\U00018df2\U00018e00-\U00019191\U000191a0-\U000191d2"
    "\U0001b123-\U0001b128\U0001b168\U0001d6a6\U0001df1f-\U0001df24\U0001df2b-\U0001df81\U0001df90-\U0001df96\U0001dfcd-\U0001dfff\U0001e6c0-\U0001e6de"
    "\U0001e6e0-\U0001e6e2\U0001e6e4\U0001e6e5\U0001e6e7-\U0001e6ed\U0001e6f0-\U0001e6f4\U0001e6fe\U0001e6ff\U0002b73a-\U0002b73f\U0002b81e"
    "\U0002cea2-\U0002cead\U000323b0-\U00033479\U0003d000-\U0003fc3f"
)
LATE_NUMBERS = (
    "\U00011de0-\U00011de9\U0001246f\U00012475-\U0001247f\U00012550-\U00012686\U00016ff4-\U00016ff6"
)
LATE_MARKS = (
    "\U00011930\u07fd\u0898-\u089f\u08ca-\u08d3\u09fe\u0c3c\u0d3b\u0d3c\u0eba\u1715\u1abf-\u1ace\u1df6-\u1dfa\ua82c\U00010d24-\U00010d27\U00010eab\U00010eac"
    "\U00010efd-\U00010eff\U00010f46-\U00010f50\U00010f82-\U00010f85\U00011070\U0001133b\U0001145e\U00011839\U0001183a\U0001193d\U0001193e\U00011943"
    "\U000119e0\U00011a34\U00011a47\U00011a99\U00011d42\U00011d44\U00011d45\U00011d97\U00011f41\U00011f42\U00016ff0\U00016ff1\U0001e08f"
    "\U0001e130-\U0001e136\U0001e2ae\U0001e2ec-\U0001e2ef\U0001e4ec-\U0001e4ef"
)
LATE_LOWER = (
    (0x1C89, 0x1C89, 1), (0xA7CB, 0xA7CB, 0x264 - 0xA7CB), (0xA7CC, 0xA7CC, 1), (0xA7CE, 0xA7CE, 1), (0xA7D2, 0xA7D2, 1), (0xA7D4, 0xA7D4, 1),
    (0xA7DA, 0xA7DA, 1), (0xA7DC, 0xA7DC, 0x19B - 0xA7DC), (0x10D50, 0x10D65, 0x20), (0x16EA0, 0x16EB8, 0x1B),
)


def split_pattern(late: bool) -> regex.Pattern:
    """The split pattern; the form for texts with late letters or numbers is slower."""
    if not late:
        return regex.compile(SPLIT.format(letter=r"\p{L}", number=r"\p{N}", other=rf"^{SPACE}\p{{L}}\p{{N}}"))
    letter, number = rf"\p{{L}}--[{LATE_LETTERS}]", rf"\p{{N}}--[{LATE_NUMBERS}]"
    other = rf"[^{SPACE}\p{{L}}\p{{N}}]||[{LATE_LETTERS}{LATE_NUMBERS}]"
    return regex.compile(SPLIT.format(letter=letter, number=number, other=other), regex.V1)


def latin_pattern() -> re.Pattern:
    """The split pattern for text of small letters below U+0100, where a plain class of each kind will do."""
    of = {kind: "".join(chr(c) for c in range(256) if unicodedata.category(chr(c))[0] == kind and not chr(c).isupper()) for kind in "LN"}
    space = "\t\n\v\f\r \x85\xa0"
    return re.compile(SPLIT.format(letter=of["L"], number=of["N"], other="^" + space + of["L"] + of["N"]))


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    letters = {b: chr(b) for b in shown}
    for n, b in enumerate(b for b in range(256) if b not in letters):
        letters[b] = chr(256 + n)
    return [letters[b] for b in range(256)]


def beyond_latin(text: str) -> bool:
    """Whether there are characters that one byte can't hold; a quick test, as all late ones are."""
    try:
        text.encode("latin-1")
    except UnicodeEncodeError:
        return True
    return False


class RankArrayBpe:
    """Encoder of a `tokenizers` JSON file of the kind BPE with a word-end suffix and no decoder."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        if model["type"] != "BPE" or model["unk_token"] is not None or spec["decoder"] is not None:
            raise ValueError("only BPE without an unknown token and without a decoder is read")
        self.ids: dict[str, int] = model["vocab"]
        self.ranks = {tuple(pair): rank for rank, pair in enumerate(model["merges"])}
        self.suffix = model["end_of_word_suffix"] or ""
        self.letters = byte_letters()
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.special_split = regex.compile("(" + "|".join(regex.escape(t) for t in sorted(self.special, key=len, reverse=True)) + ")")
        self.tokens = {i: t for t, i in [*self.ids.items(), *self.special.items()]}
        self.words, self.late_words, self.latin_words = split_pattern(False), split_pattern(True), latin_pattern()
        self.late = regex.compile(f"[{LATE_LETTERS}{LATE_NUMBERS}]")
        self.late_marks = regex.compile(f"([{LATE_MARKS}])")
        self.late_case = regex.compile("[" + "".join(f"{chr(first)}-{chr(last)}" for first, last, _ in LATE_LOWER) + "]")
        self.late_lower = {c: chr(c + by) for first, last, by in LATE_LOWER for c in range(first, last + 1)}

    def pieces(self, word: str) -> list[str]:
        """The parts of one word when no adjacent pair has a rank any more."""
        symbols = [self.letters[b] for b in word.encode("utf-8", "surrogatepass")]
        symbols[-1] += self.suffix
        if len(symbols) > LONG_WORD:
            return self._pieces_of_long(symbols)
        none = len(self.ranks)
        rank_of = self.ranks.get
        ranks = [rank_of(pair, none) for pair in zip(symbols, symbols[1:], strict=False)]
        while ranks:
            least = min(ranks)
            if least == none:
                break
            at = ranks.index(least)
            symbols[at] += symbols.pop(at + 1)
            ranks.pop(at)
            if at:
                ranks[at - 1] = rank_of((symbols[at - 1], symbols[at]), none)
            if at < len(ranks):
                ranks[at] = rank_of((symbols[at], symbols[at + 1]), none)
        return symbols

    def _pieces_of_long(self, symbols: list[str]) -> list[str]:
        """The same merges in the same order, with the rank array in short blocks whose least ranks stand in a heap.

        The rank of a block's last part is that of the pair with the next block's first. A heap
        entry counts only while its rank is the block's least; a block that loses its last part
        is skipped from then on.
        """
        none, rank_of, size = len(self.ranks), self.ranks.get, LONG_WORD // 2
        parts = [symbols[i : i + size] for i in range(0, len(symbols), size)]
        ranks = [[rank_of(pair, none) for pair in zip(p, [*p[1:], *following[:1]], strict=False)] for p, following in zip(parts, [*parts[1:], []], strict=True)]
        if len(ranks[-1]) < len(parts[-1]):
            ranks[-1].append(none)  # the word's last part has no pair
        after, before = list(range(1, len(parts) + 1)), list(range(-1, len(parts) - 1))
        heap = [(least, b) for b, r in enumerate(ranks) if (least := min(r)) < none]
        heapq.heapify(heap)

        def changed(b: int) -> None:
            least = min(ranks[b])
            if least < none:
                heapq.heappush(heap, (least, b))

        while heap:
            least, b = heapq.heappop(heap)
            if not ranks[b] or min(ranks[b]) != least:
                continue
            part, rank = parts[b], ranks[b]
            at, beyond = rank.index(least), after[b]
            if at + 1 < len(part):
                part[at] += part.pop(at + 1)
                rank.pop(at + 1)
            else:
                part[at] += parts[beyond].pop(0)
                ranks[beyond].pop(0)
                if parts[beyond]:
                    changed(beyond)
                else:
                    after[b] = after[beyond]
                    if after[b] < len(parts):
                        before[after[b]] = b
            right = part[at + 1] if at + 1 < len(part) else parts[after[b]][0] if after[b] < len(parts) else None
            rank[at] = none if right is None else rank_of((part[at], right), none)
            if at:
                rank[at - 1] = rank_of((part[at - 1], part[at]), none)
            elif before[b] >= 0:
                near = before[b]
                ranks[near][-1] = rank_of((parts[near][-1], part[0]), none)
                changed(near)
            changed(b)
        return [p for part in parts for p in part]

    def split(self, text: str) -> list[str]:
        """The words of a text without special tokens. White space only parts words, so runs of it needn't be made one blank first."""
        if not beyond_latin(text):  # such text is its own normal form
            return self.latin_words.findall(text.lower())
        apart = self.late_marks.split(text)
        text = unicodedata.normalize("NFC", text) if len(apart) == 1 else "".join(unicodedata.normalize("NFC", t) for t in apart)
        text = text.replace("\u03a3", "\u03c3")  # no final sigma by context
        if self.late_case.search(text):
            text = text.translate(self.late_lower)
        text = text.lower()
        return (self.late_words if self.late.search(text) else self.words).findall(text)

    def parts(self, text: str) -> Iterator[tuple[bool, list[str]]]:
        """Runs of words (False) and special tokens (True), in order."""
        for n, run in enumerate(self.special_split.split(text) if "<|" in text else [text]):
            if n % 2:
                yield True, [run]
            elif run:
                yield False, self.split(run)

    def word_ids(self, word: str) -> list[int]:
        return [self.ids[p] for p in self.pieces(word) if p in self.ids]

    def encode(self, text: str) -> list[int]:
        out: list[int] = []
        for special, words in self.parts(text):
            for word in words:
                out += [self.special[word]] if special else self.word_ids(word)
        return out

    def decode(self, ids: list[int]) -> str:
        """Tokens joined by blanks, as the library does where a file names no decoder."""
        return " ".join(self.tokens[i] for i in ids if i in self.tokens)


@functools.lru_cache(maxsize=1)
def encoder(path: str) -> Callable[[str], tuple[bytes, bytes]]:
    """text -> (ids as little-endian unsigned 32-bit integers, decoded text in UTF-8), with words remembered; one for all tasks of a worker."""
    bpe = RankArrayBpe(path)
    ids_of: dict[str, bytes] = {}
    text_of: dict[str, bytes] = {}
    special = {t: (np.array([i], "<u4").tobytes(), t.encode()) for t, i in bpe.special.items()}

    held = 0

    def learn(words: list[str]) -> None:
        nonlocal held
        if len(ids_of) > REMEMBERED or held > REMEMBERED_BYTES:
            ids_of.clear()
            text_of.clear()
            held = 0
        for word in set(words):
            if word not in ids_of:
                ids = bpe.word_ids(word)
                ids_of[word] = np.array(ids, "<u4").tobytes()
                text_of[word] = bpe.decode(ids).encode()
                held += 4 * len(word) + len(ids_of[word]) + len(text_of[word])

    def encode(text: str) -> tuple[bytes, bytes]:
        all_ids: list[bytes] = []
        decoded: list[bytes] = []
        for is_special, words in bpe.parts(text):
            if is_special:
                ids, said = special[words[0]]
                all_ids.append(ids)
                decoded.append(said)
                continue
            try:
                ids = [ids_of[w] for w in words]
            except KeyError:
                learn(words)
                ids = [ids_of[w] for w in words]
            all_ids += ids
            decoded += filter(None, [text_of[w] for w in words])
        return b"".join(all_ids), b" ".join(decoded)

    return encode


def encode_documents(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, the columns in `keep`, token_ids array<int>, decoded: one row for each row, null texts as empty.

    `tokenizer` is the path of the vocabulary file, readable on every executor. Any length of
    text is encoded whole; an empty table gives no rows.
    """
    kept = checked(docs, *dict.fromkeys([id_col, *keep, text_col]))
    names = [c for c in kept.columns if c in (id_col, *keep)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer)
        for batch in batches:
            for part in slices(batch, text_col):
                done = [encode(t or "") for t in part.column(text_col).to_pylist()]
                columns = {c: part.column(c) for c in names}
                lengths = np.cumsum([0] + [len(i) // 4 for i, _ in done]).astype(np.int32)
                ids = pa.ListArray.from_arrays(pa.array(lengths), pa.array(np.frombuffer(b"".join(i for i, _ in done), "<u4").astype(np.int32)))
                columns |= {"token_ids": ids, "decoded": pa.array([d.decode() for _, d in done], pa.string())}
                yield pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))

    types = dict(kept.dtypes)
    return kept.mapInArrow(run, ", ".join([*(f"`{c}` {types[c]}" for c in names), "token_ids array<int>", "decoded string"]))


def slices(batch: pa.RecordBatch, text_col: str, most: int = 4_000_000) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows of about `most` bytes of text, so that memory doesn't follow the batch size."""
    import pyarrow.compute as pc

    sizes = np.cumsum(pc.fill_null(pc.binary_length(batch.column(text_col)), 0).to_numpy(zero_copy_only=False))
    start = 0
    while start < batch.num_rows:
        base = sizes[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(sizes, base + most, side="right")))
        yield batch.slice(start, stop - start)
        start = stop


def digests(docs: DataFrame, tokenizer: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256; only digests leave the task.

    One row for each row: a null text counts as empty (no tokens, the digests of no bytes),
    rows repeated whole and null ids stay as they are, other columns are not read. Texts and
    words of any length are encoded whole. An empty table gives no rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer)
        for batch in batches:
            counts, of_ids, of_text = [], [], []
            for text in batch.column("text"):
                ids, decoded = encode(text.as_py() or "")
                counts.append(len(ids) // 4)
                of_ids.append(hashlib.sha256(ids).hexdigest())
                of_text.append(hashlib.sha256(decoded).hexdigest())
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(counts, pa.int64()), pa.array(of_ids, pa.string()), pa.array(of_text, pa.string())],
                names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    schema = "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string"
    return checked(docs, "doc_id", "text").mapInArrow(run, schema)


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op7_rank_array_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(spark.read.parquet(f"{sf_dir}/documents.parquet"), default_tokenizer())
