import zlib

import duckdb
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from repetix.llm import latent_votes, registry, simhash_trie, snapshot_chat, suffix_decontam

from ..compare import assert_same


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_oracle(spark, sf_dir, duck, name):
    assert_same(registry.queries()[name](spark, sf_dir).toPandas(), duck.sql(registry.oracle_sql()[name]).df())


def test_every_operator_is_registered():
    assert sorted(int(n[2:].split("_")[0]) for n in registry.queries()) == list(range(1, 11))


def test_quality_on_held_out_labels(spark):
    sf = "/root/testdata/sf0.01"
    rows = {r["doc_id"]: r for r in registry.queries()["op1_latent_votes"](spark, sf).collect()}
    labels = duckdb.sql(f"SELECT doc_id, quality FROM '{sf}/labels.parquet'").fetchall()
    assert len(rows) == 1000 and all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for r in rows.values())
    held_out = [(rows[i]["predicted"], q) for i, q in labels if rows[i]["held_out"]]
    assert sum(p == q for p, q in held_out) / len(held_out) > 0.95


def test_quality_edges(spark):
    docs = spark.createDataFrame([(1, None, "x"), (2, "", "x"), (None, "a b", "x"), (2, "", "x"), (5, "w " * 50000, "x")], "doc_id bigint, text string, score string")
    none = spark.createDataFrame([], "doc_id bigint, quality int")
    model = latent_votes.fit_votes(docs, none)
    assert [r["score"] for r in latent_votes.score_documents(docs, model).collect()] == [0.5] * 5
    some = spark.createDataFrame([(1, 1), (2, 0), (2, 1), (None, 1), (5, None), (5, 1)], "doc_id bigint, quality int")
    scored = latent_votes.score_documents(docs, latent_votes.fit_votes(docs, some), keep=("text",))
    assert scored.columns == ["doc_id", "text", "score"] and all(0 <= r["score"] <= 1 for r in scored.collect())
    assert latent_votes.score_documents(docs.where("false"), model).count() == 0


def test_a_repeated_labelled_id_is_collected_once(spark, monkeypatch):
    docs = spark.range(3000).select(F.when(F.col("id") < 2990, 0).otherwise(F.col("id")).alias("doc_id"), F.concat(F.lit("text number "), F.col("id") % 3).alias("text"))
    labels = docs.select("doc_id", (F.col("doc_id") % 2).alias("quality")).distinct()
    seen = []
    monkeypatch.setattr(latent_votes.LatentVotes, "fit", lambda rows: seen.append(rows) or "model")
    assert latent_votes.fit_votes(docs, labels) == "model"
    learnt = [i for i in [0, *range(2990, 3000)] if zlib.crc32(str(i).encode()) % 3 != 1]
    assert len(seen[0]) == len(learnt) and sorted(r[2] for r in seen[0]) == sorted(i % 2 for i in learnt)


def test_a_long_word_is_read_whole():
    count = latent_votes.term_counter()
    terms = lambda text: dict(zip(*(a.tolist() for a in count(text)), strict=True))
    head = "好" * 64
    slots = [latent_votes._slot(f"w {c * 64}") for c in "坏新"]
    long = terms(head + "坏" * 64 + "新" * 64)
    assert all(s in long and s not in terms(head + "x" * 128) for s in slots)
    assert long.keys() > {latent_votes._slot("w " + head)}
    pieces = terms(f"{head} {'坏' * 64} {'新' * 64}")
    assert all(long[s] == pytest.approx(pieces[s]) for s in slots)


def test_blocked_product_equals_plain_cosines():
    import numpy as np

    count = latent_votes.term_counter()
    texts = [f"word{i % 7} other{i % 3} {'!!' if i % 2 else 'x'} tail{i}" for i in range(40)]
    rows = [(*count(t), i % 2) for i, t in enumerate(texts)]
    model = latent_votes.LatentVotes.fit(rows, rank=8)
    got = model.score([r[:2] for r in rows], neighbours=5)
    folded = latent_votes.unit(latent_votes.dense([r[:2] for r in rows]) @ model.fold)
    for i in range(40):
        cos = folded[i] @ model.vectors.T
        near = np.argsort(-cos)[:5]
        w = np.maximum(cos[near], 0) ** 4
        if len(set(np.round(cos, 5))) == 40:
            assert got[i] == pytest.approx((w * model.labels[near]).sum() / w.sum(), abs=1e-4)


def test_collapse(spark):
    talk = [("user", "hi"), ("assistant", "yo"), ("user", "more"), ("assistant", "ok")]
    rows = [(1, t, *talk[t]) for t in range(2)] + [(2, t, *talk[t]) for t in range(4)] + [(3, t, *talk[t]) for t in range(4)]
    rows += [(4, 0, "user", "hi"), (4, 1, "assistant", "other"), (5, 0, None, None), (6, 0, "user", "<|im_end|>"), (6, 0, "user", "<|im_end|>"), (None, 0, "user", "z"), (7, 0, "user", "w" * 100_000)]
    df = spark.createDataFrame([(*r, "x", "x") for r in rows], "conv_id bigint, turn bigint, role string, text string, place string, h1 string")
    got = {r["conv_id"]: r for r in snapshot_chat.collapse_and_render(df).collect()}
    assert set(got) == {2, 4, 5, 6, None, 7}
    assert got[2]["n_turns"] == 4 and got[2]["n_copies"] == 2
    assert got[2]["rendered"].count("<|im_start|>") == 4 and got[2]["rendered"].endswith("ok<|im_end|>\n")
    assert got[5]["rendered"] == "<|im_start|>unknown\n<|im_end|>\n"
    assert got[6]["n_turns"] == 1 and got[6]["rendered"].count("<|im_end|>") == 1
    assert snapshot_chat.collapse_and_render(df.where("false")).count() == 0


def test_pipeline_equals_brute_force(spark):
    sf = "/root/testdata/sf0.001"
    out = {r["doc_id"]: r for r in corpus_pipeline.run(spark, sf).collect()}
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    scores = {r["doc_id"]: r["score"] for r in registry.queries()["op1_latent_votes"](spark, sf).collect()}
    texts = {r["doc_id"]: r["text"] for r in docs.collect() if scores[r["doc_id"]] >= 0.5}
    low = lambda t: "".join(c.lower() if "A" <= c <= "Z" else c for c in t)
    last = {}
    for i in sorted(texts):
        last[low(texts[i])] = i
    left = sorted(last.values())
    prints = {i: simhash_trie.fingerprint(texts[i]) for i in left}
    parent = {i: i for i in left}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for n, i in enumerate(left):
        for j in left[n + 1 :]:
            if bin(prints[i] ^ prints[j]).count("1") <= 3:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    left = [i for i in left if find(i) == i]
    items = [(str(r["item_id"]), suffix_decontam.words_of(r["text"])) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    windows = {tuple(w[i : i + min(13, len(w))]) for _, w in items for i in range(max(1, len(w) - 12)) if w}
    sizes = {len(w) for w in windows}
    kept = []
    for i in left:
        words = suffix_decontam.words_of(texts[i])
        hit = {p for s in sizes for j in range(len(words) - s + 1) if tuple(words[j : j + s]) in windows for p in range(j, j + s)}
        if not (hit and 20 * len(hit) >= len(words)):
            kept.append(i)
    assert sorted(out) == kept
    from tokenizers import Tokenizer

    from repetix.llm.rank_array_bpe import default_tokenizer

    library = Tokenizer.from_file(default_tokenizer())
    assert all(list(out[i]["token_ids"]) == library.encode(texts[i], add_special_tokens=False).ids for i in kept)


def test_stages_keep_columns(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").selectExpr("*", "'x' AS score", "'x' AS row_no")
    odd = spark.createDataFrame([(None, None, None, None, None), (None, None, None, None, None), (1, "", "en", "s", 0)], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, sf_dir).columns == list(corpus_pipeline.COLUMNS)
        assert stage(spark, odd.where("false"), sf_dir).count() == 0
        assert stage(spark, odd, sf_dir).count() <= 3
    assert corpus_pipeline.exact_copies(spark, odd, sf_dir).count() == 1


def test_decisions_hold_when_files_are_dealt_differently(spark, tmp_path, monkeypatch):
    rows = [(i, f"text {i % 40} " + " ".join(f"w{i % 40}x{j}" for j in range(20)), "en", "s", 0) for i in range(400)]
    schema = "doc_id bigint, text string, lang string, source string, n_chars bigint"
    spark.createDataFrame(rows, schema).repartition(24).write.parquet(str(tmp_path / "docs"))
    docs = spark.read.parquet(str(tmp_path / "docs"))
    open_cost = "spark.sql.files.openCostInBytes"

    def then_dealt_otherwise(decide):
        def run(*args):
            spark.conf.set(open_cost, "4194304")
            found = decide(*args)
            spark.conf.set(open_cost, "1")
            return found

        return run

    for module, name in ((corpus_pipeline.exact_dedup, "deduplicate"), (simhash_trie, "near_duplicates")):
        monkeypatch.setattr(module, name, then_dealt_otherwise(getattr(module, name)))
    try:
        assert {r["doc_id"] for r in corpus_pipeline.exact_copies(spark, docs, "").collect()} == set(range(360, 400))
        assert {r["doc_id"] for r in corpus_pipeline.near_copies(spark, docs, "").collect()} == set(range(40))
    finally:
        spark.conf.unset(open_cost)
