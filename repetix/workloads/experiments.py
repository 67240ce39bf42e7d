"""The experiments: measures on growing prefixes, trees, and timings of all-pairs distances."""

from __future__ import annotations

from pyspark.sql import functions as F

from repetix.operators import distance, longstring, metrics, phylogeny, profile, sketch
from repetix.operators.distinct import Hll
from repetix.session import written

from .common import Registry, docs

query = Registry()
QUERIES, ORACLES = query.queries, query.oracles
PREFIXES, LONGEST, SEQUENCES, SEQUENCE_LENGTH = 10, 5, 29, 81_000
#: Symbols of the longest prefix of a source: parses need the whole prefix in one task.
STUDY = 50_000


def prefixes(spark, sf_dir):
    """(id, prefix_len, text): ten equal steps of the five longest documents; that choice is the experiment."""
    longest = docs(spark, sf_dir).withColumn("n", F.length("text")).orderBy(F.desc("n"), "id").limit(LONGEST)
    steps = longest.withColumn("step", F.explode(F.sequence(F.lit(1), F.lit(PREFIXES))))
    length = F.floor(F.col("n") * F.col("step") / PREFIXES).cast("int")
    return steps.select(F.col("id").alias("doc_id"), length.alias("prefix_len"), F.left("text", length).alias("text"))


def concatenations(spark, sf_dir, by, most):
    """(id, text): the documents that share `by` as one string in doc_id order, its first `most` symbols. Documents beyond these are left out by their offsets, before any are put together."""
    rows = docs(spark, sf_dir, *by).withColumn("key", F.concat_ws("/", *by))
    placed = longstring.offsets(longstring.chunk_table(rows, "id", by="key")).where(F.col("start") < most)
    whole = placed.groupBy("id").agg(F.sort_array(F.collect_list(F.struct("start", "at", "text"))).alias("parts"))
    return whole.select("id", F.left(F.array_join(F.transform("parts", lambda p: p["text"]), ""), F.lit(most)).alias("text"))


def source_prefixes(spark, sf_dir):
    """(id, prefix_len, text): ten equal steps of the documents of each source as one string, which is repetitive, up to STUDY symbols."""
    rows = concatenations(spark, sf_dir, ["source"], STUDY).withColumn("n", F.length("text"))
    steps = rows.withColumn("step", F.explode(F.sequence(F.lit(1), F.lit(PREFIXES))))
    length = F.floor(F.col("n") * F.col("step") / PREFIXES).cast("int")
    return steps.select(F.col("id").alias("doc_id"), length.alias("prefix_len"), F.left("text", length).alias("text"))


def prefix_measures_of(spark, sf_dir, strings=prefixes):
    rows = written(strings(spark, sf_dir).select(F.struct("doc_id", "prefix_len").alias("id"), "text").repartition(64), "prefixes")
    near = sketch.estimate_delta(sketch.build_sketch(rows, max_length=128)).select("id", F.col("delta").alias("delta_sketch"))
    codecs = rows.select("id", *[profile.codec_size(c)(F.col("text")).cast("double").alias(c) for c in ("xz", "lzma2_raw")])
    wide = profile.exact_delta(rows).select("id", "delta").join(near, "id").join(profile.parse_sizes(rows).select("id", F.col("r").cast("double").alias("r"), F.col("z").cast("double").alias("z")), "id").join(codecs, "id")
    return wide.unpivot("id", ["delta", "delta_sketch", "r", "z", "xz", "lzma2_raw"], "measure", "value").select(F.col("id.doc_id").alias("id"), F.col("id.prefix_len").alias("prefix_len"), "measure", "value")


@query("prefix_measures")
def prefix_measures(spark, sf_dir):
    return metrics.normalised(prefix_measures_of(spark, sf_dir))


@query("prefix_trend_correlation")
def prefix_trend(spark, sf_dir):
    return metrics.trend_agreement(written(prefix_measures_of(spark, sf_dir), "prefix-measures"))


@query("prefix_measures_by_source")
def prefix_measures_by_source(spark, sf_dir):
    return metrics.normalised(prefix_measures_of(spark, sf_dir, source_prefixes))


@query("prefix_trend_by_source")
def prefix_trend_by_source(spark, sf_dir):
    return metrics.trend_agreement(written(prefix_measures_of(spark, sf_dir, source_prefixes), "prefix-measures"))


def sequences(spark, sf_dir):
    """(id, text): 29 strings, the concatenations of documents by language and source, each cut to 81,000 symbols."""
    return concatenations(spark, sf_dir, ["lang", "source"], SEQUENCE_LENGTH).orderBy("id").limit(SEQUENCES)


def tree_distances(spark, sf_dir):
    """The three distances between the sequences."""
    rows = written(sequences(spark, sf_dir).repartition(8), "sequences")
    cd = Hll()
    sketches = written(sketch.build_sketch(rows, cd=cd, max_length=64), "sketches")
    return {"sketch": distance.all_pairs_sketch(sketches, cd), "delta": distance.all_pairs_exact(rows), "xz": distance.all_pairs_codec(rows, "xz")}


@query("all_pairs_sequences")
def all_pairs_sequences(spark, sf_dir):
    found = [d.withColumn("measure", F.lit(m)) for m, d in tree_distances(spark, sf_dir).items()]
    return found[0].unionByName(found[1]).unionByName(found[2])


BUILDERS = {"neighbour_joining": phylogeny.neighbour_joining, "average_linkage": phylogeny.average_linkage}


def tree_of(builder: str):
    def run(spark, sf_dir):
        rows = sequences(spark, sf_dir)
        cd = Hll()
        ids, full = phylogeny.matrix(distance.all_pairs_sketch(sketch.build_sketch(rows, cd=cd, max_length=64), cd))
        return phylogeny.tree_table(spark, builder, ids, BUILDERS[builder](full))

    return run


for _builder in BUILDERS:
    query(f"tree_{_builder}")(tree_of(_builder))


@query("tree_distance")
def tree_distance(spark, sf_dir):
    """Normalised distances between the trees of the three measures, by both tree builders."""
    matrices = {m: phylogeny.matrix(d) for m, d in tree_distances(spark, sf_dir).items()}
    trees = {(name, m): (ids, build(full)) for name, build in BUILDERS.items() for m, (ids, full) in matrices.items()}
    return phylogeny.robinson_foulds(phylogeny.forest_table(spark, trees, ["builder"]), ["builder"]).select("tree_a", "tree_b", "rf", "builder")
