"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import functions as F

from repetix.operators import distance, longstring, packed, profile, sketch
from repetix.operators.distinct import Hll
from repetix.plans.accuracy import sampled_lengths
from repetix.session import local_session
from repetix.workloads import experiments, stream_queries
from repetix.workloads.common import docs


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local_session()
    seconds: dict[str, float] = {}
    rows = docs(spark, sf_dir, "lang", "source").repartition(32).persist()
    n_bytes = rows.agg(F.sum(F.octet_length("text"))).first()[0]
    packed.estimate_strings(rows.limit(50), [1, 2, 4]).count()  # start the workers

    def timed(name: str, job) -> list:
        start = time.perf_counter()
        out = (job() if callable(job) else job).collect()
        seconds[name] = round(time.perf_counter() - start, 3)
        return out

    sparse, fine = sampled_lengths(128, 2.0), sampled_lengths(128, 1.25)
    timed("sketch_documents_sparse_grid", packed.estimate_strings(rows, sparse))
    timed("sketch_documents_fine_grid", packed.estimate_strings(rows, fine))
    cd = packed.Packed()
    timed("sketch_by_source_sparse_grid", sketch.estimate_delta(cd.from_strings(rows, ["source"], sparse), ["source"], cd))
    chunks = longstring.chunk_table(rows, "id")
    timed("sketch_one_long_string_sparse_grid", sketch.estimate_delta(packed.long_string_sketch(chunks, sparse, cd), cd=cd))
    exact = {r["id"]: r["delta"] for r in timed("exact_delta_documents", profile.exact_delta(rows))}
    timed("exact_delta_suffix_arrays", profile.delta_from_lcp(rows))
    errors = {}
    for ratio in (2.0, 1.25, 1.1):
        near = packed.estimate_strings(rows, sampled_lengths(128, ratio)).collect()
        off = sorted(abs(r["delta"] - exact[r["id"]]) / exact[r["id"]] for r in near if exact[r["id"]])
        errors[str(ratio)] = {"mean": round(sum(off) / len(off), 5), "p99": round(off[int(0.99 * len(off))], 5), "max": round(off[-1], 5)}

    # the documents of each source as one stream; the state is what a stream holds between batches
    spark.conf.set("spark.sql.shuffle.partitions", "64")  # twenty streams over eight partitions would leave cores idle
    streams = timed("stream_by_source", lambda: stream_queries.document_streams(spark, sf_dir, transform=False, longest=128))
    spark.conf.set("spark.sql.shuffle.partitions", "8")
    symbols, state = sum(r["n"] for r in streams), max((r["state_bytes"] for r in streams), default=0)

    sequences = experiments.written(experiments.sequences(spark, sf_dir).repartition(8), "sequences")
    hll = Hll()
    timed("all_pairs_sketch", distance.all_pairs_sketch(sketch.build_sketch(sequences, cd=hll, lengths=sparse), hll))
    timed("all_pairs_exact", lambda: distance.all_pairs_exact(sequences))
    timed("all_pairs_xz", distance.all_pairs_codec(sequences.repartition(29), "xz"))

    rate = lambda name: round(n_bytes / 1e6 / seconds[name] * 60, 1)
    print(
        json.dumps(
            {
                "metric": "headline queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf_dir), "mb": round(n_bytes / 1e6, 1),
                "mb_per_minute": {n: rate(n) for n in seconds if not n.startswith("all_pairs")},
                "relative_error_by_ratio": errors,
                "stream": {"symbols": symbols, "largest_state_bytes": state, "microseconds_a_symbol": round(1e6 * seconds["stream_by_source"] / max(1, symbols), 3)},
            }
        )
    )
    spark.stop()


def scaling() -> None:
    """One narrow pass and one set of sketches with 1, 2, 4 and all cores, each in a process of its own."""
    from subprocess import run

    for cores in sorted({1, 2, 4, os.cpu_count() or 1}):
        out = run([sys.executable, __file__], env={**os.environ, "BENCH_CPUS": str(cores)}, capture_output=True, text=True, timeout=1800).stdout.strip().splitlines()[-1]
        found = json.loads(out)
        print(json.dumps({"cores": cores, "mb_per_minute": {n: found["mb_per_minute"][n] for n in ("sketch_documents_sparse_grid", "sketch_by_source_sparse_grid")}}))


if __name__ == "__main__":
    scaling() if sys.argv[1:] == ["scaling"] else main()
