import pytest

import __spark_entry__
from repetix import workloads

from .compare import assert_same


@pytest.mark.parametrize("name", sorted(workloads.oracle_sql()))
def test_oracle(spark, sf_dir, duck, name):
    assert_same(workloads.queries()[name](spark, sf_dir).toPandas(), duck.sql(workloads.oracle_sql()[name]).df())


@pytest.mark.parametrize("name", ["hll_delta", "theta_delta", "hll_merge_delta", "sketch_rollup", "long_string_delta", "maximiser_histogram", "tree_neighbour_joining", "lz78_phrases_turns", "sketch_windows_session", "near_copies_by_sketch"])
def test_runs(spark, sf_dir, name):
    assert workloads.queries()[name](spark, sf_dir).count() > 0


def test_entry(spark):
    rows = __spark_entry__.entry(spark).collect()
    assert len(rows) == 200 and max(r["error"] for r in rows) < 0.1
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_estimates_of_documents(spark, sf_dir):
    from repetix.operators import metrics, profile
    from repetix.workloads.common import docs

    exact = profile.exact_delta(docs(spark, sf_dir))
    near = workloads.queries()["hll_delta"](spark, sf_dir)
    summary = metrics.error_summary(metrics.relative_errors(exact, near)).first()
    assert summary["strings"] == 200 and summary["mean"] < 0.02 and summary["max"] < 0.1


def test_suffix_arrays_agree_on_documents(spark, sf_dir):
    a = workloads.queries()["exact_delta_documents"](spark, sf_dir).drop("k_checked").toPandas()
    assert_same(a, workloads.queries()["delta_from_lcp_documents"](spark, sf_dir).toPandas())


def test_heuristic_misses_adversarial_strings(spark, sf_dir):
    found = {(r["id"], r["stops_before"]) for r in workloads.queries()["local_max_misses"](spark, sf_dir).collect()}
    assert {("plateau", "stand"), ("two scales", "stand"), ("parity-1024", "fall")} <= found
