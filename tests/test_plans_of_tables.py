"""Queries that once made their rows up read them."""

import pytest

from repetix import workloads

from .compare import assert_same
from .test_whole_job import run


@pytest.mark.parametrize("name,table", [("accuracy_plan", "lineitem"), ("adversarial_delta", "customer")])
def test_made_up_rows_come_from_tables(spark, sf_dir, duck, name, table):  # F22, F23
    df = workloads.queries()[name](spark, sf_dir)
    assert any(f.endswith(f"{table}.parquet") for f in df.inputFiles())
    assert_same(df.toPandas(), duck.sql(workloads.oracle_sql()[name]).df())


def test_parities_are_adversarial(spark, tmp_path):  # F23
    spark.range(1, 5000).withColumnRenamed("id", "c_custkey").write.parquet(f"{tmp_path}/customer.parquet")
    got = {r["id"]: (r["delta"], r["k_hat"]) for r in run(spark, "adversarial_delta", str(tmp_path))}
    assert got["parity-64-3"] == (pytest.approx(40 / 13), 13) and got["parity-256-2"] == (pytest.approx(160 / 49), 49)
    assert got["parity-1024-1"] == (pytest.approx(640 / 193), 193) and len(got) == 79 + 20 + 5 + 2
