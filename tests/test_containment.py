"""Windows of items among those of many rows."""

import pytest

from repetix.operators import relational
from repetix.operators.distinct import window_rows

from .test_pairs_unbroadcast import plan_of


@pytest.mark.parametrize("few", [0, 1 << 20])
def test_containment_sends_only_asked_windows(spark, monkeypatch, few):  # F2
    monkeypatch.setattr(relational, "FEW", few)
    items = spark.createDataFrame([(1, "abcabc"), (2, "xyz")], "id bigint, text string")
    rows = spark.createDataFrame([(7, "zzabczz" * 3), (8, "yz")], "id bigint, text string")
    found = relational.containment(window_rows(items, (3,)), window_rows(rows, (3,)))
    assert {tuple(r) for r in found.select("id", "k", "d", "shared").collect()} == {(1, 3, 3, 1), (2, 3, 1, 0)}
    assert "SortMergeJoin" in plan_of(found).split("== Physical Plan ==")[1]
