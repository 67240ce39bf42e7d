"""Rows of two frames, whatever their order, with doubles to six places."""

import math


def cell(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return None
    if hasattr(v, "item"):
        v = v.item()
    if isinstance(v, float):
        return round(v, 6)
    if isinstance(v, (list, tuple)) or hasattr(v, "tolist"):
        return tuple(map(cell, v))
    return v


def rows(frame):
    frame = frame[sorted(frame.columns)]
    out = []
    for r in frame.itertuples(index=False):
        out.append(tuple(None if str(v) in ("NaT", "<NA>") else cell(v) for v in r))
    return sorted(out, key=repr)


def assert_same(a, b):
    assert sorted(a.columns) == sorted(b.columns)
    x, y = rows(a), rows(b)
    assert len(x) == len(y)
    for p, q in zip(x, y, strict=True):
        assert all(u == v or (isinstance(u, (int, float)) and isinstance(v, (int, float)) and abs(u - v) < 2e-6) for u, v in zip(p, q, strict=True)), (p, q)
