"""Sizes of codecs, those of LZMA with a small dictionary."""

import bz2
import lzma
import random
import zlib

from repetix.operators import profile

from .test_whole_job import documents, run


def test_lzma_sizes_by_one_small_dictionary():  # F9
    rng = random.Random(1)
    texts = [b"", b"a", b"ab" * 9, "".join(rng.choice("abcdef ") for _ in range(30_000)).encode(), bytes(rng.randrange(256) for _ in range(700)), b"x" * 1_500_000]
    for b in texts:
        assert profile.CODECS["xz"](b) == len(lzma.compress(b, lzma.FORMAT_XZ, preset=9))
        assert profile.CODECS["lzma2_raw"](b) == len(lzma.compress(b, lzma.FORMAT_RAW, filters=[{"id": lzma.FILTER_LZMA2, "preset": 9}]))
    assert profile.DICTIONARY < profile.PRESET_DICTIONARY


def test_codec_sizes_in_one_pass(spark, tmp_path):  # F9
    texts = ["", "abc" * 50, "\u00e4\u00f6 " * 40]
    got = {r["id"]: (r["gzip"], r["bzip2"], r["xz"], r["lzma2_raw"]) for r in run(spark, "codec_sizes_documents", documents(spark, tmp_path, texts))}
    raw = lambda b: len(lzma.compress(b, lzma.FORMAT_RAW, filters=[{"id": lzma.FILTER_LZMA2, "preset": 9}]))
    assert got == {i: (len(zlib.compress(b, 9, 31)), len(bz2.compress(b, 9)), len(lzma.compress(b, preset=9)), raw(b)) for i, b in enumerate(t.encode() for t in texts)}
