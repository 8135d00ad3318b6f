"""Counting one collection's suffixes in another's transform."""

import random

import numpy as np
import pytest

from blockbwt.operators import baselines, construct, incremental
from blockbwt.operators.collection import StringCollection
from blockbwt.operators.incremental import Counts, merge, smaller_in
from blockbwt.storage import materialise


def some_strings(symbols, n, longest, seed, first):
    rng = random.Random(seed)
    return [(first + 2 * i, "".join(rng.choice(symbols) for _ in range(rng.randrange(longest)))) for i in range(n)] + [(first + 2 * n, "")]


@pytest.mark.parametrize("limit", [10**9, 0])
@pytest.mark.parametrize("symbols", ["ACGT", "é日b$"])
def test_smaller_in(spark, symbols, limit):
    """Held by every worker or walked by joins; ids of both interleave, and one has symbols that the other lacks."""
    a, b = some_strings(symbols, 25, 12, 1, 0), some_strings(symbols[:3], 25, 9, 2, 3)
    one, two = (StringCollection(spark.createDataFrame(x, "sid long, s string")) for x in (a, b))
    for rows, own, others, other in ((a, one, b, two), (b, two, a, one)):
        bwt = materialise(construct.bwt_build(other))
        got = {(x.sid, x.pos): x.before for x in smaller_in(own, other, bwt, limit).collect()}
        theirs = [(t[q:].encode(), j) for j, t in others for q in range(len(t) + 1)]
        assert got == {(i, p): sum(x < (s[p:].encode(), i) for x in theirs) for i, s in rows for p in range(len(s) + 1)}
    built = construct.bwt_build(StringCollection(one.df.unionByName(two.df)))
    merged = merge(one, materialise(construct.bwt_build(one)), two, materialise(construct.bwt_build(two)), limit)
    assert sorted(map(tuple, merged.collect())) == sorted(map(tuple, built.collect()))


def test_parts_above_the_limit_are_merged(spark):
    coll = StringCollection(spark.createDataFrame(some_strings("AC", 12, 5, 3, 0), "sid long, s string"))
    assert sorted(map(tuple, baselines.bwt_partition_merge(coll, 2, 1).collect())) == sorted(map(tuple, construct.bwt_build(coll).collect()))


def test_the_driver_gets_no_symbols(spark, monkeypatch):
    """Neither blocks nor ids of a transform are collected or broadcast."""
    from pyspark import SparkContext

    a, b = (StringCollection(spark.createDataFrame(some_strings("ACGT", 30, 9, i, i), "sid long, s string"), tuple("ACGT")) for i in (1, 2))
    bwt = materialise(construct.bwt_build(b))
    monkeypatch.setattr(SparkContext, "broadcast", lambda *_: pytest.fail("a broadcast"))
    monkeypatch.setattr(type(a.df), "toArrow", lambda *_: pytest.fail("rows on the driver"))
    assert smaller_in(a, b, bwt).count() == sum(len(x.s) + 1 for x in a.df.collect())


def test_arrivals_are_merged_without_the_driver(spark, monkeypatch):
    """Nor does the stream's index take a transform there."""
    from pyspark import SparkContext

    from blockbwt.streaming import streams

    monkeypatch.setattr(SparkContext, "broadcast", lambda *_: pytest.fail("a broadcast"))
    assert streams.incremental_index(spark, "/root/testdata/sf0.001").agg({"bwt_pos": "max"}).first()[0] > 0


@pytest.mark.parametrize("walked", [4_000_000, 20])
def test_tasks_walk_shares_of_the_strings(spark, monkeypatch, walked):
    """However many tasks they're dealt to; none, where there are no strings or nothing to walk through."""
    monkeypatch.setattr(incremental, "_WALKED", walked)
    a, b = some_strings("ACGT", 40, 12, 1, 0), some_strings("AC", 30, 9, 2, 3)
    for rows, others in ((a, b), ([], b), (a, [])):
        one, two = (StringCollection(spark.createDataFrame(x, "sid long, s string"), tuple("ACGT")) for x in (rows, others))
        got = sorted((x.sid, x.pos, x.before) for x in smaller_in(one, two, materialise(construct.bwt_build(two))).collect())
        theirs = [(t[q:], j) for j, t in others for q in range(len(t) + 1)]
        assert got == sorted((i, p, sum(x < (s[p:], i) for x in theirs)) for i, s in rows for p in range(len(s) + 1))


def test_counts_take_few_bytes():
    n, points = 1_000_000, np.frombuffer("0123456789#Custome r".encode("utf-32-le"), np.uint32)
    symbols = np.unique(points)
    text = np.random.default_rng(1).choice(symbols, n).astype(np.uint32).tobytes().decode("utf-32-le")
    held = Counts.of(symbols, [text[:300_000], text[300_000:]], n, np.arange(10))
    assert held.text.nbytes + held.before.nbytes <= 3 * n
    assert held.starts[-1] == n + 10
