"""Size tables of packed strings against plain counts."""

import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from blockbwt.operators import packedsizes, splitters
from blockbwt.operators.collection import DNA, StringCollection
from blockbwt.storage import materialise


def some_reads(spark, longest=90):
    rng = random.Random(5)
    base = "".join(rng.choice("ACGT") for _ in range(200))
    texts = [base[a : a + rng.randrange(longest)] for a in (rng.randrange(150) for _ in range(150))]
    texts += ["", "A", "T" * 40, "G" + "A" * 31, "G" + "A" * 40, "TTTT", "A" * 33] * 3
    return texts, StringCollection(spark.createDataFrame(list(enumerate(texts)), "sid long, s string"), DNA, longest)


def plain(texts, m1, step, rounds):
    """Depth by depth, as the definition says."""
    out, live, depth = set(), [t[p:] for t in texts for p in range(len(t) + 1)], 0
    for k in range(1, rounds + 1):
        depth += step
        n = Counter(x[:depth].ljust(depth, "\0") for x in live)
        large = set() if k == rounds else {b for b, c in n.items() if c > m1 and "\0" not in b}
        out |= {(b, depth, "\0" in b, c) for b, c in n.items() if b not in large}
        live = [x for x in live if x[:depth] in large]
    return out


@pytest.mark.parametrize("ell", [1, 3, 4, 8, 9, 31, 32, 33])
def test_sizes(spark, ell):
    texts, coll = some_reads(spark)
    found = splitters.size_table(coll, ell)
    assert {tuple(x) for x in found.collect()} == plain(texts, 0, ell, 1)
    assert ("Generate" in found._jdf.queryExecution().executedPlan().toString()) == (ell > 32)


@pytest.mark.parametrize("m1,step,rounds,wanted", [(5, 4, 8, 10**6), (2, 5, 9, 10**6), (2, 16, 3, 10**6), (3, 4, 8, 2)])
def test_refined(spark, monkeypatch, m1, step, rounds, wanted):
    """To 32 symbols and beyond; more buckets than a task holds."""
    monkeypatch.setattr(packedsizes, "WANTED", wanted)
    texts, coll = some_reads(spark)
    first = materialise(splitters.size_table(coll, step), "sizes")
    assert {tuple(x) for x in splitters.refine(coll, first, m1, step, rounds=rounds).collect()} == plain(texts, m1, step, rounds)


def test_no_row_for_a_suffix(spark, monkeypatch):
    """The rounds of buckets of reads are counted from packed strings."""
    monkeypatch.setattr(splitters, "suffixes", lambda coll: pytest.fail("suffixes are listed"))
    texts, coll = some_reads(spark)
    assert {tuple(x) for x in splitters.refine(coll, materialise(splitters.size_table(coll, 4), "sizes"), 5, 4, rounds=8).collect()} == plain(texts, 5, 4, 8)


def test_counts_are_sent_in_parts(monkeypatch):
    """What's held at once is bounded; the parts add up."""
    rng = np.random.default_rng(3)
    codes, lens = rng.integers(0, 256, (500, 5), np.uint8), np.full(500, 20, np.uint16)
    batch = pa.RecordBatch.from_arrays([pa.array([codes.tobytes()], pa.binary()), pa.array([lens.tobytes()], pa.binary())], ["codes", "lens"])
    found = []
    for held in (10**6, 40):
        monkeypatch.setattr(packedsizes, "HELD", held)
        parts = list(packedsizes._counted(5, 12)([batch] * 4))
        total = Counter()
        for p in parts:
            for k, v, n in zip(*(p.column(c).to_pylist() for c in ("len", "value", "n"))):
                total[k, v] += n
        found.append((len(parts), total))
    assert found[0][1] == found[1][1] and found[0][1].total() == 4 * 500 * 21 and found[1][0] > found[0][0]


def test_few_symbols(spark):
    """Fewer than four symbols, and strings of no symbol at all."""
    for texts in (["010110", "", "1", "0110"], ["", ""]):
        coll = StringCollection(spark.createDataFrame(list(enumerate(texts)), "sid long, s string"), ("0", "1"))
        assert {tuple(x) for x in splitters.size_table(coll, 3).collect()} == plain(texts, 0, 3, 1)
