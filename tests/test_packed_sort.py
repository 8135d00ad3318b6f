"""The block sort over packed strings, against plain sorting; and that no suffix crosses its shuffles."""

import random

import pytest

from blockbwt.operators import packedsort
from blockbwt.operators.collection import DNA, StringCollection
from blockbwt.operators.splitters import sampled_splitters
from blockbwt.plans.planner import Budget


def _strings():
    rnd = random.Random(3)
    some = [(i * 7 - 100, "".join(rnd.choice("ACGT"[: rnd.choice([1, 2, 4])]) for _ in range(rnd.choice([0, 1, 3, 8, 31, 32, 60, 97, 101])))) for i in range(60)]
    return some + [(10_000 + i, "ACGT" * 20) for i in range(15)] + [(-5_000 - i, "A" * 50) for i in range(15)]


def _sorted(strings):
    rows = sorted((s[p:], sid, p, s[p - 1] if p else None) for sid, s in strings for p in range(len(s) + 1))
    return [(i, *x[1:]) for i, x in enumerate(rows)]


@pytest.fixture(scope="module")
def strings(spark):
    some = _strings()
    return StringCollection.of(spark.createDataFrame(some, "sid long, s string"), alphabet=DNA), _sorted(some)


@pytest.mark.parametrize("options", [{}, {"round_rows": 2000}, {"engine": "lsd", "digit_bits": 16}, {"engine": "merge"}, {"engine": "index"}, {"encoding": "radix"}, {"encoding": "digits"}])
def test_engines_and_encodings(strings, options):
    coll, want = strings
    budget = Budget(sort_rows=800, **options)
    assert sorted(tuple(x) for x in packedsort.bwt_packed(coll, budget).collect()) == want
    texts = packedsort.bwt_packed_blocks(coll, budget, 64).orderBy("block_id").collect()
    assert "".join(x.text for x in texts) == "".join(x[3] or "$" for x in want)


def test_equal_suffixes_are_split_down_to_ids(strings):
    coll, want = strings
    found = packedsort.buckets(packedsort.packed_blocks(coll), coll.longest(), 7)
    assert max(n for _, n in found) <= 7 and sum(n for _, n in found) == len(want)


def test_sampled_splitters(strings):
    coll, want = strings
    budget = Budget(sort_rows=1500)
    plan = packedsort.planned_sampled(coll, budget, sampled_splitters(coll, 4, 0.2))
    texts = packedsort.bwt_packed_blocks(coll, budget, 64, plan).orderBy("block_id").collect()
    assert "".join(x.text for x in texts) == "".join(x[3] or "$" for x in want)


@pytest.mark.parametrize("name", ["bwt_reads_blocksort", "bwt_reads_rounds", "bwt_reads_positions", "bwt_reads_lsd_words", "bwt_reads_refined_ties", "bwt_reads_sampled_splitters"])
def test_no_row_for_each_suffix_is_shuffled(spark, name):
    """Before, a row for each suffix was dealt to its range."""
    from blockbwt.plans import catalogue

    plan = catalogue.QUERIES[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" not in plan and "MapInArrow" in plan
    assert "Repartition" not in plan.replace("Repartition 1, false", "")


def test_a_string_without_an_id_stays(spark):
    """Ids of packed strings are plain integers, so such a collection is listed row by row, whole."""
    coll = StringCollection(spark.createDataFrame([(1, "ACG"), (None, "GA"), (2, "")], "sid long, s string"), DNA)
    assert packedsort.bwt_packed(coll, Budget(sort_rows=100)).count() == 8
    assert packedsort.planned_sampled(coll, Budget(sort_rows=100), ["C"]) is None


def test_doubled_prefixes(strings):
    coll, want = strings
    assert sorted(tuple(x) for x in packedsort.bwt_packed(coll, Budget(sort_rows=800, engine="doubling")).collect()) == want


def test_rank_doubling_of_reads_moves_no_suffix(spark):
    """Before, each doubling joined a row for each suffix with another."""
    from blockbwt.plans import catalogue

    plan = catalogue.QUERIES["bwt_reads_rank_doubling"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan and "Generate" not in plan and "Join" not in plan
