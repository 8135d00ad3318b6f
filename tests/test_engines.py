"""Every constructor against plain sorting, on the worked example and random collections."""

import random

import pytest
from pyspark.sql import functions as F

from blockbwt.functions import measures
from blockbwt.operators import baselines, construct, fmindex, kmers, overlaps
from blockbwt.operators.collection import DNA, StringCollection, concat_offsets, locate_offset
from blockbwt.operators.splitters import partition_by_splitters, refine, sampled_splitters, size_table, size_table_split, with_base
from blockbwt.plans.planner import Budget, greedy, plan_ranges
from blockbwt.storage import materialise


def brute(rows):
    found = sorted((x[p:].encode(), i, p, x[p - 1] if p else None) for i, x in rows for p in range(len(x) + 1))
    return [(k, i, p, c) for k, (_, i, p, c) in enumerate(found)]


def collection(spark, rows, alphabet=None):
    return StringCollection(spark.createDataFrame(rows, "sid long, s string"), alphabet)


def random_rows(symbols, n=40, longest=14, seed=1):
    rng = random.Random(seed)
    return [(3 * i, "".join(rng.choice(symbols) for _ in range(rng.randrange(longest)))) for i in range(n)]


CASES = {
    "dna": random_rows("ACGT"),
    "one symbol": random_rows("A", 25, 8),
    "equal strings": [(i, "abab") for i in range(30)] + [(99, "")],
    "text": random_rows("$!\n xé日", 30, 20),
    "empty": [(5, ""), (6, "")],
    "long": random_rows("ACGT", 4, 200),
}
BUILDS = {
    "direct": construct.bwt_direct,
    "block sort": lambda c: construct.bwt_build(c, Budget(sort_rows=20, ell=1)),
    "rounds": lambda c: construct.bwt_build(c, Budget(sort_rows=20, round_rows=90, ell=2)),
    "word passes": lambda c: construct.bwt_build(c, Budget(sort_rows=50, engine="lsd")),
    "radix passes": lambda c: construct.bwt_build(c, Budget(sort_rows=50, engine="lsd", digit_bits=8)),
    "positions": lambda c: construct.bwt_build(c, Budget(sort_rows=50, round_rows=200, listing="position")),
    "digits": lambda c: construct.bwt_build(c, Budget(sort_rows=50, encoding="digits")),
    "index": lambda c: construct.bwt_build(c, Budget(engine="index", encoding="radix")),
    "merge": lambda c: construct.bwt_build(c, Budget(engine="merge")),
    "bytes": lambda c: construct.bwt_build(c, Budget(encoding="utf8")),
    "ties": construct.bwt_refined_ties,
    "doubling": lambda c: baselines.bwt_rank_doubling(c, 2),
    "merge of parts": baselines.bwt_partition_merge,
    "local": baselines.bwt_local,
}


@pytest.mark.parametrize("case", ["dna", "equal strings", "text", "empty"])
@pytest.mark.parametrize("build", list(BUILDS))
def test_build(spark, case, build):
    got = BUILDS[build](collection(spark, CASES[case])).collect()
    assert sorted(map(tuple, got)) == brute(CASES[case])


@pytest.mark.parametrize("build", ["block sort", "word passes", "doubling"])
def test_long_and_single_symbol(spark, build):
    for case in ("long", "one symbol"):
        assert sorted(map(tuple, BUILDS[build](collection(spark, CASES[case])).collect())) == brute(CASES[case])


@pytest.mark.parametrize("mode", ["rewrite", "delta"])
def test_column_insertion(spark, mode):
    rows = random_rows("ACGT", 15, 7)
    assert sorted(map(tuple, baselines.bwt_column_insertion(collection(spark, rows), mode).collect())) == brute(rows)
    if mode == "rewrite":
        for options in ({"every": 3}, {"checkpoint": "none"}):
            some = [(i, s[:3]) for i, s in rows[:6]]
            assert sorted(map(tuple, baselines.bwt_column_insertion(collection(spark, some), mode, **options).collect())) == brute(some)


def test_worked_example_and_forms(spark):
    coll = collection(spark, [(0, "ACGT"), (1, "TAGT"), (2, "GGAA")], DNA)
    bwt = materialise(construct.bwt_build(coll, Budget(sort_rows=4, ell=1)))
    assert construct.bwt_string(bwt) == "TTAAG$TAG$CAGG$"
    assert sum(x.len for x in construct.bwt_runs(bwt, 4).collect()) == 15
    assert all(v == 0 for v in measures.verify_bwt(coll, bwt).first())
    assert {(x.sid, x.s) for x in fmindex.invert(bwt).collect()} == {(0, "ACGT"), (1, "TAGT"), (2, "GGAA")}
    broken = bwt.replace("C", "G", "sym")
    assert measures.verify_bwt(coll, broken).first().wrong_symbols == 1


def test_no_strings(spark):
    coll = collection(spark, [], DNA)
    assert construct.bwt_build(coll).count() == 0
    assert baselines.bwt_rank_doubling(coll).count() == 0


def test_terminal_bucket_above_capacity(spark):
    rows = [(i, "AC") for i in range(200)]
    coll = collection(spark, rows, DNA)
    plan = construct.make_plan(coll, Budget(sort_rows=50, ell=1))
    assert any(x.terminal and x.n > 50 for x in plan.collect())  # the case occurs
    assert sorted(map(tuple, construct.bwt_build(coll, Budget(sort_rows=50, ell=1), plan).collect())) == brute(rows)


def test_refinement_stops_at_capacity(spark):
    coll = collection(spark, random_rows("ACGT", 200, 20))
    first = size_table(coll, 1)
    assert max(x.n for x in first.collect()) > 60
    for adaptive in (False, True):
        sizes = refine(coll, first, 60, 3, adaptive).collect()
        assert all(x.n <= 60 or x.terminal for x in sizes) and len({x.depth for x in sizes}) > 1
        assert sum(x.n for x in sizes) == sum(len(s) + 1 for _, s in coll.df.collect())
    assert sorted(size_table(coll, 3).collect()) == sorted(size_table_split(coll, 3, 5).collect())


def test_plans():
    assert greedy([3, 3, 3, 9, 1], 6) == [0, 0, 1, 2, 3]
    with pytest.raises(ValueError):
        Budget(sort_rows=10, round_rows=5)
    b = Budget.plan(64 << 30, 2 << 30, 64, 10**10, 4)
    assert b.sort_rows <= b.round_rows and b.ell > 4


def test_plan_nests(spark):
    coll = collection(spark, random_rows("ACGT", 120, 20))
    plan = plan_ranges(with_base(materialise(size_table(coll, 2))), Budget(sort_rows=60, round_rows=300, nodes=3)).collect()
    plan.sort(key=lambda x: x.base)
    at = 0
    for x in plan:
        assert x.base == at
        at += x.n
    for k in {x.small_range for x in plan}:
        some = [x for x in plan if x.small_range == k]
        assert len({(x.round, x.node) for x in some}) == 1 and (sum(x.n for x in some) <= 60 or len(some) == 1)
    assert [x.small_range for x in plan] == sorted(x.small_range for x in plan)


def test_distributed_plan(spark):
    """Ranges and rounds never exceed their limits but where one bucket does; they nest, and follow the buckets' order."""
    coll = collection(spark, random_rows("ACGT", 200, 30))
    based = materialise(with_base(materialise(size_table(coll, 3))))
    for m1, m2 in ((60, 400), (25, 60), (2000, None)):
        plan = plan_ranges(based, Budget(sort_rows=m1, round_rows=m2, nodes=3), most=0).collect()
        plan.sort(key=lambda x: x.base)
        assert [x.bucket for x in plan] == sorted(x.bucket for x in plan)
        for column, limit in (("small_range", m1), ("round", m2 or 10**9)):
            numbers = [getattr(x, column) for x in plan]
            assert numbers == sorted(numbers) and set(numbers) == set(range(max(numbers) + 1))
            for k in set(numbers):
                some = [x for x in plan if getattr(x, column) == k]
                assert sum(x.n for x in some) <= limit or len({x.small_range for x in some}) == 1 and (len(some) == 1 or column == "round")
        assert all(len({x.round for x in plan if x.small_range == k}) == 1 for k in {x.small_range for x in plan})
        whole = materialise(plan_ranges(based, Budget(sort_rows=m1, round_rows=m2), most=0))
        got = construct.bwt_build(coll, Budget(sort_rows=m1, round_rows=m2, ell=3), whole)
        assert sorted(map(tuple, got.collect())) == brute([tuple(x) for x in coll.df.collect()])


def test_million_buckets_stay_off_the_driver(spark, monkeypatch):
    from blockbwt.plans import planner

    based = spark.range(1_000_000).select(F.lpad(F.col("id").cast("string"), 7, "0").alias("bucket"), F.lit(7).alias("depth"), F.lit(False).alias("terminal"), F.lit(3).cast("long").alias("n"), (F.col("id") * 3).alias("base"))
    monkeypatch.setattr(planner, "greedy", None)  # what the driver would pack with
    plan = plan_ranges(based, Budget(sort_rows=1000, round_rows=100_000, nodes=4), most=200_000)
    row = plan.groupBy("small_range").agg(F.sum("n").alias("n"), F.count_distinct("round").alias("rounds")).agg(F.max("n"), F.max("rounds"), F.sum("n"), F.min("n")).first()
    assert row[0] <= 1000 and row[1] == 1 and row[2] == 3_000_000 and row[3] >= 400
    assert "Python" not in plan._jdf.queryExecution().executedPlan().toString()


def test_approximate_mapping_of_mixed_lengths(spark):
    rng = random.Random(5)
    text = lambda n: "".join(rng.choice("ACGT") for _ in range(n))
    reference = [(i, text(80)) for i in range(6)] + [(7, "ACG")]
    reads = []
    for i in range(40):
        j, n = rng.randrange(6), rng.randrange(9, 40)
        at = rng.randrange(80 - n)
        r = list(reference[j][1][at : at + n])
        for _ in range(rng.randrange(3)):
            r[rng.randrange(n)] = rng.choice("ACGT")
        reads.append((100 + i, "".join(r)))
    reads.append((200, "ACG"))
    coll = collection(spark, reference, DNA)
    index = fmindex.build_index(construct.bwt_build(coll), 64)
    got = fmindex.map_reads_approx(index, coll, collection(spark, reads, DNA), 2, 5).collect()
    want = {(i, j, p, d) for i, r in reads for j, t in reference for p in range(len(t) - len(r) + 1) for d in [sum(a != b for a, b in zip(r, t[p:]))] if d <= 2}
    assert sorted(map(tuple, got)) == sorted(want)
    with pytest.raises(ValueError):
        fmindex.map_reads_approx(index, coll, collection(spark, [(1, "AC")], DNA), 2)


def test_kmers_from_order_and_containment(spark):
    rows = random_rows("ACGT", 50, 30) + [(900, ""), (901, "ACGTACGTAC"), (902, "ACGTACGTAC"), (903, "GTAC")]
    coll = collection(spark, rows, DNA)
    bwt = materialise(construct.bwt_build(coll))
    for k in (1, 3, 8):
        want = {}
        for _, s in rows:
            for p in range(len(s) - k + 1):
                want[s[p : p + k]] = want.get(s[p : p + k], 0) + 1
        assert {x.kmer: x.n for x in kmers.kmer_counts_from_order(coll, bwt, k).collect()} == want
    inside = {(i, j) for i, s in rows for j, t in rows if i != j and s and s in t and (len(s) < len(t) or j < i)}
    assert {tuple(x) for x in overlaps.contained_in_others(coll, 3).collect()} == inside
    assert {tuple(x) for x in overlaps.contained(coll).collect()} >= {(902, 901)}
    assert {(x.sid, x.s) for x in fmindex.invert(bwt).collect()} == set(rows)


def test_splitters(spark):
    rows = random_rows("ACGT", 30)
    coll = collection(spark, rows)
    got = {(x.sid, x.pos): x.part for x in partition_by_splitters(coll, ["C", "G", "GT"]).collect()}
    assert all(got[i, p] == sum(s[p:] >= c for c in ("C", "G", "GT")) for i, s in rows for p in range(len(s) + 1))
    assert sorted(map(tuple, construct.bwt_sampled(coll, 4, 0.5).collect())) == brute(rows)
    cuts = sampled_splitters(coll, 5, 1.0)
    assert cuts == sorted(set(cuts))
    with pytest.raises(ValueError):
        partition_by_splitters(coll, ["G", "C"])


def test_limits(spark):
    coll = collection(spark, [(0, "A" * 50)])
    with pytest.raises(ValueError):
        construct.explicit_suffixes(coll, 10)
    with pytest.raises(baselines.CapacityError):
        baselines.bwt_local(coll, 10)
    with pytest.raises(baselines.CapacityError):
        baselines.bwt_single(collection(spark, [(0, "ACGT")]), 3)
    with pytest.raises(ValueError):
        baselines.bwt_single(collection(spark, [(0, "A"), (1, "C")]))
    assert sorted(map(tuple, baselines.bwt_single(collection(spark, [(4, "ACGTACGTTACGACG")]), block=2).collect())) == brute([(4, "ACGTACGTTACGACG")])


def test_default_plan_shape(spark):
    """No Python, no single-partition exchange of suffixes, and one exchange for the sort."""
    coll = collection(spark, random_rows("ACGT", 60), DNA)
    plan = construct.bwt_build(coll, Budget(sort_rows=100))._jdf.queryExecution().executedPlan().toString()
    assert "Arrow" not in plan and "Python" not in plan and "SinglePartition" not in plan
    assert plan.count("REPARTITION_BY_NUM") == 1 and "NestedLoop" not in plan


def test_searches(spark):
    rows = random_rows("ACGT", 60, 20)
    coll = collection(spark, rows)
    index = fmindex.build_index(construct.bwt_build(coll), 64)
    patterns = spark.createDataFrame([(0, ""), (1, "A"), (2, "AC"), (3, "ACG"), (4, "TTTTTTTTT"), (5, "X")], "pid long, pattern string")
    want = {(k, i, p) for k, q in [tuple(x) for x in patterns.collect()] for i, s in rows for p in range(len(s) + 1) if s[p:].startswith(q)}
    assert {tuple(x) for x in fmindex.locate_patterns(index, patterns).collect()} == want
    assert {tuple(x) for x in fmindex.scan_patterns(coll, patterns).collect()} == want
    counts = {x.pid: x.occurrences for x in fmindex.count_patterns(index, patterns).collect()}
    assert counts == {k: sum(x[0] == k for x in want) for k in range(6)}


def test_unitigs_and_cycles(spark):
    edges = spark.createDataFrame([(1, 2, 9), (2, 3, 9), (3, 4, 9), (10, 11, 9), (11, 10, 9), (20, 21, 9), (20, 22, 9)], "src long, dst long, len int")
    got = {x.node: (x["first"], x.place) for x in overlaps.unitigs(edges).collect()}
    assert got == {1: (1, 0), 2: (1, 1), 3: (1, 2), 4: (1, 3), 10: (10, None), 11: (10, None)}


def test_offsets(spark):
    rows = random_rows("ACGT", 50, 9)
    coll = collection(spark, rows)
    offsets = materialise(concat_offsets(coll))
    want, at = {}, 0
    for i, s in sorted(rows):
        for p in range(len(s) + 1):
            want[at] = (i, p)
            at += 1
    got = locate_offset(offsets, spark.range(at).withColumnRenamed("id", "goff"), 3)
    assert {x.goff: (x.sid, x.pos) for x in got.collect()} == want


def test_measures():
    assert measures.resident_bits(64, 2, 32, 32) == {"whole": 160, "word": 64}
    assert measures.radix_passes(64, 2, 32) == 4
    assert measures.explicit_symbols(10**8, 100) == 505 * 10**9


def test_fasta_headers_and_codecs(spark, tmp_path):
    from blockbwt.sources import fasta

    rows = [("r1 a>b", "ACGT" * 40), (">>x", "A"), ("c > d > e", ""), ("last", "GG")]
    df = spark.createDataFrame(rows, "header string, s string").coalesce(2)
    for codec in (None, "gzip", "bzip2"):
        path = str(tmp_path / f"f-{codec}")
        fasta.write_fasta(df, path, compression=codec)
        got = {tuple(x) for x in fasta.read_fasta_any(spark, path).collect()}
        assert {(h.lstrip(">"), s) for h, s in rows} == {(h.lstrip(">"), s) for h, s in got} and ("r1 a>b", "ACGT" * 40) in got
