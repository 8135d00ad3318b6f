"""The leaves of crowded regions of the LSH forest."""

import random

from blockbwt.llm import lsh_forest as lsh


def test_leaves_by_depth_make_no_row_a_depth(spark):
    """Each node of a region is in the leaf of the least depth at which few share its prefix, or in a run of those that share all."""
    rng = random.Random(4)
    keys = [bytes(2 * lsh.MIN_DEPTH) + bytes(rng.choice((0, 0, 1)) for _ in range(2 * (lsh.DEPTH - lsh.MIN_DEPTH))) for _ in range(60)] + [bytes(2 * lsh.DEPTH)] * 30
    rows = [(r, bytearray(k), bytearray(b"%d" % i), bytearray(b"%d" % (i % 7))) for r in (1, 2) for i, k in enumerate(keys)]
    found = lsh._leaves(spark.createDataFrame(rows, "region long, key binary, node binary, root binary"), 8)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "Generate" not in plan
    got: dict = {}
    for x in found.collect():
        got.setdefault(x.leaf, []).append(int(bytes(x.node)))
    assert sum(map(len, got.values())) == len(rows)
    want: dict = {}
    for i, k in enumerate(keys):
        for d in range(lsh.MIN_DEPTH + 1, lsh.DEPTH + 1):
            same = [j for j, q in enumerate(keys) if q[: 2 * d] == k[: 2 * d]]
            if len(same) <= 8 or d == lsh.DEPTH:
                want[i] = same
                break
    for leaf in got.values():
        assert all(set(leaf) == set(want[i]) if len(want[i]) <= 8 else set(leaf) <= set(want[i]) for i in leaf)


def test_only_hot_keys_are_copied(spark, monkeypatch):
    """A key of few rows has one row in the join's table, and every row finds its key however keys are marked."""
    monkeypatch.setattr(lsh, "HOT", 50)
    rows = [(k, bytearray(b"%d-%d" % (k, i))) for k in range(300) for i in range(2 if k > 3 else 200)]
    df = spark.createDataFrame(rows, "region long, node binary")
    table = df.groupBy("region").count().where("region <> 7")
    assert lsh._copies(table, "count").count() == 295 + 4 * lsh.SALTS
    for most in (100_000, 0):
        got = sorted((x.region, bytes(x.node), x["count"]) for x in lsh._spread_join(df, table, "region", "count", most).collect())
        assert got == sorted((k, bytes(n), 2 if k > 3 else 200) for k, n in rows if k != 7)
