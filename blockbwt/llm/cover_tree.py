"""Operator 4: exact top-k inner products by dual cover trees.

All vectors are dealt to cells by their nearest pivot (of PIVOTS chosen farthest
first from a sample of SAMPLE vectors), and cells to blocks of about BLOCK
vectors by a hash, so a vector that a third of all rows repeat fills many
blocks. Each block has a cover tree: a node's children are a greedy net of its
points at a radius smaller by BASE, and every node knows the exact radius that
covers its points. Queries have blocks and trees of their own.

A pair of a query node and a candidate node is bounded by
<cq, cr> + rq |cr| + rr |cq| + rq rr. It's pruned when that is below the worst
of the query group's kth scores so far. Those start from one block of the query
block's own cell, are carried to all other blocks, whole block pairs are pruned
by the same bound, and what remains is searched by the two trees together. A
block answers with k candidates a query at most, and only with those that still
can be among the k. What a candidate block is asked is split into portions of
ASKING query blocks.

Scores are 64-bit integers throughout: products are formed in doubles where
every sum is below 2 ** 53, else in 64-bit integers; one that might not fit a
long is an error. Nothing is approximate.

Defined results: a vector that is null, or holds a null or non-finite component,
takes no part, nor does one without an id; vectors of other lengths have no
product with a query and aren't its candidates; rows that repeat id and vector
count once; a query's own id is no candidate; ties go to the smaller id; with
fewer than k candidates all are returned; an empty table gives no row.
"""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

K, SAMPLE, PIVOTS, BLOCK, BASE, LEAF, BUNDLE, ASKING = 20, 2048, 32, 4096, 1.5, 64, 1024, 64
_EXACT, _LONG = float(1 << 53), float(1 << 63)
#: Below every score: what a place that isn't taken yet holds.
_NONE = np.iinfo(np.int64).min


class CoverTree:
    """Points in the tree's order; nodes as arrays: from, to, centre, radius, first child and last."""

    def __init__(self, ids: np.ndarray, points: np.ndarray):
        order, nodes = np.arange(len(ids)), []
        whole, points = points, points.astype(np.float64)  # trees are steered in doubles, scores taken from `whole`
        stack = [(0, len(ids), -1)]
        norms = (points**2).sum(1)
        children: dict[int, list[int]] = {}
        while stack:
            a, b, parent = stack.pop()
            own, node = order[a:b], len(nodes)
            centre = points[own].mean(0)
            radius = float(np.sqrt(np.maximum(0, ((points[own] - centre) ** 2).sum(1)).max()))
            nodes.append((a, b, centre, radius * (1 + 1e-9) + 1e-6))
            if parent >= 0:
                children.setdefault(parent, []).append(node)
            if b - a <= LEAF or radius < 1e-9:
                continue
            left, net, of = np.ones(b - a, bool), 0, np.zeros(b - a, np.int64)
            reach = (radius / BASE) ** 2
            while left.any() and net * 4 <= b - a:
                at = own[int(left.argmax())]
                near = norms[own] - 2 * (points[own] @ points[at]) + norms[at] <= reach
                near[int(left.argmax())] = True
                of[near & left] = net
                left &= ~near
                net += 1
            if left.any() or net < 2:  # a net that's no coarser than the points: the node stays whole
                continue
            by = np.argsort(of, kind="stable")
            order[a:b] = own[by]
            cuts = [a, *(a + np.flatnonzero(np.diff(of[by])) + 1).tolist(), b]
            stack += [(x, y, node) for x, y in zip(cuts, cuts[1:])]
        self.ids, self.points, self.children = ids[order], _scoring(whole[order]), children
        self.a, self.b = np.array([x[0] for x in nodes]), np.array([x[1] for x in nodes])
        self.centres, self.radii = np.array([x[2] for x in nodes]), np.array([x[3] for x in nodes])
        self.lengths = np.sqrt((self.centres**2).sum(1))

    def packed(self) -> bytes:
        small = np.int16 if np.abs(self.points).max() < 1 << 15 else np.int64
        return common.pack(pickle.dumps((self.ids, self.points.astype(small), self.a, self.b, self.children), 5))

    @classmethod
    def unpacked(cls, data: bytes) -> CoverTree:
        out = cls.__new__(cls)
        out.ids, points, out.a, out.b, out.children = pickle.loads(common.unpack(data))
        out.points = _scoring(points)
        out.centres = np.array([out.points[a:b].mean(0) for a, b in zip(out.a, out.b)])
        out.radii = np.array([np.sqrt(((out.points[a:b] - c) ** 2).sum(1).max()) for a, b, c in zip(out.a, out.b, out.centres)]) * (1 + 1e-9) + 1e-6
        out.lengths = np.sqrt((out.centres**2).sum(1))
        return out


def _scoring(points: np.ndarray) -> np.ndarray:
    """Integers as doubles where those hold them, which multiply faster."""
    return points.astype(np.float64) if np.abs(points).max(initial=0) < _EXACT else points.astype(np.int64)


def bound(dots, rq, rr, lq, lr):
    """An upper bound of all products, with room for rounding."""
    out = dots + rq * lr + rr * lq + rq * rr
    return out + 1e-9 * (np.abs(out) + lq * lr) + 1e-3


class Best:
    """The k best of each query of a block: scores and ids, worst last; `floor` is what a candidate has to reach."""

    def __init__(self, n: int, k: int, floor: np.ndarray):
        self.scores, self.ids = np.full((n, k), _NONE), np.full((n, k), np.iinfo(np.int64).max)
        self.given, self.floor = floor, floor.copy()

    def add(self, a: int, b: int, ids: np.ndarray, scores: np.ndarray) -> None:
        """Scores of candidates; _NONE for one that isn't any."""
        k = self.scores.shape[1]
        # only columns that reach some query's floor
        fits = (scores >= self.floor[a:b, None]) & (scores != _NONE)
        some = fits.any(0)
        if not some.any():
            return
        ids, scores, fits = ids[some], scores[:, some], fits[:, some]
        all_scores = np.hstack([self.scores[a:b], np.where(fits, scores, _NONE)])
        all_ids = np.hstack([self.ids[a:b], np.broadcast_to(ids, scores.shape)])
        at = np.lexsort((all_ids, ~all_scores), axis=1)[:, :k]  # ~x falls as x rises, and has no overflow
        self.scores[a:b], self.ids[a:b] = np.take_along_axis(all_scores, at, 1), np.take_along_axis(all_ids, at, 1)
        self.floor[a:b] = np.maximum(self.given[a:b], self.scores[a:b, -1])


def products(q: np.ndarray, r: np.ndarray) -> np.ndarray:
    """Exact inner products of integers as 64-bit integers."""
    most = float(np.abs(q).max(initial=0)) * float(np.abs(r).max(initial=0)) * q.shape[1]
    if most < _EXACT:
        return (q.astype(np.float64, copy=False) @ r.astype(np.float64, copy=False).T).astype(np.int64)
    if most >= _LONG:
        raise OverflowError("an inner product may not fit a long")
    return q.astype(np.int64) @ r.astype(np.int64).T


def dual_search(q: CoverTree, r: CoverTree, best: Best) -> None:
    """Searches both trees together, the most promising child pairs first."""
    stack = [(0, 0)]
    while stack:
        x, y = stack.pop()
        a, b = q.a[x], q.b[x]
        if bound(q.centres[x] @ r.centres[y], q.radii[x], r.radii[y], q.lengths[x], r.lengths[y]) < best.floor[a:b].min():
            continue
        cx, cy = q.children.get(x), r.children.get(y)
        if cx is None and cy is None:
            c, d = r.a[y], r.b[y]
            for e in range(c, d, BLOCK):
                f = min(d, e + BLOCK)
                scores = products(q.points[a:b], r.points[e:f])
                own = q.ids[a:b, None] == r.ids[None, e:f]
                best.add(a, b, r.ids[e:f], np.where(own, _NONE, scores) if own.any() else scores)
        elif cy is None or cx is not None and q.radii[x] >= r.radii[y]:
            stack += [(i, y) for i in cx]
        else:
            near = np.argsort(r.centres[cy] @ q.centres[x], kind="stable")
            stack += [(x, cy[i]) for i in near]


def integers(vector: Column) -> Column:
    return F.transform(vector, lambda x: F.floor(x.cast("double") * 64))


def usable(vector: Column) -> Column:
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double")) == float("inf")))
    return vector.isNotNull() & ~F.coalesce(bad, F.lit(False)) & (F.size(vector) > 0)


def _pivots(rows: DataFrame) -> dict[int, np.ndarray]:
    """By dimension, farthest first from a sample of SAMPLE rows of the smallest hashes. Pivots steer the dealing alone; any give exact results."""
    sample = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE).collect()
    out = {}
    for dim in {len(x.v) for x in sample}:
        p = np.unique(np.array([x.v for x in sample if len(x.v) == dim], np.float64), axis=0)
        far, chosen = np.full(len(p), np.inf), []
        for _ in range(min(PIVOTS, len(p))):
            chosen.append(int(far.argmax()) if chosen else 0)
            far = np.minimum(far, ((p - p[chosen[-1]]) ** 2).sum(1))
        out[dim] = p[chosen]
    return out


def _dealt(pivots: dict[int, np.ndarray]):
    def run(batches):
        for batch in batches:
            for a in range(0, batch.num_rows, 8192):
                some = batch.slice(a, 8192)
                lens = np.diff(some.column(1).offsets.to_numpy())
                cell = np.zeros(len(lens), np.int64)
                vectors = some.column(1).to_pylist()
                for dim in set(lens.tolist()):
                    at = np.flatnonzero(lens == dim)
                    if dim in pivots:
                        x, p = np.array([vectors[i] for i in at], np.float64), pivots[dim]
                        cell[at] = ((p**2).sum(1) - 2 * x @ p.T).argmin(1)
                    cell[at] += dim * PIVOTS
                yield pa.RecordBatch.from_arrays([*some.columns, pa.array(cell)], names=["vec_id", "v", "cell"])

    return run


def _tree(rows: pa.Table) -> pa.Table:
    ids = rows["vec_id"].to_numpy()
    order = np.argsort(ids, kind="stable")
    points = np.array(rows["v"].to_pylist(), np.int64)[order]
    tree = CoverTree(ids[order], points)
    packed = tree.packed()
    return pa.table({"block": rows["block"][:1], "cell": rows["cell"][:1], "number": rows["number"][:1], "dim": pa.array([points.shape[1]], pa.int32()), "centre": pa.array([tree.centres[0].tolist()], pa.list_(pa.float64())), "radius": pa.array([tree.radii[0]]), "tree": pa.array([packed], pa.binary())})


_BLOCK_REST = "dim int, centre array<double>, radius double, tree binary"


def blocks(dealt: DataFrame, size: int) -> DataFrame:
    """(block, cell, number, dim, centre, radius, tree): every cell in blocks of about `size` vectors, numbered from 0."""
    counts = dealt.groupBy("cell").agg(F.count(F.lit(1)).alias("n"))
    salted = dealt.join(F.broadcast(counts), "cell")  # PIVOTS rows a dimension
    salt = F.pmod(F.xxhash64("vec_id", F.lit(5)), F.greatest(F.lit(1), F.ceil(F.col("n") / size)))
    named = salted.select("vec_id", "v", "cell", salt.cast("long").alias("number"), F.xxhash64("cell", salt).alias("block"))
    return named.groupBy("block").applyInArrow(_tree, f"block long, cell long, number long, {_BLOCK_REST}")


def _search(k: int):
    def run(candidates: pa.Table, asked: pa.Table) -> pa.Table:
        """One candidate block and a portion of what it's asked."""
        found = {"block": [], "query_id": [], "vec_id": [], "score": []}
        for blob in candidates["tree"].to_pylist():
            tree = CoverTree.unpacked(blob)
            for block, q, floor in zip(asked["q"].to_pylist(), asked["tree"].to_pylist(), asked["floors"].to_pylist()):
                queries = CoverTree.unpacked(q)
                given = np.full(len(queries.ids), _NONE) if floor is None else np.frombuffer(floor, np.int64)
                best = Best(len(queries.ids), k, given)
                dual_search(queries, tree, best)
                at = best.scores != _NONE
                found["block"].append(np.full(int(at.sum()), block, np.int64))
                found["query_id"].append(np.broadcast_to(queries.ids[:, None], at.shape)[at])
                found["vec_id"].append(best.ids[at])
                found["score"].append(best.scores[at])
        return pa.table({c: pa.array(np.concatenate(x) if x else np.zeros(0, np.int64), pa.int64()) for c, x in found.items()})

    return run


_FOUND = "block long, query_id long, vec_id long, score long"


def _asked(candidates: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """wanted (r, q, tree, floors): what query blocks find in candidate blocks r, by portions of about ASKING of them."""
    portions = wanted.groupBy("r").agg(F.ceil(F.count(F.lit(1)) / ASKING).alias("k"))
    left = candidates.select(F.col("block").alias("r"), "tree").join(portions, "r").select("r", F.explode(F.sequence(F.lit(0).cast("long"), F.col("k") - 1)).alias("portion"), "tree")
    right = wanted.join(portions, "r").select("r", F.pmod(F.xxhash64("q", F.lit(9)), F.col("k")).alias("portion"), "q", "tree", "floors")
    return left.groupBy("r", "portion").cogroup(right.groupBy("r", "portion")).applyInArrow(_search(k), _FOUND)


def _top(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def _pairs(batches):
    """Block pairs that aren't pruned: of each query block and a bundle of candidate blocks."""
    for batch in batches:
        for x in batch.to_pylist():
            some = [y for y in x["bundle"] if y["dim"] == x["dim"] and y["block"] != x["home"]]
            if not some:
                continue
            c = np.array([y["centre"] for y in some])
            q = np.array(x["centre"])
            ub = bound(c @ q, x["radius"], np.array([y["radius"] for y in some]), np.sqrt(q @ q), np.sqrt((c**2).sum(1)))
            keep = [y["block"] for y, u in zip(some, ub.tolist()) if x["floor"] is None or u >= x["floor"]]
            yield pa.RecordBatch.from_arrays([pa.array([x["block"]] * len(keep), pa.int64()), pa.array(keep, pa.int64())], names=["q", "r"])


def _with_floors(k: int):
    """A query block and what its home block gave -> the kth scores so far, in the tree's order."""

    def run(block: pa.Table, found: pa.Table) -> pa.Table:
        out = []
        q, score = found["query_id"].to_numpy(), found["score"].to_numpy()
        for x in block.to_pylist():
            ids = CoverTree.unpacked(x["tree"]).ids
            order = np.lexsort((~score, q))
            qs, ss = q[order], score[order]
            at = np.searchsorted(qs, ids) + k - 1
            inside = np.minimum(at, len(qs) - 1)
            floors = np.where((at < len(qs)) & (qs[inside] == ids), ss[inside], _NONE) if len(qs) else np.full(len(ids), _NONE)
            least = int(floors.min())
            out.append({c: x[c] for c in ("block", "home", "dim", "centre", "radius", "tree")} | {"floors": floors.astype(np.int64).tobytes(), "floor": None if least == _NONE else least})
        return pa.Table.from_pylist(out, schema)

    schema = pa.schema([("block", pa.int64()), ("home", pa.int64()), ("dim", pa.int32()), ("centre", pa.list_(pa.float64())), ("radius", pa.float64()), ("tree", pa.binary()), ("floors", pa.binary()), ("floor", pa.int64())])
    return run


def top_k(df: DataFrame, is_query: Column, k: int = K, vec_id: str = "vec_id", embedding: str = "embedding", block: int = BLOCK) -> DataFrame:
    """(query_id, rank, vec_id, score): the k best rows of df for each row where is_query holds."""
    given = df.select(F.col(vec_id).cast("long").alias("vec_id"), F.col(embedding).alias("e"), F.coalesce(is_query, F.lit(False)).alias("q")).where("vec_id is not null")
    rows = given.where(usable(F.col("e"))).select("vec_id", integers(F.col("e")).alias("v"), "q").dropDuplicates(["vec_id", "v"])
    pivots = _pivots(rows)
    sent = _dealt(pivots)
    dealt = common.materialise(rows.select("vec_id", "v").mapInArrow(sent, "vec_id long, v array<bigint>, cell long").join(rows.where("q").select("vec_id", "q").distinct(), "vec_id", "left"), "vectors")
    plain = dealt.select("vec_id", "v", "cell")
    candidates = common.materialise(blocks(plain, block), "blocks")
    queries = common.materialise(blocks(dealt.where("q").select("vec_id", "v", "cell"), max(64, block // 8)), "query-blocks")
    # first, one block of a query block's own cell: its blocks are shares of it by hash, so any will do
    in_cell = candidates.groupBy("cell").agg(F.count(F.lit(1)).alias("c"))  # PIVOTS rows a dimension
    homes = queries.join(F.broadcast(in_cell), "cell").withColumn("number", F.pmod("block", "c")).drop("c")
    homes = homes.join(candidates.select("cell", "number", F.col("block").alias("home")), ["cell", "number"]).drop("number")
    homes = common.materialise(homes, "homes")
    first = _asked(candidates, homes.select(F.col("home").alias("r"), F.col("block").alias("q"), "tree", F.lit(None).cast("binary").alias("floors")), k)
    first = common.materialise(first, "found")
    floors = homes.groupBy("block").cogroup(first.groupBy("block")).applyInArrow(_with_floors(k), f"block long, home long, {_BLOCK_REST}, floors binary, floor long")
    floors = common.materialise(floors, "floors")
    # then all other blocks that the bound leaves, by bundles of summaries
    bundles = max(1, -(-candidates.count() // BUNDLE))
    summary = F.struct("block", "dim", "centre", "radius")
    bundled = candidates.groupBy(F.pmod("block", F.lit(bundles)).alias("g")).agg(F.collect_list(summary).alias("bundle"))
    spread = floors.select("block", "home", "dim", "centre", "radius", "floor", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(bundles - 1).cast("long"))).alias("g"))
    pairs = common.materialise(spread.join(bundled, "g").mapInArrow(_pairs, "q long, r long"), "pairs")
    wanted = pairs.join(floors.select(F.col("block").alias("q"), "tree", "floors"), "q").select("r", "q", "tree", "floors")
    second = _asked(candidates, wanted, k)
    both = first.unionByName(second).select("query_id", "vec_id", "score")
    return _top(both, k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op4_cover_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(common.table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


SQL = """
WITH v AS (SELECT DISTINCT vec_id, list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT)) AS e
           FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
           AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
p AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
             CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda z: z[1] * z[2])) AS BIGINT) AS score
      FROM v q JOIN v c ON q.vec_id % 20 = 0 AND q.vec_id <> c.vec_id),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM p)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20
"""
