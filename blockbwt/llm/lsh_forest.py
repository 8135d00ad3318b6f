"""Operator 9: near-duplicates by an LSH forest over MinHash signatures.

Documents with equal shingle sets are one node. A node has TREES signatures of
DEPTH components; a tree is the sorted order of its nodes' signatures. Nodes that
agree on the first MIN_DEPTH components of a tree form a region.

1. The orders are ranges of (tree, signature, node), so a region of any size is
   spread over tasks. Neighbours in an order share its longest prefixes, as deep
   as that place of the order has them: they are the first candidates, one a node
   and tree. They're verified on full sets, and the links joined to components.
2. A region whose nodes are all of one component is done, however large. The
   others are open. A node's depth in an open region adapts to how crowded it is:
   the least one, from MIN_DEPTH on, at which at most LEAF nodes share its prefix.
   All pairs of different components of such a leaf are candidates; where even
   whole signatures are shared by more, the leaf is cut into runs by node.
3. A leaf deeper than MIN_DEPTH has left out pairs with shorter common prefixes.
   Regions that are still open and larger than LEAF after that go through an
   exact join on their rarest shingles (a pair at or above the threshold shares
   one of the rarest (1 - threshold) of either), again only across components,
   and by blocks of nodes, not by pairs: nothing is capped.

A pair at 0.75 shares no region, and is missed, with probability
(1 - 0.75 ** 3) ** 20 = 2e-5, one at 0.8 with 6e-7. Links are whatever full sets
say; nothing else makes one.

Defined results: null, empty and blank texts have no shingle and are linked with
nothing; rows with a null doc_id join components but never name one, and are
kept only where nobody else is; rows that repeat are one node and share the
answer; an empty table gives no row.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

WORDS, THRESHOLD = 5, (75, 100)
TREES, DEPTH, MIN_DEPTH, LEAF = 20, 8, 3, 12
#: Nodes that a block holds and that one comparison takes, about.
BLOCK, ASKING = 512, 2048
#: Rows of one key that a task of a join takes as they are; more are dealt to so many tasks.
HOT, SALTS = 512, 16
_STORE = 250_000

_SEEDS = np.random.default_rng(90_001)
_FACTORS = (_SEEDS.integers(0, 1 << 32, TREES * DEPTH, dtype=np.uint32) | 1).astype(np.uint32)
_ADDENDS = _SEEDS.integers(0, 1 << 32, TREES * DEPTH, dtype=np.uint32)
_STEPS = [np.uint64(x) for x in (_SEEDS.integers(0, 1 << 63, WORDS, dtype=np.uint64) << np.uint64(1) | np.uint64(1))]


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        import xxhash

        self[word] = value = xxhash.xxh3_64_intdigest(word)
        return value


def _mix(x: np.ndarray) -> np.ndarray:
    """The finaliser of a published 64-bit generator; a bijection."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingles(text: str | None, hashes: dict) -> np.ndarray:
    """The sorted distinct hashes of a text's runs of WORDS words, or of all its words if they are fewer."""
    words = (text or "").encode().lower().split()  # bytes: ASCII letters and white space only
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(hashes.__getitem__, words), np.uint64, n)
    k = min(n, WORDS)
    out = np.full(n - k + 1, np.uint64(k * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF))
    for i in range(k):
        out = _mix(out + h[i : n - k + 1 + i] * _STEPS[i])
    return np.unique(out)


def _signatures(sets: list[np.ndarray]) -> np.ndarray:
    """Of sets that aren't empty: for each tree DEPTH components of 16 bits."""
    ends = np.cumsum([len(x) for x in sets])
    starts = np.concatenate([[0], ends[:-1]])
    s = (np.concatenate(sets) >> np.uint64(32)).astype(np.uint32)
    out = np.empty((len(sets), TREES * DEPTH), ">u2")
    for k in range(TREES * DEPTH):
        out[:, k] = (np.minimum.reduceat(s * _FACTORS[k] ^ _ADDENDS[k], starts) & 0xFFFF).astype(np.uint16)
    return out


def _name(s: np.ndarray) -> bytes:
    import xxhash

    return xxhash.xxh3_128_digest(s.tobytes())


def _sketch(batches):
    hashes = _Hashes()
    for whole in batches:
        for batch in common.slices(whole, 2, 1 << 19):
            sets = [shingles(x.as_py(), hashes) for x in batch.column(2)]
            if len(hashes) > _STORE:
                hashes.clear()
            full = [x for x in sets if len(x)]
            signed = iter(_signatures(full) if full else ())
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0),
                    batch.column(1),
                    pa.array([len(x) for x in sets], pa.int64()),
                    pa.array([_name(x) if len(x) else None for x in sets], pa.binary()),
                    pa.array([next(signed).tobytes() if len(x) else None for x in sets], pa.binary()),
                ],
                names=["doc_id", "text_hash", "n", "node", "signature"],
            )


def _sets(batches):
    hashes = _Hashes()
    for batch in batches:
        nodes, texts, at = batch.column(0), batch.column(1), 0
        while at < len(nodes):  # sets may be larger than their texts: few at a time
            some = [shingles(x.as_py(), hashes).tobytes() for x in texts[at : at + 500]]
            if len(hashes) > _STORE:
                hashes.clear()
            yield pa.RecordBatch.from_arrays([nodes[at : at + 500], pa.array(some, pa.binary())], names=["node", "shingles"])
            at += 500


def _linked(batches):
    """Pairs whose full sets reach the threshold."""
    for batch in batches:
        keep = []
        for a, b in zip(batch.column(2), batch.column(3)):
            x, y = np.frombuffer(a.as_buffer(), np.uint64), np.frombuffer(b.as_buffer(), np.uint64)
            shared = len(np.intersect1d(x, y, assume_unique=True))
            keep.append(THRESHOLD[1] * shared >= THRESHOLD[0] * (len(x) + len(y) - shared))
        yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(keep)), batch.column(1).filter(pa.array(keep))], names=["a", "b"])


def verify(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """(a, b) of distinct pairs that full sets confirm. Lengths that rule a pair out do so before its sets travel."""
    size = F.octet_length("shingles")
    left, right = sets.select(F.col("node").alias("a"), F.col("shingles").alias("x")), sets.select(F.col("node").alias("b"), F.col("shingles").alias("y"))
    sizes = sets.select("node", size.alias("n"))
    fit = pairs.join(sizes.select(F.col("node").alias("a"), F.col("n").alias("na")), "a").join(sizes.select(F.col("node").alias("b"), F.col("n").alias("nb")), "b")
    fit = fit.where(THRESHOLD[1] * F.least("na", "nb") >= THRESHOLD[0] * F.greatest("na", "nb")).select("a", "b")
    return fit.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(common.trimmed(_linked), "a binary, b binary")


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, root) of every node that has a link and isn't itself a root; a root is its component's smallest node.

    Alternating stars: every node's larger neighbours are hung to its smallest
    one, then its smaller neighbours. The links become stars in about log n
    rounds; each round is written, so none reaches back further.
    """
    edges = common.materialise(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    for _ in range(most_rounds):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = common.materialise(large, "edges")
        small = large.groupBy("u").agg(F.min("v").alias("m"))
        moved = large.join(small, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        edges = common.materialise(small.select("u", F.col("m").alias("v")).unionByName(moved).distinct(), "edges")
        if edges.join(edges.select(F.col("v").alias("u")).distinct(), "u", "left_semi").isEmpty():
            dup = edges.groupBy("u").count().where("count > 1")
            if dup.isEmpty():
                return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")


def _prefix(depth: int):
    return F.substring("key", 1, 2 * depth)


def _in_order(batches):
    """Rows (t, key, node) of a range of the orders -> with the region, the node before and the one after, where they're of the same region."""
    width, last = 2 * MIN_DEPTH, None
    out = []

    def flush():
        found = pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), kinds)], names=["t", "key", "node", "before", "after", "edge"])
        out.clear()
        return found

    kinds = [pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary(), pa.bool_()]
    held = None  # a row whose follower isn't known yet
    for batch in batches:
        for t, key, node in zip(*(c.to_pylist() for c in batch.columns)):
            region = (t, key[:width])
            same = held is not None and last == region
            if held is not None:
                t0, key0, node0, before0, first0 = held
                after = node if same else None
                if before0 is not None or after is not None or first0:
                    out.append((t0, key0, node0, before0, after, first0))
            held = (t, key, node, held[2] if same else None, held is None)
            last = region
            if len(out) >= 5000:
                yield flush()
    if held is not None:
        out.append((*held[:4], None, True))
    if out:
        yield flush()


def _orders(nodes: DataFrame) -> DataFrame:
    """(region, key, node, before) of every node in a tree where another one shares its region: ranges of the sorted orders, and at their edges the last row of the range before.

    Ranges are written, since the sample behind them mustn't be drawn twice. The
    driver gets two rows a range, of which the shuffle has a bounded number.
    """
    tree = nodes.select("signature", "node", F.explode(F.sequence(F.lit(0), F.lit(TREES - 1))).alias("t"))
    keyed = tree.select("t", F.expr(f"substring(signature, t * {2 * DEPTH} + 1, {2 * DEPTH})").alias("key"), "node")
    ranged = keyed.repartitionByRange("t", "key", "node").sortWithinPartitions("t", "key", "node")
    placed = common.materialise(ranged.mapInArrow(common.trimmed(_in_order), "t int, key binary, node binary, before binary, after binary, edge boolean"), "orders")
    edges = sorted((x.t, bytes(x.key), bytes(x.node), x.before is not None, x.after is not None) for x in placed.where("edge").select("t", "key", "node", "before", "after").collect())
    width, joined, alone = 2 * MIN_DEPTH, [], []
    for i, (t, key, node, before, after) in enumerate(edges):
        behind = edges[i - 1] if i else None
        ahead = edges[i + 1] if i + 1 < len(edges) else None
        same = lambda x: x is not None and (x[0], x[1][:width]) == (t, key[:width])
        if not before and same(behind):
            joined.append((t, node, behind[2]))
        elif not before and not after and not same(ahead):
            alone.append((t, node))
    spark = nodes.sparkSession
    more = F.broadcast(spark.createDataFrame(joined, "t int, node binary, behind binary"))
    lone = F.broadcast(spark.createDataFrame(alone, "t int, node binary"))
    found = placed.join(more, ["t", "node"], "left").join(lone, ["t", "node"], "left_anti")
    return found.select(F.xxhash64("t", _prefix(MIN_DEPTH)).alias("region"), "key", "node", F.coalesce("before", "behind").alias("before"))


def _leaves(rows: DataFrame, most: int) -> DataFrame:
    """rows (region, key, node, root) with `leaf`: the least depth at which at most `most` of them share the key's prefix, or a run of those that share all of it.

    Depth by depth: rows that share a prefix settle together, so those that go on
    are whole groups. Each depth is written, since what settles and what goes on
    are read from it.
    """
    out, left = None, rows.select("region", "key", "node", "root")
    for d in range(MIN_DEPTH + 1, DEPTH + 1):
        each = left.withColumn("leaf", F.xxhash64("region", _prefix(d)))
        counts = each.groupBy("leaf").agg(F.count(F.lit(1)).alias("c"))
        placed = common.materialise(_spread_join(each, counts, "leaf", "c").select("region", "key", "node", "root", "leaf", "c"), "leaves")
        run = F.when(F.col("c") > most, F.pmod(F.xxhash64("node", "region"), F.ceil(F.col("c") / most))).otherwise(0)
        settled = (placed if d == DEPTH else placed.where(F.col("c") <= most)).select("node", "root", F.xxhash64("leaf", run).alias("leaf"))
        out = settled if out is None else out.unionByName(settled)
        left = placed.where(F.col("c") > most).drop("leaf", "c")
        if d < DEPTH and left.isEmpty():
            break
    return out


def _across(rows: DataFrame, by: str) -> DataFrame:
    """(a, b): the pairs of nodes of one `by`, of which each has a bounded number, that are of different components."""
    left, right = rows.select(by, F.col("node").alias("a"), F.col("root").alias("ra")), rows.select(by, F.col("node").alias("b"), F.col("root").alias("rb"))
    return left.join(right, by).where("a < b and ra <> rb").select("a", "b").distinct()


def _compare(members: pa.Table, asking: pa.Table) -> pa.Table:
    """Links between the asking nodes and the block's members of other components: one for each node and component at most."""
    nodes, roots = members["node"].to_pylist(), members["root"].to_pylist()
    sets = [np.frombuffer(x, np.uint64) for x in members["shingles"].to_pylist()]
    lens = np.array([len(x) for x in sets], np.int64)
    flat, owner = (np.concatenate(sets), np.repeat(np.arange(len(sets)), lens)) if sets else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
    order = np.argsort(flat, kind="stable")
    flat, owner = flat[order], owner[order]
    left, right = [], []
    for node, root, blob in zip(asking["node"].to_pylist(), asking["root"].to_pylist(), asking["shingles"].to_pylist()):
        x = np.frombuffer(blob, np.uint64)
        lo = np.searchsorted(flat, x)
        n = np.searchsorted(flat, x, side="right") - lo
        ends = np.cumsum(n)
        at = np.arange(ends[-1]) + np.repeat(lo - (ends - n), n)
        shared = np.bincount(owner[at], minlength=len(sets))
        found = set()
        for i in np.flatnonzero(THRESHOLD[1] * shared >= THRESHOLD[0] * (len(x) + lens - shared)).tolist():
            if roots[i] != root and roots[i] not in found:
                found.add(roots[i])
                left.append(min(node, nodes[i]))
                right.append(max(node, nodes[i]))
    return pa.table({"a": pa.array(left, pa.binary()), "b": pa.array(right, pa.binary())})


def _rest(nodes: DataFrame, sets: DataFrame) -> DataFrame:
    """Links (a, b) between `nodes` (node, root, anchor) of different components: a node is compared with the blocks that have one of its rarest shingles.

    Blocks hold about BLOCK nodes of one family (the same anchor), so a node
    meets a large family a few times, not once for each member; and the
    component that most holders of a shingle belong to asks nothing of itself.
    """
    many = nodes.groupBy("anchor").agg(F.count(F.lit(1)).alias("c"))
    salt = F.pmod(F.xxhash64("node"), F.ceil(F.col("c") / BLOCK))
    members = common.materialise(nodes.join(many, "anchor").select("node", "root", F.xxhash64("anchor", salt).alias("block")), "members")
    tokens = F.expr("transform(sequence(0, cast(octet_length(shingles) div 8 as int) - 1), i -> substring(shingles, 8 * i + 1, 8))")
    each = sets.join(members, "node").select("node", "root", "block", F.expr("cast(octet_length(shingles) div 8 as int)").alias("n"), F.explode(tokens).alias("s"))
    each = common.materialise(each, "shingles")
    counts = common.materialise(each.groupBy("s").agg(F.count(F.lit(1)).alias("df")).where("df > 1"), "counts")
    # shingles of one holder alone come first in a prefix and find nobody
    alone = each.groupBy("node").agg(F.first("n").alias("size")).join(_with_counts(each, counts).groupBy("node").agg(F.count(F.lit(1)).alias("held")), "node")
    ranked = _with_counts(each, counts).join(alone.select("node", (F.col("size") - F.col("held")).alias("skip")), "node")
    rank = F.row_number().over(Window.partitionBy("node").orderBy("df", "s")) + F.col("skip")
    longest = F.col("n") - F.ceil(F.col("n") * THRESHOLD[0] / float(THRESHOLD[1]) - 1e-9) + 1
    rare = common.materialise(ranked.withColumn("k", rank).where(F.col("k") <= longest).select("s", "node", "root", "block"), "rare")
    by_root = rare.groupBy("s", "root").agg(F.count(F.lit(1)).alias("c"))
    mixed = by_root.groupBy("s").agg(F.max_by("root", F.struct("c", "root")).alias("major"), F.count(F.lit(1)).alias("roots")).where("roots > 1").select("s", "major")
    minor = rare.join(mixed, "s").where("root <> major").select("s", "node")
    holders = rare.select("s", "block").distinct()
    asked = common.materialise(minor.join(holders, "s").select("node", "block").distinct(), "asked")
    portions = asked.groupBy("block").agg(F.ceil(F.count(F.lit(1)) / ASKING).alias("k"))
    full = sets.join(members.select("node", "root", F.col("block").alias("own")), "node")
    left = full.withColumnRenamed("own", "block").join(portions, "block").select("block", F.explode(F.sequence(F.lit(0).cast("long"), F.col("k") - 1)).alias("portion"), "node", "root", "shingles")
    right = asked.join(portions, "block").join(full.drop("own"), "node").select("block", F.pmod(F.xxhash64(F.lit(3), "node"), F.col("k")).alias("portion"), "node", "root", "shingles")
    right = common.materialise(right, "asking")
    return left.groupBy("block", "portion").cogroup(right.groupBy("block", "portion")).applyInArrow(_compare, "a binary, b binary").distinct()


def _with_counts(each: DataFrame, counts: DataFrame, hot: int = 512, most: int = 100_000) -> DataFrame:
    """each joined with counts (s, df) on s. Shingles of more than `hot` holders, a passage that many texts share, are looked up where their rows are if they are few, else dealt to several tasks."""
    common_ones = counts.where(F.col("df") > hot)
    n = common_ones.count()
    if not n:
        return each.join(counts, "s")
    table = common_ones.select("s", F.col("df").alias("hot"))
    if n <= most:
        marked = each.join(F.broadcast(table), "s", "left")
    else:
        copies = table.withColumn("salt", F.explode(F.array(*map(F.lit, range(16)))))
        marked = each.withColumn("salt", F.pmod(F.xxhash64("node", F.lit(13)), F.lit(16)).cast("int")).join(copies, ["s", "salt"], "left").drop("salt")
    rare = marked.where("hot is null").drop("hot").join(counts.where(F.col("df") <= hot), "s")
    return rare.unionByName(marked.where("hot is not null").withColumnRenamed("hot", "df").select(*rare.columns))


def near_duplicates(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id, kept), a row for each row of df."""
    return _answer(*_grouped(df, doc_id, text))


def representatives(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, text_hash): of each group its one text of the least id, null last, and every text without a shingle."""
    docs, nodes, roots = _grouped(df, doc_id, text)
    placed = nodes.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    least = placed.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("z"), "doc_id", "text_hash")).alias("f"))
    return least.select("f.doc_id", "f.text_hash").unionByName(docs.where("node is null").select("doc_id", "text_hash").distinct())


def _grouped(df: DataFrame, doc_id: str, text: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Rows with their nodes, nodes (equal sets of shingles) with their first text, and (node, root) of linked nodes."""
    common.small_batches(df.sparkSession)
    rows = df.select(F.col(doc_id).cast("long").alias("doc_id"), F.xxhash64(F.col(text)).alias("text_hash"), F.col(text).alias("text"))
    docs = common.materialise(rows.select("doc_id", "text_hash", "text").mapInArrow(common.trimmed(_sketch), "doc_id long, text_hash long, n long, node binary, signature binary"), "sketches")
    named = docs.where("node is not null")
    first = named.groupBy("node").agg(F.min(F.struct(F.col("doc_id").isNull().alias("z"), "doc_id", "text_hash", "signature")).alias("f"))
    nodes = first.select("node", "f.doc_id", "f.text_hash", "f.signature")
    regions = common.materialise(_orders(nodes), "regions")
    # full sets of the nodes that have a neighbour, from the one text that stands for each
    wanted = regions.select("node").distinct().join(nodes.select("node", F.col("doc_id").alias("d"), F.col("text_hash").alias("h")), "node")
    texts = rows.join(wanted, (F.col("text_hash") == F.col("h")) & F.col("doc_id").eqNullSafe(F.col("d")))
    sets = common.materialise(texts.select("node", "text").mapInArrow(common.trimmed(_sets), "node binary, shingles binary").dropDuplicates(["node"]), "sets")
    near = regions.where("before is not null").select(F.least("node", "before").alias("a"), F.greatest("node", "before").alias("b")).distinct()
    links = common.materialise(verify(near, sets), "links")
    roots = common.materialise(components(links), "roots")
    open_rows = common.materialise(_open(regions.select("region", "key", "node"), roots), "open")
    pairs = _across(open_rows.where(F.col("n") <= LEAF), "region")
    crowded = open_rows.where(F.col("n") > LEAF)
    pairs = pairs.unionByName(_across(_leaves(crowded, 2 * LEAF), "leaf")).distinct()
    links = links.unionByName(common.materialise(verify(pairs.join(near, ["a", "b"], "left_anti"), sets), "links"))
    roots = common.materialise(components(links), "roots")
    still = _open(crowded.select("region", "key", "node"), roots)
    large = common.materialise(still.groupBy("node").agg(F.first("root").alias("root"), F.min("region").alias("anchor")), "large")
    if not large.isEmpty():
        links = links.unionByName(common.materialise(_rest(large, sets), "links"))
        roots = common.materialise(components(links), "roots")
    return docs, nodes, roots


def _open(rows: DataFrame, roots: DataFrame) -> DataFrame:
    """rows (region, key, node) of the regions that hold nodes of different components, with `root` and the region's number of nodes."""
    placed = rows.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    state = placed.groupBy("region").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count(F.lit(1)).alias("n")).where("lo <> hi").select("region", "n")
    return _spread_join(placed, state, "region", "n").select("region", "key", "node", "root", "n")


def _spread_join(rows: DataFrame, table: DataFrame, by: str, size: str, most: int = 100_000) -> DataFrame:
    """An inner join with a table of one row a key, which has the key's number of rows in `size`. Rows of a key with more than HOT of them are dealt to SALTS tasks; no other key is copied."""
    table = common.materialise(table, "keys")
    many = table.where(F.col(size) > HOT).select(by, F.lit(True).alias("hot"))
    n = many.count()
    if not n:
        return rows.join(table, by)
    dealt = rows.withColumn("salt", F.pmod(F.xxhash64("node", F.lit(13)), F.lit(SALTS)).cast("int"))
    if n <= most:
        marked = dealt.join(F.broadcast(many), by, "left")
    else:
        marked = dealt.join(many.withColumn("salt", F.explode(F.array(*map(F.lit, range(SALTS))))), [by, "salt"], "left")
    placed = marked.withColumn("salt", F.when(F.col("hot"), F.col("salt")).otherwise(0)).drop("hot")
    return placed.join(_copies(table, size), [by, "salt"]).drop("salt")


def _copies(table: DataFrame, size: str) -> DataFrame:
    """table with `salt`: a row for each of SALTS tasks where a key's size is above HOT, so less than one for each row of such a key; 0 elsewhere."""
    salts = F.when(F.col(size) > HOT, F.array(*map(F.lit, range(SALTS)))).otherwise(F.array(F.lit(0)))
    return table.withColumn("salt", F.explode(salts))


def _answer(docs: DataFrame, nodes: DataFrame, roots: DataFrame) -> DataFrame:
    classes = nodes.select("node", F.col("doc_id").alias("first"))
    members = roots.select("node", "root").unionByName(roots.select(F.col("root").alias("node"), "root").distinct())
    least = members.join(classes, "node").groupBy("root").agg(F.min("first").alias("component_id"))
    named = members.join(least, "root").select("node", "component_id")
    every = classes.join(named, "node", "left").select("node", F.coalesce("component_id", "first").alias("component_id"))
    done = docs.select("doc_id", "n", "node").join(every, "node", "left")
    component = F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
    return done.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"))


def op9_lsh_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(common.table(spark, sf_dir, "documents"))


#: Every pair that shares a shingle, counted; components by reachability.
SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT doc_id, CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
      ELSE list_distinct(list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' '))) END AS sh FROM w),
e AS MATERIALIZED (SELECT doc_id, unnest(sh) AS x FROM s),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM e a JOIN e b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS MATERIALIZED (SELECT a, b FROM p JOIN s x ON x.doc_id = a JOIN s y ON y.doc_id = b WHERE 100 * c >= 75 * (len(x.sh) + len(y.sh) - c)),
linked AS MATERIALIZED (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
r AS (SELECT doc_id, doc_id AS other FROM documents UNION SELECT r.doc_id, linked.b FROM r JOIN linked ON linked.a = r.other),
m AS (SELECT doc_id, min(other) AS component_id FROM r GROUP BY doc_id)
SELECT s.doc_id, CAST(len(sh) AS BIGINT) AS n_shingles, component_id, s.doc_id = component_id AS kept FROM s JOIN m ON m.doc_id = s.doc_id
"""
