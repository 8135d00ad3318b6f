"""Buckets of suffixes: prefix splitters, their size table, refinement, and other splitters.

A bucket is the suffixes that share a prefix of its depth, shorter suffixes
padded with U+0000. One whose padded prefix holds padding is terminal: its
suffixes are equal, only their strings' ids order them, and no longer prefix
could split it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from blockbwt.storage import materialise

from . import packedsizes
from .collection import END, StringCollection, positions, suffixes

#: Rows of buckets, some 60 bytes each, that are broadcast; more are joined by shuffles.
BROADCAST_BUCKETS = 200_000
SIZES = "bucket string, depth int, terminal boolean, n long"


def prefix_bucket(depth: int | Column, s: str = "s", pos: str = "pos") -> Column:
    depth = F.lit(depth) if isinstance(depth, int) else depth
    return F.rpad(F.substring(F.col(s), F.col(pos) + 1, depth), depth, F.lit(END))


def terminal(bucket: Column) -> Column:
    return F.contains(bucket, F.lit(END))


def size_table(coll: StringCollection, ell: int) -> DataFrame:
    """(bucket, depth, terminal, n): one scan; tasks count their own suffixes before the small shuffle, those of packed strings as integers."""
    if ell < 1:
        raise ValueError("the prefix length has to be 1 or more")
    if packedsizes.takes(coll, ell):
        counts = packedsizes.prefix_counts(coll, ell)
    else:
        counts = suffixes(coll).select(prefix_bucket(ell).alias("bucket")).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))
    return counts.select("bucket", F.lit(ell).alias("depth"), terminal(F.col("bucket")).alias("terminal"), "n")


def size_table_split(coll: StringCollection, ell: int, parts: int) -> DataFrame:
    """The same by subsets of the strings with tables of their own, which are then added up."""
    own = suffixes(coll).select(F.pmod("sid", F.lit(parts)).alias("part"), prefix_bucket(ell).alias("bucket")).groupBy("part", "bucket").count()
    merged = own.groupBy("bucket").agg(F.sum("count").alias("n"))
    return merged.select("bucket", F.lit(ell).alias("depth"), terminal(F.col("bucket")).alias("terminal"), "n")


def refine(coll: StringCollection, sizes: DataFrame, m1: int, step: int, adaptive: bool = False, rounds: int | None = None) -> DataFrame:
    """Splits every bucket of more than m1 suffixes that isn't terminal by up to `step` further symbols, until none is left or `rounds` tables are made, the first one counted.

    Each round scans the suffixes of the oversized buckets alone: their prefixes,
    fewer than all suffixes / m1, are broadcast up to a counted number and joined
    by a shuffle beyond it. Of packed strings no row is made for a suffix, up to 32
    symbols. adaptive takes fewer symbols where the largest bucket is only mildly
    too large.
    """
    done, sizes, sigma, made = None, sizes.select("bucket", "depth", "terminal", "n"), None, 1
    splitter = packedsizes.Splitter(coll)
    while True:
        if made == rounds:
            return sizes if done is None else done.unionByName(sizes)
        large = sizes.where((F.col("n") > m1) & ~F.col("terminal"))
        found = large.agg(F.count(F.lit(1)).alias("buckets"), F.max("n").alias("most"), F.max("depth").alias("depth")).first()
        kept = sizes.where((F.col("n") <= m1) | F.col("terminal"))
        done = kept if done is None else done.unionByName(kept)
        if not found.buckets:
            return done
        deepest, more = found.depth, step
        if adaptive:
            sigma = sigma or max(2, len(coll.symbols()))
            more, over = 1, found.most / m1
            while more < step and sigma**more < over:
                more += 1
        wanted = large.select(F.col("bucket").alias("wanted"))
        counts = splitter.counts(wanted, found.buckets, deepest, deepest + more)
        if counts is None:
            wanted = F.broadcast(wanted) if found.buckets <= BROADCAST_BUCKETS else wanted
            each = suffixes(coll).select(prefix_bucket(deepest).alias("short"), prefix_bucket(deepest + more).alias("bucket"))
            counts = each.join(wanted, F.col("short") == F.col("wanted"), "left_semi").groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))
        # written: each round reads it more than once
        sizes = materialise(counts.select("bucket", F.lit(deepest + more).alias("depth"), terminal(F.col("bucket")).alias("terminal"), "n"), "sizes")
        made += 1


def with_base(sizes: DataFrame) -> DataFrame:
    """Adds the number of suffixes before each bucket.

    Two levels, so that no task sorts all buckets: by their first symbols, and
    within those. A mixed-depth bucket sorts by its own prefix, since no bucket
    is a prefix of another.
    """
    lead = F.substring("bucket", 1, 2).alias("lead")
    groups = sizes.groupBy(lead).agg(F.sum("n").alias("total"))
    starts = groups.select("lead", F.coalesce(F.sum("total").over(Window.orderBy("lead").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    own = F.sum("n").over(Window.partitionBy("lead").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1))
    return sizes.withColumn("lead", lead).join(F.broadcast(starts), "lead").withColumn("base", F.coalesce(own, F.lit(0)) + F.col("start")).drop("lead", "start")


def assign_bucket(rows: DataFrame, plan: DataFrame, depths: list[int], small: bool, keep: list[str], key=prefix_bucket, plan_key=None) -> DataFrame:
    """rows (sid, s, pos) joined with the plan's row of their bucket, of which every suffix matches one at most.

    A small plan is looked up depth by depth in one pass over the rows; a larger
    one by an equi-join for each depth. key(depth) names a suffix's bucket, and
    plan_key(bucket, depth) the plan's, where that's not its prefix.
    """
    plan_key = plan_key or (lambda bucket, depth: bucket)
    out = None
    if small:
        at = rows
        for d in depths:
            own = plan.where(F.col("depth") == d).select(plan_key(F.col("bucket"), d).alias(f"_k{d}"), F.struct(*keep).alias(f"_b{d}"))
            at = at.join(F.broadcast(own), key(d) == F.col(f"_k{d}"), "left" if len(depths) > 1 else "inner").drop(f"_k{d}")
        found = F.coalesce(*[F.col(f"_b{d}") for d in depths]) if depths else None
        if found is None:
            return None
        named = at.withColumn("_b", found).where("_b is not null")
        return named.select(*rows.columns, *[F.col(f"_b.{c}") for c in keep])
    for d in depths:
        own = plan.where(F.col("depth") == d).select(plan_key(F.col("bucket"), d).alias("_k"), *keep)
        part = rows.withColumn("_k", key(d)).join(own, "_k").drop("_k")
        out = part if out is None else out.unionByName(part)
    return out


def sampled_splitters(coll: StringCollection, parts: int, fraction: float = 0.01, seed: int = 7, most: int = 100_000) -> list[str]:
    """Up to parts - 1 splitters at even places of a sorted random sample; of a larger sample the `most` rows of the smallest hashes are taken, from all partitions alike."""
    sample = suffixes(coll).sample(False, fraction, seed).select(F.expr("substring(s, pos + 1, 256)").alias("x"), F.xxhash64("sid", "pos", F.lit(seed)).alias("h"))
    texts = sorted((x.x for x in sample.orderBy("h").limit(most).collect()), key=lambda x: x.encode())
    if not texts:
        return []
    at = [texts[len(texts) * i // parts] for i in range(1, parts)]
    return sorted(set(x for x in at if x), key=lambda x: x.encode())


def partition_by_splitters(coll: StringCollection, splitters: list[str], rows: DataFrame | None = None) -> DataFrame:
    """The suffixes (or `rows` of them) with `part`: part i holds the suffixes from splitter i - 1 on and below splitter i; one equal to a splitter goes right."""
    if any(a.encode() >= b.encode() for a, b in zip(splitters, splitters[1:])):
        raise ValueError("splitters must increase")
    suffix = F.expr("substring(s, pos + 1)")
    rows = suffixes(coll) if rows is None else rows
    if len(splitters) <= 64:
        part = sum((F.when(suffix >= x, 1).otherwise(0) for x in splitters), F.lit(0))
        return rows.withColumn("part", part.cast("int"))
    import pandas as pd

    encoded = coll.df.sparkSession.sparkContext.broadcast([x.encode() for x in splitters])

    @F.pandas_udf("int")
    def place(x: pd.Series) -> pd.Series:
        from bisect import bisect_right

        return x.map(lambda t: bisect_right(encoded.value, t.encode()))

    return rows.withColumn("part", place(suffix))


def sids_range(bounds: list[int], sid: str = "sid") -> Column:
    """The range of a string id among sorted bounds, from 0."""
    if not bounds:
        return F.lit(0)
    return F.size(F.filter(F.array(*[F.lit(b).cast("long") for b in bounds]), lambda b: b <= F.col(sid)))


__all__ = ["SIZES", "assign_bucket", "partition_by_splitters", "positions", "prefix_bucket", "refine", "sampled_splitters", "sids_range", "size_table", "size_table_split", "terminal", "with_base"]
