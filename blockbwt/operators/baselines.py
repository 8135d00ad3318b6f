"""What the block-sort method is compared with. Every one returns the same transform."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockbwt.functions.words import Packing
from blockbwt.storage import materialise

from .collection import StringCollection, ordered_ranks, previous, suffixes
from .construct import _tied, bwt_build, packed_suffixes, word_keys
from .fmindex import occ_checkpoints
from .incremental import CapacityError, smaller_in
from .sorters import by_arrow
from .splitters import size_table, with_base


def _state(coll: StringCollection) -> DataFrame:
    """The empty suffixes, in the order of their strings."""
    ends = coll.df.select("sid", F.length("s").alias("pos"), previous(F.col("s"), F.length("s")).alias("sym"))
    return ordered_ranks(ends, ["sid"], "rank").select("rank", "sid", "pos", "sym")


def _shifted(gaps):
    """Ranks of old rows once new ones, whose places less their number are `gaps`, stand between them."""

    @F.pandas_udf("long")
    def shifted(rank: pd.Series) -> pd.Series:
        return rank + np.searchsorted(gaps.value, rank.to_numpy(), side="right")

    return shifted


def _places(live: DataFrame, starts: dict[str, int], step: int = 4096) -> DataFrame:
    """live (rank, sid, pos, sym) with `place`: its symbol's start and the rows of that symbol before it, from counts by block of ranks, so that no task has all rows of a symbol."""
    keyed = live.withColumn("block", F.floor(F.col("rank") / step))
    before = occ_checkpoints(keyed.select(F.col("rank").alias("bwt_pos"), "sym"), step).select("block", "sym", "before")
    base = F.element_at(F.create_map(*[F.lit(x) for k, v in starts.items() for x in (k, v)]), F.col("sym"))
    inside = F.row_number().over(Window.partitionBy("block", "sym").orderBy("rank")) - 1
    return keyed.withColumn("inside", inside).join(before, ["block", "sym"]).withColumn("place", base + F.col("before") + F.col("inside")).drop("inside", "before", "block")


def bwt_column_insertion(coll: StringCollection, mode: str = "rewrite", every: int = 1, checkpoint: str = "written", delta_limit: int = 5_000_000) -> DataFrame:
    """One string column an iteration: after step j the state is the transform of all suffixes of up to j symbols.

    `rewrite` sorts all rows stably by the symbol before them; `delta` computes
    the places of the n new rows alone and shifts the rest by a search in them
    (n 64-bit places a worker, so n is bounded). checkpoint says where the state
    is cut: `written` to the shared folder each `every` iterations, or `none`, which
    keeps the lineage and ranks each symbol's rows in one window, as a plan that
    refers to the state more than once would grow with its power.
    """
    if mode not in ("rewrite", "delta"):
        raise ValueError(mode)
    state = materialise(_state(coll), "columns")
    n, strings = state.count(), coll.df
    if mode == "delta" and n > delta_limit:
        raise CapacityError(f"{n} strings; the delta mode takes {delta_limit}")
    spark = strings.sparkSession
    for j in range(coll.longest()):
        live = state.where("pos > 0")
        totals = {x.sym: x["count"] for x in live.groupBy("sym").count().collect()}  # a row for each symbol
        starts, at = {}, n
        for c in sorted(totals, key=lambda c: c.encode()):
            starts[c], at = at, at + totals[c]
        if not starts:
            break
        if checkpoint == "written" and (mode == "delta" or every == 1):
            placed = _places(live, starts)
        else:
            base = F.element_at(F.create_map(*[F.lit(x) for k, v in starts.items() for x in (k, v)]), F.col("sym"))
            placed = live.withColumn("place", base + F.row_number().over(Window.partitionBy("sym").orderBy("rank")) - 1)
        if mode == "rewrite":
            moved = placed.select(F.col("place").alias("rank"), "sid", (F.col("pos") - 1).alias("pos")).join(strings, "sid")
            new = state.join(strings.select("sid", F.length("s").alias("m")), "sid").where("pos = m").select("rank", "sid", "pos", "sym")
            state = new.unionByName(moved.select("rank", "sid", "pos", previous().alias("sym")))
        else:
            lens = strings.select("sid", F.length("s").alias("m"), "s")
            fresh = placed.select(F.col("place").alias("rank"), "sid", "pos").join(lens, "sid").where(F.col("pos") == F.col("m") - j)
            fresh = materialise(fresh.select("rank", "sid", (F.col("pos") - 1).alias("pos"), previous(F.col("s"), F.col("pos") - 1).alias("sym")), "fresh")
            added = np.sort(np.array([x.rank for x in fresh.select("rank").collect()], np.int64))
            gaps = spark.sparkContext.broadcast(added - np.arange(len(added)))
            state = state.withColumn("rank", _shifted(gaps)("rank")).unionByName(fresh)
        if checkpoint == "written" and (mode == "delta" or j % every == every - 1):
            state = materialise(state, "columns")
    return state.select(F.col("rank").cast("long").alias("bwt_pos"), "sid", F.col("pos").cast("int").alias("pos"), "sym")


def bwt_partition_merge(coll: StringCollection, parts: int = 3, limit: int = 20_000_000) -> DataFrame:
    """The transform of each part of the strings by itself, merged: a suffix's place is its own plus the number of smaller suffixes in every other part.

    The strings of all other parts walk through each part's running counts, which
    is what makes the merge costly. Tasks read those counts; those of a part above
    the limit are joined. What is below a suffix is added up in one shuffle.
    """
    split = materialise(coll.df.withColumn("part", F.pmod(F.xxhash64("sid"), F.lit(parts)).cast("int")), "parts")
    each = [StringCollection(split.where(F.col("part") == p).select("sid", "s"), coll.symbols()) for p in range(parts)]
    own = [materialise(bwt_build(x), "part-bwt") for x in each]
    out = None
    for p in range(parts):
        others = StringCollection(split.where(F.col("part") != p).select("sid", "s"), coll.symbols())
        below = materialise(smaller_in(others, each[p], own[p], limit), "below").select("sid", "pos", "before", F.lit(None).cast("string").alias("sym"))
        placed = own[p].select("sid", "pos", F.col("bwt_pos").alias("before"), "sym").unionByName(below)
        out = placed if out is None else out.unionByName(placed)
    return out.groupBy("sid", "pos").agg(F.sum("before").alias("bwt_pos"), F.max("sym").alias("sym")).select("bwt_pos", "sid", "pos", "sym")


def bwt_rank_doubling(coll: StringCollection, ell: int = 4) -> DataFrame:
    """Ranks of prefixes of 2h symbols from pairs of ranks of h; rows whose rank is settled leave. Takes strings of any length.

    It begins with the buckets of ell symbols, so even its first groups are many;
    terminal ones are settled at once by the string's id.
    """
    sizes = with_base(materialise(size_table(coll, ell), "sizes"))
    from .splitters import prefix_bucket, terminal

    rows = suffixes(coll).select("sid", "pos", previous().alias("sym"), prefix_bucket(ell).alias("bucket"))
    joined = rows.join(sizes.select("bucket", "base", "n"), "bucket")
    # a bucket of equal suffixes may hold one of every string: their ids are ranked over all tasks
    ended = ordered_ranks(joined.where(terminal(F.col("bucket"))).select("sid", "pos", "sym", "base"), ["base", "sid"], "g")
    firsts = ended.groupBy("base").agg(F.min("g").alias("g0"))
    ended = ended.join(firsts, "base").select("sid", "pos", "sym", (F.col("base") + F.col("g") - F.col("g0")).alias("rank"), F.lit(1).cast("long").alias("n"))
    state = materialise(ended.unionByName(joined.where(~terminal(F.col("bucket"))).select("sid", "pos", "sym", F.col("base").alias("rank"), "n")), "ranks")
    h = ell
    while not state.where("n > 1").isEmpty():
        other = state.select("sid", (F.col("pos") - h).alias("pos"), F.col("rank").alias("second"))
        open_rows = state.where("n > 1").join(other, ["sid", "pos"]).withColumnRenamed("rank", "from").drop("n")
        newer = _tied(ordered_ranks(open_rows, ["from", "second"], "g"), ["from", "second"], base="from").select("sid", "pos", "sym", F.col("start").alias("rank"), "n")
        state = materialise(state.where("n = 1").unionByName(newer), "ranks")
        h *= 2
    return state.select(F.col("rank").cast("long").alias("bwt_pos"), "sid", F.col("pos").cast("int").alias("pos"), "sym")


#: Symbols of the longest first prefix of a single string's blocks.
LONGEST_PREFIX = 16


def bwt_single(coll: StringCollection, capacity: int = 3_000_000_000, block: int = 1_000_000) -> DataFrame:
    """One long string, refused above the capacity. Its first blocks are buckets of a prefix that is lengthened until each has `block` suffixes at most, or LONGEST_PREFIX symbols; what is still tied in a block is ordered by ranks of doubled prefixes."""
    rows = coll.df.agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("s")).alias("m")).first()
    if rows.n != 1:
        raise ValueError("one string")
    if rows.m > capacity:
        raise CapacityError(f"{rows.m} symbols; the capacity is {capacity}")
    ell = 2
    while ell < LONGEST_PREFIX:
        sizes = size_table(coll, ell).agg(F.max(F.when(~F.col("terminal"), F.col("n")))).first()[0] or 0
        if sizes <= block:
            break
        ell *= 2
    return bwt_rank_doubling(coll, ell)


def bwt_local(coll: StringCollection, max_rows: int = 2_000_000) -> DataFrame:
    """All suffixes sorted by index in one task, as a device would: refused above max_rows."""
    rows = coll.df.agg(F.sum(F.length("s") + 1)).first()[0] or 0
    if rows > max_rows:
        raise CapacityError(f"{rows} suffixes; one task takes {max_rows}")
    packing = Packing(coll.symbols())
    keys = word_keys(coll, packing)
    listed = packed_suffixes(coll, packing).select(F.lit(0).alias("small_range"), F.lit(0).cast("long").alias("start"), "sid", "pos", previous().alias("sym"), *keys)
    return by_arrow(listed, "index").select(F.col("rank").alias("bwt_pos"), "sid", "pos", "sym")


def bwt_one_partition(coll: StringCollection) -> DataFrame:
    """The plain way, a global window: everything in one task. Shows why places come from sizes."""
    spelled = suffixes(coll).select("sid", "pos", previous().alias("sym"), F.expr("substring(s, pos + 1)").alias("suffix"))
    place = F.row_number().over(Window.orderBy("suffix", "sid")) - 1
    return spelled.select(place.cast("long").alias("bwt_pos"), "sid", "pos", "sym")


__all__ = [x for x in dir() if x.startswith("bwt_") or x == "CapacityError"]
