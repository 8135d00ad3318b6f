"""Construction of the transform by the block-sort method, and its forms of output.

A transform is (bwt_pos, sid, pos, sym): for each place in the order of all
suffixes the suffix and the symbol before it, null before a whole string.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockbwt.functions.words import Packing, digit_keys, utf8_key
from blockbwt.plans.planner import Budget, plan_ranges
from blockbwt.storage import fresh_path, materialise

from .collection import END, StringCollection, explicit_suffixes, ordered_ranks, positions, previous, suffixes
from .sorters import by_partition, sort_ranges
from .splitters import BROADCAST_BUCKETS, assign_bucket, partition_by_splitters, refine, sampled_splitters, size_table, with_base


def bwt_direct(coll: StringCollection) -> DataFrame:
    """The definition itself: all suffixes spelled out and sorted. Quadratic, and refused for large inputs."""
    spelled = explicit_suffixes(coll).join(coll.df, "sid")
    ranked = ordered_ranks(spelled.select("sid", "pos", "suffix", previous().alias("sym")), ["suffix", "sid"], "bwt_pos")
    return ranked.select("bwt_pos", "sid", "pos", "sym")


def make_plan(coll: StringCollection, budget: Budget) -> DataFrame:
    """Sizes by prefix, oversized buckets refined, consecutive ones packed into small ranges and rounds; written once."""
    sizes = refine(coll, materialise(size_table(coll, budget.ell), "sizes"), budget.sort_rows, budget.step or budget.ell)
    return materialise(plan_ranges(with_base(sizes), budget), "plan")


def packed_suffixes(coll: StringCollection, packing: Packing) -> DataFrame:
    """(sid, s, packed, pos): strings are packed before they're exploded, so once each."""
    return coll.df.select("sid", "s", packing.packed(F.col("s")).alias("packed")).select("sid", "s", "packed", F.explode(positions()).alias("pos"))


def word_keys(coll: StringCollection, packing: Packing) -> list:
    return packing.keys(F.col("packed"), F.col("pos"), coll.longest(), F.length("s") - F.col("pos"))


class _Listing:
    """Lists the suffixes of rounds of a plan with their sort keys."""

    def __init__(self, coll: StringCollection, plan: DataFrame, budget: Budget):
        self.coll, self.budget, self.plan = coll, budget, plan
        huge = (F.col("n") > budget.sort_rows) & F.col("terminal")
        stats = plan.agg(F.count(F.lit(1)).alias("n"), F.collect_set("depth").alias("depths"), F.max("small_range").alias("last"), F.max("round").alias("rounds"), F.count_if(huge).alias("huge")).first()
        self.depths, self.ranges, self.rounds = sorted(stats.depths or []), (stats["last"] or 0) + 1, (stats["rounds"] or 0) + 1
        self.small, self.huge = stats.n <= BROADCAST_BUCKETS, stats.huge
        starts = plan.groupBy("small_range").agg(F.min("base").alias("start"))
        self.keyed = plan.join(F.broadcast(starts) if self.small else starts, "small_range").withColumn("huge", huge)
        self.packing = Packing(coll.symbols(), budget.encoding) if budget.encoding not in ("utf8", "digits") else None

    def _keys(self, packing: Packing | None) -> list:
        if packing:
            return word_keys(self.coll, packing)
        if self.budget.encoding == "utf8":
            return [utf8_key(F.col("s"), F.col("pos")).alias("w0")]
        return digit_keys(F.col("s"), self.coll.symbols(), F.col("pos"), self.coll.longest())

    def rows(self, where=None) -> DataFrame:
        """(small_range, start, base, huge, sid, pos, sym, keys): filtered to the buckets wanted before any key is made."""
        plan = self.keyed if where is None else self.keyed.where(where)
        packing, listed = self.packing, ["small_range", "start", "base", "huge"]
        each = packed_suffixes(self.coll, packing) if packing else suffixes(self.coll)
        if packing and all(packing.fits(d) for d in self.depths):
            each = each.withColumn("w", packing.word(F.col("packed"), F.col("pos"), 0))
            left = F.length("s") - F.col("pos")
            placed = assign_bucket(each, plan, self.depths, self.small, listed, lambda d: packing.bucket(d, F.col("w"), left), packing.bucket_of)
        else:
            placed = assign_bucket(each, plan, self.depths, self.small, listed)
        if self.budget.listing == "words":
            return placed.select(*listed, "sid", "pos", previous().alias("sym"), *self._keys(packing))
        # positions alone are held for a round; each one's words come from the strings
        held = materialise(placed.select(*listed, "sid", "pos", previous().alias("sym")), "positions")
        strings = self.coll.df.select("sid", "s", *([packing.packed(F.col("s")).alias("packed")] if packing else []))
        return held.join(strings, "sid").select(*listed, "sid", "pos", "sym", *self._keys(packing))

    def sorted(self, where=None) -> DataFrame:
        if not self.depths:  # no strings, no suffixes
            return self.coll.df.sparkSession.createDataFrame([], "bwt_pos long, sid long, pos int, sym string")
        listed = self.rows(where)
        usual = listed.where(~F.col("huge")) if self.huge else listed
        if self.budget.engine == "catalyst":
            out = by_partition(usual.repartitionById(self.ranges, F.col("small_range")))
        else:
            out = sort_ranges(usual, self.budget.engine, self.budget.digit_bits)
        if self.huge:
            # equal suffixes of more strings than a task sorts: their ids alone order them
            found = ordered_ranks(listed.where("huge").select("base", "sid", "pos", "sym"), ["base", "sid"], "g")
            first = found.groupBy("base").agg(F.min("g").alias("g0"))
            # fewer rows than all suffixes / m1
            ranks = found.join(F.broadcast(first) if self.huge <= BROADCAST_BUCKETS else first, "base")
            out = out.unionByName(ranks.select((F.col("base") + F.col("g") - F.col("g0")).alias("rank"), "sid", "pos", "sym"))
        return out.select(F.col("rank").cast("long").alias("bwt_pos"), "sid", F.col("pos").cast("int").alias("pos"), "sym")


def bwt_build(coll: StringCollection, budget: Budget | None = None, plan: DataFrame | None = None, **changes) -> DataFrame:
    """The block-sort method. Ranks come from the size table, so nothing is sorted or counted as a whole.

    One round is one job; more are a union here, of which each lists its own
    buckets. `bwt_rounds` writes them one after the other.
    """
    budget = replace(budget or Budget(), **changes)
    plan = make_plan(coll, budget) if plan is None else plan
    listing = _Listing(coll, plan, budget)
    if listing.rounds == 1:
        return listing.sorted()
    out = None
    for r in range(listing.rounds):
        part = listing.sorted(F.col("round") == r)
        out = part if out is None else out.unionByName(part)
    return out


def listed_rounds(coll: StringCollection, plan: DataFrame, budget: Budget, where) -> DataFrame:
    """The places of the suffixes in some buckets of a plan: a round's or a node's share."""
    return _Listing(coll, plan, budget).sorted(where)


def bwt_rounds(coll: StringCollection, budget: Budget, path: str | None = None, done: set[int] = frozenset(), by: str = "round") -> str:
    """Runs each round (or node's range) as a job that writes path/round=i, and skips those in `done`: a restart goes on where it stopped."""
    plan = make_plan(coll, budget)
    listing = _Listing(coll, plan, budget)
    path = path or fresh_path(coll.df.sparkSession, "rounds")
    for (r,) in sorted(plan.select(by).distinct().collect()):
        if r not in done:
            listing.sorted(F.col(by) == r).write.mode("overwrite").option("compression", "zstd").parquet(f"{path}/{by}={r}")
    return path


def bwt_sampled(coll: StringCollection, parts: int = 8, fraction: float = 0.01, seed: int = 7) -> DataFrame:
    """Blocks between splitters drawn from a sample; sizes are counted after the fact and vary with the sample, ranks don't."""
    packing = Packing(coll.symbols())
    placed = partition_by_splitters(coll, sampled_splitters(coll, parts, fraction, seed), packed_suffixes(coll, packing))
    cut = materialise(placed.select("part", "sid", "pos", previous().alias("sym"), *word_keys(coll, packing)), "parts")
    sizes = sorted(tuple(x) for x in cut.groupBy("part").count().collect())
    starts, at = [], 0
    for p, n in sizes:
        starts.append((p, at))
        at += n
    begins = coll.df.sparkSession.createDataFrame(starts, "part int, start long")
    listed = cut.join(F.broadcast(begins), "part").withColumnRenamed("part", "small_range")
    out = sort_ranges(listed)
    return out.select(F.col("rank").cast("long").alias("bwt_pos"), "sid", F.col("pos").cast("int").alias("pos"), "sym")


def bwt_refined_ties(coll: StringCollection, carry: int = 1) -> DataFrame:
    """Sorts on the first word, then fetches further words for tied suffixes alone, until none is tied (most significant digits first)."""
    packing = Packing(coll.symbols())
    longest = coll.longest()
    words = packing.words(longest)
    packed = coll.df.select("sid", packing.packed(F.col("s")).alias("packed"), F.length("s").alias("len"))
    word = lambda j: packing.word(F.col("packed"), F.col("pos"), j)
    first = suffixes(coll).select("sid", "pos", previous().alias("sym")).join(packed, "sid")
    rows = _tied(ordered_ranks(first.select("sid", "pos", "sym", word(0).alias("w")), ["w"], "g"), ["w"])
    done = rows.where("n = 1").select("start", "sid", "pos", "sym")
    for j in range(1, words + 1):
        tied = rows.where("n > 1").select("sid", "pos", "sym", "start")
        if tied.isEmpty():
            break
        left = (F.col("len") - F.col("pos")).cast("long")
        fetched = tied.join(packed, "sid")
        # equal words to the end: the length, then the string
        key = [word(j).alias("k")] if j < words else [left.alias("k"), F.col("sid").alias("k2")]
        keys = ["k"] if j < words else ["k", "k2"]
        keyed = fetched.select("sid", "pos", "sym", F.col("start").alias("from"), *key)
        rows = _tied(ordered_ranks(keyed, ["from", *keys], "g"), ["from", *keys], base="from")
        done = done.unionByName(rows.where("n = 1").select("start", "sid", "pos", "sym"))
    return done.select(F.col("start").cast("long").alias("bwt_pos"), "sid", F.col("pos").cast("int").alias("pos"), "sym")


def _tied(ranked: DataFrame, by: list[str], base: str | None = None) -> DataFrame:
    """(sid, pos, sym, start, n): where each group of equal keys begins and how many rows it has. ranked has the place `g` among all ranked rows.

    Groups are aggregated, not windowed: a tie of any size is no task of its own.
    With base, places begin anew where each value of it does.
    """
    ranked = materialise(ranked, "ranked")
    groups = ranked.groupBy(*by).agg(F.min("g").alias("g0"), F.count(F.lit(1)).alias("n"))
    if base is None:
        groups = groups.withColumn("start", F.col("g0"))
    else:
        firsts = ranked.groupBy(base).agg(F.min("g").alias("first"))
        groups = groups.join(firsts, base).withColumn("start", F.col(base) + F.col("g0") - F.col("first"))
    return materialise(ranked.join(groups.select(*by, "start", "n"), by).select("sid", "pos", "sym", "start", "n"), "ties")


def emit(sorted_rows: DataFrame, end: str = "$") -> DataFrame:
    """The transform with a printable end marker."""
    return sorted_rows.withColumn("sym", F.coalesce("sym", F.lit(end)))


def bwt_blocks(bwt: DataFrame, block: int = 65536, end: str = "$") -> DataFrame:
    """(block_id, text): the transform's text in blocks of a bounded length."""
    cells = bwt.select(F.floor(F.col("bwt_pos") / block).alias("block_id"), "bwt_pos", F.coalesce("sym", F.lit(end)).alias("c"))
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("bwt_pos", "c"))), lambda x: x["c"]), "")
    return cells.groupBy("block_id").agg(text.alias("text"))


def bwt_string(bwt: DataFrame, limit: int = 1 << 24, end: str = "$") -> str:
    """The whole text, for small transforms only."""
    if (n := bwt.count()) > limit:
        raise ValueError(f"{n} symbols; the limit is {limit}")
    return "".join(x.text for x in bwt_blocks(bwt, end=end).orderBy("block_id").collect())


def bwt_runs(bwt: DataFrame, block: int = 65536) -> DataFrame:
    """(start, sym, len): maximal runs. Blocks are run apart; a run that reaches the next block's first row is joined to it there."""
    cells = bwt.select("bwt_pos", F.coalesce("sym", F.lit(END)).alias("c"), F.floor(F.col("bwt_pos") / block).alias("b"))
    inside = Window.partitionBy("b").orderBy("bwt_pos")
    # the row before a block's first one is the one before it: a row for each block
    lasts = cells.groupBy("b").agg(F.max_by("c", "bwt_pos").alias("last")).select((F.col("b") + 1).alias("b"), "last")
    marked = cells.join(lasts, "b", "left").withColumn("new", ~F.coalesce(F.lag("c").over(inside), F.col("last")).eqNullSafe(F.col("c")))
    starts = ordered_ranks(marked.where("new").select("bwt_pos", "c"), ["bwt_pos"], "run")
    total = bwt.count()
    following = starts.select((F.col("run") - 1).alias("run"), F.col("bwt_pos").alias("next"))
    joined = starts.join(following, "run", "left")
    return joined.select(F.col("bwt_pos").alias("start"), F.when(F.col("c") != END, F.col("c")).alias("sym"), (F.coalesce("next", F.lit(total)) - F.col("bwt_pos")).alias("len"))


def suffix_order(bwt: DataFrame) -> DataFrame:
    """(rank, sid, pos): the generalised suffix array."""
    return bwt.select(F.col("bwt_pos").alias("rank"), "sid", "pos")


def lcp_table(coll: StringCollection, bwt: DataFrame, block: int = 65536) -> DataFrame:
    """(rank, sid, pos, lcp): symbols shared with the suffix before, which needs one fetch of the strings for each of the two."""
    cells = bwt.select("bwt_pos", "sid", "pos")
    shifted = cells.select((F.col("bwt_pos") + 1).alias("bwt_pos"), F.col("sid").alias("sid0"), F.col("pos").alias("pos0"))
    pairs = cells.join(shifted, "bwt_pos", "left")
    texts = coll.df
    both = pairs.join(texts, "sid").join(texts.select(F.col("sid").alias("sid0"), F.col("s").alias("s0")), "sid0", "left")
    a, b = F.expr("substring(s, pos + 1)"), F.expr("substring(s0, pos0 + 1)")
    n = F.least(F.length(a), F.length(b))
    # the first place where they differ; none (0) means that the shorter one is a prefix
    same = F.when(F.col("s0").isNull(), 0).otherwise(F.coalesce(F.array_position(F.zip_with(F.split(F.substring(a, F.lit(1), n), ""), F.split(F.substring(b, F.lit(1), n), ""), lambda x, y: x == y), False) - 1, n))
    common = F.when(F.col("s0").isNull() | (n == 0), 0).when(same < 0, n).otherwise(same)
    return both.select(F.col("bwt_pos").alias("rank"), "sid", "pos", common.cast("int").alias("lcp"))
