"""Queries on a transform: symbol starts, rank checkpoints, LF mapping, inversion, and pattern search.

Strings end with different markers, so a marker never maps by counting: rows
before whole strings end a walk.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockbwt.storage import materialise

from . import packedkmers
from .collection import END, StringCollection, ordered_ranks
from .packedsort import packable

STEP = 1024


def symbol_starts(bwt: DataFrame) -> DataFrame:
    """(sym, n, start): suffixes that begin with each symbol; the empty ones, one a string, come first under a null."""
    counts = bwt.groupBy("sym").agg(F.count(F.lit(1)).alias("n"))
    before = F.sum("n").over(Window.orderBy(F.col("sym").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, -1))
    return counts.select("sym", "n", F.coalesce(before, F.lit(0)).alias("start"))  # a row for each symbol


@dataclass
class Index:
    """bwt; blocks (block, text, counts: running counts of each symbol before the block); starts by symbol; step."""

    bwt: DataFrame
    blocks: DataFrame
    starts: dict[str, tuple[int, int]]
    step: int


def occ_checkpoints(bwt: DataFrame, step: int = STEP) -> DataFrame:
    """(block, sym, n, before): each symbol's number in a block and before it. Sums go over groups of blocks first, so no task has them all."""
    own = bwt.where("sym is not null").groupBy(F.floor(F.col("bwt_pos") / step).alias("block"), "sym").agg(F.count(F.lit(1)).alias("n"))
    grid = bwt.select(F.floor(F.col("bwt_pos") / step).alias("block")).distinct().crossJoin(F.broadcast(bwt.where("sym is not null").select("sym").distinct()))
    full = grid.join(own, ["block", "sym"], "left").select("block", "sym", F.coalesce("n", F.lit(0)).alias("n"), F.floor(F.col("block") / 1024).alias("g"))
    groups = full.groupBy("g", "sym").agg(F.sum("n").alias("t"))
    earlier = F.sum("t").over(Window.partitionBy("sym").orderBy("g").rowsBetween(Window.unboundedPreceding, -1))
    inside = F.sum("n").over(Window.partitionBy("g", "sym").orderBy("block").rowsBetween(Window.unboundedPreceding, -1))
    starts = groups.select("g", "sym", F.coalesce(earlier, F.lit(0)).alias("start"))
    return full.join(starts, ["g", "sym"]).select("block", "sym", "n", (F.coalesce(inside, F.lit(0)) + F.col("start")).alias("before"))


def build_index(bwt: DataFrame, step: int = STEP) -> Index:
    """Written once: searches read its blocks at every step."""
    bwt = materialise(bwt, "bwt")
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("bwt_pos", F.coalesce("sym", F.lit(END)).alias("c")))), lambda x: x["c"]), "")
    texts = bwt.groupBy(F.floor(F.col("bwt_pos") / step).alias("block")).agg(text.alias("text"))
    before = occ_checkpoints(bwt, step).groupBy("block").agg(F.map_from_entries(F.collect_list(F.struct("sym", "before"))).alias("counts"))
    starts = {x.sym: (x.start, x.n) for x in symbol_starts(bwt).where("sym is not null").collect()}
    return Index(bwt, materialise(texts.join(before, "block", "left"), "blocks"), starts, step)


def lf(bwt: DataFrame, step: int = STEP) -> DataFrame:
    """(bwt_pos, next_pos): the place of the suffix that is one symbol longer; null where a string begins."""
    starts = symbol_starts(bwt).where("sym is not null").select("sym", F.col("start").alias("first"))
    keyed = bwt.select("bwt_pos", "sym", F.floor(F.col("bwt_pos") / step).alias("block"))
    inside = F.row_number().over(Window.partitionBy("block", "sym").orderBy("bwt_pos")) - 1
    placed = keyed.where("sym is not null").withColumn("inside", inside).join(occ_checkpoints(bwt, step).select("block", "sym", "before"), ["block", "sym"]).join(F.broadcast(starts), "sym")
    moved = placed.select("bwt_pos", (F.col("first") + F.col("before") + F.col("inside")).alias("next_pos"))
    return moved.unionByName(bwt.where("sym is null").select("bwt_pos", F.lit(None).cast("long").alias("next_pos")))


def invert(bwt: DataFrame) -> DataFrame:
    """(sid, s) back from the transform. Place i below n is the end of string i in the order of ids; every other place finds its end and how far it is by doubling, so a string of m symbols takes log2(m) joins of (place, distance) pairs, and each place gives its one symbol."""
    n = bwt.where("sym is null").count()
    state = materialise(lf(bwt).where("next_pos is not null").select(F.col("next_pos").alias("at"), F.col("bwt_pos").alias("up"), F.lit(1).cast("long").alias("far")), "walk")
    while not state.where(F.col("up") >= n).isEmpty():
        then = state.select(F.col("at").alias("up"), F.col("up").alias("then"), F.col("far").alias("more"))
        moved = state.where(F.col("up") >= n).join(then, "up").select("at", F.col("then").alias("up"), (F.col("far") + F.col("more")).alias("far"))
        state = materialise(state.where(F.col("up") < n).unionByName(moved), "walk")
    ends = bwt.where(F.col("bwt_pos") < n).select(F.col("bwt_pos").alias("at"), F.col("bwt_pos").alias("up"), F.lit(0).cast("long").alias("far"))
    symbols = state.unionByName(ends).join(bwt.select(F.col("bwt_pos").alias("at"), "sym"), "at").where("sym is not null")
    said = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct((-F.col("far")).alias("k"), "sym"))), lambda x: x["sym"]), "")
    texts = symbols.groupBy(F.col("up").alias("bwt_pos")).agg(said.alias("s"))
    ids = bwt.where(F.col("bwt_pos") < n).select("bwt_pos", "sid")
    return ids.join(texts, "bwt_pos", "left").select("sid", F.coalesce("s", F.lit("")).alias("s"))


def _intervals(index: Index, patterns: DataFrame, every: int = 6) -> DataFrame:
    """(pid, pattern, lo, hi) of patterns (pid, pattern), all searched backwards together, one symbol a step; unmatched ones leave."""
    total = index.bwt.count()
    state = patterns.select("pid", "pattern", F.lit(0).cast("long").alias("lo"), F.lit(total).cast("long").alias("hi"), F.length("pattern").alias("left"))
    longest = patterns.agg(F.max(F.length("pattern"))).first()[0] or 0
    if not index.starts:
        return state.where("left = 0").select("pid", "pattern", "lo", "hi")
    first = F.create_map(*[F.lit(x) for k, (v, _) in index.starts.items() for x in (k, v)])
    done = state.where("left = 0")
    state = state.where("left > 0")
    blocks = index.blocks.select(F.col("block").alias("b"), "text", "counts")
    for i in range(longest):
        ends = state.select("pid", "pattern", "left", F.explode(F.array(F.struct(F.lit(0).alias("end"), F.col("lo").alias("r")), F.struct(F.lit(1).alias("end"), F.col("hi").alias("r")))).alias("e"))
        ends = ends.select("pid", "pattern", "left", "e.end", "e.r", F.substring("pattern", F.col("left"), F.lit(1)).alias("c"))
        # a place at the very end belongs to the last block
        asked = ends.withColumn("b", F.floor((F.col("r") - F.when(F.col("r") == total, 1).otherwise(0)) / index.step))
        head = F.substring("text", F.lit(1), (F.col("r") - F.col("b") * index.step).cast("int"))
        count = F.length(head) - F.length(F.replace(head, F.col("c"), F.lit("")))
        found = asked.join(blocks, "b").select("pid", "pattern", "left", "end", (F.element_at(first, F.col("c")) + F.coalesce(F.element_at("counts", F.col("c")), F.lit(0)) + count).alias("r"))
        both = found.groupBy("pid", "pattern", "left").agg(F.min(F.when(F.col("end") == 0, F.col("r"))).alias("lo"), F.min(F.when(F.col("end") == 1, F.col("r"))).alias("hi"))
        state = both.where("lo is not null and hi > lo").select("pid", "pattern", "lo", "hi", (F.col("left") - 1).alias("left"))
        if i % every == every - 1:
            state = materialise(state, "intervals")
        done = done.unionByName(state.where("left = 0"))
        state = state.where("left > 0")
    return done.select("pid", "pattern", "lo", "hi")


def _searched(index: Index, patterns: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(pid, pattern), and (pattern, lo, hi) of the different patterns that occur: equal ones are searched once."""
    asked = materialise(patterns.select("pid", "pattern"), "patterns")
    once = materialise(ordered_ranks(asked.select("pattern").distinct(), ["pattern"], "pid").select("pid", "pattern"), "patterns")
    return asked, _intervals(index, once).select("pattern", "lo", "hi")


def count_patterns(index: Index, patterns: DataFrame) -> DataFrame:
    """(pid, occurrences) of every pattern; those of an empty one are all suffixes."""
    asked, found = _searched(index, patterns)
    counted = asked.join(found, "pattern", "left")
    return counted.select("pid", F.coalesce(F.col("hi") - F.col("lo"), F.lit(0)).cast("long").alias("occurrences"))


def locate_patterns(index: Index, patterns: DataFrame) -> DataFrame:
    """(pid, sid, pos): intervals joined with the transform by blocks of places."""
    asked, spans = _searched(index, patterns)
    each = spans.select("pattern", "lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") / index.step), F.floor((F.col("hi") - 1) / index.step))).alias("block"))
    rows = index.bwt.select("bwt_pos", "sid", "pos", F.floor(F.col("bwt_pos") / index.step).alias("block"))
    places = each.join(rows, "block").where("bwt_pos >= lo and bwt_pos < hi").select("pattern", "sid", "pos")
    return places.join(asked, "pattern").select("pid", "sid", "pos")


def scan_patterns(coll: StringCollection, patterns: DataFrame) -> DataFrame:
    """(pid, sid, pos) without an index: every suffix's prefix of a pattern's length, by equi-joins of one length at a time. Patterns of 9 to 31 symbols are looked for in packed strings, range by range, and no suffix is a row."""
    lens = [x[0] for x in patterns.select(F.length("pattern")).distinct().collect() if x[0] is not None]
    each = coll.df.select("sid", "s", F.explode(F.sequence(F.lit(0), F.length("s"))).alias("pos"))
    packed = [n for n in lens if packedkmers.FIRST < n <= packedkmers.LONGEST] if packable(coll) else []
    out = packedkmers.pattern_places(coll, patterns, packed) if packed else None
    lens = [n for n in lens if n not in packed]
    for n in sorted(lens):
        some = patterns.where(F.length("pattern") == n).select("pid", "pattern")
        hit = each.withColumn("pattern", F.substring("s", F.col("pos") + 1, F.lit(n))).where(F.length("pattern") == n).join(some, "pattern").select("pid", "sid", "pos")
        out = hit if out is None else out.unionByName(hit)
    return out


def map_reads(index: Index, reads: StringCollection) -> DataFrame:
    """(read, sid, pos): exact places of reads in the indexed strings."""
    return locate_patterns(index, reads.df.select(F.col("sid").alias("pid"), F.col("s").alias("pattern"))).withColumnRenamed("pid", "read")


def map_reads_approx(index: Index, reference: StringCollection, reads: StringCollection, k: int, seed: int = 16) -> DataFrame:
    """(read, sid, pos, mismatches <= k) of reads of any lengths: of k + 1 pieces of a read one is exact, so the index finds each piece's first `seed` symbols, and whole reads are then compared.

    A read has to have more than k symbols, so that every piece has one.
    """
    if not reads.df.where(F.length("s") <= k).isEmpty():
        raise ValueError("reads are too short for so many mismatches")
    piece = F.expr(f"length(s) div {k + 1}")
    each = reads.df.select(F.col("sid").alias("read"), F.col("s").alias("r"), piece.alias("piece"), F.explode(F.sequence(F.lit(0), F.lit(k))).alias("j"))
    cut = each.select("read", (F.col("j") * F.col("piece")).cast("int").alias("off"), F.substring("r", (F.col("j") * F.col("piece") + 1).cast("int"), F.least(F.col("piece"), F.lit(seed)).cast("int")).alias("pattern"))
    cut = materialise(cut, "seeds")
    # equal seeds are searched once
    patterns = materialise(ordered_ranks(cut.select("pattern").distinct(), ["pattern"], "pid").select("pid", "pattern"), "patterns")
    places = locate_patterns(index, patterns).join(patterns, "pid").select("pattern", "sid", F.col("pos").alias("at"))
    found = cut.join(places, "pattern").select("read", "sid", (F.col("at") - F.col("off")).cast("int").alias("pos")).where("pos >= 0").distinct()
    texts = found.join(reads.df.select(F.col("sid").alias("read"), F.col("s").alias("r")), "read").join(reference.df.select("sid", F.col("s").alias("t")), "sid")
    fits = texts.where(F.col("pos") + F.length("r") <= F.length("t"))
    window = F.substring("t", F.col("pos") + 1, F.length("r"))
    # equal lengths: mismatches are places that differ
    apart = F.aggregate(F.zip_with(F.split("r", ""), F.split(window, ""), lambda a, b: (a != b).cast("int")), F.lit(0), lambda a, x: a + x)
    return fits.withColumn("mismatches", apart).where(F.col("mismatches") <= k).select("read", "sid", "pos", "mismatches")
