"""Range plans: consecutive buckets packed for a task's, a round's and a node's capacity."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockbwt.operators.collection import ordered_ranks
from blockbwt.storage import materialise

#: Buckets that the driver may plan by itself; beyond it, groups are packed apart.
DRIVER_BUCKETS = 1_000_000
PLAN = "bucket string, depth int, terminal boolean, n long, base long, small_range int, round int, node int"


@dataclass(frozen=True)
class Budget:
    """sort_rows: suffixes one task sorts (m1). round_rows: suffixes listed at once (m2). ell: symbols of the first prefix."""

    sort_rows: int = 1_000_000
    round_rows: int | None = None
    ell: int = 4
    nodes: int = 1
    step: int | None = None
    encoding: str = "auto"
    engine: str = "catalyst"
    #: Bits of a word sorted at once by the `lsd` engine; 62 is a whole word.
    digit_bits: int = 62
    #: What's listed for a suffix: its `words`, or its `position` alone, whose words are fetched from the strings where it's sorted.
    listing: str = "words"

    def __post_init__(self):
        if self.sort_rows < 1 or self.ell < 1 or self.nodes < 1:
            raise ValueError("capacities, prefix length and nodes have to be 1 or more")
        if self.round_rows is not None and self.sort_rows > self.round_rows:
            raise ValueError("a task may not sort more than a round lists")
        if self.listing not in ("words", "position") or not 1 <= self.digit_bits <= 62:
            raise ValueError("a listing is words or position; a digit has 1 to 62 bits")

    @classmethod
    def plan(cls, cluster_bytes: int, task_bytes: int, row_bytes: int, suffixes: int, sigma: int, nodes: int = 1) -> Budget:
        """Capacities from memory: rows of row_bytes; a prefix long enough that an even bucket fills a quarter of a task."""
        m1, m2 = max(1, task_bytes // row_bytes), max(1, cluster_bytes // row_bytes)
        ell = 1
        while ell < 12 and suffixes / sigma**ell > m1 / 4:
            ell += 1
        return cls(m1, m2 if m2 < suffixes else None, ell, nodes) if m2 >= m1 else cls(m2, m2, ell, nodes)


def sort_rows(task_bytes: int, word_bits: int = 64, index_bits: int = 64) -> int:
    """Rows of the index sort in a task: a word and an index each, whatever the suffixes' length."""
    return task_bytes * 8 // (word_bits + index_bits)


def greedy(sizes: list[int], limit: int) -> list[int]:
    """Range of each size in order; a range never exceeds the limit unless one size does by itself."""
    out, at, held = [], -1, limit + 1
    for n in sizes:
        if held + n > limit:
            at, held = at + 1, 0
        held += n
        out.append(at)
    return out


def plan_ranges(based: DataFrame, budget: Budget, most: int = DRIVER_BUCKETS) -> DataFrame:
    """The size table with base offsets -> PLAN. Rounds are ranges under m2, small ranges are ranges under m1 within a round; a node has about the Nth part.

    The driver packs greedily where the counted buckets are at most `most`;
    longer tables are packed where they are.
    """
    if based.count() > most:
        return plan_ranges_distributed(based, budget)
    rows = sorted(based.collect(), key=lambda x: x.base)
    total = sum(x.n for x in rows)
    rounds = greedy([x.n for x in rows], budget.round_rows or max(1, total))
    node = [min(budget.nodes - 1, int(budget.nodes * (x.base + x.n / 2) / max(1, total))) for x in rows]
    out, small, at = [], 0, 0
    while at < len(rows):  # a small range lies within one round and one node
        end = at
        while end < len(rows) and (rounds[end], node[end]) == (rounds[at], node[at]):
            end += 1
        inner = greedy([x.n for x in rows[at:end]], budget.sort_rows)
        out += [(x.bucket, x.depth, x.terminal, x.n, x.base, small + k, rounds[at], node[at]) for x, k in zip(rows[at:end], inner)]
        small, at = small + inner[-1] + 1, end
    return based.sparkSession.createDataFrame(out, PLAN)


def slot(base: Column, n: Column, limit: int) -> Column:
    """A number that rises with `base` and under which the sizes n never add up to more than limit, unless one does by itself.

    Items of up to half the limit share the half that they begin in, so they end
    within the next half. A larger item is alone: it begins last in its half.
    """
    half = max(1, limit // 2)
    return F.floor(base / F.lit(half)) * 2 + (n > half).cast("long")


def plan_ranges_distributed(based: DataFrame, budget: Budget) -> DataFrame:
    """PLAN for size tables of any length. A bucket's range follows from its base offset and size alone; ranges, of which there are about four for each m1 suffixes at most, are numbered by a distributed rank, and rounds and nodes are made of whole ranges."""
    rows = materialise(based.withColumn("slot", slot(F.col("base"), F.col("n"), budget.sort_rows)), "slots")
    ranges = rows.groupBy("slot").agg(F.min("base").alias("start"), F.sum("n").alias("size"))
    total = max(1, rows.agg(F.sum("n")).first()[0] or 1)
    node = F.least(F.lit(budget.nodes - 1), F.floor(F.lit(budget.nodes) * (F.col("start") + F.col("size") / 2) / F.lit(total)))
    limit = budget.round_rows or total
    kept = ranges.withColumn("node", node.cast("int")).withColumn("wide", slot(F.col("start"), F.col("size"), limit) if limit < total else F.lit(0).cast("long"))
    numbered = ordered_ranks(kept, ["slot"], "small_range")
    rounds = ordered_ranks(numbered.select("wide").distinct(), ["wide"], "round")
    named = numbered.join(rounds, "wide").select("slot", F.col("small_range").cast("int").alias("small_range"), F.col("round").cast("int").alias("round"), "node")
    return rows.join(named, "slot").select(*[c.split()[0] for c in PLAN.split(", ")])


def plan_summary(plan: DataFrame, limit: int) -> DataFrame:
    """Rounds, scans (one more for the sizes), small ranges, the largest one, fill and imbalance."""
    each = plan.groupBy("round", "small_range").agg(F.sum("n").alias("n"))
    return each.agg(
        F.count_distinct("round").alias("rounds"),
        (F.count_distinct("round") + 1).alias("scans"),
        F.count(F.lit(1)).alias("small_ranges"),
        F.max("n").alias("largest"),
        F.round(F.avg("n") / limit, 6).alias("fill"),
        F.round(F.max("n") / F.avg("n"), 6).alias("imbalance"),
    )
