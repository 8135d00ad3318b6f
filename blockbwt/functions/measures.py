"""Costs: sizes that are argued, times and memory that are measured, and what follows from either."""

from __future__ import annotations

import math
import resource
import time
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blockbwt.operators.collection import StringCollection


def collection_cost(coll: StringCollection, bits: int = 2) -> DataFrame:
    """One row: strings, symbols, suffixes, and what they take spelled out, as positions, and as a suffix array of 8 bytes."""
    n = F.length("s").cast("long")
    sums = coll.df.agg(F.count(F.lit(1)).alias("strings"), F.sum(n).alias("symbols"), F.sum((n + 1) * (n + 2) / 2).cast("long").alias("explicit_symbols"))
    rows = F.col("strings") + F.col("symbols")
    return sums.select("strings", "symbols", rows.alias("suffixes"), "explicit_symbols", (F.col("explicit_symbols") * bits / 8).alias("explicit_bytes"), F.ceil(F.log2(rows)).cast("long").alias("position_bits"), (F.ceil(F.log2(rows)) * rows / 8).alias("position_bytes"), (rows * 8).alias("suffix_array_bytes"))


def explicit_symbols(strings: int, length: int) -> int:
    """Of all suffixes without the end markers: n m (m + 1) / 2."""
    return strings * length * (length + 1) // 2


def position_bits(suffixes: int) -> int:
    return max(1, math.ceil(math.log2(max(2, suffixes))))


def resident_bits(length: int, symbol_bits: int, word: int, index: int) -> dict[str, int]:
    """Bits a string keeps where the sort is: whole strings and indices, or one word and an index."""
    return {"whole": -(-length * symbol_bits // word) * word + index, "word": word + index}


def radix_passes(length: int, symbol_bits: int, word: int) -> int:
    return -(-length * symbol_bits // word)


def position_table(sizes: DataFrame) -> DataFrame:
    """sizes (strings, length) -> with `explicit_symbols` and the `bits` of a position among all suffixes, in whole numbers."""
    m = F.col("length")
    # the bits of the largest position, which no logarithm could round
    bits = F.length(F.bin(F.greatest(F.lit(1).cast("long"), F.col("strings") * (m + 1) - 1))).cast("long")
    return sizes.withColumn("explicit_symbols", F.expr("strings * (length * (length + 1) div 2)")).withColumn("bits", bits)


def resident_table(grid: DataFrame, index: int) -> DataFrame:
    """grid (length, bits, word) -> with what `resident_bits` and `radix_passes` give: `whole`, `one_word` and `passes`."""
    rows = grid.withColumn("passes", F.expr("(cast(length as long) * bits + word - 1) div word"))
    return rows.select("length", "bits", "word", (F.col("passes") * F.col("word") + index).alias("whole"), (F.col("word") + index).cast("long").alias("one_word"), "passes")


def speedups(times: DataFrame, by: str, unit: str, seconds: str) -> DataFrame:
    """times (by, unit, seconds) -> with `speedup` over the smallest unit of each group, and `efficiency`."""
    first = F.first_value(seconds).over(Window.partitionBy(by).orderBy(unit))
    return times.withColumn("speedup", F.round(first / F.col(seconds), 6)).withColumn("efficiency", F.round(first / F.col(seconds) / F.col(unit), 6))


def growth(times: DataFrame, by: str, length: str, seconds: str) -> DataFrame:
    """Relative growth over the shortest strings of each method, at equal symbols."""
    first = F.first_value(seconds).over(Window.partitionBy(by).orderBy(length))
    return times.withColumn("growth", F.round(F.col(seconds) / first - 1, 6))


def balance_report(sizes: DataFrame, part: str, n: str = "n") -> DataFrame:
    each = sizes.groupBy(part).agg(F.sum(n).alias("n"))
    return each.agg(F.count(F.lit(1)).alias("parts"), F.max("n").alias("largest"), F.round(F.max("n") / F.avg("n"), 6).alias("imbalance"))


def size_report(sizes: DataFrame) -> DataFrame:
    """(depth, terminal, buckets, suffixes, largest) of a size table."""
    return sizes.groupBy("depth", "terminal").agg(F.count(F.lit(1)).alias("buckets"), F.sum("n").alias("suffixes"), F.max("n").alias("largest"))


def verify_bwt(coll: StringCollection, bwt: DataFrame) -> DataFrame:
    """One row of violations, all 0 for a right transform: places that aren't a permutation, suffixes missing or twice, wrong symbols, neighbours out of order.

    Neighbours are compared where both strings are fetched; no other transform is needed.
    """
    texts = coll.df
    rows = texts.agg(F.sum(F.length("s") + 1)).first()[0] or 0
    cells = bwt.join(texts, "sid")
    symbol = F.when(F.col("pos") > 0, F.substring("s", F.col("pos"), F.lit(1)))
    one = cells.agg(
        (F.lit(rows) - F.count_distinct("sid", "pos")).cast("long").alias("missing"),
        (F.count(F.lit(1)) - F.count_distinct("bwt_pos")).cast("long").alias("repeated"),
        F.count_if((F.col("bwt_pos") < 0) | (F.col("bwt_pos") >= rows)).cast("long").alias("outside"),
        F.count_if(~F.col("sym").eqNullSafe(symbol)).cast("long").alias("wrong_symbols"),
    )
    keyed = cells.select("bwt_pos", "sid", F.expr("substring(s, pos + 1)").alias("x"))
    after = keyed.select((F.col("bwt_pos") - 1).alias("bwt_pos"), F.col("sid").alias("sid2"), F.col("x").alias("y"))
    bad = keyed.join(after, "bwt_pos").where((F.col("x") > F.col("y")) | ((F.col("x") == F.col("y")) & (F.col("sid") >= F.col("sid2"))))
    return one.crossJoin(bad.agg(F.count(F.lit(1)).alias("out_of_order")))


@contextmanager
def timed(times: dict[str, float], phase: str):
    began = time.perf_counter()
    try:
        yield
    finally:
        times[phase] = times.get(phase, 0.0) + time.perf_counter() - began


def run_to_noop(df: DataFrame) -> float:
    """Seconds of a plan whose rows go nowhere."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def io_bytes(spark: SparkSession) -> dict[str, int]:
    """Bytes of all stages so far, by the status store: read and written by scans and sinks, and shuffled."""
    sc = spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    empty = sc._jvm.java.util.ArrayList()
    stages = sc._jsc.sc().statusStore().stageList(empty, False, False, sc._gateway.new_array(sc._jvm.double, 0), empty)
    out = {"read": 0, "written": 0, "shuffled": 0}
    for i in range(stages.size()):
        x = stages.apply(i)
        out["read"] += x.inputBytes()
        out["written"] += x.outputBytes()
        out["shuffled"] += x.shuffleWriteBytes()
    return out


def peak_memory(spark: SparkSession) -> dict[str, float]:
    """MB at peak, with where each figure is from: the driver's Python by its resource usage, the JVM's pools by their own peaks."""
    pools = spark._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans()
    jvm = sum(pools.get(i).getPeakUsage().getUsed() for i in range(pools.size()))
    return {"python_rss_mb": resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024, "jvm_pools_mb": jvm / 1e6}


PUBLISHED_NODES = {
    ("included", 1): (565, 3108, 6886),
    ("included", 2): (338, 1797, 3998),
    ("included", 3): (266, 1426, 3071),
    ("included", 4): (230, 1192, 2584),
    ("excluded", 1): (468, 2624, 5882),
    ("excluded", 2): (241, 1317, 2994),
    ("excluded", 3): (169, 944, 2067),
    ("excluded", 4): (133, 712, 1580),
}
PUBLISHED_LENGTHS = {"column insertion": ((100, 6141), (200, 9334), (400, 23950)), "block sort": ((100, 565), (200, 724), (400, 1269))}
PUBLISHED_BASELINE = ((100, 6141), (500, 23094), (1000, 46899))
