"""Operator 7: chat formatting after cumulative-snapshot collapse (DataFrame functions only).

A logger that saves a conversation after each turn leaves its prefixes behind.
Every turn gets the hash of its conversation up to and with it: the running xor
of two 64-bit hashes of (place, role, text), which a place makes sensitive to
order. A conversation whose whole hash is another's hash before its end is a
snapshot and goes (an anti-join); of equal ones the smallest conv_id stays. The
rest is rendered in parts of PART_TURNS turns.

Running values are taken within ranges of (conv_id, turn, role, text), so a
conversation of any length is spread over tasks, and carried from range to range
by one row for each conversation and range.

Defined results: turns are ordered by turn, role and text, nulls first; rows
that repeat count once; a null role renders as `unknown`, a null text as nothing
(though it's another turn than an empty text); a null conv_id is a conversation
like others; an empty table gives no row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

PART_TURNS = 1000


def _ranged(turns: DataFrame) -> DataFrame:
    order = [F.col(c).asc_nulls_first() for c in ("conv_id", "turn", "role", "text")]
    return common.materialise(turns.repartitionByRange(*order).withColumn("range", F.spark_partition_id()), "turns")


def _carry(rows: DataFrame, value: Column, name: str) -> DataFrame:
    """(range, conv_id, carried): value aggregated over the conversation's earlier ranges."""
    each = rows.groupBy("range", "conv_id").agg(value.alias("v"))
    earlier = Window.partitionBy("conv_id").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    return each.withColumn(name, (F.sum("v") if name == "count_before" else F.bit_xor("v")).over(earlier)).select("range", F.col("conv_id").alias("c"), F.coalesce(name, F.lit(0)).cast("long").alias(name))


def _joined(rows: DataFrame, carried: DataFrame) -> DataFrame:
    other = carried.withColumnRenamed("range", "r")
    return rows.join(other, (F.col("range") == F.col("r")) & F.col("conv_id").eqNullSafe(F.col("c"))).drop("r", "c")


def prefixes(df: DataFrame, conv_id: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """(conv_id, turn, role, text, place, h1, h2): each turn with its place from 1 and the hashes of the conversation so far."""
    turns = df.select(F.col(conv_id).alias("conv_id"), F.col(turn).alias("turn"), F.col(role).alias("role"), F.col(text).alias("text")).distinct()
    rows = _ranged(turns)
    within = Window.partitionBy("range", "conv_id").orderBy(F.col("turn").asc_nulls_first(), F.col("role").asc_nulls_first(), F.col("text").asc_nulls_first())
    counted = _joined(rows, _carry(rows, F.count(F.lit(1)), "count_before"))
    placed = counted.withColumn("place", F.row_number().over(within) + F.col("count_before"))
    said = [F.col("role").isNull(), F.coalesce("role", F.lit("")), F.col("text").isNull(), F.coalesce("text", F.lit(""))]
    hashed = common.materialise(placed.withColumn("e1", F.xxhash64("place", *said)).withColumn("e2", F.xxhash64(F.lit(77), *said, "place")).drop("count_before"), "turn-hashes")
    run = within.rowsBetween(Window.unboundedPreceding, 0)
    for e, h in (("e1", "h1"), ("e2", "h2")):
        carried = _carry(hashed.select("range", "conv_id", e), F.bit_xor(e), f"{h}_before")
        hashed = _joined(hashed, carried).withColumn(h, F.bit_xor(e).over(run).bitwiseXOR(F.col(f"{h}_before")))
    return hashed.select("range", "conv_id", "turn", "role", "text", "place", "h1", "h2")


def collapse(turns: DataFrame) -> DataFrame:
    """(conv_id, n_turns, n_copies) of the conversations that are no other's beginning; turns: what `prefixes` returns."""
    wholes = turns.groupBy("conv_id").agg(F.max(F.struct("place", "h1", "h2")).alias("w")).select("conv_id", "w.place", "w.h1", "w.h2")
    ends = wholes.select(F.col("conv_id").alias("c"), F.col("place").alias("n"))
    inner = turns.select("conv_id", "place", "h1", "h2").join(ends, F.col("conv_id").eqNullSafe(F.col("c")) & (F.col("place") < F.col("n"))).select("place", "h1", "h2").distinct()
    # of equal conversations a null id stays only if there's no other
    one = wholes.groupBy("place", "h1", "h2").agg(F.min("conv_id").alias("conv_id"), F.count(F.lit(1)).alias("n_copies"))
    return one.join(inner, ["place", "h1", "h2"], "left_anti").select("conv_id", F.col("place").alias("n_turns"), "n_copies")


def rendered(role: Column, text: Column) -> Column:
    return F.concat(F.lit("<|"), F.coalesce(role, F.lit("unknown")), F.lit("|>\n"), F.coalesce(text, F.lit("")), F.lit("<|end|>\n"))


def format_chats(df: DataFrame, conv_id: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """(conv_id, part, n_turns, n_copies, text): maximal conversations in parts of PART_TURNS turns."""
    turns = common.materialise(prefixes(df, conv_id, turn, role, text), "prefixes")
    kept = collapse(turns).withColumnRenamed("conv_id", "c")
    body = turns.join(kept, F.col("conv_id").eqNullSafe(F.col("c")))
    part = F.floor((F.col("place") - 1) / PART_TURNS).alias("part")
    said = F.array_sort(F.collect_list(F.struct("place", rendered(F.col("role"), F.col("text")).alias("t"))))
    parts = body.groupBy("conv_id", part).agg(F.max("n_turns").cast("long").alias("n_turns"), F.max("n_copies").alias("n_copies"), said.alias("said"))
    return parts.select("conv_id", "part", "n_turns", "n_copies", F.array_join(F.transform("said", lambda x: x["t"]), "").alias("text"))


def op7_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return format_chats(common.table(spark, sf_dir, "conversations"))


SQL = f"""
WITH t AS (SELECT DISTINCT conv_id, turn, role, text FROM conversations),
p AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS place FROM t),
c AS (SELECT conv_id, count(*) AS n, list({{'r': role, 't': text}} ORDER BY place) AS said FROM p GROUP BY conv_id),
k AS (SELECT min(conv_id) AS conv_id, any_value(n) AS n, count(*) AS n_copies, said FROM c GROUP BY said),
m AS (SELECT * FROM k WHERE NOT EXISTS (SELECT 1 FROM c WHERE c.n > k.n AND c.said[1] = k.said[1] AND c.said[1:k.n] = k.said))
SELECT m.conv_id, CAST((place - 1) // {PART_TURNS} AS BIGINT) AS part, CAST(any_value(n) AS BIGINT) AS n_turns, CAST(any_value(n_copies) AS BIGINT) AS n_copies,
       string_agg('<|' || coalesce(role, 'unknown') || '|>' || chr(10) || coalesce(text, '') || '<|end|>' || chr(10), '' ORDER BY place) AS text
FROM m JOIN p ON p.conv_id IS NOT DISTINCT FROM m.conv_id GROUP BY m.conv_id, part
"""
