"""Operator 10: mixing sources to target weights (DataFrame functions only).

Efraimidis-Spirakis sampling: a document's key is an exponential variate, drawn
from a hash of its id, over its quality weight; a source's documents in order of
their keys are a weighted sample without replacement. A source whose target is
e times its size and a rest takes e complete epochs, and then documents in that
order up to the rest; the one document at the edge gives its first words only.

A source may hold any share of the rows, so it's never sorted as a whole. Keys
fall into buckets of rising keys; sums by (source, bucket) say which buckets are
wholly in or out, and only the one bucket at a source's edge is sorted. A key
depends on the id, the size and the text, so rows that share an id, null ones
too, have keys of their own; only equal rows share one, and stand at one place.

Defined results: a null text has size 0; null sources are one source, the last;
null quality or none weighs 1; rows that repeat are each taken on their own;
sources of size 0 have target 0 and take nothing; an empty table gives no row.
The weights' order is by code point, which is Spark's order of strings.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blockbwt.operators.collection import ordered_ranks

from . import common

WEIGHTS, SHARE, MOST = (5, 2, 1), 1.5, 2
SEED = 20_117
#: About as many rows are sorted at a source's edge.
BUCKET_ROWS, LEAST_BUCKETS = 100_000, 256
#: So many sources are ranked in one task; more by ranges.
ONE_TASK_SOURCES = 1_000_000


def words_in(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(common.WORD)), F.lit(0)).cast("long")


def quality_weight(quality: Column) -> Column:
    """Of labelled documents: good ones come twice as early on average, bad ones half as early."""
    return F.when(quality == 1, 2.0).when(quality == 0, 0.5).otherwise(1.0)


def sampling_key(doc_id: Column, size: Column, text_hash: Column, weight: Column, seed: int = SEED) -> Column:
    """An exponential variate over the weight; the same for equal rows, and from run to run."""
    uniform = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.coalesce(doc_id, F.lit(-1)), size, text_hash), 11) + 0.5) / float(1 << 53)
    return -F.log(uniform) / weight


def targets(sources: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """(source, source_size) -> with `target`: min(most * size, level * weight), the fixed point of resharing the excess.

    One row a source; each round is one small aggregate, and a round that caps
    no further source is the last. Beyond the ranking, nothing is in one task.
    """
    if sources.count() <= ONE_TASK_SOURCES:
        sources = sources.withColumn("_rank", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1)
    else:
        sources = ordered_ranks(sources, [F.col("source").asc_nulls_last()], "_rank")
    rank = F.col("_rank")
    weight = F.element_at(F.array(*map(F.lit, weights)), (rank % len(weights) + 1).cast("int")).cast("double")
    ranked = common.materialise(sources.select("source", "source_size", weight.alias("weight"), (F.col("source_size") * float(most)).alias("cap")), "sources")
    total = (ranked.agg(F.sum("source_size")).first()[0] or 0) * share
    level, open_weight = 0.0, None
    while total:
        capped = F.col("cap") < F.col("weight") * level
        full, rest = ranked.agg(F.sum(F.when(capped, F.col("cap"))), F.sum(F.when(~capped, F.col("weight")))).first()
        if rest is None or rest == open_weight:
            break
        level, open_weight = (total - (full or 0.0)) / rest, rest
    return ranked.select("source", "source_size", F.least("cap", F.col("weight") * level).alias("target"))


def mix(df: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", quality: DataFrame | None = None, weights: tuple = WEIGHTS, share: float = SHARE, most: float = MOST, seed: int = SEED, carry: bool = False) -> DataFrame:
    """(doc_id, source, size, source_size, target, taken), a row for each row of df. quality: (doc_id, quality_weight) of some documents.

    With `carry`, a column `row` holds the row of df itself, for `take`.
    """
    rows = df.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(source).alias("source"), words_in(F.col(text)).alias("size"), F.xxhash64(F.col(text)).alias("h"), *([F.struct(*df.columns).alias("row")] if carry else []))
    if quality is not None:
        rows = rows.join(quality.groupBy("doc_id").agg(F.max("quality_weight").alias("quality_weight")), "doc_id", "left")
    else:
        rows = rows.withColumn("quality_weight", F.lit(1.0))
    rows = rows.withColumn("key", sampling_key(F.col("doc_id"), F.col("size"), F.col("h"), F.coalesce("quality_weight", F.lit(1.0)), seed)).drop("quality_weight", "h")
    sized = common.materialise(rows, "sizes")
    n = sized.count()
    buckets = max(LEAST_BUCKETS, n // BUCKET_ROWS)
    # 1 - exp(-key) rises with the key and is uniform where weights are 1
    sized = sized.withColumn("bucket", F.least(F.floor((1 - F.exp(-F.col("key"))) * buckets), F.lit(buckets - 1)))
    sums = common.materialise(sized.groupBy("source", "bucket").agg(F.sum("size").alias("n")), "sums")
    wanted = targets(sums.groupBy("source").agg(F.sum("n").alias("source_size")), weights, share, most)
    wanted = wanted.withColumn("epochs", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0)).withColumn("rest", F.round(F.col("target") - F.col("epochs") * F.col("source_size")).cast("long"))
    before = F.sum("n").over(Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1))
    steps = sums.withColumn("bucket_before", F.coalesce(before, F.lit(0))).withColumnRenamed("source", "s").withColumnRenamed("bucket", "b")
    plan = steps.join(wanted, F.col("s").eqNullSafe(F.col("source"))).select("s", "b", "n", "bucket_before", "source_size", "target", "epochs", "rest")
    here = sized.join(F.broadcast(plan) if _small(plan) else plan, F.col("source").eqNullSafe(F.col("s")) & (F.col("bucket") == F.col("b")))
    edge = (F.col("bucket_before") < F.col("rest")) & (F.col("bucket_before") + F.col("n") > F.col("rest"))
    whole = F.when(F.col("bucket_before") < F.col("rest"), F.col("size")).otherwise(0)
    keep = ["doc_id", "source", "size", "source_size", "target", *(["row"] if carry else [])]
    sure = here.where(~edge).select(*keep, (F.col("epochs") * F.col("size") + whole).cast("long").alias("taken"))
    order = Window.partitionBy("source", "bucket").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    left = F.col("rest") - F.col("bucket_before") - F.coalesce(F.sum("size").over(order), F.lit(0))
    part = F.greatest(F.lit(0), F.least(F.col("size"), left))
    torn = here.where(edge).select(*keep, (F.col("epochs") * F.col("size") + part).cast("long").alias("taken"))
    return sure.unionByName(torn)


def _small(plan: DataFrame, most: int = 200_000) -> bool:
    """Whether the plan's rows, of about 80 bytes, are proven few enough to broadcast; else the join shuffles."""
    return plan.count() <= most


def labelled_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    return common.table(spark, sf_dir, "labels").select("doc_id", quality_weight(F.col("quality")).alias("quality_weight"))


def apply(df: DataFrame, mixed: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """`take` for a mix without its rows, mixed: (doc_id, size, taken). doc_id has to be unique here; null ids aren't taken."""
    took = mixed.select(F.col("doc_id").alias(doc_id), "size", "taken").where("taken > 0")
    return _copies(df.join(took, doc_id), text).select(*df.columns)


def take(mixed: DataFrame, text: str = "text") -> DataFrame:
    """The rows that a mix carries as often as it takes each, whatever their ids; what isn't a whole copy is the text's first words."""
    each = mixed.where("taken > 0").select("row.*", F.col("size").alias("_size"), F.col("taken").alias("_taken"))
    return _copies(each, text, "_size", "_taken").drop("_size", "_taken", "_first")


def _copies(took: DataFrame, text: str, size: str = "size", taken: str = "taken") -> DataFrame:
    copies = F.array_repeat(F.lit(None).cast("long"), F.expr(f"cast({taken} div {size} as int)"))
    cuts = F.when(F.expr(f"{taken} % {size} > 0"), F.array(F.expr(f"{taken} % {size}"))).otherwise(F.array().cast("array<bigint>"))
    each = took.withColumn("_first", F.explode(F.concat(copies, cuts)))
    words = F.array_join(F.slice(F.regexp_extract_all(F.col(text), F.lit(common.WORD), F.lit(0)), F.lit(1), F.col("_first").cast("int")), " ")
    return each.withColumn(text, F.when(F.col("_first").isNull(), F.col(text)).otherwise(words))


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = mix(common.table(spark, sf_dir, "documents"), quality=labelled_weights(spark, sf_dir))
    return done.select("doc_id", "size", "source_size", "target", "taken", "source")
