"""Streaming additions: size tables, windows and strings over arriving rows.

Sources are folders of Parquet files that arrive one by one; every query here
runs over all that's there and stops (`availableNow`), so its final state can be
compared with a batch.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockbwt.operators.collection import StringCollection
from blockbwt.operators.construct import bwt_build
from blockbwt.operators.splitters import prefix_bucket
from blockbwt.plans.planner import Budget
from blockbwt.storage import fresh_path, materialise
from blockbwt.tables import load, reads


def stage(df: DataFrame, files: int, order: str, descending: bool = False) -> str:
    """df in `files` Parquet files, written one after the other in the order of `order`: sources take them by their age."""
    path = fresh_path(df.sparkSession, "arriving")
    key = F.unix_micros(F.col(order)) if dict(df.dtypes)[order] == "timestamp" else F.col(order)
    cuts = df.agg(F.percentile_approx(key, [i / files for i in range(1, files)], 100_000)).first()[0] or []
    spans = list(zip([None, *cuts], [*cuts, None]))
    for low, high in reversed(spans) if descending else spans:
        some = df if low is None else df.where(key > low)
        (some if high is None else some.where(key <= high)).coalesce(1).write.mode("append").parquet(path)
    return path


def arriving(spark: SparkSession, path: str, schema) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def finish(stream: DataFrame, mode: str) -> DataFrame:
    """Runs to the end of what's there; what the sink then holds."""
    spark, out = stream.sparkSession, fresh_path(stream.sparkSession, "stream-out")
    if mode == "append":
        q = stream.writeStream.outputMode(mode).option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True).format("parquet").start(out)
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/{number:06d}")

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True).foreachBatch(keep).start()
    q.awaitTermination()
    last = max((int(p["batchId"]) for p in q.recentProgress), default=0)
    return spark.read.schema(stream.schema).parquet(f"{out}/{last:06d}")


def size_table_stream(spark: SparkSession, sf_dir: str, ell: int = 4) -> DataFrame:
    """The size table kept up to date while reads arrive."""
    own = reads(spark, sf_dir).df
    path = stage(own, 3, "sid")
    rows = arriving(spark, path, own.schema).select("sid", "s", F.explode(F.sequence(F.lit(0), F.length("s"))).alias("pos"))
    return finish(rows.select(prefix_bucket(ell).alias("bucket")).groupBy("bucket").agg(F.count(F.lit(1)).alias("n")), "complete")


def _table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Event time has to be an instant; the tables' has no zone."""
    return load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def _events(spark: SparkSession, sf_dir: str, files: int = 3, closing: bool = False) -> DataFrame:
    """The events as they arrive. `closing` sends a last row without ids, a month later: the watermark passes every window before it, so that each is emitted and its state dropped."""
    e = _table(spark, sf_dir)
    path = stage(e, files, "ts")
    if closing:
        last = e.agg((F.max("ts") + F.expr("interval 30 days")).alias("ts")).where("ts is not null")
        row = last.select(*[F.col("ts") if c == "ts" else F.lit(None).cast(t).alias(c) for c, t in e.dtypes])
        row.coalesce(1).write.mode("append").parquet(path)
    return arriving(spark, path, e.schema)


#: Events without an id only close windows.
def _real():
    return F.count("event_id").alias("n")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of each day by type."""
    w = _events(spark, sf_dir, closing=True).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day"), "event_type").agg(_real())
    return finish(w, "append").where("n > 0").select(F.col("window.start").alias("day"), "event_type", "n")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of each two days, every day."""
    w = _events(spark, sf_dir, closing=True).withWatermark("ts", "1 day").groupBy(F.window("ts", "2 days", "1 day")).agg(_real())
    return finish(w, "append").where("n > 0").select(F.col("window.start").alias("begin"), "n")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user's sessions, two hours apart."""
    w = _events(spark, sf_dir, closing=True).withWatermark("ts", "1 day").groupBy("user_id", F.session_window("ts", "2 hours")).agg(_real())
    return finish(w, "append").where("n > 0").select("user_id", F.col("session_window.start").alias("begin"), "n")


def window_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user's event types of a day as a string, in order of time: what a window holds is bounded by its day."""
    e = _events(spark, sf_dir, closing=True).withWatermark("ts", "1 day")
    said = F.collect_list(F.struct("ts", "event_id", F.substring("event_type", 1, 1).alias("c")))
    done = finish(e.groupBy("user_id", F.window("ts", "1 day")).agg(said.alias("said"), _real()), "append").where("n > 0")
    return done.select("user_id", F.col("window.start").alias("day"), F.array_join(F.transform(F.array_sort("said"), lambda x: x["c"]), "").alias("s"))


def late_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Files in reverse order: what the watermark drops and what it keeps are all rows."""
    e = _table(spark, sf_dir)
    rows = arriving(spark, stage(e, 3, "ts", descending=True), e.schema).withWatermark("ts", "1 hour")
    query = rows.groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    out = fresh_path(spark, "late")
    q = query.writeStream.outputMode("update").option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True).foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(f"{out}/b={i}")).start()
    q.awaitTermination()
    dropped = sum(s["numRowsDroppedByWatermark"] for p in q.recentProgress for s in p["stateOperators"])
    kept = spark.read.parquet(out).groupBy("window").agg(F.max("n").alias("n")).agg(F.sum("n")).first()[0] or 0
    return spark.createDataFrame([(dropped > 0, kept > 0)], "some_dropped boolean, some_kept boolean")


def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event sent twice."""
    e = _table(spark, sf_dir)
    twice = arriving(spark, stage(e.unionAll(e), 3, "ts"), e.schema).withWatermark("ts", "1 day")
    return finish(twice.dropDuplicatesWithinWatermark(["event_id"]), "append").select("event_id", "user_id", "event_type")


GAP_HOURS = 6


def _closed_strings(gap: int):
    """Buffers a user's events (micros,event_id,symbol) and emits every string that a gap has closed, or whose time the watermark has passed."""

    def run(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        held = [x.split(",") for x in state.get[0].split(";")] if state.exists else []
        held = [(int(t), int(i), c) for t, i, c in held]
        for part in parts:
            held += [(int(t), int(i), c) for t, i, c in zip(part["at"], part["event_id"], part["c"]) if not pd.isna(i)]
        held.sort()
        cuts = [0, *(k for k in range(1, len(held)) if held[k][0] - held[k - 1][0] >= gap)]
        runs = [held[a:b] for a, b in zip(cuts, [*cuts[1:], len(held)])] if held else []
        still = runs.pop() if runs and not state.hasTimedOut else []
        if still:
            state.update((";".join(f"{t},{i},{c}" for t, i, c in still),))
            state.setTimeoutTimestamp(max((still[-1][0] + gap) // 1000 + 1, state.getCurrentWatermarkMs() + 1))
        elif state.exists:
            state.remove()
        yield pd.DataFrame({"user_id": [key[0]] * len(runs), "begin": [x[0][0] for x in runs], "s": ["".join(c for _, _, c in x) for x in runs]})

    return run


def user_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user's event types as strings that a gap of GAP_HOURS ends, from state of our own: what is held is the open string."""
    e = _events(spark, sf_dir, closing=True).withWatermark("ts", "1 hour")
    rows = e.select("user_id", "ts", F.unix_micros("ts").alias("at"), "event_id", F.substring("event_type", 1, 1).alias("c"))
    done = rows.groupBy("user_id").applyInPandasWithState(_closed_strings(GAP_HOURS * 3_600_000_000), "user_id long, begin long, s string", "buffer string", "append", "EventTimeTimeout")
    return finish(done, "append").select("user_id", F.timestamp_micros("begin").alias("begin"), "s")


def user_strings_windowed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same without custom state: an ordered collection by user."""
    e = _events(spark, sf_dir)
    said = F.collect_list(F.struct("ts", "event_id", F.substring("event_type", 1, 1).alias("c")))
    done = finish(e.groupBy("user_id").agg(said.alias("said")), "complete")
    return done.select("user_id", F.array_join(F.transform(F.array_sort("said"), lambda x: x["c"]), "").alias("s"))


def static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Arriving reads with their buckets' share of a batch's size table."""
    own = reads(spark, sf_dir).df
    sizes = own.groupBy(F.substring("s", 1, 2).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))
    rows = arriving(spark, stage(own, 3, "sid"), own.schema).withColumn("bucket", F.substring("s", 1, 2))
    return finish(rows.join(F.broadcast(sizes), "bucket").select("sid", "bucket", "n"), "append")


def interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors within an hour after a click of the same user, of two streams with watermarks."""
    e = _events(spark, sf_dir)
    clicks = e.where("event_type = 'click'").select(F.col("user_id").alias("u0"), F.col("event_id").alias("click"), F.col("ts").alias("t0")).withWatermark("t0", "2 hours")
    errors = e.where("event_type = 'error'").select(F.col("user_id").alias("u1"), F.col("event_id").alias("error"), F.col("ts").alias("t1")).withWatermark("t1", "2 hours")
    met = clicks.join(errors, F.expr("u0 = u1 and t1 >= t0 and t1 <= t0 + interval 1 hour"))
    return finish(met.select("click", "error"), "append")


def incremental_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """customer.c_name in three arrivals; each batch's own transform is merged with the one so far by rank counting."""
    from blockbwt.operators.incremental import merge

    rows = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("sid"), F.col("c_name").alias("s"))
    symbols = StringCollection(rows).symbols()
    held: dict[str, DataFrame | None] = {"bwt": None, "texts": None}

    def add(batch: DataFrame, number: int) -> None:
        texts = materialise(batch, "batch")
        if texts.isEmpty():
            return
        new = StringCollection(texts, symbols)
        if held["bwt"] is None:
            held["bwt"], held["texts"] = materialise(bwt_build(new, Budget()), "bwt"), texts
        else:
            old = StringCollection(held["texts"], symbols)
            held["bwt"] = materialise(merge(old, held["bwt"], new, materialise(bwt_build(new, Budget()), "bwt")), "bwt")
            held["texts"] = materialise(held["texts"].unionByName(texts), "texts")

    q = arriving(spark, stage(rows, 3, "sid"), rows.schema).writeStream.foreachBatch(add).option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True).start()
    q.awaitTermination()
    return held["bwt"].select("bwt_pos", "sid", "pos", "sym")


