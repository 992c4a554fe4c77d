"""Windows over events in batch and as streams, and streams that build graphs."""

from __future__ import annotations

import sys
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.scratch import scratch_root, written
from ..sources.graph import PropertyGraph

cloudpickle.register_pickle_by_value(sys.modules[__name__])


def micros(ts: str | Column) -> Column:
    """Microseconds since 1970 of a timestamp without zone."""
    column = F.col(ts) if isinstance(ts, str) else ts
    day = F.datediff(column.cast("date"), F.lit("1970-01-01").cast("date")).cast("long")
    minute = F.hour(column).cast("long") * 60 + F.minute(column)
    return (day * 1440 + minute) * 60_000_000 + (F.extract(F.lit("SECOND"), column) * 1_000_000).cast("long")


def tumbling(events: DataFrame, minutes: int) -> DataFrame:
    """hour (window number since 1970), event_type, n."""
    return events.groupBy(F.floor(micros("ts") / (minutes * 60_000_000)).alias("hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))


def sliding(events: DataFrame, minutes: int, slide: int) -> DataFrame:
    """start (number of the slide at which the window begins), n."""
    at = F.floor(micros("ts") / (slide * 60_000_000))
    starts = F.explode(F.array(*[at - i for i in range(minutes // slide)]))
    return events.select(starts.alias("start")).groupBy("start").agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, minutes: int) -> DataFrame:
    """user_id, sessions, longest (events of the longest): a session ends with a pause of ``minutes``."""
    s = events.groupBy(F.session_window(F.col("ts").cast("timestamp"), f"{minutes} minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return s.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))


def late(events: DataFrame, microseconds: int) -> DataFrame:
    """late, n: the batch form of a watermark; arrival order is the id, cut in ranges whose maxima are carried on.
    The ranges are those of a sort by id, so their number is that of the shuffle's partitions."""
    e = events.select("event_id", micros("ts").alias("t")).repartitionByRange("event_id").withColumn("b", F.spark_partition_id())
    e = written(e, "arrivals")
    tops = e.groupBy("b").agg(F.max("t").alias("top"))
    before = tops.select("b", F.max("top").over(Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)).alias("before"))  # a row for each range
    inner = F.max("t").over(Window.partitionBy("b").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0))
    seen = e.withColumn("inner", inner).join(before, "b").select("t", F.greatest("inner", "before").alias("seen"))
    return seen.groupBy((F.col("t") < F.col("seen") - microseconds).alias("late")).agg(F.count(F.lit(1)).alias("n"))


def stream(spark: SparkSession, path: str) -> DataFrame:
    """A file of events as a stream."""
    return spark.readStream.schema(spark.read.parquet(path).schema).parquet(f"{path}*" if path.endswith(".parquet") else path)


def run_to_end(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a streaming query over all that is there now; each batch is a file set in shared storage, read back at the end."""
    spark = df.sparkSession
    place = f"{scratch_root(spark)}/stream-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{place}/out/batch={number}")

    df.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{place}/state").trigger(availableNow=True).start().awaitTermination()
    out = spark.read.schema(df.schema.add("batch", "long")).parquet(f"{place}/out")
    if mode != "append":  # each batch holds the whole or the changed result
        last = out.agg(F.max("batch")).first()[0]
        return out.where(F.col("batch") == last).drop("batch") if mode == "complete" else out
    return out.drop("batch")


def stream_tumbling(spark: SparkSession, path: str, minutes: int) -> DataFrame:
    """Watermarked tumbling counts; the complete result of the last batch."""
    e = stream(spark, path).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 day")
    counts = e.groupBy(F.window("ts", f"{minutes} minutes").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return run_to_end(counts, "complete").select(F.floor(micros(F.col("w.start").cast("timestamp_ntz")) / (minutes * 60_000_000)).alias("hour"), "event_type", "n")


def pairs_within(spark: SparkSession, path: str, kind: str, minutes: int) -> DataFrame:
    """A stream of (a, b): users with events of one type within ``minutes``, by an interval join of the stream with itself."""
    e = stream(spark, path).where(F.col("event_type") == kind).withColumn("ts", F.col("ts").cast("timestamp"))
    a = e.select(F.col("user_id").alias("ua"), F.col("ts").alias("ta"), F.col("event_type").alias("ka")).withWatermark("ta", "1 hour")
    b = e.select(F.col("user_id").alias("ub"), F.col("ts").alias("tb"), F.col("event_type").alias("kb")).withWatermark("tb", "1 hour")
    span = F.expr(f"INTERVAL {minutes} MINUTES")
    met = a.join(b, (F.col("ka") == F.col("kb")) & (F.col("ua") < F.col("ub")) & (F.col("tb") >= F.col("ta") - span) & (F.col("tb") <= F.col("ta") + span))
    return met.select(F.col("ua").alias("a"), F.col("ub").alias("b"))


def stream_pairs(spark: SparkSession, path: str, kind: str, minutes: int) -> DataFrame:
    """The distinct pairs of :func:`pairs_within` when the stream has been read to its end."""
    return run_to_end(pairs_within(spark, path, kind, minutes)).distinct()


def stream_counters(spark: SparkSession, path: str) -> DataFrame:
    """user_id, value: counters held as state, one update a batch and user."""

    def count(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "value": [n]})

    counted = stream(spark, path).groupBy("user_id").applyInPandasWithState(count, "user_id long, value long", "n long", "update", "NoTimeout")
    return run_to_end(counted, "update").groupBy("user_id").agg(F.max("value").alias("value"))


def mine_snapshots(spark: SparkSession, path: str, mine: Callable[[PropertyGraph], DataFrame], kind: str, minutes: int) -> DataFrame:
    """Mines the graph built so far after the stream's edges have been gathered: mining itself is a batch on a snapshot."""
    return mine(PropertyGraph.build(stream_pairs(spark, path, kind, minutes)))


def stream_distinct(spark: SparkSession, path: str, key: list[str], wait: str = "7 days") -> DataFrame:
    """Events without those that repeat ``key`` within the watermark: state is kept for ``wait`` only."""
    e = stream(spark, path).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", wait)
    return run_to_end(e.dropDuplicatesWithinWatermark(key))


def mine_each_batch(spark: SparkSession, path: str, mine: Callable[[PropertyGraph], DataFrame], kind: str, minutes: int) -> list[DataFrame]:
    """Results after each micro-batch: new pairs of users join those of the batches before, and the whole graph is mined
    again. The pairs so far are a table in shared storage, replaced by a new one each time."""
    gathered: list[DataFrame] = []
    results: list[DataFrame] = []

    def step(batch: DataFrame, number: int) -> None:
        whole = batch.distinct() if not gathered else gathered[-1].unionByName(batch).distinct()
        gathered.append(written(whole, f"pairs-{number}"))
        if not gathered[-1].isEmpty():
            results.append(written(mine(PropertyGraph.build(gathered[-1])), f"mined-{number}"))

    place = f"{scratch_root(spark)}/stream-{uuid.uuid4().hex}"
    met = pairs_within(spark, path, kind, minutes)
    met.writeStream.foreachBatch(step).option("checkpointLocation", place).trigger(availableNow=True).start().awaitTermination()
    return results
