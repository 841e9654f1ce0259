"""Streams of events: windowed matrices, deduplication, state, incremental products."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from sevenfold.operators.hybrid import sql_multiply
from sevenfold.operators.tiles import durable, release, shared_folder

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def stream_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of files, with their declared schema."""
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", 1).parquet(sf_dir)


def slices_by_time(spark: SparkSession, sf_dir: str, parts: int = 3) -> list[DataFrame]:
    """The events of January in ``parts`` slices of time, in order."""
    events = spark.read.schema(EVENTS).parquet(f"{sf_dir}/events.parquet")
    cuts = [f"2024-01-{1 + k * 31 // parts:02d}" for k in range(parts)]
    part = F.lit(0)
    for cut in cuts[1:]:
        part = part + (F.col("ts") >= F.lit(cut).cast("timestamp")).cast("int")
    return [events.where(part == k) for k in range(parts)]


def stream_of_slices(slices: list[DataFrame]) -> DataFrame:
    """A stream of which every slice is a micro-batch: a file each, one file a trigger."""
    spark = slices[0].sparkSession
    root = f"{shared_folder(spark)}/in-{uuid.uuid4().hex}"
    for part in slices:
        part.coalesce(1).write.mode("append").parquet(root)
    return spark.readStream.schema(slices[0].schema).option("maxFilesPerTrigger", 1).parquet(root)


def run_available_now(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there, to Parquet or, for complete output, to durable batches."""
    spark = stream.sparkSession
    root = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/state").trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", f"{root}/out").start()
    else:  # complete or update: the last batch that has rows is the result
        query = writer.foreachBatch(lambda df, number: df.write.mode("overwrite").parquet(f"{root}/out") if df.limit(1).count() else None).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{root}/out")


def run_in_slices(slices: list[DataFrame], build) -> tuple[DataFrame, int]:
    """Feed ``slices`` to one append-mode stream, each as a micro-batch of its own.

    ``build`` makes the query of the stream. Every slice is written, then the
    stream goes on from its checkpoint, so the order of the files within a slice
    doesn't matter and the watermark of one slice holds for the next. Returns
    the result and how many (partly aggregated) rows came too late.
    """
    spark = slices[0].sparkSession
    root = f"{shared_folder(spark)}/slices-{uuid.uuid4().hex}"
    late = 0
    for part in slices:
        part.write.mode("append").parquet(f"{root}/in")
        stream = build(spark.readStream.schema(part.schema).parquet(f"{root}/in"))
        writer = stream.writeStream.outputMode("append").option("checkpointLocation", f"{root}/state").trigger(availableNow=True)
        query = writer.format("parquet").option("path", f"{root}/out").start()
        query.awaitTermination()
        late += sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])
    return spark.read.schema(stream.schema).parquet(f"{root}/out"), late


def late_replay(spark: SparkSession, sf_dir: str, back: str = "15 days", every: int = 10) -> list[DataFrame]:
    """The events, and after them every tenth once more with its time moved back."""
    events = spark.read.schema(EVENTS).parquet(f"{sf_dir}/events.parquet")
    moved = events.where(F.pmod("event_id", F.lit(every)) == 0).withColumn("ts", F.col("ts") - F.expr(f"INTERVAL {back}"))
    return [events, moved]


def windowed_cells(stream: DataFrame, kind: str, size: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Counts by user within tumbling, sliding or session windows (``size`` is then the gap)."""
    marked = stream.withWatermark("ts", late)
    w = F.session_window("ts", size) if kind == "session" else F.window("ts", size, slide)
    counted = marked.groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n"))
    return counted.select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "user_id", "n")


def dedupe_events(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def stream_enrich(stream: DataFrame, static: DataFrame, on: str) -> DataFrame:
    """Stream-static join."""
    return stream.join(static, on)


def stream_transitions(stream: DataFrame, forget_hours: int = 24) -> DataFrame:
    """Transitions between a user's successive events; the state is the last event, forgotten some hours of event time later."""

    def follow(key, batches, state: GroupState):
        if state.hasTimedOut:
            state.remove()
            return
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        kinds = rows["event_type"].tolist()
        pairs = list(zip([last, *kinds[:-1]], kinds, strict=True))
        state.update((kinds[-1],))
        forget = max(int(rows["ts"].max().timestamp() * 1000), state.getCurrentWatermarkMs()) + forget_hours * 3600 * 1000
        state.setTimeoutTimestamp(forget)
        yield pd.DataFrame([(key[0], a, b) for a, b in pairs if a is not None], columns=["user_id", "before", "after"])

    return stream.withWatermark("ts", "1 hour").groupBy("user_id").applyInPandasWithState(follow, "user_id long, before string, after string", "last string", "append", GroupStateTimeout.EventTimeTimeout)


def incremental_product(stream: DataFrame, to_cells, b: DataFrame) -> DataFrame:
    """C = A B kept up to date: every batch adds its dA times B, as the product is bilinear."""
    spark = stream.sparkSession
    root = f"{shared_folder(spark)}/product-{uuid.uuid4().hex}"

    def add(batch: DataFrame, number: int):
        delta = sql_multiply(to_cells(batch), b)
        delta.write.mode("overwrite").parquet(f"{root}/delta/batch={number}")

    stream.writeStream.foreachBatch(add).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
    deltas = spark.read.schema("i long, j long, v long").parquet(f"{root}/delta")
    return deltas.groupBy("i", "j").agg(F.sum("v").alias("v")).where("v <> 0")


def two_sided_product(stream: DataFrame, to_a, to_b) -> DataFrame:
    """C = A B where both factors grow: every batch adds dA B + A dB + dA dB, each by sparse joins of what changed."""
    spark = stream.sparkSession
    root = f"{shared_folder(spark)}/product-{uuid.uuid4().hex}"
    cells = "i long, j long, v long"
    held: dict[str, DataFrame] = {}

    def summed(x: DataFrame) -> DataFrame:
        return x.groupBy("i", "j").agg(F.sum("v").alias("v")).where("v <> 0")

    def add(batch: DataFrame, number: int):
        da, db = durable(to_a(batch)), durable(to_b(batch))
        a, b = (held.get(k, spark.createDataFrame([], cells)) for k in "ab")
        delta = sql_multiply(da, b).unionByName(sql_multiply(a, db)).unionByName(sql_multiply(da, db))
        summed(delta).write.mode("overwrite").parquet(f"{root}/delta/batch={number}")
        for name, old, new in (("a", a, da), ("b", b, db)):
            before = held.get(name)
            held[name] = durable(summed(old.unionByName(new)))
            release(before)
            release(new)

    stream.writeStream.foreachBatch(add).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
    return summed(spark.read.schema(cells).parquet(f"{root}/delta"))
