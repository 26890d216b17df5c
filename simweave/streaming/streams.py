"""Structured Streaming forms: windows, late data, deduplication, stream-static and windowed similarity, state."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from simweave.plans.staging import shared_dir, stage


def _dir(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:10]}"


def replay(df: DataFrame, order: str, files: int, late: DataFrame | None = None) -> DataFrame:
    """df as a file stream: files written in the order of a column, one micro-batch each, late rows in a last file."""
    spark, path = df.sparkSession, _dir(df.sparkSession, "stream")
    bounds = df.approxQuantile(order, [k / files for k in range(1, files)], 0.0) if dict(df.dtypes)[order] != "timestamp" else None
    value = F.col(order).cast("double")
    if bounds is None:
        bounds = df.select(value.alias("v")).approxQuantile("v", [k / files for k in range(1, files)], 0.0)
    low = None
    for high in [*bounds, None]:
        part = df
        if low is not None:
            part = part.where(value > low)
        if high is not None:
            part = part.where(value <= high)
        part.coalesce(1).write.mode("append").parquet(path)
        low = high
    if late is not None:
        late.coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there and read its result: append mode writes files, the others a memory table."""
    spark = stream.sparkSession
    check = _dir(spark, "progress")
    if mode == "append":
        out = _dir(spark, "stream-out")
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", check).outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    name = f"stream_{uuid.uuid4().hex[:10]}"
    stream.writeStream.format("memory").queryName(name).option("checkpointLocation", check).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def windowed_counts(events: DataFrame, kind: str = "tumbling", lateness: str = "1 hour") -> DataFrame:
    """Counts by window and event_type; kind is 'tumbling' (1 hour), 'sliding' (2 hours every hour) or 'session' (30 minutes a user)."""
    marked = events.withWatermark("ts", lateness)
    if kind == "session":
        return marked.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")
    window = F.window("ts", "1 hour") if kind == "tumbling" else F.window("ts", "2 hours", "1 hour")
    return marked.groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def deduplicated(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """First row of each event_id within the watermark."""
    return events.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"])


def clicks_to_purchases(events_a: DataFrame, events_b: DataFrame, hours: int = 1) -> DataFrame:
    """Pairs of a click and a later purchase of one user within hours: an interval join of two streams."""
    a = events_a.where("event_type = 'click'").select(F.col("event_id").alias("a"), F.col("ts").alias("ta"), F.col("user_id").alias("ua")).withWatermark("ta", "1 hour")
    b = events_b.where("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("ts").alias("tb"), F.col("user_id").alias("ub")).withWatermark("tb", "1 hour")
    return a.join(b, F.expr(f"ua = ub AND tb > ta AND tb <= ta + interval {hours} hours")).select("a", "b")


class IncrementalJoin:
    """New objects against each other (candidates) and against a stored signature table (cross), batch by batch; stored objects are
    not joined with each other again. Results and signatures are partitioned by batch.

    A batch that is run again replaces its own partitions, so the sink is idempotent.
    """

    def __init__(self, spark: SparkSession, sign, candidates, cross, verify):
        self.spark, self.sign, self.candidates, self.cross, self.verify = spark, sign, candidates, cross, verify
        self.store, self.pairs = _dir(spark, "signature-store"), _dir(spark, "pair-store")

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        new = stage(self.sign(batch), "batch-signatures")
        old = self.spark.read.schema("id long, sig array<long>, batch long").parquet(self.store).where(F.col("batch") < batch_id).drop("batch") if batch_id else new.limit(0)
        new.withColumn("batch", F.lit(batch_id).cast("long")).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("batch").parquet(self.store)
        touched = self.candidates(new)
        if batch_id:
            met = self.cross(new, old)
            touched = touched.unionByName(met.select(F.least("id_a", "id_b").alias("id_a"), F.greatest("id_a", "id_b").alias("id_b")))
        out = self.verify(touched.where("id_a < id_b").distinct(), old.unionByName(new)).withColumn("batch", F.lit(batch_id).cast("long"))
        out.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("batch").parquet(self.pairs)

    def run(self, stream: DataFrame) -> DataFrame:
        stream.writeStream.foreachBatch(self).option("checkpointLocation", _dir(self.spark, "progress")).trigger(availableNow=True).start().awaitTermination()
        return self.spark.read.parquet(self.pairs).drop("batch")


def drift_processor() -> StatefulProcessor:
    """The processor behind drift(), as a local class: it travels by value, also to workers without this package."""

    class DriftProcessor(StatefulProcessor):
        """Running event-type counts of a user; emits the cosine of each batch's counts with the counts before."""

        KINDS = ("click", "view", "purchase", "signup", "error")

        def init(self, handle: StatefulProcessorHandle) -> None:
            self.counts = handle.getValueState("counts", "kind_counts array<double>")

        def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
            now = [0.0] * (len(self.KINDS) + 1)
            for frame in rows:
                for kind, n in frame["event_type"].value_counts().items():
                    now[self.KINDS.index(kind) if kind in self.KINDS else len(self.KINDS)] += float(n)
            before = list(self.counts.get()[0]) if self.counts.exists() else [0.0] * len(now)
            size = lambda v: sum(x * x for x in v) ** 0.5
            cosine = sum(x * y for x, y in zip(now, before, strict=True)) / (size(now) * size(before)) if any(before) else 1.0
            self.counts.update(([x + y for x, y in zip(now, before, strict=True)],))
            yield pd.DataFrame({"user_id": [key[0]], "events": [int(sum(now))], "cosine": [cosine]})

        def close(self) -> None:
            pass

    return DriftProcessor()


def drift(events: DataFrame) -> DataFrame:
    """user_id, events and cosine with the user's own past for every user and micro-batch."""
    return events.select("user_id", "event_type").groupBy("user_id").transformWithStateInPandas(
        drift_processor(), "user_id long, events long, cosine double", outputMode="Update", timeMode="None"
    )
