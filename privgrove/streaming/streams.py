"""Streaming forms: scoring, noisy windows, late rows, deduplication, budget meters, incremental histograms."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from privgrove.functions.noise import laplace, uniform
from privgrove.plans.tree import TreeModel
from privgrove.sources.io import shared_dir


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream; watermarks need timestamps with a zone."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events*.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def arriving(parts: list[DataFrame], name: str) -> DataFrame:
    """A stream whose micro-batches are the parts, in their order."""
    spark, path = parts[0].sparkSession, shared_dir(parts[0].sparkSession, f"stream-{name}")
    for k, part in enumerate(parts):
        part.coalesce(1).write.parquet(f"{path}/{k}")
    return spark.readStream.schema(parts[0].schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/*")


def on_time(stream: DataFrame, key: str, time: str = "ts", delay: str = "1 hour") -> DataFrame:
    """Rows once each that are not behind the watermark, the latest time of earlier batches less the delay."""
    return stream.withWatermark(time, delay).dropDuplicates([key, time])


def with_rocksdb(spark: SparkSession) -> SparkSession:
    """A session of its own whose streams keep their state in RocksDB, as stateful processors need."""
    own = spark.newSession()
    own.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    return own


def drained(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there now and give the result as a table read from the shared folder: in update mode the
    updates of all batches, in complete mode the last state."""
    spark = df.sparkSession
    path = shared_dir(spark, f"stream-{name}")
    if mode == "append":
        df.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{path}/out")

    def save(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/out/batch={number}" if mode == "update" else f"{path}/out")

    df.writeStream.outputMode(mode).foreachBatch(save).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{path}/out")


def scored(stream: DataFrame, model: TreeModel) -> DataFrame:
    """Margins of a stream under a released model: stateless, free of privacy cost."""
    return model.predict(model.spec.encode(stream), "expression").select("row_key", "margin")


def dp_window_counts(events: DataFrame, epsilon: float, key: str, size: str = "1 day", slide: str | None = None) -> DataFrame:
    """Noisy counts of time windows. Disjoint windows cost epsilon once; with a slide, an event is in several windows and
    costs epsilon in each."""
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    counts = events.groupBy(window.alias("w")).agg(F.count(F.lit(1)).alias("n"))
    start = F.date_format("w.start", "yyyy-MM-dd HH:mm:ss")
    return counts.select(start.alias("start"), (F.col("n") + laplace(uniform(key, start), 1 / epsilon)).alias("n"))


def session_counts(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    s = F.session_window("ts", gap)
    return events.groupBy("user_id", s.alias("s")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("s.start").alias("start"), "n")


class BudgetMeter(StatefulProcessor):
    """What is left of each unit's budget: every row of a unit spends `cost`, until nothing is left."""

    def __init__(self, budget: float, cost: float):
        self.budget, self.cost = budget, cost

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.left = handle.getValueState("left", "left double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        left = self.left.get()[0] if self.left.exists() else self.budget
        n = sum(map(len, rows))
        used = min(n, int(left / self.cost + 1e-9))
        left -= used * self.cost
        self.left.update((left,))
        yield pd.DataFrame({"user_id": [key[0]], "allowed": [used], "refused": [n - used], "remaining": [round(left, 9)]})

    def close(self) -> None:
        pass


def budget_meter(events: DataFrame, budget: float = 1.0, cost: float = 0.1) -> DataFrame:
    """What every batch's rows of a unit are allowed and refused, and what the unit has left then."""
    return events.groupBy("user_id").transformWithStateInPandas(BudgetMeter(budget, cost), "user_id long, allowed long, refused long, remaining double", "Update", "None")


def incremental_histogram(stream: DataFrame, lo: float, hi: float, bins: int, col: str = "value") -> DataFrame:
    """Raw bin counts of every micro-batch, kept apart by batch number so that a repeated batch counts once; the sum over
    batches feeds one release."""
    path = shared_dir(stream.sparkSession, "stream-histogram")

    def add(batch: DataFrame, number: int) -> None:
        place = F.least(F.greatest(F.ceil((F.col(col) - lo) / (hi - lo) * bins) - 1, F.lit(0)), F.lit(bins - 1)).cast("int")
        batch.where(F.col(col).isNotNull()).groupBy(place.alias("bin")).agg(F.count(F.lit(1)).alias("n")).write.mode("overwrite").parquet(f"{path}/counts/batch={number}")

    stream.writeStream.foreachBatch(add).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.parquet(f"{path}/counts").groupBy("bin").agg(F.sum("n").alias("n"))
