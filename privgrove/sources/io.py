"""Tables, formats, models, ledgers and releases."""

from __future__ import annotations

import gc
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str, names=TABLES) -> None:
    """Temporary views of the tables, for SQL."""
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def shared_dir(spark: SparkSession, name: str = "work") -> str:
    """A new folder below spark.checkpoint.dir, which driver and executors share; where it is unset, below
    /tmp/checkpoints if the session is a local one, else an error: executors would each write to a disk of their own."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        root = "/tmp/checkpoints"
    return f"{root.rstrip('/')}/grove-{name}-{uuid.uuid4().hex}"


def round_trip(df: DataFrame, fmt: str, path: str | None = None, **options: str) -> DataFrame:
    """Write in a format and read it back with the same schema."""
    path = path or shared_dir(df.sparkSession, fmt)
    df.write.mode("overwrite").options(**options).format(fmt).save(path)
    return df.sparkSession.read.options(**options).schema(df.schema).format(fmt).load(path)


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write in the shared folder and read back: nothing of how the rows came about, such as a join's shuffle, stays with them."""
    path = shared_dir(df.sparkSession, name)
    df.write.mode("overwrite").option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def freed(spark: SparkSession) -> None:
    """Let Spark remove the shuffle files of frames that are gone, as it does when the driver's garbage is collected."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def bucketed(df: DataFrame, table: str, buckets: int, col: str) -> DataFrame:
    """A bucketed and sorted table: joins and aggregates on col then need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, col).sortBy(col).saveAsTable(table)
    return df.sparkSession.table(table)


def to_libsvm(df: DataFrame, label: str, features: list[str]) -> DataFrame:
    """One text line per row: label, then index:value of the present, non-zero features."""
    parts = [F.when(F.col(c).isNotNull() & (F.col(c) != 0), F.concat(F.lit(f"{k}:"), F.col(c).cast("string"))) for k, c in enumerate(features)]
    return df.select(F.concat_ws(" ", F.col(label).cast("string"), *parts).alias("value"))


def from_libsvm(lines: DataFrame) -> DataFrame:
    """(label, features map<int,double>) of sparse text lines."""
    words = F.split(F.trim("value"), r"\s+")
    pairs = F.transform(F.slice(words, F.lit(2), F.greatest(F.size(words) - 1, F.lit(0))), lambda w: F.struct(F.split_part(w, F.lit(":"), F.lit(1)).cast("int").alias("k"), F.split_part(w, F.lit(":"), F.lit(2)).cast("double").alias("v")))
    return lines.select(F.element_at(words, 1).cast("double").alias("label"), F.map_from_entries(pairs).alias("features"))


class ReleaseCache:
    """Noised answers by query id: an answer that was released is read again, never drawn and charged again."""

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path, self.known = spark, path or shared_dir(spark, "releases"), set()

    def get_or_release(self, query_id: str, release: Callable[[], DataFrame]) -> tuple[DataFrame, bool]:
        """(answer, whether it is new)."""
        at, new = f"{self.path}/{query_id}", query_id not in self.known
        if new:
            release().write.mode("errorifexists").parquet(at)
            self.known.add(query_id)
        return self.spark.read.parquet(at), new
