"""Tables as users: pruned scans, views, other formats, slot layouts, virtual users, streams."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table, pruned to ``columns`` where given."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``, which driver and executors share; a temporary folder where it is unset in a local run."""
    shared = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not shared:
        if spark.sparkContext.master.partition("[")[0] != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        shared = tempfile.mkdtemp(prefix="veilstat-core-")
        atexit.register(shutil.rmtree, shared, ignore_errors=True)
        spark.sparkContext.setCheckpointDir(shared)
    return shared.rstrip("/")


def scratch(spark: SparkSession) -> str:
    """A new folder in the shared one."""
    return f"{shared_dir(spark)}/veilstat-{uuid.uuid4().hex}"


def ready_to_checkpoint(spark: SparkSession) -> None:
    """Let ``checkpoint()`` write to the shared folder."""
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(shared_dir(spark))


def register_views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    for name in names or TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def load_any(spark: SparkSession, path: str, fmt: str, schema: str, **options) -> DataFrame:
    """CSV, JSON, ORC or text users with a stated schema; nothing is inferred."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def line_key() -> Column:
    """A unique user key of lineitem rows."""
    return F.concat_ws(".", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.to_date("l_shipdate").cast("string"))


def line_users(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").select(line_key().alias("user_id"), *columns)


def json_field(df: DataFrame, column: str, schema: str) -> DataFrame:
    return df.withColumn(column, F.from_json(column, schema))


def range_users(spark: SparkSession, n: int, partitions: int | None = None) -> DataFrame:
    """Virtual users for scale tests."""
    return spark.range(0, n, 1, partitions).select(F.col("id").alias("user_id")) if partitions else spark.range(n).select(F.col("id").alias("user_id"))


def append_estimates(df: DataFrame, path: str) -> None:
    df.write.mode("append").parquet(path)


def stream_events(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def rate_users(spark: SparkSession, rows_per_second: int) -> DataFrame:
    """An endless source for soak tests."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
