"""Readers and writers: declared schemas, file formats, a partitioned and bucketed layout for pings."""

from __future__ import annotations

import atexit
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

ADDRESS = "user_id bigint, addr_seq int, city int, district int, place_name string, addr_text string"
PING = "user_id bigint, city int, lat_u bigint, lon_u bigint, ts timestamp_ntz"
ALIAS_LIST = "city int, district int, std_name string, cand_name string"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A Parquet table; columns and filters reach the scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_table(spark: SparkSession, path: str, fmt: str, schema: str | StructType) -> DataFrame:
    """An address, ping or alias file as CSV, JSON, ORC or Parquet, by its declared schema."""
    reader = spark.read.schema(schema)
    return reader.option("header", "true").csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def load_alias_list(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    """A manual alias list: the truth table the method is measured against."""
    return read_table(spark, path, fmt, ALIAS_LIST).distinct()


def write_partitioned(df: DataFrame, path: str) -> None:
    """Parquet by city and district, so the district block prunes partitions."""
    df.repartition("city", "district").write.mode("overwrite").partitionBy("city", "district").parquet(path)


def save_bucketed(df: DataFrame, table: str, buckets: int = 512) -> None:
    """A table bucketed by user: author sets and pings saved this way join without a shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, "user_id").sortBy("user_id").saveAsTable(table)


def scratch_dir(spark: SparkSession) -> str:
    """The folder shared by driver and executors. Where the session names none, only a single-machine session gets one."""
    sc = spark.sparkContext
    named = sc.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if sc.master.split("[")[0] != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = f"/tmp/checkpoints/{sc.applicationId}"
        sc.setCheckpointDir(named)
    return named


def release_shuffles(spark: SparkSession) -> None:
    """Spark deletes the shuffle files of a finished query when the driver's collector finds its plan; on a quiet driver that may take long."""
    spark.sparkContext._jvm.System.gc()


def settle(df: DataFrame, release: bool = False) -> DataFrame:
    """df written once to the shared folder and read back: a short plan that survives lost executors. `release` after large shuffles."""
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/settled-{uuid.uuid4().hex}"
    df.write.parquet(path)
    atexit.register(_remove, spark, path)
    if release:
        release_shuffles(spark)
    return spark.read.schema(df.schema).parquet(path)


def _remove(spark: SparkSession, path: str) -> None:
    """Deletes a scratch table at exit, where the session still lives."""
    if spark.sparkContext._jsc is None or spark.sparkContext._jsc.sc().isStopped():
        return
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
