"""Snapshots and bucketed tables in the folder that driver and executors share."""

from __future__ import annotations

import math
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Rows a bucket holds before another one is opened, up to the session's number of shuffle partitions.
BUCKET_ROWS = 1 << 18


def shared_folder(spark: SparkSession) -> str:
    """The session's checkpoint folder. Only a session on one machine gets a temporary one where none is named."""
    jsc = spark.sparkContext._jsc.sc()
    if jsc.getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None and not jsc.isLocal():
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(named or tempfile.mkdtemp(prefix="graphmoves-"))
    return jsc.getCheckpointDir().get()


def snapshot(df: DataFrame) -> DataFrame:
    """Cut lineage by a written table; a lost executor costs nothing of it."""
    path = f"{shared_folder(df.sparkSession)}/g{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._path = path
    return out


def buckets_for(spark: SparkSession, rows: int) -> int:
    return max(1, min(int(spark.conf.get("spark.sql.shuffle.partitions")), math.ceil(rows / BUCKET_ROWS)))


def bucketed(df: DataFrame, column: str, buckets: int) -> DataFrame:
    """A snapshot bucketed by a column: joins and aggregates on it need no exchange. One file a bucket."""
    spark = df.sparkSession
    name = f"g{uuid.uuid4().hex}"
    path = f"{shared_folder(spark)}/{name}"
    df.repartition(buckets, column).write.bucketBy(buckets, column).sortBy(column).option("path", path).saveAsTable(name)
    out = spark.table(name)
    out._path, out._table = path, name
    return out


def kept_by(df: DataFrame, owner: DataFrame) -> DataFrame:
    """Marks df as reading the owner's table, so that drop(df) deletes that."""
    for name in ("_path", "_table"):
        if hasattr(owner, name):
            setattr(df, name, getattr(owner, name))
    return df


def drop(*frames: DataFrame | None) -> None:
    for df in frames:
        if df is not None and hasattr(df, "_path"):
            spark = df.sparkSession
            if hasattr(df, "_table"):
                spark.sql(f"DROP TABLE IF EXISTS {df._table}")
            p = spark._jvm.org.apache.hadoop.fs.Path(df._path)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
