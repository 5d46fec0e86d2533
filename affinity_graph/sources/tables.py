"""Tables, edge lists and sinks."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir. Where that is unset one of our own serves a local master only."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="affinity-graph-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write a table to the shared folder and read it back; cuts lineage in a way that survives lost executors."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def is_directory(spark: SparkSession, path: str) -> bool:
    """Whether a path of any store that Spark reads is a folder."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def read_edge_list(spark: SparkSession, path: str, fmt: str = "csv", src: str = "src", dst: str = "dst", **options: str) -> DataFrame:
    """Raw pairs from Parquet, ORC, CSV, JSON, or text with two numbers a line; rows that do not parse have nulls."""
    if fmt == "text":
        parts = F.split(F.trim("value"), "[\\s,]+")
        lines = spark.read.text(path).where(~F.col("value").rlike("^\\s*(#|%|$)"))
        return lines.select(F.get(parts, F.lit(0)).try_cast("bigint").alias("src"), F.get(parts, F.lit(1)).try_cast("bigint").alias("dst"))
    reader = spark.read.options(**options)
    if fmt in ("csv", "json"):
        reader = reader.schema(f"{src} BIGINT, {dst} BIGINT")
    return reader.format(fmt).load(path).select(F.col(src).cast("bigint").alias("src"), F.col(dst).cast("bigint").alias("dst"))


def write_edges(edges: DataFrame, path: str, tiles: int = 0, compression: str = "zstd") -> None:
    """Edges as Parquet sorted by (lo, hi) inside files, optionally in ``tiles`` folders by range of lo."""
    if not tiles:
        edges.sortWithinPartitions("lo", "hi").write.option("compression", compression).parquet(path)
        return
    top = edges.agg(F.max("lo")).head()[0] or 0
    tile = F.floor(F.col("lo") * F.lit(tiles) / F.lit(top + 1)).cast("int")
    edges.withColumn("tile", tile).repartition("tile").sortWithinPartitions("lo", "hi").write.partitionBy("tile").option("compression", compression).parquet(path)


def write_bucketed(edges: DataFrame, name: str, buckets: int = 32) -> None:
    """A table bucketed and sorted by ``lo``, so that joins on it need no exchange."""
    edges.write.bucketBy(buckets, "lo").sortBy("lo", "hi").mode("overwrite").saveAsTable(name)


def export(df: DataFrame, path: str, fmt: str) -> None:
    """A profile or series as csv, json or orc."""
    writer = df.write.mode("overwrite")
    (writer.option("header", True) if fmt == "csv" else writer).format(fmt).save(path)
