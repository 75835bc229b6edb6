"""Tables that outlive a stage: written to the folder that the cluster shares."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder named in ``spark.checkpoint.dir``; where that is unset, a local one if all runs in this process (tests, bench).

    On a cluster executors would each write to a disk of their own, so an unset folder is an error there.
    """
    sc = spark.sparkContext
    found = sc.getConf().get("spark.checkpoint.dir", None)
    if not found:
        held = sc._jsc.sc().getCheckpointDir()
        found = held.get() if held.isDefined() else None
    if not found:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        found = "file://" + tempfile.mkdtemp(prefix="rulegraph-")
        sc.setCheckpointDir(found)
    return found.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    """A fresh path under the shared folder, removed when the application's file system closes."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    return path


def staged(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Writes df once to the shared folder and reads it back: lineage ends here.

    Unlike a local checkpoint this survives the loss of executors.
    """
    spark = df.sparkSession
    path = new_path(spark, name)
    writer = df.write.option("compression", "zstd")
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def staged_parts(parts: list[DataFrame], name: str) -> DataFrame:
    """The same for parts of one table written one after the other, so disk holds one part's shuffles."""
    spark, path = parts[0].sparkSession, new_path(parts[0].sparkSession, name)
    for part in parts:
        part.write.mode("append").option("compression", "zstd").parquet(path)
    return spark.read.schema(parts[0].schema).parquet(path)


def staged_by(parts: list[DataFrame], name: str, keys: list[str]) -> DataFrame:
    """The same for parts written one after the other into buckets of ``keys``: windows and aggregates within the keys need no shuffle.

    Parts that are dealt by ``repartition(buckets(spark), *keys)`` give one file for each bucket.
    """
    spark = parts[0].sparkSession
    table, path = f"{name}_{uuid.uuid4().hex}", new_path(spark, name)
    for part in parts:
        part.write.mode("append").option("compression", "zstd").option("path", path).bucketBy(buckets(spark), *keys).sortBy(*keys).saveAsTable(table)
    return spark.table(table)


def buckets(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
