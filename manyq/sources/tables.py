"""Readers and writers: pruned table scans, edge lists in several formats, block stores, and epochs in the shared folder."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_written: list[tuple[SparkSession, str]] = []


def load(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    """A table, or some of its columns: what is not named is not read."""
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*columns) if columns else df


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share; a local one only where none is named and Spark itself is local."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    root = "file://" + tempfile.mkdtemp(prefix="manyq-")
    spark.conf.set("spark.checkpoint.dir", root)
    return root


def written(df: DataFrame, label: str) -> tuple[DataFrame, str]:
    """df written to the shared folder and read again, and the folder: for those who drop it when it is not needed any more."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/manyq/{label}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def epoch(df: DataFrame, label: str) -> DataFrame:
    """Write df to the shared folder and read it again: a wave's single committed output, and the end of its lineage."""
    return written(df, label)[0]


def forget(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


@atexit.register
def _forget_epochs() -> None:
    for spark, path in _written:
        with contextlib.suppress(Exception):  # the session may be gone
            forget(spark, path)


def read_edges(spark: SparkSession, path: str, fmt: str) -> DataFrame:
    """(src, dst, w) from csv, json, orc, parquet, or text lines `src dst:w dst:w ...`."""
    schema = "src long, dst long, w long"
    if fmt == "text":
        parts = F.split("value", " ")
        return (
            spark.read.text(path)
            .select(F.get(parts, 0).cast("long").alias("src"), F.explode(F.slice(parts, 2, F.size(parts))).alias("to"))
            .select("src", F.split("to", ":")[0].cast("long").alias("dst"), F.split("to", ":")[1].cast("long").alias("w"))
        )
    return spark.read.schema(schema).format(fmt).load(path)


def write_edges(edges: DataFrame, path: str, fmt: str) -> None:
    if fmt == "text":
        to = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("dst", "w"))), lambda x: F.concat_ws(":", x["dst"], x["w"])), " ")
        edges.groupBy("src").agg(to.alias("to")).select(F.concat_ws(" ", "src", "to").alias("value")).write.mode("overwrite").text(path)
    else:
        edges.select("src", "dst", "w").write.mode("overwrite").format(fmt).save(path)


def save_blocked(blocks: DataFrame, name: str, buckets: int) -> None:
    """Blocks as a table bucketed by part_id: joins and cogroups on part_id then leave them where they are."""
    blocks.write.mode("overwrite").bucketBy(buckets, "part_id").sortBy("part_id").saveAsTable(name)


def load_blocked(spark: SparkSession, name: str, parts: list[int] | None = None) -> DataFrame:
    """All blocks, or those of some parts: the filter prunes buckets and reaches the scan."""
    df = spark.table(name)
    return df if parts is None else df.where(F.col("part_id").isin(parts))
