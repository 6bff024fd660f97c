"""Readers and writers."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The cluster's ``spark.checkpoint.dir``; only in local mode a folder of this machine may stand in."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="fragsim-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def spread(df: DataFrame) -> DataFrame:
    """Rows of an input that is too small to give every core splits of its own, dealt over the cores; a large
    one is left as it is read."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return df.repartition(cores) if size < cores << 25 else df


def staged(df: DataFrame, name: str, **options: str) -> DataFrame:
    """``df`` written to the shared folder and read again, for results that several stages read: the scan and the
    text functions before it run once, and a lost executor takes nothing with it."""
    path = f"{shared_folder(df.sparkSession)}/fragsim-{name}-{uuid.uuid4().hex}"
    df.write.options(**options).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def read_corpus(spark: SparkSession, path: str, kind: str = "text", **options: str) -> DataFrame:
    """origin, unit_text of a user's corpus: whole text files, or a table with columns origin and text."""
    if kind == "text":
        files = spark.read.option("recursiveFileLookup", "true").text(path, wholetext=True)
        return files.select(F.input_file_name().alias("origin"), F.col("value").alias("text"))
    if kind == "binary":
        files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path)
        return files.select(F.col("path").alias("origin"), F.col("content").cast("string").alias("text"))
    if kind not in ("parquet", "json", "orc", "csv"):
        raise ValueError(f"unknown corpus kind {kind}")
    reader = spark.read.options(**options)
    if kind == "csv":
        reader = reader.option("header", "true").option("multiLine", "true").option("escape", '"')
    return reader.format(kind).load(path).select("origin", "text")


def write_fragments(fragments: DataFrame, path: str) -> None:
    """Preprocessing output, laid out by size band so that later runs prune."""
    fragments.repartition("home_band").write.partitionBy("home_band").mode("overwrite").parquet(path)


def write_postings(postings: DataFrame, name: str, buckets: int = 16) -> None:
    """Posting table bucketed by band and action: later lookups need no shuffle on this side."""
    postings.write.bucketBy(buckets, "band", "action").sortBy("band", "action").mode("overwrite").saveAsTable(name)


def write_pairs(pairs: DataFrame, path: str, kind: str = "json") -> None:
    pairs.write.mode("overwrite").format(kind).save(path)
