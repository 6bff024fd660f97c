"""Helpers shared by the training-data operators: table access and durable intermediate results."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bits of a key filter.  Its size is fixed, so what is broadcast is at most FILTER_BITS / 64 rows of 16
#: bytes whatever the input; a filter that fills up only lets more rows through to the exact join.
FILTER_BITS = 1 << 23
#: A key with more rows than this is hot; its rows are dealt over so many parts of a join.
HOT_ROWS, HOT_PARTS = 512, 32
_open: list[list[str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """Folder that the driver and all executors see: the cluster's ``spark.checkpoint.dir``.

    Only in local mode, where driver and executors are one machine, a folder of it may stand in.
    """
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="fragsim-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def scratch(spark: SparkSession, name: str) -> str:
    """A new path for a table of this run; ``temporary`` deletes it at its end."""
    path = f"{shared_root(spark)}/fragsim-{name}-{uuid.uuid4().hex}"
    if _open:
        _open[-1].append(path)
    return path


@contextmanager
def temporary(spark: SparkSession) -> Iterator[None]:
    """Deletes the tables that are made inside, once what needs them has been written."""
    _open.append([])
    try:
        yield
    finally:
        for path in _open.pop():
            drop_path(spark, path)


def persist(df: DataFrame, name: str, compression: str = "snappy") -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it again: the lineage ends there, and a
    lost executor takes nothing with it."""
    path = scratch(df.sparkSession, name)
    df.write.option("compression", compression).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete an intermediate table through Hadoop's file system layer (any store)."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def join_on(left: DataFrame, right: DataFrame, keys: list[str], how: str = "inner") -> DataFrame:
    """Equi-join in which nulls match nulls; the keys come from the left side."""
    for k in keys:
        right = right.withColumnRenamed(k, f"_key_{k}")
    on = reduce(lambda a, b: a & b, (left[k].eqNullSafe(right[f"_key_{k}"]) for k in keys))
    return left.join(right, on, how).drop(*(f"_key_{k}" for k in keys))


def key_filter(keys: DataFrame, key: Column) -> DataFrame:
    """Bloom filter (one hash) of a column as a table: word, bits."""
    slots = keys.select(F.pmod(F.xxhash64(key), F.lit(FILTER_BITS)).alias("slot"))
    return slots.groupBy(F.shiftright("slot", 6).alias("_word")).agg(F.expr("bit_or(shiftleft(1L, cast(slot % 64 as int)))").alias("_bits"))


def may_have(df: DataFrame, words: DataFrame, key: Column, flag: str = "_maybe") -> DataFrame:
    """``df`` with a flag that is true for all keys of the filter and few others."""
    rows = df.withColumn("_slot", F.pmod(F.xxhash64(key), F.lit(FILTER_BITS)))
    rows = rows.join(F.broadcast(words), F.shiftright("_slot", 6) == F.col("_word"), "left")
    return rows.withColumn(flag, F.expr("coalesce(shiftright(_bits, cast(_slot % 64 as int)) & 1 = 1, false)")).drop("_slot", "_word", "_bits")


def unused(taken: list[str], *names: str) -> list[str]:
    """The names, lengthened until no column of ``taken`` clashes with them (case does not count)."""
    have, out = {c.lower() for c in taken}, []
    for name in names:
        while name.lower() in have:
            name = "_" + name
        have.add(name.lower())
        out.append(name)
    return out


def numbered(df: DataFrame, name: str) -> DataFrame:
    """``df`` with a number of its own for every row, written once so that the numbers stay."""
    return persist(df.withColumn(name, F.monotonically_increasing_id()), "numbered")


def spread_join(left: DataFrame, right: DataFrame, keys: list[str], hot: DataFrame, how: str = "inner") -> DataFrame:
    """Equi-join with a ``right`` that has each key once.  Rows of the keys in ``hot`` (and of few others) are
    dealt over ``HOT_PARTS`` parts, each of which gets its copy of the right row, so no key fills a task."""
    part, flag = unused([*left.columns, *right.columns], "_part", "_hot")
    words = key_filter(hot, F.xxhash64(*keys))
    own = F.pmod(F.xxhash64(*left.columns), F.lit(HOT_PARTS)).cast("int")
    left = may_have(left, words, F.xxhash64(*keys), flag).withColumn(part, F.when(F.col(flag), own).otherwise(0)).drop(flag)
    copies = F.when(F.col(flag), F.sequence(F.lit(0), F.lit(HOT_PARTS - 1))).otherwise(F.array(F.lit(0)))
    right = may_have(right, words, F.xxhash64(*keys), flag).withColumn(part, F.explode(copies)).drop(flag)
    return left.join(right, [*keys, part], how).drop(part)
