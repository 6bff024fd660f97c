"""Exact deduplication with a log-structured merge index of text digests.

Every memtable is flushed twice: its rows ``(doc_id, digest, copies)`` as an immutable segment, and one entry
per digest ``(digest, keep_id, group_size)`` as a sorted run of the index, with a filter of fixed size beside
it.  Before a flush the filters of all runs are probed; entries that pass are merge-joined with the runs,
and what is found there is a *hit*.  As soon as a level holds ``FANOUT`` runs they are compacted into one run of
the next level, which keeps per digest the surviving identifier and the size of the group.  After the last
memtable all levels are merged into the base.

Hits, across runs and inside one, are verified: their texts are compared byte by byte, and a digest that
stands for different texts is split by text.  Rows whose digest no filter of repeated digests lets through
are alone and need no join.  The result does not depend on the number of memtables.

All work is done by DataFrame operators of the JVM.  Hot groups (one text in a third of the rows) are
combined on the map side, and their rows are dealt over parts of the join; only 32-byte digests and
identifiers are shuffled for the rows that have no copy.

Defined results: a null text counts as the empty text; an empty table gives an empty result; rows that
repeat one identifier *and* one text are one group, of which a single row is kept; a null identifier
survives only if all rows of its group have none; columns beside the two used do not matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import HOT_ROWS, drop_path, key_filter, may_have, persist, scratch, spread_join

#: Runs of one level that are compacted into one of the next.
FANOUT = 3
_SEGMENT, _RUN = "doc_id long, digest binary, copies long", "digest binary, keep_id long, group_size long"


def sha256_digest(text: Column) -> Column:
    return F.unhex(F.sha2(text, 256))


class DigestIndex:
    """Log-structured index of digests below ``root``; segments and runs are immutable Parquet folders."""

    def __init__(self, spark: SparkSession, root: str | None = None, keep: str = "min", digest=sha256_digest) -> None:
        if keep not in ("min", "max"):
            raise ValueError("keep is 'min' or 'max'")
        self.spark, self.keep, self.digest = spark, keep, digest
        self.best = F.min if keep == "min" else F.max
        self.root = root or scratch(spark, "digests")
        self.segments: list[str] = []
        self.levels: list[list[str]] = []
        self.hits: list[str] = []
        self.written = 0

    def _read(self, schema: str, paths: list[str]) -> DataFrame:
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    def runs(self) -> list[str]:
        return [p for level in self.levels for p in level]

    def flush(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """Flush a memtable; returns the digests of it that older runs have."""
        segment = f"{self.root}/segment-{len(self.segments):05d}"
        rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), self.digest(F.coalesce(F.col(text_col), F.lit(""))).alias("digest"))
        rows.groupBy("doc_id", "digest").agg(F.count("*").alias("copies")).write.parquet(segment)
        self.segments.append(segment)
        new = self._merge(self._read(_SEGMENT, [segment]).select("digest", F.col("doc_id").alias("keep_id"), F.col("copies").alias("group_size")))
        new = persist(new, "memtable")
        found = f"{segment}-hits"
        self.probe(new).write.parquet(found)
        self.hits.append(found)
        self._write(new, 0)
        return self.spark.read.schema("digest binary").parquet(found)

    def probe(self, new: DataFrame) -> DataFrame:
        """Digests of ``new`` (one row each) that a run has: the filters first, the runs for what passes."""
        runs = self.runs()
        if not runs:
            return new.select("digest").limit(0)
        words = self._read("_word long, _bits long", [f"{r}.filter" for r in runs]).groupBy("_word").agg(F.expr("bit_or(_bits)").alias("_bits"))
        passed = may_have(new.select("digest"), words, F.col("digest")).where("_maybe").drop("_maybe")
        old = may_have(self._read(_RUN, runs).select("digest"), key_filter(passed, F.col("digest")), F.col("digest")).where("_maybe").drop("_maybe")
        return passed.join(old, "digest", "left_semi")

    def _merge(self, entries: DataFrame) -> DataFrame:
        return entries.groupBy("digest").agg(self.best("keep_id").alias("keep_id"), F.sum("group_size").alias("group_size"))

    def _write(self, entries: DataFrame, level: int) -> None:
        path = f"{self.root}/run-{self.written:05d}"
        self.written += 1
        entries.sortWithinPartitions("digest").write.parquet(path)
        run = self._read(_RUN, [path])
        key_filter(run, F.col("digest")).write.parquet(f"{path}.filter")
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(path)
        if len(self.levels[level]) >= FANOUT:
            full, self.levels[level] = self.levels[level], []
            self._write(self._merge(self._read(_RUN, full)), level + 1)
            for old in full:
                drop_path(self.spark, old)
                drop_path(self.spark, f"{old}.filter")

    def entries(self) -> DataFrame:
        return self._read(_SEGMENT, self.segments)

    def compact(self) -> DataFrame:
        """Merge all levels into one run, the base: digest, keep_id, group_size."""
        runs = self.runs()
        if len(runs) > 1:
            self.levels = [[] for _ in self.levels]
            self._write(self._merge(self._read(_RUN, runs)), len(self.levels))
            for old in runs:
                drop_path(self.spark, old)
                drop_path(self.spark, f"{old}.filter")
        return self.merged()

    def merged(self) -> DataFrame:
        return self._merge(self._read(_RUN, self.runs())) if len(self.runs()) > 1 else self._read(_RUN, self.runs())

    def hit_texts(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """Rows whose digest occurs more than once (with few others that pass the filter)."""
        words = key_filter(self.merged().where("group_size > 1"), F.col("digest"))
        rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
        rows = rows.withColumn("digest", self.digest(F.col("text")))
        return may_have(rows, words, F.col("digest")).where("_maybe").drop("_maybe")

    def collisions(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """Byte verification: digests under which different texts were found."""
        groups = self.hit_texts(docs, id_col, text_col).groupBy("digest").agg(F.min("text").alias("low"), F.max("text").alias("high"))
        return groups.where("low <> high").select("digest")


def dedup_exact(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", memtables: int = 4, digest=sha256_digest) -> DataFrame:
    """One row per row of ``docs``: doc_id, keep_id, group_size, kept, digest (see the module's text).

    ``memtables`` splits the input by identifier and text into that many flushed runs.
    """
    index = DigestIndex(docs.sparkSession, keep=keep, digest=digest)
    for i in range(memtables):
        index.flush(docs.where(F.pmod(F.xxhash64(F.col(id_col), F.coalesce(F.col(text_col), F.lit(""))), F.lit(memtables)) == i) if memtables > 1 else docs, id_col, text_col)
    base = index.compact()
    collided = persist(index.collisions(docs, id_col, text_col), "collided")
    entries = index.entries()  # rows that agree in identifier and text are in one memtable
    split = not collided.isEmpty()
    if split:
        entries, base = entries.join(collided, "digest", "left_anti"), base.join(collided, "digest", "left_anti")
    words = key_filter(base.where("group_size > 1"), F.col("digest"))
    marked = may_have(entries, words, F.col("digest"))
    columns = ["doc_id", "digest", "copies", "keep_id", "group_size"]
    alone = marked.where("not _maybe").select("doc_id", "digest", "copies", F.col("doc_id").alias("keep_id"), F.col("copies").alias("group_size"))
    near = marked.where("_maybe").drop("_maybe")
    groups = may_have(base, words, F.col("digest")).where("_maybe").drop("_maybe")
    rows = alone.unionByName(spread_join(near, groups, ["digest"], base.where(F.col("group_size") > HOT_ROWS)).select(*columns))
    if split:
        texts = persist(index.hit_texts(docs, id_col, text_col).join(collided, "digest", "left_semi"), "split")
        per_id = texts.groupBy("digest", "text", "doc_id").agg(F.count("*").alias("copies"))
        per_text = texts.groupBy("digest", "text").agg(index.best("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
        hot = per_text.where(F.col("group_size") > HOT_ROWS).select("digest", "text")
        rows = rows.unionByName(spread_join(per_id, per_text, ["digest", "text"], hot).select(*columns))
    one = rows.withColumn("nth", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))))
    kept = F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("nth") == 1)
    return one.select("doc_id", "keep_id", "group_size", kept.alias("kept"), "digest")
