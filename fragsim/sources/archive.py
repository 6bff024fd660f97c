"""Corpora of many small files kept in archives: one row per member, read where Spark reads the archive."""

from __future__ import annotations

import io
import tarfile
import zipfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Members whose texts make one Arrow batch.
BATCH_CHARS = 16 << 20


def _members(name: str, content: bytes) -> Iterator[tuple[str, bytes]]:
    if name.endswith(".zip"):
        with zipfile.ZipFile(io.BytesIO(content)) as z:
            for info in z.infolist():
                if not info.is_dir():
                    yield info.filename, z.read(info)
        return
    with tarfile.open(fileobj=io.BytesIO(content)) as t:
        for info in t:
            if info.isfile():
                yield info.name, t.extractfile(info).read()


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names, texts, held = [], [], 0
    for batch in batches:
        for path, content in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            for member, data in _members(path, content):
                text = data.decode("utf-8", "replace")
                names.append(f"{path}!/{member}")
                texts.append(text)
                held += len(text)
                if held >= BATCH_CHARS:
                    yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(texts, pa.string())], ["origin", "text"])
                    names, texts, held = [], [], 0
    if names:
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(texts, pa.string())], ["origin", "text"])


def read_archives(spark: SparkSession, path: str, pattern: str = "*.{zip,tar,tgz,tar.gz}") -> DataFrame:
    """origin (archive!/member), text of every member of the archives below ``path``.

    Archives go through Spark's reader, so any store works, and one archive is one unit of work; each must
    fit in a task's memory.  Bytes that are not UTF-8 become replacement characters.
    """
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", pattern).load(path)
    return files.select("path", "content").mapInArrow(_unpack, "origin string, text string")
