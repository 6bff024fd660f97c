"""WARC archives of pages and their capture index.

Writing: every page becomes one WARC/1.1 record whose block is an HTTP response with the page's UTF-8
bytes.  Of equal payloads the page with the largest identifier is a ``response``; the others are
``revisit`` records that refer to it and carry the HTTP head only.  Records are laid down by Spark's text
writer with the record end as line separator, so any store that Spark writes to will do, and a lost
executor's files are written again.

Reading: archives come back as whole files through Spark's binary reader; records are cut by their
Content-Length.  Each archive gives one *capture run*, sorted by URL key and timestamp.

Index merge: runs are cut at common key ranges, and the pieces of a range are merged by a loser tree, so
each output partition is sorted and the partitions follow each other: a global capture history.

Defined results: a null html is an empty payload, a null url an empty target; control characters in a
URL are percent-encoded; payloads shorter than ``min_revisit_bytes`` are always responses; rows that
repeat the largest identifier of a payload are all responses; an empty table gives an empty history;
other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import persist, scratch

_END = "\r\n\r\n"
_URN = "urn:page:"
#: Bytes of an archive file aimed at; a file is read as one row.
ARCHIVE_BYTES = 32 << 20
#: Index rows that one merge task holds.
RANGE_ROWS = 200_000
# The base32 alphabet of RFC 4648.
_BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"

INDEX_SCHEMA = "urlkey string, captured_at string, page_id long, record_type string, payload_bytes long, payload_digest string, refers_to long, url string, archive string, record_offset long, record_length long"


def base32_of_hex(digest: Column) -> Column:
    """Upper-case base32 of 40 hex digits, in column expressions: 5 hex digits are 4 base32 letters."""
    letters = []
    for i in range(8):
        n = F.conv(F.substring(digest, 5 * i + 1, 5), 16, 10).cast("int")
        letters += [F.substring(F.lit(_BASE32), F.shiftright(n, s).bitwiseAND(31) + 1, F.lit(1)) for s in (15, 10, 5, 0)]
    return F.concat(*letters)


def url_key(url: str) -> str:
    """Sort-friendly form: reversed host parts, then path and query; no scheme, port, ``www`` or fragment."""
    rest = url.partition("#")[0]
    rest = rest.partition("://")[2] if "://" in rest else rest
    cut = min([i for i in (rest.find("/"), rest.find("?")) if i >= 0], default=len(rest))
    host = rest[:cut].rpartition("@")[2].partition(":")[0].lower()
    host = host[4:] if host.startswith("www.") else host
    return ",".join(reversed(host.split("."))) + ")" + (rest[cut:] or "/")


def write_archives(pages: DataFrame, path: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", date: Column | None = None, min_revisit_bytes: int = 0) -> None:
    """Write one record per page below ``path``.

    ``date`` is the capture time; without it captures follow each other by the second, by identifier.
    """
    when = F.timestamp_seconds(F.lit(1_704_067_200) + F.pmod(F.coalesce(F.col(id_col), F.lit(0)), F.lit(300_000_000))) if date is None else date
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.coalesce(F.col(url_col), F.lit("")).alias("url"), F.coalesce(F.col(html_col), F.lit("")).alias("html"), when.alias("at"))
    rows = rows.withColumn("size", F.octet_length("html")).withColumn("hex", F.sha1("html"))
    groups = rows.where(F.col("size") >= min_revisit_bytes).groupBy("hex", "size").agg(F.max("page_id").alias("owner"), F.count("*").alias("n"), F.max_by("url", "page_id").alias("owner_url"), F.max_by("at", "page_id").alias("owner_at"))
    owners = persist(groups.where("n > 1").drop("n"), "owners")
    rows = rows.join(owners, ["hex", "size"], "left")
    revisit = F.col("owner").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("owner"))
    clean = lambda c: F.regexp_replace(F.regexp_replace(c, "[\r]", "%0D"), "[\\x00-\\x1f]", "%0A")
    stamp = lambda c: F.date_format(c, "yyyy-MM-dd'T'HH:mm:ss'Z'")
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.col("size").cast("string"), F.lit(_END))
    urn = lambda c: F.concat(F.lit(f"<{_URN}"), F.coalesce(c.cast("string"), F.lit("")), F.lit(">"))
    block_size = F.octet_length(http) + F.when(revisit, 0).otherwise(F.col("size"))
    refers = F.concat(
        F.lit("\r\nWARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest\r\nWARC-Refers-To: "), urn(F.col("owner")),
        F.lit("\r\nWARC-Refers-To-Target-URI: "), clean(F.col("owner_url")), F.lit("\r\nWARC-Refers-To-Date: "), stamp(F.col("owner_at")),
    )
    record = F.concat(
        F.lit("WARC/1.1\r\nWARC-Type: "), F.when(revisit, "revisit").otherwise("response"), F.lit("\r\nWARC-Record-ID: "), urn(F.col("page_id")),
        F.lit("\r\nWARC-Target-URI: "), clean(F.col("url")), F.lit("\r\nWARC-Date: "), stamp(F.col("at")),
        F.lit("\r\nWARC-Payload-Digest: sha1:"), base32_of_hex(F.col("hex")), F.when(revisit, refers).otherwise(""),
        F.lit("\r\nContent-Type: application/http; msgtype=response\r\nContent-Length: "), block_size.cast("string"), F.lit(_END),
        http, F.when(revisit, "").otherwise(F.col("html")),
    )
    mean = pages.agg(F.avg(F.octet_length(html_col))).first()[0] or 0
    per_file = max(1, int(ARCHIVE_BYTES / (mean + 600)))
    rows.select(record.alias("value")).write.option("lineSep", _END).option("maxRecordsPerFile", per_file).text(path)


def parse_archive(content: bytes, archive: str = "") -> list[tuple]:
    """Index rows (columns of INDEX_SCHEMA) of the records of one archive; bad records raise."""
    out, at, view = [], 0, memoryview(content)
    while at < len(content):
        head_end = content.find(b"\r\n\r\n", at)
        lines = content[at:head_end].decode().split("\r\n") if head_end >= 0 else [""]
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"{archive}: no WARC record at byte {at}")
        fields = {k.lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        start = head_end + 4
        stop = start + int(fields["content-length"])
        if content[stop : stop + 4] != b"\r\n\r\n":
            raise ValueError(f"{archive}: the record at byte {at} has another length")
        http_end = content.find(b"\r\n\r\n", start, stop) + 4
        http = {k.lower(): v.strip() for k, _, v in (x.partition(":") for x in content[start : http_end - 4].decode().split("\r\n")[1:])}
        digest = fields["warc-payload-digest"].removeprefix("sha1:")
        kind = fields["warc-type"]
        size = int(http["content-length"])
        if kind == "response":
            payload = view[http_end:stop]
            if len(payload) != size or base64.b32encode(hashlib.sha1(payload).digest()).decode() != digest:
                raise ValueError(f"{archive}: the payload at byte {http_end} does not match its digest")
        number = lambda name: int(n) if (n := fields.get(name, "").strip("<>").removeprefix(_URN)) else None  # noqa: B023, E731
        url = fields.get("warc-target-uri", "")
        out.append((url_key(url), fields["warc-date"], number("warc-record-id"), kind, size, digest, number("warc-refers-to"), url, archive, at, stop + 4 - at))
        at = stop + 4
    return out


def _key(row: tuple) -> tuple:
    """Order of captures: URL key, time, then identifier (none first)."""
    return row[0], row[1], row[2] is not None, row[2] or 0, row[8], row[9]


def _batch(rows: list[tuple], extra: list[tuple[str, pa.DataType]]) -> pa.RecordBatch:
    strings = {0, 1, 3, 5, 7, 8}
    names = [x.split()[0] for x in INDEX_SCHEMA.split(", ")] + [n for n, _ in extra]
    kinds = [pa.string() if i in strings else pa.int64() for i in range(11)] + [t for _, t in extra]
    columns = list(zip(*rows, strict=True)) if rows else [[] for _ in names]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A sorted run of index rows for each archive, numbered inside the run."""
    for batch in batches:
        for path, content in zip(batch.column(0), batch.column(1), strict=True):
            rows = sorted(parse_archive(content.as_py(), path.as_py()), key=_key)
            for i in range(0, len(rows), 10_000):
                yield _batch([(*r, i + j) for j, r in enumerate(rows[i : i + 10_000])], [("nth", pa.int64())])


def capture_runs(spark: SparkSession, path: str) -> DataFrame:
    """Index rows of all archives below ``path``; ``archive`` and ``nth`` give the run and the place in it."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "part-*").load(path)
    return files.select("path", "content").mapInArrow(_runs, INDEX_SCHEMA + ", nth long")


class LoserTree:
    """Merges sorted lists; every step replays one leaf-to-root path of losers."""

    def __init__(self, runs: list[list], key) -> None:
        self.runs, self.key, self.k = runs, key, max(1, len(runs))
        self.place = [0] * len(runs)
        self.heads = [self._head(i) for i in range(len(runs))]
        self.losers = [-1] * self.k
        self.winner = self._build(1) if runs else -1

    def _head(self, run: int):
        at = self.place[run]
        return (self.key(self.runs[run][at]), run) if at < len(self.runs[run]) else None

    def _beats(self, a: int, b: int) -> bool:
        return self.heads[b] is None or (self.heads[a] is not None and self.heads[a] < self.heads[b])

    def _build(self, node: int) -> int:
        if node >= self.k:
            return node - self.k
        left, right = self._build(2 * node), self._build(2 * node + 1)
        win, lose = (left, right) if self._beats(left, right) else (right, left)
        self.losers[node] = lose
        return win

    def __iter__(self):
        while self.winner >= 0 and self.heads[self.winner] is not None:
            run = self.winner
            yield self.runs[run][self.place[run]]
            self.place[run] += 1
            self.heads[run] = self._head(run)
            node = (run + self.k) // 2
            while node:
                if self._beats(self.losers[node], run):
                    run, self.losers[node] = self.losers[node], run
                node //= 2
            self.winner = run


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Merge the run pieces of a key range; rows come sorted by run and place."""
    runs: list[list[tuple]] = []
    last = None
    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if row[8] != last:
                runs.append([])
                last = row[8]
            runs[-1].append(row[:11])
    part, held, at = TaskContext.get().partitionId(), [], 0
    for row in LoserTree(runs, _key):
        held.append((*row, part, at))
        at += 1
        if len(held) == 10_000:
            yield _batch(held, [("range_no", pa.int64()), ("range_seq", pa.int64())])
            held = []
    yield _batch(held, [("range_no", pa.int64()), ("range_seq", pa.int64())])


def merge_runs(runs: DataFrame, range_rows: int = RANGE_ROWS) -> DataFrame:
    """Global capture history: index rows with range_no and range_seq, in which they are ordered."""
    runs = persist(runs, "runs")
    ranges = max(1, -(-runs.count() // range_rows))
    spread = max(ranges, runs.sparkSession.sparkContext.defaultParallelism)
    pieces = runs.repartitionByRange(spread, "urlkey", "captured_at", F.col("page_id").asc_nulls_first(), "archive", "record_offset").sortWithinPartitions("archive", "nth")
    return pieces.drop("nth").mapInArrow(_merge, INDEX_SCHEMA + ", range_no long, range_seq long")


def archive_and_index(pages: DataFrame, path: str | None = None, **options) -> DataFrame:
    """Write ``pages`` as archives, read them back and return the merged capture history."""
    spark = pages.sparkSession
    path = path or scratch(spark, "archives")
    write_archives(pages, path, **options)
    return merge_runs(capture_runs(spark, path))
