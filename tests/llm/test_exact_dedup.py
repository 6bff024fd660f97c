"""Exact deduplication against plain grouping, colliding digests, runs and edge cases."""

import hashlib
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from fragsim.llm import queries
from fragsim.llm.exact_dedup import DigestIndex, dedup_exact


def grouped(rows, best=min):
    """rows: (id, text) -> sorted (id, keep, size, kept)."""
    groups = defaultdict(list)
    for d, t in rows:
        groups[t or ""].append(d)
    out = []
    for ids in groups.values():
        known = [d for d in ids if d is not None]
        keep, used = (best(known) if known else None), False
        for d in ids:
            kept = d == keep and not used
            used |= kept
            out.append((d, keep, len(ids), kept))
    return sorted(out, key=str)


def shown(df):
    return sorted(((r.doc_id, r.keep_id, r.group_size, r.kept) for r in df.collect()), key=str)


ROWS = [
    (1, None), (2, ""), (3, "a"), (4, "b"), (5, "a"), (5, "a"), (6, "A"), (7, "a "), (8, "word " * 60_000), (9, "word " * 60_000),
    (None, "b"), (None, "alone"), (10, "é"), (11, "é"),
]


@pytest.mark.parametrize("keep", ["min", "max"])
@pytest.mark.parametrize("memtables", [1, 3])
def test_edge_cases(spark, keep, memtables):
    df = spark.createDataFrame([(*r, "x", 1, 2) for r in ROWS], "doc_id long, text string, digest string, copies int, keep_id int")
    assert shown(dedup_exact(df, keep=keep, memtables=memtables)) == grouped(ROWS, {"min": min, "max": max}[keep])
    assert dedup_exact(df.where(F.lit(False)), keep=keep).collect() == []


def test_colliding_digests_are_split_by_text(spark):
    """A digest of one byte puts different texts under one key; byte verification tells them apart."""
    rows = [(i, f"text {i % 90}") for i in range(400)] + ROWS
    df = spark.createDataFrame(rows, "doc_id long, text string")
    weak = lambda t: F.unhex(F.substring(F.sha2(t, 256), 1, 1).cast("string"))
    assert shown(dedup_exact(df, keep="max", memtables=2, digest=weak)) == grouped(rows, max)


def test_runs_of_later_days_join_the_index(spark):
    index = DigestIndex(spark, keep="min")
    index.flush(spark.createDataFrame([(1, "a"), (2, "b")], "doc_id long, text string"))
    index.compact()
    index.flush(spark.createDataFrame([(3, "a"), (4, "c")], "doc_id long, text string"))
    got = {bytes(r.digest): (r.keep_id, r.group_size) for r in index.compact().collect()}
    assert got == {hashlib.sha256(t.encode()).digest(): v for t, v in (("a", (1, 2)), ("b", (2, 1)), ("c", (4, 1)))}


def test_flush_probes_older_runs(spark):
    index, rows = DigestIndex(spark), lambda *t: spark.createDataFrame(list(enumerate(t)), "doc_id long, text string")
    hits = [{bytes(r.digest) for r in index.flush(rows(*t)).collect()} for t in (["a", "b"], ["b", "c"], ["a", "d"], ["e", "c"])]
    of = lambda t: hashlib.sha256(t.encode()).digest()
    assert hits == [set(), {of("b")}, {of("a")}, {of("c")}]
    assert [len(x) for x in index.levels] == [1, 1] and index.compact().count() == 5 and len(index.runs()) == 1


def test_query_equals_grouping(spark, sf):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    out = queries.op6_exact_dedup(spark, sf)
    assert shown(out) == grouped(docs, max)
    text = dict(docs)
    assert all(r.text_sha256 == hashlib.sha256((text[r.doc_id] or "").encode()).hexdigest() for r in out.collect())
