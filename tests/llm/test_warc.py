import base64
import hashlib

from pyspark.sql import functions as F

from fragsim.llm import queries, warc


def expected(pages):
    owner = {}
    for p, _, h in pages:
        owner[h or ""] = max(p, owner.get(h or "", p))
    out = []
    for p, _, h in pages:
        body = (h or "").encode()
        digest = base64.b32encode(hashlib.sha1(body).digest()).decode()
        first = owner[h or ""]
        out.append((p, len(body), digest, "response" if p == first else "revisit", None if p == first else first))
    return sorted(out, key=str)


def rows(df):
    return sorted((tuple(r) for r in df.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to").collect()), key=str)


def test_query_round_trip(spark, sf):
    pages = [tuple(r) for r in spark.read.parquet(f"{sf}/pages.parquet").select("page_id", "url", "html").collect()]
    assert rows(queries.op4_warc_index(spark, sf)) == expected(pages)


def test_edge_cases_and_global_order(spark):
    pages = [(1, "http://b.org/x", "same"), (2, "http://www.a.org:80/y?q#f", "same"), (3, None, None), (4, "http://a.org/", ""), (5, "http://a.org/\r\nX: y", "é\r\n\r\nWARC/1.1\r\n\r\n"), (6, "http://b.org/x", "z" * 300_000), (7, "http://b.org/x", "same")]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").withColumn("size", F.lit("clash")).repartition(3)
    out = warc.archive_and_index(df).cache()
    assert rows(out) == expected(pages)
    ordered = [(r.urlkey, r.captured_at, r.page_id) for r in sorted(out.collect(), key=lambda r: (r.range_no, r.range_seq))]
    assert ordered == sorted(ordered) and "org,a)/y?q" in {k for k, _, _ in ordered}
    assert rows(warc.archive_and_index(df.where(F.lit(False)))) == []
    small = warc.archive_and_index(df, min_revisit_bytes=5)
    assert {r.record_type for r in small.collect()} == {"response"}


def test_loser_tree():
    runs = [[1, 4, 9], [], [2, 2, 8], [0], [3, 7]]
    assert list(warc.LoserTree(runs, lambda x: x)) == sorted(sum(runs, []))
    assert list(warc.LoserTree([], lambda x: x)) == []
