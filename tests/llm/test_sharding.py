"""Uniform sharding: laws of sizes and slots, the drawn matrix, uniformity, edge cases."""

import random
import zlib
from collections import Counter

from pyspark.sql import functions as F

from fragsim.llm import queries
from fragsim.llm.sharding import assign_shards, communication_matrix, draw_hypergeometric, shard_rows, shard_sizes, write_shards


def lawful(rows, shards=8):
    counts = Counter(r.shard for r in rows)
    sizes = [counts.get(s, 0) for s in range(shards)]
    assert max(sizes) - min(sizes) <= 1 and sum(sizes) == len(rows)
    assert all(sorted(r.slot for r in rows if r.shard == s) == list(range(sizes[s])) for s in range(shards))


def test_query(spark, sf):
    text = {r.doc_id: (r.text or "").encode() for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = queries.op9_shards(spark, sf).collect()
    lawful(rows)
    assert sorted(r.doc_id for r in rows) == sorted(text)
    assert all((r.size, r.text_crc32, r.law, r.grown_shard) == (len(text[r.doc_id]) + 1, zlib.crc32(text[r.doc_id]), "rows", None) for r in rows)


def test_result_does_not_depend_on_files_and_tasks(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    place = lambda df: {(r.doc_id, r.shard, r.slot) for r in assign_shards(df).collect()}
    assert place(docs) == place(docs.repartition(13))
    assert place(docs) != {(r.doc_id, r.shard, r.slot) for r in assign_shards(docs, seed=18).collect()}


def test_matrix_has_its_sums_and_the_hypergeometric_mean():
    rows, sizes = [5, 0, 17, 100, 3], shard_sizes(125, 4)
    mean = [0.0] * 4
    for seed in range(300):
        m = communication_matrix(rows, sizes, seed)
        assert [sum(x) for x in m] == rows and [sum(c) for c in zip(*m, strict=True)] == sizes
        mean = [a + b / 300 for a, b in zip(mean, m[2], strict=True)]
    assert all(abs(a - 17 * s / 125) < 0.6 for a, s in zip(mean, sizes, strict=True))


def test_draws_follow_the_law():
    rng = random.Random(4)
    got = Counter(draw_hypergeometric(rng, 6, 15, 5) for _ in range(20_000))
    from math import comb

    for k in range(6):
        assert abs(got[k] / 20_000 - comb(6, k) * comb(9, 5 - k) / comb(15, 5)) < 0.02


def test_every_place_is_equally_likely(spark):
    """Chi-square of (row, shard) over seeds; neighbours in the input do not stay neighbours."""
    df = spark.createDataFrame([(i, "t") for i in range(16)], "doc_id long, text string").coalesce(1)
    seen = Counter((r.doc_id, r.shard) for seed in range(20) for r in assign_shards(df, shards=2, seed=seed, partitions=4, buckets=2).collect())
    chi = sum((seen[i, 0] - 10) ** 2 / 10 + (seen[i, 1] - 10) ** 2 / 10 for i in range(16))
    assert chi < 45  # 16 degrees of freedom: far beyond the 99.9 % point of 39.3


def test_edge_cases(spark, tmp_path):
    rows = [(1, None, 9, 9), (2, "", 9, 9), (3, "x", 9, 9), (3, "x", 9, 9), (3, "x", 9, 9), (None, "y", 9, 9), (4, "word " * 60_000, 9, 9)]
    df = spark.createDataFrame(rows, "doc_id long, text string, shard int, size int")
    out = assign_shards(df).collect()
    lawful(out)
    assert sorted(r.size for r in out) == [1, 1, 2, 2, 2, 2, 300_001]
    whole = shard_rows(df).collect()
    lawful(whole)
    assert sorted(str((r.doc_id, r.text)) for r in whole) == sorted(str(r[:2]) for r in rows) and {r["size"] for r in whole} == {9}
    assert assign_shards(df.where(F.lit(False))).collect() == [] and shard_rows(df.where(F.lit(False))).collect() == []
    write_shards(df, f"file://{tmp_path}/out")
    assert spark.read.parquet(f"file://{tmp_path}/out").count() == 7
