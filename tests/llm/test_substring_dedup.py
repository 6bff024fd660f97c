from pyspark.sql import functions as F

from fragsim.llm import queries, substring_dedup

from . import brute

COLUMNS = ["doc_id", "n_words", "n_removed", "kept_sha256"]


def rows(df):
    return sorted(tuple(r) for r in df.select(*COLUMNS).collect())


def test_query_equals_brute_force(spark, sf):
    docs = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    want = sorted(brute.substring(docs))
    assert rows(queries.op10_substring_dedup(spark, sf)) == want
    assert any(r[2] for r in want)


def test_edge_cases_and_batches(spark):
    p = " ".join(f"w{i}" for i in range(60))
    same = "la " * 130
    part = " ".join(f"w{i}" for i in range(4, 57))
    docs = [(0, part), (20, p + " mid " + p), (21, "r " + part + " mid " + part), (1, None), (2, ""), (3, p), (4, "a " + p + " b"), (5, p[:150]), (6, same), (7, "x " + same), (8, p + " " + p), (9, "  " + p + "\x1c"), (10, "q" * 9_000_000), (11, " ".join(f"w{i}" for i in range(49))), (12, " ".join(f"w{i}" for i in range(1, 51)))]
    df = spark.createDataFrame(docs, "doc_id long, text string").withColumn("gone", F.lit(1)).withColumn("shared", F.lit(1))
    want = sorted(brute.substring(docs))
    for batches in (1, 3):
        assert rows(substring_dedup.remove_repeats(df, batches=batches)) == want
    assert rows(substring_dedup.remove_repeats(df.where(F.lit(False)))) == []
    twice = substring_dedup.remove_repeats(spark.createDataFrame([(1, p), (1, p), (2, p)], "doc_id long, text string"))
    assert sorted((r.doc_id, r.n_removed, r.kept_text) for r in twice.collect()) == [(1, 0, p), (1, 0, p), (2, 60, "")]


def test_words_are_compared_not_their_hashes(spark):
    """A long Thue-Morse word and its complement collide under every polynomial hash modulo 2**64."""
    bits = [bin(i).count("1") % 2 for i in range(4096)]
    one, two = "".join("ab"[b] for b in bits), "".join("ba"[b] for b in bits)
    text = lambda x: " ".join(f"w{i}" if i != 30 else x for i in range(61))
    df = spark.createDataFrame([(1, text(one)), (2, text(two)), (3, text(one))], "doc_id long, text string")
    for batches in (2,):
        assert {r.doc_id: r.n_removed for r in substring_dedup.remove_repeats(df, batches=batches).collect()} == {1: 0, 2: 0, 3: 61}


def test_rows_of_one_identifier_are_judged_by_their_texts(spark):
    p, q = (" ".join(f"{c}{i}" for i in range(60)) for c in "pq")
    data = [(1, p), (5, p), (5, q), (5, "x " + q), (None, "r " + q), (-(1 << 63), "s " + p), (7, q)]
    df = spark.createDataFrame(data, "doc_id long, text string")
    for batches in (2,):
        got = sorted((r.doc_id or 0, r.n_words, r.n_removed) for r in substring_dedup.remove_repeats(df, batches=batches).collect())
        assert got == sorted([(1, 60, 60), (5, 60, 60), (5, 60, 60), (5, 61, 60), (0, 61, 0), (-(1 << 63), 61, 0), (7, 60, 60)])


def test_batch_meets_history(spark):
    p = " ".join(f"w{i}" for i in range(200))
    part = " ".join(f"w{i}" for i in range(70, 150))
    rows = lambda *data: spark.createDataFrame([(i, 0, t) for i, t in data], "id long, mark long, text string")
    index = substring_dedup.FingerprintIndex(spark)
    all_rows = rows((1, p))
    assert index.add(all_rows, all_rows).collect() == []
    for step, (i, text, n) in enumerate([(2, "a " + part + " b", 31), (3, p, 151), (4, "other " * 3, 0), (5, "c " + part, 31)]):
        batch = rows((i, text))
        all_rows = all_rows.unionByName(batch)
        removed = index.add(batch, all_rows, after=i - 1).collect()
        assert {r.id for r in removed} <= {i} and len({s for r in removed for s in range(r.span // 65536, r.span // 65536 + r.span % 65536)}) == n
        assert sum(map(len, index.levels)) == bin(step + 2).count("1")  # runs are merged like the digits of a counter
    entries = index.entries()
    assert entries.count() == entries.select("h", "block").distinct().count() > 0
