from pyspark.sql import functions as F

from fragsim.llm import decontam, queries

from . import brute

COLUMNS = ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]


def rows(df):
    return sorted(tuple(r) for r in df.select(*COLUMNS).collect())


def test_query_equals_brute_force(spark, sf):
    docs = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    items = [tuple(r) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    got = rows(queries.op8_suffix_decontamination(spark, sf))
    assert got == sorted(brute.contamination(docs, items))
    assert any(r[2] for r in got)


def fixture(spark):
    a = " ".join(f"w{i}" for i in range(14))
    docs = [(1, "x " + a.upper() + " y"), (2, a[:20]), (3, None), (4, ""), (5, "Tiny, text! tiny-text"), (6, "é " * 30), (7, a + " " + a), (7, a + " " + a), (8, "tiny"), (9, "z " * 200_000 + a)]
    items = [(10, a), (11, a[3:]), (12, "tiny text"), (13, None), (14, " ... "), (15, "é " * 12), (16, "solo"), (10, a)]
    return docs, items, spark.createDataFrame(docs, "doc_id long, text string").withColumn("n_words", F.lit("clash")), spark.createDataFrame(items, "item_id long, text string")


def test_edge_cases_and_slices(spark):
    docs, items, d, b = fixture(spark)
    want = sorted(brute.contamination(docs, items))
    assert rows(decontam.scan(d, b)) == want
    assert rows(decontam.scan(d, b, slice_bytes=40)) == want
    assert rows(decontam.scan(d, b.where("item_id > 99"))) == sorted(brute.contamination(docs, []))
    assert rows(decontam.scan(d.where(F.lit(False)), b)) == []


def test_equal_identifiers_with_different_texts(spark):
    dirty, clean = " ".join(f"w{i}" for i in range(12)), " ".join(f"v{i}" for i in range(12))
    d = spark.createDataFrame([(1, dirty), (1, clean), (None, dirty), (None, clean)], "doc_id long, text string")
    b = spark.createDataFrame([(1, dirty), (2, "tiny"), (3, "q " * 11)], "item_id long, text string")
    for limit in (1 << 20, 30):
        got = decontam.scan(d, b, slice_bytes=limit).collect()
        assert sorted((str(r.doc_id), r.n_words, r.n_hit) for r in got) == [("1", 12, 0), ("1", 12, 12), ("None", 12, 0), ("None", 12, 12)]
        marked = decontam.flag(d.withColumn("_text", F.lit("own")), b, "bad", slice_bytes=limit)
        assert sorted((r.text, r.bad, r._text) for r in marked.collect()) == sorted([(dirty, True, "own"), (clean, False, "own")] * 2)


def test_longest_matches(spark):
    _, _, d, b = fixture(spark)
    whole, cut = ({(r.doc_id, r.n_words, str(r.matches)) for r in decontam.scan(d, b, slice_bytes=n).collect()} for n in (1 << 20, 40))
    assert whole == cut
    got = {r.doc_id: r for r in decontam.scan(d, b).collect()}
    first = got[1].matches[0]
    assert (first.item_id, first.item_word, first.doc_word, first.length) == ("10", 0, 1, 14) and got[1].longest == 14
    assert [m.length for m in got[7].matches] == [14] and got[9].matches[0].doc_word == 200_000 and got[3].matches == []


def test_longest_match_by_brute_force(spark):
    import random

    rng = random.Random(4)
    text = lambda n: " ".join(rng.choice("ab") for _ in range(n))
    docs, items = [(i, text(60)) for i in range(12)], [(i, text(25)) for i in range(6)]
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {r.doc_id: r for r in decontam.scan(d, b, window=6).collect()}
    for i, t in docs:
        w, best = t.split(), 0
        for _, x in items:
            y = x.split()
            for p in range(60):
                for q in range(25):
                    n = 0
                    while p + n < 60 and q + n < 25 and w[p + n] == y[q + n]:
                        n += 1
                    best = max(best, n)
        assert got[i].longest == (best if best >= 6 else 0)
        for m in got[i].matches:
            y = dict(items)[int(m.item_id)].split()
            assert y[m.item_word : m.item_word + m.length] == w[m.doc_word : m.doc_word + m.length]
