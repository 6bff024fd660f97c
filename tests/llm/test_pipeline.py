"""The pipeline's decisions, stage by stage, against plain Python on a small table."""

import re

from pyspark.sql import functions as F

import corpus_pipeline
from fragsim.llm import langid, queries

from . import brute


def near_components(rows):
    """Smallest identifier of each row's chain of pairs that share 0.8 or more of their five-word shingles."""
    sets = []
    for _, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", brute.lower_ascii(t or ""))
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    owner = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            both, either = len(sets[i] & sets[j]), len(sets[i] | sets[j])
            if not either or 5 * both >= 4 * either:
                a, b = owner[i], owner[j]
                owner = [b if x == a else x for x in owner]
    return [min(d for (d, _), o in zip(rows, owner, strict=True) if o == mine) for mine in owner]


def test_stages_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    stage = dict(corpus_pipeline.STAGES)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "simhash_near_dedup", "decontamination", "source_mixing", "sharding"]

    labelled = {r.doc_id: r for r in langid.identify(docs, langid.train(docs)).collect()}
    spoken = stage["language_id"](spark, docs, sf).cache()
    want = {d for d, r in labelled.items() if r.lang_pred != "und" and r.score >= corpus_pipeline.MIN_LANGUAGE_SCORE}
    assert {r.doc_id for r in spoken.collect()} == want and spoken.columns == docs.columns

    rows = [(r.doc_id, r.text) for r in spoken.collect()]
    parts = near_components(rows)
    single = stage["simhash_near_dedup"](spark, spoken, sf).cache()
    assert {r.doc_id for r in single.collect()} == set(parts) and single.columns == docs.columns

    items = [tuple(r) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    rows = [(r.doc_id, r.text) for r in single.collect()]
    clean = stage["decontamination"](spark, single, sf).cache()
    assert {r.doc_id for r in clean.collect()} == {r[0] for r in brute.contamination(rows, items) if not r[5]}

    mixed = stage["source_mixing"](spark, clean, sf).cache()
    assert mixed.columns == docs.columns
    size = lambda r: (len((r.text or "").encode()) + 3) // 4
    kept, given = sum(map(size, mixed.collect())), sum(map(size, clean.collect()))
    assert 0.6 * given < kept <= 0.8 * given

    out = stage["sharding"](spark, mixed, sf).collect()
    assert sorted(r.doc_id for r in out) == sorted(r.doc_id for r in mixed.collect())
    counts = [sum(r.shard == s for r in out) for s in range(8)]
    assert max(counts) - min(counts) <= 1 and all(sorted(r.slot for r in out if r.shard == s) == list(range(counts[s])) for s in range(8))
    assert queries.source_domain() is not None


def test_run_equals_stages(spark, sf):
    out = corpus_pipeline.run(spark, sf)
    assert out.columns == ["doc_id", "text", "lang", "source", "n_chars", "shard", "slot"] and out.count() > 50


def words(tag, n=40):
    return " ".join(f"{tag}{i}" for i in range(n))


def test_rows_decide_not_identifiers(spark, sf):
    """Null and repeated identifiers, null texts, clashing names, an empty table."""
    item = next(r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect() if len(r.text.split()) > 12)
    data = [(1, words("a")), (2, words("a")), (2, words("b")), (3, words("c")), (3, words("c")), (None, words("d")), (None, words("d")), (None, words("e")), (4, words("f") + " " + item), (None, "x " + item), (4, words("g")), (5, None), (6, "")]
    docs = spark.createDataFrame([(i, t, "en", "src1", None if t is None else len(t), 7.5, "own") for i, t in data], "doc_id long, text string, lang string, source string, n_chars long, score double, _text string")
    docs = docs.withColumns({"_row": F.lit(3), "_contaminated": F.lit("own"), "_copy": F.lit(1), "_id": F.lit(1), "shard": F.lit(9)})
    stage = dict(corpus_pipeline.STAGES)
    spoken = stage["language_id"](spark, docs, sf)
    assert spoken.columns == docs.columns and sorted(r.text for r in spoken.collect()) == sorted(t for _, t in data if t)
    assert {(r.score, r._text, r._row) for r in spoken.collect()} == {(7.5, "own", 3)}
    single = stage["simhash_near_dedup"](spark, docs.where("text <> ''"), sf)
    key = lambda r: (r.doc_id or 0, r.text)
    want = [(1, words("a")), (2, words("b")), (3, words("c")), (None, words("d")), (None, words("e")), *data[8:11]]
    assert single.columns == docs.columns and sorted(map(key, single.collect())) == sorted((i or 0, t) for i, t in want)
    clean = stage["decontamination"](spark, docs, sf)
    assert sorted(r.text or "" for r in clean.collect()) == sorted(t or "" for _, t in data if item not in (t or ""))
    mixed = stage["source_mixing"](spark, spark.createDataFrame([(None, words(f"m{i}x"), "en", "src1", 1) for i in range(50)], docs.select("doc_id", "text", "lang", "source", "n_chars").schema), sf)
    assert 30 <= mixed.count() <= 40
    sharded = stage["sharding"](spark, docs, sf).collect()
    assert len(sharded) == len(data) and sorted((r.text or "", r.doc_id or 0) for r in sharded) == sorted((t or "", i or 0) for i, t in data)
    assert len({(r.shard, r.slot) for r in sharded}) == len(data)
    for _, fn in corpus_pipeline.STAGES:
        assert fn(spark, docs.where(F.lit(False)), sf).collect() == []
