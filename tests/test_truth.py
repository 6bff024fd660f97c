"""Passages and mutants of every document."""

from fragsim.operators import truth as R


def test_passages_equal_contains(spark):
    items = ["two three", "ne two thr", "...", "!", "one", "a b c d e f g", "b c d e f", "Ünï x", " c d ", "three", "", None, "four five six seven eig", "ONE"]
    texts = ["one two three four", "a b c d e f g h", "xa b c d e f gx ...", "Hi! Ünï x", None, "", "Zero four five six seven eight", "bONE b  c d"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = sorted(tuple(r) for r in R.passages(docs, bench).collect())
    assert got == [(i, d) for i, x in enumerate(items) for d, t in enumerate(texts) if x and t and x in t]


def test_every_document_gets_mutants(spark):
    texts = [" ".join(f"Sentence{k} number{d} about thing{d * k} goes further{k}." for k in range(12)) for d in range(1, 5)]
    docs = spark.createDataFrame(list(enumerate(texts, 11)), "doc_id long, text string")
    assert sorted((r.base_id, r.kind) for r in R.mutants(docs).collect()) == [(b, k) for b in range(11, 15) for k in range(7)]


def test_categories_equal_plain_counts(spark):
    from collections import Counter

    from fragsim.sources.prose import prose_fragments

    texts = {1: "One two three. Four five six. Seven eight.", 2: "One  two three.\nFour five six. Seven eight.", 3: "One two three. Four five six.", 4: "One two three. One two three. Four.", 5: "", 6: None, 7: "Ten eleven."}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    pairs = spark.createDataFrame([(1, 2), (1, 3), (1, 4), (3, 4), (4, 7), (5, 6), (1, 5)], "left_id long, right_id long")
    frags = prose_fragments(docs, "doc_id", "text")
    words = {r.fragment_id: r.words for r in frags.collect()}
    got = {(r.left_id, r.right_id): r for r in R.categorise(pairs, frags).collect()}
    assert len(got) == 7
    for (a, b), r in got.items():
        longest = max(len(words[a]), len(words[b]))
        same = sum((Counter(words[a]) & Counter(words[b])).values())
        assert r.token_pct == (same * 100 // longest if longest else 100)
    assert got[1, 2].category == "T1" and got[5, 6].category == "T1" and got[1, 3].line_pct == 66 and got[3, 4].line_pct == 33 and got[4, 7].category == "WT3T4"
