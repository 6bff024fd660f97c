"""Source mixing: budgets against a plain recursion, epochs against a plain permutation, edge cases."""

import hashlib
import math
from collections import defaultdict

from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from fragsim.llm.mixing import leaf_budgets, mix_sources

SCHEMA = "doc_id long, text string, lang string, source string, domain string, tokens int, epoch int"
WEIGHTS = {"domain": {"a": 3.0, "b": 1.0}, "lang": {"x": 2.0}}


def fill(amount, children):
    """children: name -> (capacity, weight); hands out what siblings cannot take until nothing moves."""
    part, open_ = dict.fromkeys(children, 0.0), {k for k, (_, w) in children.items() if w > 0}
    while open_ and amount > 1e-9:
        whole = sum(children[k][1] for k in open_)
        full = {k for k in open_ if children[k][0] - part[k] <= amount * children[k][1] / whole + 1e-12}
        if not full:
            for k in open_:
                part[k] += amount * children[k][1] / whole
            return part
        for k in full:
            amount -= children[k][0] - part[k]
            part[k] = children[k][0]
        open_ -= full
    return part


def budgets(leaves, budget, weights, epochs):
    """leaves: (domain, lang, source) -> tokens."""
    w = lambda level, name: weights.get(level, {}).get(name, 1.0)
    out = {}
    cap = {k: (t * epochs if w("domain", k[0]) > 0 and w("lang", k[1]) > 0 and w("source", k[2]) > 0 else 0.0) for k, t in leaves.items()}

    def below(prefix, level):
        names = defaultdict(float)
        for k, c in cap.items():
            if k[: len(prefix)] == prefix:
                names[k[len(prefix)]] += c
        return {n: (c, w(level, n)) for n, c in names.items()}

    for d, part_d in fill(budget, below((), "domain")).items():
        for x, part_l in fill(part_d, below((d,), "lang")).items():
            for s, part in fill(part_l, below((d, x), "source")).items():
                out[d, x, s] = math.floor(part + 1e-6)
    return out


@settings(max_examples=5, deadline=None)
@given(
    st.dictionaries(st.tuples(st.sampled_from("abc"), st.sampled_from("xyz"), st.sampled_from("stu")), st.integers(1, 500), min_size=1, max_size=12),
    st.integers(0, 4000),
    st.sampled_from([1.0, 2.0]),
)
def test_budgets_equal_plain_recursion(spark, leaves, budget, epochs):
    df = spark.createDataFrame([(*k, t, 1) for k, t in leaves.items()], "domain string, lang string, source string, tokens long, docs long")
    got = {(r.domain, r.lang, r.source): r.budget for r in leaf_budgets(df, F.lit(budget), WEIGHTS, epochs).collect()}
    want = budgets(leaves, float(budget), WEIGHTS, epochs)
    assert got.keys() == leaves.keys()
    assert all(abs(got[k] - want.get(k, 0)) <= 1 for k in got)


def test_epochs_are_prefixes_of_the_seeded_permutation(spark):
    rows = [(i, "w" * (4 * (i % 7 + 1)), "x", "s1", "a") for i in range(300)] + [(1000 + i, "v" * 8, "x", "s2", "a") for i in range(5)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, domain string")
    got = mix_sources(df, F.col("domain"), {}, budget_share=0.6, max_epochs=3.0, seed=9).collect()
    by_leaf = defaultdict(list)
    for r in rows:
        by_leaf[r[3]].append((r[0], len(r[1]) // 4))
    taken = defaultdict(set)
    for r in got:
        taken[r.source].add((r.doc_id, r.epoch))
    left = {r.source: r.budget for r in got}
    for source, docs in by_leaf.items():
        want, rest, total = set(), left[source], sum(t for _, t in docs)
        full, rest = divmod(rest, total)
        want |= {(d, e) for e in range(full) for d, _ in docs}
        for d, t in sorted(docs, key=lambda x: hashlib.md5(f"9|{full}|{x[0]}".encode()).hexdigest()):
            if rest < t:
                break
            want.add((d, full))
            rest -= t
        assert taken[source] == want
    # The small source is short of its half, so its sibling receives what is left.
    assert left["s2"] == 3 * 10 and left["s1"] > left["s2"]


def test_edge_cases(spark):
    rows = [
        (1, None, "x", "s", "a", 1, 1), (2, "", None, None, None, 1, 1), (3, "word " * 60_000, "x", "s", "b", 1, 1),
        (4, "same", "x", "s", "a", 1, 1), (4, "same", "x", "s", "a", 1, 1), (None, "no id", "y", None, "a", 1, 1),
    ]
    df = spark.createDataFrame(rows, SCHEMA)
    got = mix_sources(df, F.col("domain"), WEIGHTS, budget_share=1.0, max_epochs=1.0).collect()
    assert sum(r.tokens for r in got) == 75_000 + 1 + 1 + 2
    assert sum(r.doc_id == 4 for r in got) == 2 and [r.doc_id for r in got if r.lang == "y"] == [None]
    none = mix_sources(df, F.col("domain"), {"domain": {"b": 0.0}}, budget_share=1.0, max_epochs=1.0).collect()
    assert not [r for r in none if r.domain == "b"]
    assert mix_sources(df.where(F.lit(False)), F.col("domain"), WEIGHTS).collect() == []
    assert mix_sources(df.drop("lang", "source"), F.col("domain"), {}, budget_share=1.0, max_epochs=1.0).count() >= 4
