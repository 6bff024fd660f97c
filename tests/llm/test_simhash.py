from pyspark.sql import functions as F

from fragsim.llm import queries, simhash
from fragsim.llm.components import connected_components

from . import brute


def test_query_equals_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()
    prints = [brute.simhash(r.text) for r in docs]
    want = dict(zip([r.doc_id for r in docs], zip([f"{p:016x}" for p in prints], brute.components([r.doc_id for r in docs], prints), strict=True), strict=True))
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in queries.op3_simhash_anchors(spark, sf).collect()}
    assert got == want


def test_every_near_pair_meets(spark):
    """All distances up to three are found, in each half, around codewords and others; hot anchors too."""
    import random

    rng = random.Random(3)
    centres = [0, (1 << 64) - 1, *(rng.getrandbits(64) for _ in range(40))]
    prints = set(centres)
    for c in centres:
        for _ in range(12):
            x = c
            for b in rng.sample(range(64), rng.randint(1, 4)):
                x ^= 1 << b
            prints.add(x)
    prints = sorted(prints)
    signed = [p - (1 << 64) if p >> 63 else p for p in prints]
    want = brute.components(signed, prints)
    for hot in (4096, 3):
        old, simhash.HOT_ANCHOR = simhash.HOT_ANCHOR, hot
        try:
            edges = simhash.links(spark.createDataFrame([(p,) for p in signed], "fp long"))
            roots = {r.node: r.root for r in connected_components(edges).collect()}
        finally:
            simhash.HOT_ANCHOR = old
        assert [roots.get(p, p) for p in signed] == want


def test_edge_cases(spark):
    rows = [(1, None, "x"), (2, "", "x"), (3, " \t\n", "y"), (4, "one", None), (5, "ONE", "z"), (6, "word " * 60_000, "z"), (6, "word " * 60_000, "z")]
    df = spark.createDataFrame(rows, "doc_id long, text string, fingerprint string")
    got = sorted((r.doc_id, r.fingerprint, r.component_id) for r in simhash.near_duplicates(df).collect())
    assert [g[2] for g in got[:3]] == [1, 1, 1] and got[0][1] == "0" * 16
    assert got[3][2] == got[4][2] == 4 and len(got) == 7
    assert simhash.near_duplicates(df.where(F.lit(False))).collect() == []


def test_components_of_chain_and_star(spark):
    chain = [(i, i + 1) for i in range(100, 160)] + [(7, 7)] + [(500 + i, 499) for i in range(1, 40)]
    got = {r.node: r.root for r in connected_components(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert all(got[i] == 100 for i in range(100, 161)) and all(got[i] == 499 for i in [499, *range(501, 540)]) and 7 not in got
