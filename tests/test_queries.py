"""Queries against their SQL twins on the smallest tables."""

import os

import duckdb
import pytest

from fragsim.queries import registry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

CHECKED = (
    "frag_prose_tokens", "frag_markup", "metrics_prose", "metrics_basket", "text_key_groups", "band_edges", "band_assign", "subband_assign", "stop_actions", "overlap_denoms",
    "candidates_55", "candidates_55_bands", "candidates_55_max", "candidates_count_layout", "top_candidates", "ablation_table", "theta_sweep", "hash_clones",
    "clone_classes", "truth_categories", "token_bag_clones", "precision_sample", "auc", "prf", "curate_pairs", "siamese_score_fixed", "asof_activity", "stream_activity_bags", "stream_session_frags",
    "mutants", "norm_tokenset_clones", "metric_hash_groups", "stream_unique_events", "stream_click_to_purchase", "stream_action_counters", "stream_consecutive_overlap", "stream_incremental",
)


def plain(v):
    if isinstance(v, float):
        return round(v, 6)
    return str(v)


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_sql(spark, sf, name):
    df = registry.QUERIES[name](spark, sf)
    columns = sorted(df.columns)
    got = sorted((tuple(plain(v) for v in r) for r in df.select(*columns).collect()), key=str)
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{path + '/*' if os.path.isdir(path) else path}')")
    out = con.execute(registry.SQL[name])
    names = [x[0] for x in out.description]
    assert sorted(names) == columns
    order = [names.index(c) for c in columns]
    assert got == sorted((tuple(plain(r[i]) for i in order) for r in out.fetchall()), key=str)


def test_every_query_is_callable_and_registered():
    assert set(registry.SQL) <= set(registry.QUERIES) and len(registry.QUERIES) > 70 and all(map(callable, registry.QUERIES.values()))
