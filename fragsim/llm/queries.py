"""Queries of the training-data operators, one per operator, with their SQL where SQL can express them."""

from __future__ import annotations

import secrets
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: Parameters of the mixing query.
MIX_WEIGHTS = {
    "domain": {"web": 0.4, "books": 0.3, "code": 0.2, "forum": 0.1},
    "lang": {"en": 0.5, "de": 0.2, "fr": 0.2, "es": 0.1},
}
MIX_SHARE, MIX_EPOCHS, MIX_SEED = 0.5, 2.0, 7


def source_domain() -> Column:
    """Domain of a source by its number: five sources each, the rest are forums."""
    n = F.regexp_extract(F.coalesce(F.col("source"), F.lit("")), "([0-9]{1,9})$", 1)
    k = F.when(n == "", 99).otherwise(n.cast("int"))
    return F.when(k < 5, "web").when(k < 10, "books").when(k < 15, "code").otherwise("forum")


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mix_sources

    return mix_sources(table(spark, sf_dir, "documents"), source_domain(), MIX_WEIGHTS, MIX_SHARE, MIX_EPOCHS, MIX_SEED)


def _case(column: str, weights: dict[str, float]) -> str:
    return f"CASE {column} " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in weights.items()) + " ELSE 1.0 END"


def _fill_sql(nodes: str, parent: str, name: str) -> str:
    """Water filling by search for the level: a child gets least(cap, level * weight); the level is the
    one at which the parts add up, found among the levels at which a child becomes full."""
    same = " AND ".join(f"a.{c} = b.{c}" for c in parent.split(", "))
    return f"""
    {name}_try AS (SELECT b.*, b.c / b.w AS lvl FROM {nodes} b),
    {name}_sum AS (SELECT {", ".join(f"b.{c}" for c in parent.split(", "))}, b.lvl,
        sum(CASE WHEN a.lvl <= b.lvl THEN a.c ELSE 0 END) AS c_full, sum(CASE WHEN a.lvl > b.lvl THEN a.w ELSE 0 END) AS w_open, any_value(b.g) AS g
      FROM (SELECT DISTINCT {parent}, lvl, g FROM {name}_try UNION SELECT DISTINCT {parent}, 0.0, g FROM {name}_try) b JOIN {name}_try a ON {same} GROUP BY ALL),
    {name}_lvl AS (SELECT {parent}, max_by(CASE WHEN w_open > 0 THEN (g - c_full) / w_open ELSE 1e300 END, lvl) AS water
      FROM {name}_sum WHERE c_full + lvl * w_open <= g * (1 + 1e-12) GROUP BY ALL),
    {name} AS (SELECT b.*, least(b.c, a.water * b.w) AS part FROM {name}_try b JOIN {name}_lvl a ON {same})"""


OP1_SQL = f"""
WITH base AS (
  SELECT doc_id, CASE WHEN n < 5 THEN 'web' WHEN n < 10 THEN 'books' WHEN n < 15 THEN 'code' ELSE 'forum' END AS domain, lang, source, tokens, text
  FROM (SELECT doc_id, lang, source, text, (strlen(coalesce(text, '')) + 3) // 4 AS tokens, coalesce(try_cast(regexp_extract(source, '([0-9]+)$', 1) AS INT), 99) AS n FROM documents)),
leaves AS (SELECT 0 AS root, domain, lang, source, CAST(sum(tokens) AS DOUBLE) AS tokens FROM base GROUP BY ALL),
total AS (SELECT floor(sum(tokens) * {MIX_SHARE}) AS t FROM leaves),
n1 AS (SELECT root, domain, sum(tokens) * {MIX_EPOCHS} AS c, {_case("domain", MIX_WEIGHTS["domain"])} AS w, any_value(t) AS g FROM leaves, total GROUP BY ALL),
{_fill_sql("n1", "root", "f1")},
n2 AS (SELECT l.domain, l.lang, sum(l.tokens) * {MIX_EPOCHS} AS c, {_case("l.lang", MIX_WEIGHTS["lang"])} AS w, any_value(f1.part) AS g FROM leaves l JOIN f1 USING (domain) GROUP BY ALL),
{_fill_sql("n2", "domain", "f2")},
n3 AS (SELECT l.domain, l.lang, l.source, l.tokens * {MIX_EPOCHS} AS c, 1.0 AS w, f2.part AS g, l.tokens FROM leaves l JOIN f2 USING (domain, lang)),
{_fill_sql("n3", "domain, lang", "f3")},
budgets AS (SELECT domain, lang, source, CAST(floor(part + 1e-6) AS BIGINT) AS budget, CAST(tokens AS BIGINT) AS leaf FROM f3),
fit AS (SELECT *, budget // greatest(leaf, 1) AS n_full, budget - budget // greatest(leaf, 1) * leaf AS rest FROM budgets),
j AS (SELECT b.*, f.budget, f.n_full, f.rest FROM base b JOIN fit f USING (domain, lang, source)),
passes AS (SELECT j.*, unnest(range(0, n_full + 1)) AS epoch FROM j),
cut AS (SELECT *, sum(tokens) OVER (PARTITION BY domain, lang, source ORDER BY md5('{MIX_SEED}|' || epoch || '|' || coalesce(CAST(doc_id AS VARCHAR), md5(coalesce(text, '')))), doc_id ROWS UNBOUNDED PRECEDING) AS upto
  FROM passes WHERE epoch = n_full AND rest > 0)
SELECT doc_id, domain, lang, source, tokens, epoch, budget FROM passes WHERE epoch < n_full
UNION ALL SELECT doc_id, domain, lang, source, tokens, epoch, budget FROM cut WHERE upto <= rest
"""


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .exact_dedup import dedup_exact

    out = dedup_exact(table(spark, sf_dir, "documents"), keep="max")
    return out.select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


OP6_SQL = """
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id = max(doc_id) OVER w AS kept, sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW w AS (PARTITION BY coalesce(text, ''))
"""


def op9_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .sharding import assign_shards

    return assign_shards(table(spark, sf_dir, "documents"), shards=8)


def op3_simhash_anchors(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .simhash import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op8_suffix_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decontam import scan

    out = scan(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return out.drop("spans", "items")  # the longest matches and their places stay


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .substring_dedup import remove_repeats

    return remove_repeats(table(spark, sf_dir, "documents"), keep_text=False)


def op4_warc_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .warc import archive_and_index

    out = archive_and_index(table(spark, sf_dir, "pages"))
    return out.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "urlkey", "captured_at", "range_no", "range_seq")


def op7_html_wrappers(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .html_wrappers import extract_main_text

    return extract_main_text(table(spark, sf_dir, "pages"))


def op5_byte_gru(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .langid import identify, train

    docs = table(spark, sf_dir, "documents")
    return identify(docs, train(docs))


def op2_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The key comes from the session (``spark.fragsim.pii.key``); without one the run draws its own and forgets it."""
    from .pii import replace_pii

    key = spark.conf.get("spark.fragsim.pii.key", None) or secrets.token_hex(32)
    return replace_pii(table(spark, sf_dir, "documents"), key.encode())


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_mix_sources": op1_mix_sources,
    "op2_pii_surrogates": op2_pii_surrogates,
    "op3_simhash_anchors": op3_simhash_anchors,
    "op4_warc_index": op4_warc_index,
    "op5_byte_gru": op5_byte_gru,
    "op6_exact_dedup": op6_exact_dedup,
    "op7_html_wrappers": op7_html_wrappers,
    "op8_suffix_decontamination": op8_suffix_decontamination,
    "op9_shards": op9_shards,
    "op10_substring_dedup": op10_substring_dedup,
}

SQL: dict[str, str] = {"op1_mix_sources": OP1_SQL, "op6_exact_dedup": OP6_SQL}
