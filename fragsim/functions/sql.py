"""Functions for users who write SQL.  All but the front end are SQL functions, which the optimizer inlines."""

from __future__ import annotations

from pyspark.sql import SparkSession

#: Signature and body of the temporary functions.
FUNCTIONS = {
    "size_compatible": ("(a BIGINT, b BIGINT, gamma_pct INT) RETURNS BOOLEAN", "least(a, b) * 100 >= greatest(a, b) * gamma_pct"),
    "action_overlap": (
        "(a MAP<STRING, BIGINT>, b MAP<STRING, BIGINT>) RETURNS BIGINT",
        "aggregate(map_values(map_zip_with(a, b, (k, x, y) -> least(coalesce(x, 0L), coalesce(y, 0L)))), 0L, (s, v) -> s + v)",
    ),
    "action_share": (
        "(a MAP<STRING, BIGINT>, b MAP<STRING, BIGINT>) RETURNS DOUBLE",
        "aggregate(map_values(map_zip_with(a, b, (k, x, y) -> least(coalesce(x, 0L), coalesce(y, 0L)))), 0L, (s, v) -> s + v) / nullif(least("
        "aggregate(map_values(a), 0L, (s, v) -> s + v), aggregate(map_values(b), 0L, (s, v) -> s + v)), 0)",
    ),
    "fragment_words": ("(t STRING) RETURNS ARRAY<STRING>", r"regexp_extract_all(lower(coalesce(t, '')), r'([\p{L}\p{N}_]+)', 1)"),
    "lexical_key": (
        "(t STRING) RETURNS STRING",
        r"md5(array_join(transform(regexp_extract_all(lower(coalesce(t, '')), r'([\p{L}\p{N}_]+)', 1), w -> CASE WHEN rlike(w, '^[0-9]+$') THEN 'n' ELSE"
        r" concat('v', array_position(regexp_extract_all(lower(coalesce(t, '')), r'([\p{L}\p{N}_]+)', 1), w)) END), ' '))",
    ),
    "metric_key": ("(v ARRAY<BIGINT>) RETURNS STRING", "md5(array_join(transform(v, x -> string(x)), '|'))"),
}

#: Table functions.
TABLE_FUNCTIONS = {
    "fragment_windows": (
        "(t STRING, width INT, stride INT) RETURNS TABLE (place INT, words ARRAY<STRING>)",
        "SELECT p AS place, slice(w, p + 1, width) AS words FROM (SELECT fragment_words(t) AS w) LATERAL VIEW explode(sequence(0, greatest(size(w) - width, 0), stride)) s AS p",
    ),
    "fragment_lines": (
        "(t STRING) RETURNS TABLE (line_no INT, line STRING)",
        "SELECT p AS line_no, l AS line FROM (SELECT split(coalesce(t, ''), '\\n') AS a) LATERAL VIEW posexplode(a) s AS p, l",
    ),
}


def register(spark: SparkSession) -> list[str]:
    """Registers the functions in this session and returns their names."""
    for name, (signature, body) in (FUNCTIONS | TABLE_FUNCTIONS).items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{signature} RETURN {body}")
    return [*FUNCTIONS, *TABLE_FUNCTIONS]
