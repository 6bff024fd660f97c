"""All queries of the engine with their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from fragsim.queries import evaluation, filtering, preprocessing, streams

_GROUPS = (preprocessing, filtering, evaluation, streams)

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {k: f for g in _GROUPS for k, f in g.Q.items()}
SQL: dict[str, str] = {k: s for g in _GROUPS for k, s in g.S.items()}
