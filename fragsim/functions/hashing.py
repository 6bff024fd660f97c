"""Metric hash."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from fragsim.config import BASES


def metric_hash(values: dict[str, Column]) -> Column:
    """MD5 of the whole numbers that fix all metrics."""
    return F.md5(F.concat_ws("|", *(values[b].cast("string") for b in BASES)))
