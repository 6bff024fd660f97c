"""Scoring pairs: networks over Arrow batches, the same forward pass as relational SQL, and a fixed rule."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fragsim.config import METRICS


@dataclass(frozen=True)
class FixedRule:
    """Clone if the weighted absolute metric differences stay below a bound; all in column expressions."""

    weights: dict[str, int]
    bound: int


def _score(batches: Iterator[pa.RecordBatch], shared, symmetry: str, at: int) -> Iterator[pa.RecordBatch]:
    model = shared.value
    for batch in batches:
        column = batch.column(at)
        x = column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1) if len(column) else np.zeros((0, 2))
        p = model.predict(x, symmetry) if len(x) else np.zeros(0)
        arrays = [batch.column(i) for i in range(batch.num_columns) if i != at]
        names = [f.name for i, f in enumerate(batch.schema) if i != at]
        yield pa.RecordBatch.from_arrays([*arrays, pa.array(p, pa.float64())], [*names, "score"])


def score(pairs: DataFrame, model, symmetry: str = "concat") -> DataFrame:
    """Replaces column x by score.  The broadcast is the model's weights: its size does not follow the data."""
    if isinstance(model, FixedRule):
        n = len(METRICS)
        gap = sum((F.abs(F.get("x", F.lit(METRICS.index(m))) - F.get("x", F.lit(n + METRICS.index(m)))) * w for m, w in model.weights.items()), F.lit(0.0))
        return pairs.withColumn("score", F.when(gap < model.bound, 1.0).otherwise(0.0)).drop("x")
    shared = pairs.sparkSession.sparkContext.broadcast(model)
    kept = [c for c in pairs.columns if c != "x"]
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pairs.select(*kept).schema)
    return pairs.mapInArrow(partial(_score, shared=shared, symmetry=symmetry, at=pairs.columns.index("x")), f"{fields}, score double")


def score_sql(inputs: DataFrame, weights: DataFrame, layers: int, shared_layers: int) -> DataFrame:
    """Forward pass of a twin network as joins and sums.

    inputs: pair_id, side (0, 1), j, v; weights: layer, i (0 is the bias), j, w.  The first
    ``shared_layers`` run on each side, then the sides are laid end to end; all hidden layers rectify,
    the last is linear.  Returns pair_id, z.
    """
    act = inputs
    for layer in range(layers):
        if layer == shared_layers:
            width = act.agg(F.max("j")).first()[0]
            act = act.select("pair_id", F.lit(0).alias("side"), (F.col("j") + F.col("side") * width).alias("j"), "v")
        w = weights.where(F.col("layer") == layer)
        bias = act.select("pair_id", "side").distinct().crossJoin(F.broadcast(w.where("i = 0").select(F.col("j").alias("o"), "w"))).select("pair_id", "side", "o", F.col("w").alias("t"))
        terms = act.join(F.broadcast(w.select(F.col("i").alias("j"), F.col("j").alias("o"), "w")), "j").select("pair_id", "side", "o", (F.col("v") * F.col("w")).alias("t"))
        act = terms.unionByName(bias).groupBy("pair_id", "side", "o").agg(F.sum("t").alias("v")).select("pair_id", "side", F.col("o").alias("j"), "v")
        if layer < layers - 1:
            act = act.withColumn("v", F.greatest("v", F.lit(0)))
    return act.select("pair_id", F.col("v").alias("z"))
