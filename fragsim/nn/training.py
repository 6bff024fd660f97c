"""Training sets and training on the cluster."""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fragsim.nn.network import Network, cross_entropy
from fragsim.sources.tables import staged


def pair_key(seed: int) -> Column:
    return F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("left_id").cast("string"), F.col("right_id").cast("string")))


def split_name(key: Column, test_pct: int = 20, valid_pct: int = 2) -> Column:
    """train, valid or test by two hex digits of a key."""
    n = F.pmod(F.conv(F.substring(key, 1, 8), 16, 10).cast("long"), F.lit(100))
    return F.when(n < test_pct, "test").when(n < test_pct + valid_pct, "valid").otherwise("train")


def random_pairs(fragments: DataFrame, seed: int = 5, modulus: int = 16) -> DataFrame:
    """A linear number of pairs of unrelated fragments: neighbours of a seeded hash order inside parts."""
    from pyspark.sql.window import Window

    key = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("fragment_id").cast("string")))
    rows = fragments.select("fragment_id", key.alias("k")).withColumn("part", F.substring("k", 1, 2 if modulus > 16 else 1))
    follow = Window.partitionBy("part").orderBy("k", "fragment_id")
    pairs = rows.withColumn("next", F.lead("fragment_id").over(follow)).where(F.col("next").isNotNull())
    return pairs.select(F.least("fragment_id", "next").alias("left_id"), F.greatest("fragment_id", "next").alias("right_id")).distinct()


def curate(fragments: DataFrame, clones: DataFrame, n_pos: int, n_neg: int, seed: int = 5, negatives: DataFrame | None = None) -> DataFrame:
    """left_id, right_id, is_clone, split: a balanced, repeatable sample of labelled pairs.

    Positives come from a labelling detector; negatives are random pairs (or the given ones, such as
    survivors of the action filter) that the detector does not report.
    """
    # Both samples read the clones: the detector behind them runs once.
    pos = staged(clones.select("left_id", "right_id").distinct(), "clones")
    pool = random_pairs(fragments, seed) if negatives is None else negatives.select("left_id", "right_id").distinct()
    neg = pool.join(pos, ["left_id", "right_id"], "left_anti")
    take = lambda df, n, y: df.withColumn("k", pair_key(seed)).orderBy("k", "left_id", "right_id").limit(n).withColumn("is_clone", F.lit(y))
    both = take(pos, n_pos, 1).unionByName(take(neg, n_neg, 0))
    return both.select("left_id", "right_id", "is_clone", split_name(F.col("k")).alias("split"))


def assert_disjoint(train: DataFrame, truth: DataFrame) -> None:
    if train.select("left_id", "right_id").intersect(truth.select("left_id", "right_id")).limit(1).count():
        raise ValueError("training pairs overlap the evaluation set")


def label_ensemble(detected: dict[str, DataFrame], rule: str = "majority") -> DataFrame:
    """left_id, right_id, votes of the pairs that a union or majority of detectors reports."""
    rows = None
    for pairs in detected.values():
        part = pairs.select("left_id", "right_id").distinct()
        rows = part if rows is None else rows.unionByName(part)
    need = 1 if rule == "union" else len(detected) // 2 + 1
    return rows.groupBy("left_id", "right_id").agg(F.count("*").alias("votes")).where(F.col("votes") >= need)


def scale_column(x: Column, mean: list[float], std: list[float]) -> Column:
    """log1p, then z-scores by position; constant metrics become zero."""
    m, s = F.array(*map(F.lit, [*mean, *mean])), F.array(*map(F.lit, [v or 1.0 for v in [*std, *std]]))
    return F.zip_with(F.zip_with(x, m, lambda v, a: F.log1p(v) - a), s, lambda v, b: v / b)


def collect_examples(examples: DataFrame, limit: int = 200_000) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """x, y, split of a bounded training sample in the order of the pairs; refuses more than ``limit`` rows."""
    rows = examples.select("left_id", "right_id", "x", "is_clone", "split").limit(limit + 1).toPandas().sort_values(["left_id", "right_id"])
    if len(rows) > limit:
        raise ValueError(f"more than {limit} examples: sample first or train with local_sgd")
    return np.array(rows["x"].tolist(), float), rows["is_clone"].to_numpy(float), rows["split"].to_numpy(str)


def _round(batches: Iterator[pa.RecordBatch], shared, lr: float, batch: int, seed: int) -> Iterator[pa.RecordBatch]:
    """One pass of SGD over a partition, from the broadcast weights; gives the weights back."""
    net: Network = shared.value
    net = Network(net.inputs, net.trunk, net.comparator, net.twin, net.dropout, net.seed, list(net.weights))
    rng, n, loss = np.random.default_rng(seed), 0, 0.0
    for b in batches:
        x = b.column(0).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
        y = b.column(1).to_numpy(zero_copy_only=False).astype(float)
        for at in range(0, len(x), batch):
            part = slice(at, at + batch)
            step, grads = net.gradients(x[part], y[part], net.draw_masks(len(x[part]), rng))
            net.weights = [(w - lr * gw, c - lr * gc) for (w, c), (gw, gc) in zip(net.weights, grads, strict=True)]
            loss += step * len(x[part])
        n += len(x)
    if n:
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(net.weights)]), pa.array([n]), pa.array([loss])], ["weights", "n", "loss"])


def fit_local_sgd(net: Network, examples: DataFrame, rounds: int = 5, parts: int = 8, lr: float = 1e-2, decay: float = 0.97, batch: int = 1000, seed: int = 7) -> list[dict]:
    """Training beyond one machine: every round each of ``parts`` partitions runs SGD on its rows and the
    weights are averaged by rows.  What returns per round is ``parts`` copies of the weights."""
    log = []
    for r in range(rounds):
        shared = examples.sparkSession.sparkContext.broadcast(net)
        order = F.md5(F.concat_ws("|", F.lit(str(seed + r)), F.col("left_id").cast("string"), F.col("right_id").cast("string")))
        dealt = examples.repartition(parts, "left_id", "right_id").sortWithinPartitions(order).select("x", "is_clone")
        back = dealt.mapInArrow(partial(_round, shared=shared, lr=lr, batch=batch, seed=seed + r), "weights binary, n long, loss double").collect()
        total = sum(b["n"] for b in back)
        each = [(pickle.loads(bytes(b["weights"])), b["n"] / total) for b in back]
        net.weights = [(sum(w[i][0] * f for w, f in each), sum(w[i][1] * f for w, f in each)) for i in range(len(net.weights))]
        log.append({"epoch": r, "lr": lr, "train_loss": sum(b["loss"] for b in back) / total})
        lr *= decay
        shared.unpersist()
    return log


def evaluate(net, x: np.ndarray, y: np.ndarray) -> dict[str, float]:
    """Accuracy, precision, recall, F1, loss and AUC on a held-out sample."""
    return summary(net.predict(x), y)


def summary(p: np.ndarray, y: np.ndarray) -> dict[str, float]:
    yes = p > 0.5
    tp = float((yes & (y == 1)).sum())
    precision, recall = tp / max(1, yes.sum()), tp / max(1, (y == 1).sum())
    order = np.argsort(p, kind="stable")
    rank = np.empty(len(p))
    rank[order] = np.arange(1, len(p) + 1)
    for v in np.unique(p):
        rank[p == v] = rank[p == v].mean()
    n1 = (y == 1).sum()
    n0 = len(y) - n1
    auc = (rank[y == 1].sum() - n1 * (n1 + 1) / 2) / max(1, n1 * n0)
    return {"accuracy": float((yes == y).mean()), "precision": precision, "recall": recall, "f1": 2 * precision * recall / max(1e-12, precision + recall), "loss": cross_entropy(p, y), "auc": float(auc)}


def fit_per_band(examples: DataFrame, epochs: int = 10, lr: float = 0.05) -> DataFrame:
    """band, params, loss: a small model per size band, one task each (examples of a band are a bounded sample)."""
    import pandas as pd

    def one(rows: pd.DataFrame) -> pd.DataFrame:
        from fragsim.nn.network import fit, logistic

        x, y = np.array(rows["x"].tolist(), float), rows["is_clone"].to_numpy(float)
        net = logistic(x.shape[1] // 2)
        log = fit(net, x, y, lr=lr, batch=64, epochs=epochs)
        return pd.DataFrame({"band": [int(rows["band"].iloc[0])], "params": [net.count_params()], "loss": [log[-1]["train_loss"]]})

    return examples.groupBy("band").applyInPandas(one, "band int, params long, loss double")
