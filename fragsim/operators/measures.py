"""Accuracy and cost measures."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def unordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("left_id", "right_id").alias("left_id"), F.greatest("left_id", "right_id").alias("right_id")).distinct()


def recall_by_class(detected: DataFrame, truth: DataFrame) -> DataFrame:
    """category, tagged, found, recall_pct over truth(left_id, right_id, category)."""
    hit = unordered(detected).withColumn("hit", F.lit(1))
    joined = truth.join(hit, ["left_id", "right_id"], "left")
    out = joined.groupBy("category").agg(F.count("*").alias("tagged"), F.count("hit").alias("found"))
    return out.withColumn("recall_pct", F.round(F.col("found") * 100 / F.col("tagged"), 6))


def precision_sample(detected: DataFrame, n: int = 400, seed: int = 11, single: bool = False) -> DataFrame:
    """A blind sample: n pairs in the order of a seeded MD5, without the detector's name.  ``single``: each pair comes once
    and with the smaller identifier first, so none is shuffled to find that out."""
    key = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("left_id").cast("string"), F.col("right_id").cast("string")))
    return (detected.select("left_id", "right_id") if single else unordered(detected)).withColumn("key", key).orderBy("key").limit(n).select("left_id", "right_id")


def sample_size(confidence: float = 0.95, margin: float = 0.05) -> int:
    """Pairs to sample for a proportion: 385 for 95 % and 5 %."""
    from statistics import NormalDist

    z = NormalDist().inv_cdf(0.5 + confidence / 2)
    return math.ceil(z * z * 0.25 / margin**2)


def proportion_ci(p: float, n: int, confidence: float = 0.95) -> float:
    """Half width of the interval of a sampled share."""
    from statistics import NormalDist

    return NormalDist().inv_cdf(0.5 + confidence / 2) * math.sqrt(p * (1 - p) / n)


def agreement(verdicts: DataFrame) -> DataFrame:
    """One row: pairs, both_yes, both_no, conflicts, agree_pct, kappa of judge_a and judge_b (0/1)."""
    n = lambda c: F.sum(F.when(c, 1).otherwise(0)).cast("long")
    a, b = F.col("judge_a") == 1, F.col("judge_b") == 1
    row = verdicts.agg(F.count("*").alias("pairs"), n(a & b).alias("both_yes"), n(~a & ~b).alias("both_no"), n(a != b).alias("conflicts"), n(a).alias("yes_a"), n(b).alias("yes_b"))
    same = (F.col("both_yes") + F.col("both_no")) / F.col("pairs")
    chance = (F.col("yes_a") * F.col("yes_b") + (F.col("pairs") - F.col("yes_a")) * (F.col("pairs") - F.col("yes_b"))) / (F.col("pairs") * F.col("pairs"))
    kappa = F.when(chance >= 1, F.lit(1.0)).otherwise((same - chance) / (F.lit(1.0) - chance))
    return row.select("pairs", "both_yes", "both_no", "conflicts", F.round(same * 100, 6).alias("agree_pct"), F.round(kappa, 6).alias("kappa"))


def _weight(pred: DataFrame) -> Column:
    """How many predictions a row stands for: its column ``n``, one where there is none."""
    return F.col("n") if "n" in pred.columns else F.lit(1)


def prf(pred: DataFrame) -> DataFrame:
    """One row from (label, predicted): accuracy, precision, recall, f1.  Rows may be counted ones, as in all measures
    of predictions here: a column ``n`` says how many each stands for."""
    w = _weight(pred)
    n = lambda c: F.sum(F.when(c, w).otherwise(0)).cast("double")
    yes, pos = F.col("predicted") == 1, F.col("label") == 1
    row = pred.agg(F.coalesce(F.sum(w), F.lit(0)).cast("long").alias("rows"), n(yes & pos).alias("tp"), n(yes).alias("p"), n(pos).alias("t"), n(yes == pos).alias("ok"))
    p, r = F.col("tp") / F.col("p"), F.col("tp") / F.col("t")
    return row.select("rows", F.round(F.col("ok") / F.col("rows"), 6).alias("accuracy"), F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(2 * p * r / (p + r), 6).alias("f1"))


def roc_points(pred: DataFrame) -> DataFrame:
    """score, tpr, fpr at every distinct score, highest first.

    Ties are one point.  The running sums go over distinct scores: round scores to keep those few.
    """
    by = pred.groupBy("score").agg(F.sum(F.col("label") * _weight(pred)).cast("long").alias("pos"), F.sum(_weight(pred)).cast("long").alias("n"))
    run = Window.orderBy(F.desc("score")).rowsBetween(Window.unboundedPreceding, 0)
    whole = by.agg(F.sum("pos").alias("all_pos"), F.sum("n").alias("all_n"))
    cum = by.withColumn("tp", F.sum("pos").over(run)).withColumn("seen", F.sum("n").over(run)).crossJoin(F.broadcast(whole))
    return cum.select("score", F.round(F.col("tp") / F.col("all_pos"), 6).alias("tpr"), F.round((F.col("seen") - F.col("tp")) / (F.col("all_n") - F.col("all_pos")), 6).alias("fpr"))


def auc(pred: DataFrame) -> DataFrame:
    """One row: the chance that a positive outranks a negative, ties counting half."""
    by = pred.groupBy("score").agg(F.sum(F.col("label") * _weight(pred)).cast("long").alias("pos"), F.sum(_weight(pred)).cast("long").alias("n"))
    below = F.coalesce(F.sum(F.col("n") - F.col("pos")).over(Window.orderBy("score").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    parts = by.withColumn("wins", F.col("pos") * (below * 2 + F.col("n") - F.col("pos")))
    return parts.agg(F.round(F.sum("wins") / (F.lit(2.0) * F.sum("pos") * F.sum(F.col("n") - F.col("pos"))), 6).alias("auc"))


def binary_cross_entropy(pred: DataFrame) -> DataFrame:
    p = F.least(F.greatest(F.col("score"), F.lit(1e-12)), F.lit(1 - 1e-12))
    each = F.when(F.col("label") == 1, -F.log(p)).otherwise(-F.log(1 - p))
    return pred.agg(F.round(F.sum(each * _weight(pred)) / F.sum(_weight(pred)), 6).alias("loss"))


def detector_matrix(detected: dict[str, DataFrame]) -> DataFrame:
    """How many pairs each subset of detectors found: one flag column per detector, pairs."""
    rows = None
    for name, pairs in detected.items():
        part = unordered(pairs).withColumn("detector", F.lit(name))
        rows = part if rows is None else rows.unionByName(part)
    flags = [F.max(F.when(F.col("detector") == n, 1).otherwise(0)).alias(n) for n in detected]
    return rows.groupBy("left_id", "right_id").agg(*flags).groupBy(*detected).agg(F.count("*").alias("pairs"))
