"""Deciding pairs: collapse of equal fragments, metric-hash short cut, feature vectors, metrics-only
detectors, clone classes and explanations."""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fragsim.config import METRICS
from fragsim.sources.tables import shared_folder


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage in the folder of ``spark.checkpoint.dir`` (set here only where it is unset)."""
    sc = df.sparkSession.sparkContext
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint()


def signature() -> Column:
    """Everything later stages depend on: bag, metrics and size."""
    entries = F.transform(F.sort_array(F.map_entries("actions")), lambda e: F.concat_ws(":", e["key"], e["value"].cast("string")))
    return F.md5(F.concat_ws("|", F.col("metric_hash"), F.col("n_tokens").cast("string"), F.array_join(entries, ",")))


def collapse(fragments: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(one representative per group of equal fragments, members: class_id, fragment_id).

    Lossless: equal fragments meet the same partners with the same scores.
    """
    signed = fragments.withColumn("signature", signature())
    owners = signed.groupBy("signature").agg(F.min("fragment_id").alias("class_id"))
    members = signed.select("fragment_id", "signature").join(owners, "signature").select("class_id", "fragment_id")
    return fragments.join(owners.select(F.col("class_id").alias("fragment_id")), "fragment_id", "left_semi"), members


def expand(pairs: DataFrame, members: DataFrame) -> DataFrame:
    """Pairs of representatives as pairs of members, with the pairs inside each class.

    The output is quadratic in the size of a class: meant for reports on small groups.  Detection itself
    returns representatives and membership.
    """
    l_side = members.select(F.col("class_id").alias("left_id"), F.col("fragment_id").alias("l"))
    r_side = members.select(F.col("class_id").alias("right_id"), F.col("fragment_id").alias("r"))
    across = pairs.select("left_id", "right_id").join(l_side, "left_id").join(r_side, "right_id").select(F.least("l", "r").alias("left_id"), F.greatest("l", "r").alias("right_id"))
    a, b = members.alias("a"), members.alias("b")
    inside = a.join(b, (F.col("a.class_id") == F.col("b.class_id")) & (F.col("a.fragment_id") < F.col("b.fragment_id")))
    return across.unionByName(inside.select(F.col("a.fragment_id").alias("left_id"), F.col("b.fragment_id").alias("right_id")))


def with_sides(pairs: DataFrame, fragments: DataFrame, *columns: str) -> DataFrame:
    """Joins columns of both fragments as l_<column> and r_<column>; those that the pairs brought along are there already."""
    columns = tuple(c for c in columns if f"l_{c}" not in pairs.columns)
    if not columns:
        return pairs
    l_side = fragments.select(F.col("fragment_id").alias("left_id"), *(F.col(c).alias(f"l_{c}") for c in columns))
    r_side = fragments.select(F.col("fragment_id").alias("right_id"), *(F.col(c).alias(f"r_{c}") for c in columns))
    return pairs.join(l_side, "left_id").join(r_side, "right_id")


def by_hash(pairs: DataFrame, fragments: DataFrame) -> DataFrame:
    """Candidates with equal metric hash: reported without any model."""
    return with_sides(pairs, fragments, "metric_hash").where("l_metric_hash = r_metric_hash").drop("l_metric_hash", "r_metric_hash")


def pair_vectors(pairs: DataFrame, fragments: DataFrame, order: str = "as_is") -> DataFrame:
    """Adds x, the 48 metrics of both sides; ``both`` gives a row for each order, ``sorted`` puts the shorter first."""
    out = with_sides(pairs, fragments, "metric_vec")
    ab, ba = F.concat("l_metric_vec", "r_metric_vec"), F.concat("r_metric_vec", "l_metric_vec")
    if order == "both":
        out = out.withColumn("x", F.explode(F.array(ab, ba)))
    elif order == "sorted":
        out = out.withColumn("x", F.when(F.get("l_metric_vec", F.lit(METRICS.index("nand"))) <= F.get("r_metric_vec", F.lit(METRICS.index("nand"))), ab).otherwise(ba))
    else:
        out = out.withColumn("x", ab)
    return out.drop("l_metric_vec", "r_metric_vec")


def scaler_stats(fragments: DataFrame, log: bool = True) -> DataFrame:
    """metric, mean, std of every metric (of its log1p): one aggregation."""
    pick = lambda m: F.log1p(F.col(m).cast("double")) if log else F.col(m).cast("double")
    aggs = [a for m in METRICS for a in (F.avg(pick(m)).alias(f"{m}_mean"), F.stddev_pop(pick(m)).alias(f"{m}_std"))]
    row = fragments.agg(*aggs)
    return row.select(F.explode(F.array(*(F.struct(F.lit(m).alias("metric"), F.col(f"{m}_mean").alias("mean"), F.col(f"{m}_std").alias("std")) for m in METRICS))).alias("s")).select("s.*")


def metrics_equal(fragments: DataFrame) -> DataFrame:
    """Groups of equal metrics: class_id, members; finds T1 and T2 only."""
    return fragments.groupBy("metric_hash").agg(F.min("fragment_id").alias("class_id"), F.count("*").alias("members")).where("members > 1")


def metrics_only(pairs: DataFrame, fragments: DataFrame, tolerance: Mapping[str, int]) -> DataFrame:
    """Pairs whose listed metrics differ by at most so many percent of the larger value."""
    out = with_sides(pairs, fragments, *tolerance)
    for m, pct in tolerance.items():
        a, b = F.col(f"l_{m}"), F.col(f"r_{m}")
        out = out.where((F.greatest(a, b) - F.least(a, b)) * 100 <= F.greatest(a, b) * pct)
    return out.drop(*(f"{s}_{m}" for m in tolerance for s in "lr"))


def explain_pairs(pairs: DataFrame, fragments: DataFrame) -> DataFrame:
    """shared (action -> common frequency), deltas of all metrics, common share of the smaller bag."""
    out = with_sides(pairs, fragments, "actions", "metric_vec")
    both = F.map_filter(F.map_zip_with("l_actions", "r_actions", lambda k, x, y: F.least(F.coalesce(x, F.lit(0)), F.coalesce(y, F.lit(0)))), lambda k, v: v > 0)
    return out.withColumn("shared", both).withColumn("deltas", F.zip_with("l_metric_vec", "r_metric_vec", lambda x, y: x - y)).drop("l_actions", "r_actions", "l_metric_vec", "r_metric_vec")


def clone_classes(pairs: DataFrame, max_rounds: int = 40) -> DataFrame:
    """class_id (smallest member), member_id of the connected groups of pairs.

    Star contraction: larger neighbours, then smaller ones, are hung onto the least neighbour until only
    stars remain; each round aggregates minima and cuts its lineage by a checkpoint.
    """
    stars = checkpointed(pairs.select(F.greatest("left_id", "right_id").alias("a"), F.least("left_id", "right_id").alias("b")).distinct())
    mark = lambda e: tuple(e.agg(F.count("*"), F.expr("bit_xor(xxhash64(a, b))"), F.sum("b")).first())
    before = mark(stars)
    for _ in range(max_rounds):
        both = stars.unionByName(stars.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("a", "m"))
        up = both.where("b > a").join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        hung = up.join(up.groupBy("a").agg(F.min("b").alias("m")), "a")
        stars = checkpointed(hung.select("a", F.col("m").alias("b")).unionByName(hung.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))).distinct())
        after = mark(stars)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("clone classes did not settle")
    return stars.select(F.col("b").alias("class_id"), F.col("a").alias("member_id")).unionByName(stars.select(F.col("b").alias("class_id"), F.col("b").alias("member_id")).distinct())


def metric_correlations(fragments: DataFrame, metrics: tuple[str, ...] = METRICS) -> DataFrame:
    """a, b, r of all pairs of metrics, in one aggregation."""
    pairs = [(a, b) for i, a in enumerate(metrics) for b in metrics[i + 1 :]]
    num = lambda m: F.col(m).cast("double")
    spread = {m: F.stddev_pop(num(m)) for m in metrics}
    # Null where a metric is constant.
    row = fragments.agg(*(F.try_divide(F.covar_pop(num(a), num(b)), spread[a] * spread[b]).alias(f"{a}__{b}") for a, b in pairs))
    return row.select(F.explode(F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.col(f"{a}__{b}").alias("r")) for a, b in pairs))).alias("s")).select("s.*")


def prune_correlated(spark: SparkSession, correlations: DataFrame, cost: Mapping[str, int], cut: float = 0.9) -> DataFrame:
    """metric, kept, because: of two metrics correlated above the cut the cheaper stays (24 rows at most)."""
    found = sorted((r["a"], r["b"], r["r"]) for r in correlations.where(F.abs("r") > cut).collect())
    reason: dict[str, str] = {}
    for m in sorted(cost, key=lambda k: (-cost[k], k)):  # the costliest goes first
        for a, b, _ in found:
            other = b if a == m else a if b == m else None
            if other and other not in reason and (cost[other], other) < (cost[m], m):
                reason[m] = other
                break
    return spark.createDataFrame([(m, m not in reason, reason.get(m)) for m in cost], "metric string, kept boolean, because string")
