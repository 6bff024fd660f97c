"""Connected components of an edge table by alternating star contractions.

Every round points the larger neighbours of each node at the smallest one, then the smaller neighbours
at the smallest of them; stars remain after a number of rounds that grows with the logarithm of the
node count.  Only minima per node are aggregated (combined on the map side), no neighbour list is ever
gathered, and each round is written to the shared folder so that lineage stays short.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import persist


def _signature(edges: DataFrame) -> tuple:
    mark = F.xxhash64("a", "b")
    row = edges.agg(F.count("*").alias("n"), F.expr("bit_xor(xxhash64(a, b))").alias("x"), F.sum(F.shiftright(mark, 20)).alias("s")).first()
    return row["n"], row["x"], row["s"]


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``edges`` has two columns of one ordered type.  Returns node, root (its component's smallest node)
    for every node that has an edge to another one; loops and repeated edges do no harm."""
    left, right = edges.columns
    low, high = F.least(left, right), F.greatest(left, right)
    stars = persist(edges.where(F.col(left) != F.col(right)).select(high.alias("a"), low.alias("b")).distinct(), "edges")
    before = _signature(stars)
    for _ in range(max_rounds):
        both = stars.unionByName(stars.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("a", "m"))
        large = both.where("b > a").join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        small_least = large.groupBy("a").agg(F.min("b").alias("m"))
        hung = large.join(small_least, "a")
        hung = hung.select("a", F.col("m").alias("b")).unionByName(hung.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")))
        stars = persist(hung.distinct(), "stars")
        after = _signature(stars)
        if after == before:
            return stars.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(stars.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
        before = after
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
