"""Uniform sharding by a hypergeometric communication matrix.

A uniform random permutation of N rows into shards of fixed sizes sends, from a source partition with
n rows, numbers of rows to the shards that follow the multivariate hypergeometric law.  The matrix of
those numbers is drawn first; then every source partition is permuted on its own and cut at its row of
the matrix, the pieces are exchanged, and every shard is permuted again.  Shard sizes come out exact and
no count has to be corrected afterwards.

Source partitions are *logical*: a seeded hash of the identifier deals rows to ``partitions`` of them,
so the result depends on the rows alone, not on files or tasks.  What reaches the driver is one count per
logical partition and one per (shard, bucket): both are bounded by parameters.  Every other step is a
DataFrame operator.  A shard is permuted in ``buckets`` ranges of the random key with counted offsets, so
that no task holds a whole shard.

``assign_shards`` counts equal rows first and deals every copy by its number, so rows that repeat often
spread as others do; ``shard_rows`` numbers the rows of the table and deals each by its number too.

Defined results: a null text has size 1 and the checksum of the empty text; rows that repeat are
interchangeable and each gets a slot of its own; null identifiers are dealt like others; an empty table
gives an empty result; other columns are ignored by ``assign_shards`` and kept by ``shard_rows`` (columns
named shard or slot are replaced).
"""

from __future__ import annotations

import math
import random
from itertools import accumulate

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import numbered, persist, unused


def draw_hypergeometric(rng: random.Random, good: int, total: int, draws: int) -> int:
    """Number of ``good`` items among ``draws`` taken from ``total`` without replacement.

    Inversion outward from the mode, in time proportional to the standard deviation; integers of any
    size are fine.
    """
    low, high = max(0, draws - (total - good)), min(good, draws)
    if low == high:
        return low
    mode = min(high, max(low, (draws + 1) * (good + 1) // (total + 2)))
    log_choose = lambda n, k: math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)
    at_mode = math.exp(log_choose(good, mode) + log_choose(total - good, draws - mode) - log_choose(total, draws))
    left = rng.random() - at_mode
    down = up = mode
    p_down = p_up = at_mode
    while left > 0:
        moved = False
        if up < high:
            p_up *= (good - up) * (draws - up) / ((up + 1) * (total - good - draws + up + 1))
            up += 1
            left -= p_up
            moved = p_up > 0
            if left <= 0:
                return up
        if down > low:
            p_down *= down * (total - good - draws + down) / ((good - down + 1) * (draws - down + 1))
            down -= 1
            left -= p_down
            moved = moved or p_down > 0
            if left <= 0:
                return down
        if not moved:  # rounding left a rest in the far tail
            return mode
    return mode


def communication_matrix(rows_in: list[int], sizes_out: list[int], seed: int) -> list[list[int]]:
    """Random matrix with these row and column sums, drawn as a uniform permutation induces it."""
    rng, left, matrix = random.Random(seed), list(sizes_out), []
    for n in rows_in:
        line, rest, need = [], sum(left), n
        for size in left:
            k = draw_hypergeometric(rng, size, rest, need)
            line.append(k)
            rest, need = rest - size, need - k
        left = [a - b for a, b in zip(left, line, strict=True)]
        matrix.append(line)
    return matrix


def shard_sizes(total: int, shards: int) -> list[int]:
    return [total // shards + (i < total % shards) for i in range(shards)]


def _permuted(keyed: DataFrame, key: list[str], shards: int, seed: int, partitions: int | None, buckets: int | None) -> DataFrame:
    """Adds shard and slot; ``key`` are columns that make rows equal up to interchangeable ones.

    Unless given, the numbers of logical partitions and of buckets follow the row count, so that a group
    stays near a million rows; both have a floor that keeps small inputs spread.
    """
    spark = keyed.sparkSession
    mix = lambda salt: F.xxhash64(F.lit(f"{seed}-{salt}"), *key)
    keyed = persist(keyed, "keys")
    total = keyed.count()
    partitions = partitions or max(256, -(-total // 1_000_000))
    buckets = buckets or max(64, -(-total // (shards * 1_000_000)))
    dealt = keyed.withColumn("_part", F.pmod(mix("deal"), F.lit(partitions)).cast("int"))
    counts = {r["_part"]: r["n"] for r in dealt.groupBy("_part").agg(F.count("*").alias("n")).collect()}
    rows_in = [counts.get(p, 0) for p in range(partitions)]
    matrix = communication_matrix(rows_in, shard_sizes(total, shards), seed)
    cuts = spark.createDataFrame([(p, list(accumulate(line))) for p, line in enumerate(matrix)], "_part int, _cuts array<long>")
    local = Window.partitionBy("_part").orderBy(mix("local"), *key)
    placed = dealt.withColumn("_rank", F.row_number().over(local).cast("long") - 1).join(F.broadcast(cuts), "_part")
    placed = placed.withColumn("shard", F.size(F.filter("_cuts", lambda c: c <= F.col("_rank"))).cast("int"))
    # The second permutation: ranges of a fresh random key are the buckets of a shard.
    order = mix("again")
    placed = placed.drop("_part", "_cuts", "_rank").withColumn("_bucket", F.pmod(F.shiftright(order, 20), F.lit(buckets)).cast("int"))
    placed = persist(placed, "placed")
    offset = Window.partitionBy("shard").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    sizes = placed.groupBy("shard", "_bucket").agg(F.count("*").alias("n")).withColumn("_offset", F.coalesce(F.sum("n").over(offset), F.lit(0))).drop("n")
    again = Window.partitionBy("shard", "_bucket").orderBy(order, *key)
    slots = placed.withColumn("_nth", F.row_number().over(again).cast("long") - 1).join(F.broadcast(sizes), ["shard", "_bucket"])
    return slots.withColumn("slot", F.col("_offset") + F.col("_nth")).drop("_bucket", "_offset", "_nth")


def text_size(text: Column) -> Column:
    return F.octet_length(F.coalesce(text, F.lit(""))).cast("long") + 1


def _keys(docs: DataFrame, id_col: str, text_col: str) -> list[Column]:
    text = F.coalesce(F.col(text_col), F.lit(""))
    return [F.col(id_col).cast("long").alias("doc_id"), text_size(F.col(text_col)).alias("size"), F.crc32(text.cast("binary")).alias("text_crc32")]


def assign_shards(docs: DataFrame, shards: int = 8, id_col: str = "doc_id", text_col: str = "text", seed: int = 17, partitions: int | None = None, buckets: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every row; counts differ by one at most.

    Only identifiers, sizes and checksums are shuffled.
    """
    # Rows that agree in all three are interchangeable: count them, then give each copy a number.
    keys = docs.select(*_keys(docs, id_col, text_col)).groupBy("doc_id", "size", "text_crc32").agg(F.count("*").alias("n"))
    keys = keys.select("doc_id", "size", "text_crc32", F.explode(F.expr("sequence(1L, n)")).alias("copy"))
    out = _permuted(keys, ["doc_id", "size", "text_crc32", "copy"], shards, seed, partitions, buckets)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def shard_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shards: int = 8, seed: int = 17, partitions: int | None = None, buckets: int | None = None) -> DataFrame:
    """``docs`` with shard and slot.  The permutations move keys only; the rows then meet their slots in
    one exchange by row number."""
    keep = [c for c in docs.columns if c.lower() not in ("shard", "slot")]
    (row,) = unused(docs.columns, "_row")
    rows = numbered(docs.select(*keep), row)
    keys = rows.select(*_keys(rows, id_col, text_col), F.col(row).alias("copy"))
    slots = _permuted(keys, ["doc_id", "size", "text_crc32", "copy"], shards, seed, partitions, buckets)
    return rows.join(slots.select(F.col("copy").alias(row), "shard", "slot"), row).select(*keep, "shard", "slot")


def write_shards(docs: DataFrame, path: str, **options) -> None:
    """Write one folder per shard, rows in slot order inside each file."""
    out = shard_rows(docs, **options)
    out.repartition("shard", F.floor(F.col("slot") / 1_000_000)).sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
