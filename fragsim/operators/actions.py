"""The action filter: an inverted index per size band, looked up by equi-joins."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fragsim.config import DetectConfig
from fragsim.functions.overlap import above, bag_overlap, denominator, size_compatible
from fragsim.operators.blocks import SUFFIX_PCT, overlaps
from fragsim.sources.tables import staged

#: Largest number of rows that the exhaustive baseline will pair.
EXHAUSTIVE_ROWS = 20_000


def action_rows(fragments: DataFrame, *keep: str) -> DataFrame:
    """fragment_id, action, f and the kept columns."""
    return fragments.select("fragment_id", *keep, F.explode("actions").alias("action", "f"))


def action_df(fragments: DataFrame) -> DataFrame:
    """action, df: in how many fragments."""
    return action_rows(fragments).groupBy("action").agg(F.count("*").alias("df"))


def drop_stop_actions(fragments: DataFrame, top_k: int | None = None, max_df: int | None = None, words: list[str] | None = None) -> DataFrame:
    """Takes frequent or listed actions out of the bags.

    The stop list of ``top_k`` or ``words`` is bounded by the parameter and broadcast; with ``max_df``
    its size is left to the engine.
    """
    spark = fragments.sparkSession
    if words is not None:
        stops = F.broadcast(spark.createDataFrame([(w,) for w in words], "action string"))
    elif top_k is not None:
        stops = F.broadcast(action_df(fragments).orderBy(F.desc("df"), "action").limit(top_k).select("action"))
    else:
        stops = action_df(fragments).where(F.col("df") > max_df).select("action")
    rest = action_rows(fragments).join(stops, "action", "left_anti")
    bags = rest.groupBy("fragment_id").agg(F.map_from_entries(F.collect_list(F.struct("action", "f"))).alias("actions"), F.sum("f").alias("action_total"))
    empty = F.create_map().cast("map<string,bigint>")
    out = fragments.drop("actions", "action_total").join(bags, "fragment_id", "left")
    return out.withColumn("actions", F.coalesce("actions", empty)).withColumn("action_total", F.coalesce("action_total", F.lit(0).cast("long")))


def postings(banded: DataFrame) -> DataFrame:
    """Index rows: band, action, fragment_id, f, action_total, n_tokens; one per candidate band and action."""
    rows = banded.select("fragment_id", "n_tokens", "action_total", "actions", F.explode("cand_bands").alias("band"))
    return rows.select("band", "fragment_id", "n_tokens", "action_total", F.explode("actions").alias("action", "f"))


def _side(rows: DataFrame, prefix: str, names: list[str]) -> DataFrame:
    return rows.select(*(F.col(n).alias(f"{prefix}{n}") for n in names))


def meetings(banded: DataFrame, cfg: DetectConfig, queries: DataFrame | None = None) -> DataFrame:
    """left_id < right_id, overlap, left_total, right_total: every pair that shares an action in a band.

    A pair meets where the home band of one is among the other's bands; each pair is counted once, inside a task
    (``blocks``).  With ``queries`` one of the two is among them.
    """
    return overlaps(banded, cfg, queries)


def over_threshold(pairs: DataFrame, cfg: DetectConfig) -> DataFrame:
    """Filter on the share; with ``query`` as denominator a pair passes if either direction does."""
    ov, a, b = F.col("overlap"), F.col("left_total"), F.col("right_total")
    if cfg.denom == "query":
        return pairs.where(above(ov, a, cfg.theta_pct, cfg.inclusive) | above(ov, b, cfg.theta_pct, cfg.inclusive))
    return pairs.where(above(ov, denominator(a, b, ov, cfg.denom), cfg.theta_pct, cfg.inclusive))


def least_overlap(total: Column, cfg: DetectConfig) -> Column:
    """Fewest common elements that a pair with this denominator needs."""
    return F.floor(total * cfg.theta_pct / 100) + (0 if cfg.inclusive and cfg.theta_pct else 1)


def prefix_rows(banded: DataFrame, cfg: DetectConfig) -> DataFrame:
    """Rows of the bags with ``slack`` and ``in_prefix``.

    A bag of m elements needs o = floor(theta * m) + 1 common ones.  In the order of rising document
    frequency its last elements, ``slack`` = SUFFIX_PCT of o (fewer than o), are its suffix; all before are its
    prefix, in which any pair above the threshold has at least o - slack common elements.
    """
    rows = action_rows(banded, "n_tokens", "action_total", "home_band", "cand_bands").join(action_df(banded), "action")
    after = Window.partitionBy("fragment_id").orderBy(F.desc("df"), F.desc("action")).rowsBetween(Window.unboundedPreceding, 0)
    slack = F.greatest(F.floor(least_overlap(F.col("action_total"), cfg) * SUFFIX_PCT / 100), F.lit(0))
    return rows.withColumn("slack", slack).withColumn("in_prefix", F.sum("f").over(after) > F.col("slack"))


def prefix_meetings(first: DataFrame, second: DataFrame, cfg: DetectConfig) -> DataFrame:
    """a_fragment_id, b_fragment_id of the pairs that may pass: ``a``, the smaller bag, is from ``first``, ``b`` from ``second``.

    Both hold rows of ``prefix_rows``.  The order of a bag's actions only has to be one for that bag, so rows that were
    written under other document frequencies meet without loss.
    """
    names = ["band", "fragment_id", "action", "f", "action_total", "n_tokens", "home_band", "cand_bands", "slack"]
    rising = (F.col("a_action_total") < F.col("b_action_total")) | ((F.col("a_action_total") == F.col("b_action_total")) & (F.col("a_fragment_id") < F.col("b_fragment_id")))
    on = (F.col("a_band") == F.col("b_band")) & (F.col("a_action") == F.col("b_action")) & rising
    if cfg.exact_size:
        on = on & size_compatible(F.col("a_n_tokens"), F.col("b_n_tokens"), cfg.gamma_pct)
    home, wide = F.col("home_band"), F.explode("cand_bands")

    def met(a_band: Column, b_band: Column) -> DataFrame:
        return _side(first.where("in_prefix").withColumn("band", a_band), "a_", names).join(_side(second.withColumn("band", b_band), "b_", names), on)

    found = met(home, wide)
    if not cfg.exact_size:
        # Compatible sizes meet in both directions; of others each pair is summed in one.
        found = found.unionByName(met(wide, home).where(~F.array_contains("b_cand_bands", F.col("a_home_band"))))
    sums = found.groupBy("a_fragment_id", "b_fragment_id", "a_action_total", "b_action_total", "a_slack").agg(F.sum(F.least("a_f", "b_f")).alias("common"))
    need = least_overlap(F.col("a_action_total" if cfg.denom == "min" else "b_action_total"), cfg)
    return sums.where((F.col("common") + F.col("a_slack") >= need) & (F.col("a_action_total") >= need)).select("a_fragment_id", "b_fragment_id")


def verified(near: DataFrame, bags: DataFrame, cfg: DetectConfig) -> DataFrame:
    """The pairs of ``near`` whose whole bags (fragment_id, actions, action_total) reach the threshold."""
    # A number of partitions of its own: the comparison costs far more than the size of its input tells.
    spark = bags.sparkSession
    near = near.repartition(max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    pairs = near.select(F.least("a_fragment_id", "b_fragment_id").alias("left_id"), F.greatest("a_fragment_id", "b_fragment_id").alias("right_id"))
    l_side = bags.select(F.col("fragment_id").alias("left_id"), F.col("actions").alias("l_actions"), F.col("action_total").alias("left_total"))
    r_side = bags.select(F.col("fragment_id").alias("right_id"), F.col("actions").alias("r_actions"), F.col("action_total").alias("right_total"))
    both = pairs.join(l_side, "left_id").join(r_side, "right_id").withColumn("overlap", bag_overlap(F.col("l_actions"), F.col("r_actions")))
    return over_threshold(both, cfg).select("left_id", "right_id", "overlap", "left_total", "right_total")


def prefix_able(cfg: DetectConfig) -> None:
    if cfg.denom not in ("min", "max", "union") or cfg.element != "bag":
        raise ValueError("prefixes are for bags under min, max or union")


def prefix_candidates(banded: DataFrame, cfg: DetectConfig, keep: Sequence[str] = (), shared: bool = False, forest: bool = False) -> DataFrame:
    """The same pairs as ``over_threshold(meetings(...))``, found through prefixes and verified on the bags.

    The smaller bag's prefix meets all of the larger one inside a task (``blocks``).  What is common there, and the whole
    suffix, bound the overlap of a pair; the frequent actions of the suffix never meet, and only pairs
    whose bound reaches the threshold have their bags compared.  ``keep``, ``shared`` and ``forest`` as in ``overlaps``.
    """
    prefix_able(cfg)
    return overlaps(banded, cfg, prefix=True, threshold=True, keep=keep, shared=shared, forest=forest)


def joined_candidates(banded: DataFrame, cfg: DetectConfig) -> DataFrame:
    """``prefix_candidates`` by equi-joins alone, without Python: rows of (pair, action) are shuffled, so only for tables whose
    frequent actions are few."""
    prefix_able(cfg)
    rows = staged(prefix_rows(banded, cfg), "prefixes")
    return verified(prefix_meetings(rows, rows, cfg), banded.select("fragment_id", "actions", "action_total"), cfg)


def lossless(cfg: DetectConfig) -> bool:
    """Whether ``auto`` uses prefixes."""
    return cfg.denom in ("min", "max", "union") and cfg.element == "bag" and cfg.theta_pct >= 20


def candidates(banded: DataFrame, cfg: DetectConfig, queries: DataFrame | None = None) -> DataFrame:
    """Candidate pairs under ``cfg``; ``auto`` joins prefixes wherever they are lossless and no query set is given."""
    if cfg.prefix == "on":
        return prefix_candidates(banded, cfg)
    if cfg.prefix == "auto" and queries is None and lossless(cfg):
        return joined_candidates(banded, cfg)
    return overlaps(banded, cfg, queries, threshold=True)


def block_candidates(banded: DataFrame, cfg: DetectConfig, keep: Sequence[str] = ()) -> DataFrame:
    """The pairs of ``candidates``, found block by block whatever the prefixes: what queries and ``detect`` use.  Columns to
    ``keep`` come along as l_<column> and r_<column>."""
    if cfg.prefix == "on" or cfg.prefix == "auto" and lossless(cfg):
        return prefix_candidates(banded, cfg, keep)
    return overlaps(banded, cfg, threshold=True, keep=keep)


def top_candidates(pairs: DataFrame, k: int) -> DataFrame:
    """The k partners with the largest overlap for each fragment, ties to the smaller identifier."""
    both = pairs.select(F.col("left_id").alias("q_id"), F.col("right_id").alias("c_id"), "overlap").unionByName(pairs.select(F.col("right_id").alias("q_id"), F.col("left_id").alias("c_id"), "overlap"))
    rank = F.row_number().over(Window.partitionBy("q_id").orderBy(F.desc("overlap"), "c_id"))
    return both.withColumn("rank", rank).where(F.col("rank") <= k)


def all_pairs(fragments: DataFrame) -> DataFrame:
    """Exhaustive baseline for tests and small tables; refuses more rows than EXHAUSTIVE_ROWS."""
    n = fragments.count()
    if n > EXHAUSTIVE_ROWS:
        raise ValueError(f"{n} rows are too many to pair exhaustively")
    a, b = fragments.alias("a"), fragments.alias("b")
    return a.join(b, F.col("a.fragment_id") < F.col("b.fragment_id"))


def closed_form(n: int, queries: int) -> int:
    """Unordered pairs of ``queries`` fragments with all ``n``, pairs among queries counted once."""
    return n * queries - queries - queries * (queries - 1) // 2
