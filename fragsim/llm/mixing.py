"""Mixing sources to target weights by hierarchical budgeting.

Leaves are (domain, language, source) paths.  A token budget is given to the root and handed down: each
child's part follows its weight among its siblings, never beyond what its subtree can supply (tokens
times the largest number of epochs).  What a child cannot supply goes to its siblings first; only what
the whole sibling group cannot supply has reached the level above, because the group's own part was cut
to its capacity there.  Each leaf then yields its tokens from seeded epochs: whole passes while the
budget lasts, then the prefix of one more seeded permutation that fits.

The water level of a sibling group is found in closed form with running sums over children sorted by
capacity per weight; nothing is collected.  One task sorts the children of one parent, a short row each
(a million sources of one language take some 50 MB).  The prefix of a leaf's last epoch is cut through
256 ranges of the permutation key and then 256 ranges of the one in which the budget ends: token sums of
whole ranges decide all others, and rows are only sorted inside the last.  A source that holds a third of
the corpus is thus never sorted in one task, nor are its ranges.  Every step is a DataFrame operator.

Defined results: a null text has no tokens and is chosen at no cost with the pass or range it falls in; null
language or source are leaves of their own (shown as null); weights that are missing count 1, weights
that are not positive exclude the subtree; repeated rows count each; rows without an identifier are
permuted by their text; an empty table gives no rows; columns of other names do not matter.
"""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import join_on, persist

LEVELS = ("domain", "lang", "source")


def token_estimate(text: Column) -> Column:
    """Tokens of a text taken as a quarter of its UTF-8 bytes, rounded up."""
    return F.floor((F.octet_length(F.coalesce(text, F.lit(""))) + 3) / 4).cast("long")


def weight_column(level: str, weights: Mapping[str, float]) -> Column:
    """Weight of a child by its name at this level; names that are not listed have weight 1."""
    out = F.lit(1.0)
    for name, w in weights.items():
        out = F.when(F.col(level).eqNullSafe(F.lit(name)), F.lit(float(w))).otherwise(out)
    return out


def water_fill(children: DataFrame, parent: list[str], given: str, capacity: str, weight: str, out: str) -> DataFrame:
    """Part of ``given`` (same value for all children of a parent) for each child: by weight, at most its
    capacity; shortages go to the siblings by their weights.  Children without weight get nothing."""
    live = children.where(F.col(weight) > 0).withColumn("_ratio", F.col(capacity) / F.col(weight))
    order = Window.partitionBy(*parent).orderBy("_ratio", *[c for c in LEVELS if c in children.columns])
    before, whole = order.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy(*parent)
    live = (
        live.withColumn("_cap_before", F.coalesce(F.sum(capacity).over(before), F.lit(0.0)))
        .withColumn("_w_left", F.sum(weight).over(order.rowsBetween(Window.currentRow, Window.unboundedFollowing)))
        .withColumn("_level", (F.col(given) - F.col("_cap_before")) / F.col("_w_left"))
        .withColumn("_full", F.col("_ratio") <= F.col("_level"))
        # Past the first child that is not full the computed level falls, so the largest one is that of the first.
        .withColumn("_water", F.max(F.when(~F.col("_full"), F.col("_level"))).over(whole))
    )
    part = F.when(F.col("_full"), F.col(capacity)).otherwise(F.col("_water") * F.col(weight))
    return live.withColumn(out, part).drop("_ratio", "_cap_before", "_w_left", "_level", "_full", "_water")


def leaf_budgets(leaves: DataFrame, budget: Column, weights: Mapping[str, Mapping[str, float]], max_epochs: float) -> DataFrame:
    """domain, lang, source, tokens, docs, budget (whole tokens) of each leaf; ``leaves`` has tokens and docs."""
    cap = leaves.withColumn("_cap", F.col("tokens") * F.lit(float(max_epochs)))
    for level in LEVELS:
        cap = cap.withColumn(f"_w_{level}", weight_column(level, weights.get(level, {})))
    dead = F.greatest(*(F.when(F.col(f"_w_{x}") <= 0, 1).otherwise(0) for x in LEVELS)) == 1
    cap = cap.withColumn("_cap", F.when(dead, 0.0).otherwise(F.col("_cap")))
    given = None
    for depth, level in enumerate(LEVELS):
        path = list(LEVELS[: depth + 1])
        nodes = cap.groupBy(*path).agg(F.sum("_cap").alias("_c"), F.max(f"_w_{level}").alias("_w"))
        if depth == 0:
            nodes = nodes.withColumn("_root", F.lit(0)).withColumn("_g", budget.cast("double"))
            parent = ["_root"]
        else:
            parent = path[:-1]
            nodes = join_on(nodes, given, parent)
        given = water_fill(nodes, parent, "_g", "_c", "_w", "_part").select(*path, F.col("_part").alias("_g"))
    return join_on(leaves, given, list(LEVELS)).withColumn("budget", F.floor(F.col("_g") + 1e-6).cast("long")).drop("_g")


def permutation_key(name: Column, epoch: Column, seed: int) -> Column:
    return F.md5(F.concat_ws("|", F.lit(str(seed)), epoch.cast("string"), name))


def _fitting(rows: DataFrame, part: str) -> tuple[DataFrame, DataFrame]:
    """Rows of each leaf whose whole ``part`` fits into ``_rest`` in rising order, and those of the part in
    which it ends, with what is left for them as ``_rest``."""
    sums = rows.groupBy(*LEVELS, part).agg(F.sum("tokens").alias("_n"), F.max("_rest").alias("_r"))
    sums = sums.withColumn("_upto", F.sum("_n").over(Window.partitionBy(*LEVELS).orderBy(part))).withColumn("_before", F.col("_upto") - F.col("_n"))
    sums = sums.where("_before <= _r").select(*LEVELS, part, "_before", (F.col("_upto") <= F.col("_r")).alias("_fits"))
    near = join_on(rows, sums, [*LEVELS, part])
    cut = near.where("not _fits").withColumn("_rest", F.col("_rest") - F.col("_before"))
    return near.where("_fits").select(*rows.columns), cut.select(*rows.columns)


def mix_sources(docs: DataFrame, domain: Column, weights: Mapping[str, Mapping[str, float]], budget_share: float = 0.5, max_epochs: float = 2.0, seed: int = 7, id_col: str = "doc_id", text_col: str = "text", tokens: Column | None = None, row_col: str | None = None) -> DataFrame:
    """One row per chosen (row, epoch): id, domain, lang, source, tokens, epoch, leaf budget, and _row where
    ``row_col`` names a number that all rows have of their own.

    ``budget_share`` is the whole budget as a share of the corpus's tokens; a leaf is passed over at
    most ``max_epochs`` times.  The last epoch holds the longest prefix of its permutation whose tokens
    fit in what is left.
    """
    count = token_estimate(F.col(text_col)) if tokens is None else tokens
    lang, source = (F.col(c).cast("string") if c in docs.columns else F.lit(None).cast("string") for c in ("lang", "source"))
    name = F.coalesce(F.col(id_col).cast("string"), F.md5(F.coalesce(F.col(text_col), F.lit(""))))
    own = [F.col(row_col).alias("_row")] if row_col else []
    rows = docs.select(F.col(id_col).alias("doc_id"), domain.cast("string").alias("domain"), lang.alias("lang"), source.alias("source"), count.cast("long").alias("tokens"), name.alias("_name"), *own)
    rows = persist(rows, "rows")
    leaves = rows.groupBy(*LEVELS).agg(F.sum("tokens").alias("tokens"), F.count("*").alias("docs"))
    total = leaves.agg(F.floor(F.sum("tokens") * F.lit(float(budget_share)) + 1e-6).alias("t"))
    whole = total.first()["t"] or 0
    budgets = persist(leaf_budgets(leaves, F.lit(int(whole)), weights, max_epochs), "budgets")
    # Whole passes, then one epoch that may be cut.
    size = F.greatest(F.col("tokens"), F.lit(1))
    budgets = budgets.withColumn("_full", F.floor(F.col("budget") / size)).withColumn("_rest", F.col("budget") - F.col("_full") * F.col("tokens"))
    joined = join_on(rows, budgets.drop("docs", "tokens"), list(LEVELS))
    passes = joined.withColumn("epoch", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_full"))))
    whole_passes = passes.where("epoch < _full")
    last = passes.where("epoch = _full and _rest > 0").withColumn("_key", permutation_key(F.col("_name"), F.col("epoch"), seed))
    last = last.withColumn("_range", F.substring("_key", 1, 2)).withColumn("_fine", F.substring("_key", 3, 2))
    wide, last = _fitting(persist(last, "last"), "_range")
    narrow, last = _fitting(persist(last, "ends"), "_fine")
    in_range = Window.partitionBy(*LEVELS).orderBy("_key", "doc_id", "tokens", *(["_row"] if row_col else [])).rowsBetween(Window.unboundedPreceding, 0)
    cut = last.withColumn("_at", F.sum("tokens").over(in_range)).where("_at <= _rest")
    columns = ["doc_id", *LEVELS, "tokens", "epoch", "budget", *(["_row"] if row_col else [])]
    out = whole_passes.select(*columns)
    for part in (wide, narrow, cut):
        out = out.unionByName(part.select(*columns))
    return out
