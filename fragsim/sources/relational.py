"""Fragments of the relational tables: purchase baskets, activity traces and markup."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fragsim.sources.prose import _long, add_metric_columns


def basket_rows(lineitem: DataFrame, orders: DataFrame, part: DataFrame) -> DataFrame:
    items = lineitem.join(orders, lineitem.l_orderkey == orders.o_orderkey).join(part, lineitem.l_partkey == part.p_partkey)
    return items.select(F.col("o_custkey").alias("fragment_id"), F.col("p_brand").alias("action"), "*")


def bag_of_rows(rows: DataFrame) -> DataFrame:
    """fragment_id, actions, action_total from rows (fragment_id, action): counted, then gathered per fragment."""
    counts = rows.groupBy("fragment_id", "action").agg(F.count("*").alias("f"))
    return counts.groupBy("fragment_id").agg(F.map_from_entries(F.collect_list(F.struct("action", "f"))).alias("actions"), F.sum("f").alias("action_total"))


def basket_fragments(lineitem: DataFrame, orders: DataFrame, part: DataFrame) -> DataFrame:
    """One fragment per customer; actions are the brands bought."""
    rows = basket_rows(lineitem, orders, part)
    return bag_of_rows(rows).withColumn("n_tokens", F.col("action_total"))


def basket_metrics(lineitem: DataFrame, orders: DataFrame, part: DataFrame) -> DataFrame:
    rows = basket_rows(lineitem, orders, part)
    n = lambda c: _long(F.coalesce(F.sum(F.when(c, 1).otherwise(0)), F.lit(0)))
    per_order = rows.groupBy("fragment_id", "l_orderkey").agg(F.count("*").alias("c")).groupBy("fragment_id").agg(_long(F.max("c")).alias("mdn"))
    per_part = rows.groupBy("fragment_id", "l_partkey").agg(F.count("*").alias("c")).groupBy("fragment_id").agg(_long(F.sum(F.when(F.col("c") > 1, 1).otherwise(0))).alias("loop"))
    per_brand = rows.groupBy("fragment_id", "action").agg(F.count("*").alias("c")).groupBy("fragment_id").agg(
        _long(F.count("*")).alias("xmet"), _long(F.sum(F.when(F.col("c") > 1, 1).otherwise(0))).alias("lmet")
    )
    aggs = rows.groupBy("fragment_id").agg(
        n(F.col("l_returnflag") == "R").alias("vref"), n(F.col("l_returnflag") == "A").alias("vdec"), _long(F.countDistinct("l_orderkey")).alias("nos"),
        _long(F.count("*")).alias("nopr"), _long(F.countDistinct("o_orderpriority")).alias("noa"), n(F.col("l_discount") > 0).alias("nexp"),
        _long(F.sum(F.col("l_quantity").cast("decimal(18,2)"))).alias("nand"), n(F.col("l_linestatus") == "F").alias("exct"), n(F.col("o_orderstatus") == "P").alias("excr"),
        _long(F.countDistinct("l_suppkey")).alias("cref"), (_long(F.countDistinct(F.date_format("l_shipdate", "yyyy-MM"))) + 1).alias("comp"),
        n(F.col("l_tax") > 0.05).alias("cast"), n(F.col("o_orderstatus") == "O").alias("nbltrl"), n(F.col("l_returnflag") == "N").alias("ncltrl"),
        _long(F.countDistinct("p_type")).alias("nsltrl"), n(F.col("l_quantity") > 25).alias("nnltrl"),
        _long(F.countDistinct("p_brand")).alias("op_kinds"), _long(F.countDistinct("p_type")).alias("operand_kinds"),
    )
    out = aggs.join(per_order, "fragment_id").join(per_part, "fragment_id").join(per_brand, "fragment_id").withColumn("nnulltrl", F.lit(0).cast("long"))
    return add_metric_columns(out, {"op_kinds": F.col("op_kinds"), "operand_kinds": F.col("operand_kinds"), **{c: F.col(c) for c in out.columns if c not in ("fragment_id", "op_kinds", "operand_kinds")}})


def activity_fragments(events: DataFrame, with_key: bool = False) -> DataFrame:
    """One fragment per user; actions are event types, with ``with_key`` joined with the property k."""
    key = F.concat_ws("|", "event_type", F.get_json_object("props", "$.k")) if with_key else F.col("event_type")
    return bag_of_rows(events.select(F.col("user_id").alias("fragment_id"), key.alias("action"))).withColumn("n_tokens", F.col("action_total"))


def markup_fragments(pages: DataFrame) -> DataFrame:
    """One fragment per page; actions are tag names and link targets."""
    html = F.coalesce("html", F.lit(""))
    tags = F.transform(F.regexp_extract_all(html, F.lit("<([a-z][a-z0-9]*)"), F.lit(1)), lambda t: F.concat(F.lit("<"), t))
    links = F.regexp_extract_all(html, F.lit('href="([^"]*)"'), F.lit(1))
    plain = F.regexp_replace(html, "<[^>]*>", " ")
    words = F.regexp_extract_all(F.lower(plain), F.lit(r"[\p{L}\p{N}_]+"), F.lit(0))
    from fragsim.sources.prose import sorted_bag

    return pages.select(
        F.col("page_id").cast("long").alias("fragment_id"), F.regexp_extract("url", "://([^/]+)", 1).alias("origin"),
        _long(F.size(words) + F.size(tags)).alias("n_tokens"), sorted_bag(F.concat(tags, links)).alias("actions"), _long(F.size(tags) + F.size(links)).alias("action_total"),
    )
