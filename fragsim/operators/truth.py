"""Reference pairs: deterministic mutants of documents, their measured class, and passages."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fragsim.sources.prose import ACTION_LETTERS

#: Kinds of mutants and the class each is meant for.
KINDS = {1: "T1", 2: "T2", 3: "VST3", 4: "ST3", 5: "MT3", 6: "WT3T4", 0: "none"}
#: Sentences that a base document needs, identifiers in one range of their order, what a mutant's number adds per kind.
MIN_SENTENCES, RANGE, ID_STEP = 8, 10_000, 1_000_000_000


def sentences(text: Column) -> Column:
    """Parts of a text between blanks that follow a full stop, question or exclamation mark."""
    return F.regexp_extract_all(text, F.lit(r"[^.!?]*[^.!?\s][^.!?]*[.!?]*"), F.lit(0))


def renamed(text: Column) -> Column:
    """Every short word, the counterpart of a program's own names, under another name of its length; the long words, which
    are the actions, stay, as called names do.  One permutation of letters, so equal words stay equal."""
    parts = F.regexp_extract_all(text, F.lit(r"[\p{L}\p{N}_]+|[^\p{L}\p{N}_]+"), F.lit(0))
    return F.array_join(F.transform(parts, lambda x: F.when(F.length(x) < ACTION_LETTERS, F.translate(x, "aeiouAEIOU", "eiouaEIOUA")).otherwise(x)), "")


def mutants(documents: DataFrame) -> DataFrame:
    """mutant_id, base_id, kind, text: six variants and one stranger of every document of enough
    sentences.

    The neighbour of a document is the next one (in the order of identifiers, the last one's is the
    first) with enough sentences.
    """
    able = documents.select(F.col("doc_id").alias("base_id"), F.transform(sentences(F.coalesce("text", F.lit(""))), lambda s: F.trim(s)).alias("s"))
    able = able.where(F.size("s") >= MIN_SENTENCES)
    # The order of the base documents: identifiers only, in ranges.
    ids = able.select("base_id")
    part = F.floor(F.col("base_id") / RANGE)
    inside = Window.partitionBy("part").orderBy("base_id")
    linked = ids.withColumn("part", part).withColumn("next", F.lead("base_id").over(inside))
    heads = linked.groupBy("part").agg(F.min("base_id").alias("head"))
    ring = Window.orderBy("part")
    heads = heads.withColumn("after", F.coalesce(F.lead("head").over(ring), F.first("head").over(ring)))
    linked = linked.join(heads.select("part", "after"), "part").select("base_id", F.coalesce("next", "after").alias("next_id"))
    other = able.select(F.col("base_id").alias("next_id"), F.col("s").alias("o"))
    both = able.join(linked, "base_id").join(other, "next_id")
    keep = lambda arr, test: F.filter(arr, lambda x, i: test(i))
    replaced = F.transform("s", lambda x, i: F.when((i % 5 == 1) | (i % 5 == 3), F.get(F.col("o"), i % F.size("o"))).otherwise(x))
    woven = F.reverse(F.transform("s", lambda x, i: F.when(i % 3 == 0, x).otherwise(F.get(F.col("o"), i % F.size("o")))))
    text = {
        1: F.array_join(F.transform("s", lambda x: F.regexp_replace(x, " ", "  ")), "\n"),
        2: renamed(F.array_join("s", " ")),
        3: F.array_join(keep("s", lambda i: i % 20 != 7), " "),
        4: F.array_join(keep("s", lambda i: i % 5 != 2), " "),
        5: F.array_join(replaced, " "),
        6: F.array_join(woven, " "),
        0: F.array_join("o", " "),
    }
    each = F.explode(F.array(*(F.struct(F.lit(k).cast("long").alias("kind"), t.alias("text")) for k, t in text.items()))).alias("m")
    out = both.select("base_id", each)
    return out.select((F.col("m.kind") * ID_STEP + F.col("base_id") + F.when(F.col("m.kind") == 0, 9 * ID_STEP).otherwise(0)).alias("mutant_id"), "base_id", F.col("m.kind").alias("kind"), F.col("m.text").alias("text"))


def common_elements(pairs: DataFrame, sides: dict[str, DataFrame]) -> DataFrame:
    """left_id, right_id and per name how many elements the two bags have in common.

    ``sides`` holds per name rows (fragment_id, u), one for each element.  Bags are counted before they meet and
    meet by an equi-join, so a pair costs as many rows as its smaller vocabulary and no array is folded.
    """
    bags = None
    for name, rows in sides.items():
        part = rows.groupBy("fragment_id", "u").agg(F.count("*").alias("f")).withColumn("side", F.lit(name))
        bags = part if bags is None else bags.unionByName(part)
    mine = bags.select(F.col("fragment_id").alias("left_id"), "side", "u", F.col("f").alias("a"))
    theirs = bags.select(F.col("fragment_id").alias("right_id"), "side", "u", F.col("f").alias("b"))
    met = pairs.select("left_id", "right_id").distinct().join(mine, "left_id").join(theirs, ["right_id", "side", "u"])
    least = F.least("a", "b")
    return met.groupBy("left_id", "right_id").agg(*(F.sum(F.when(F.col("side") == name, least).otherwise(0)).alias(name) for name in sides))


def categorise(pairs: DataFrame, fragments: DataFrame, combine: str = "min") -> DataFrame:
    """Adds line_pct, token_pct and category.

    T1 and T2 by equal normal forms; else the class of the smaller (or mean, or larger) of sentence and
    token similarity (common elements as whole percent of the longer side), each interval closed below.
    """
    from fragsim.operators.pairs import with_sides

    lines = F.transform(sentences(F.col("text")), lambda s: F.lower(F.trim(s)))
    prepared = fragments.select("fragment_id", "text_key", "lex_key", "words", lines.alias("lines"))
    sides = {name: prepared.select("fragment_id", F.explode(name).alias("u")) for name in ("lines", "words")}
    sizes = prepared.select("fragment_id", "text_key", "lex_key", F.size("lines").cast("long").alias("lines"), F.size("words").cast("long").alias("words"))
    common = common_elements(pairs, sides).withColumnsRenamed({"lines": "same_lines", "words": "same_words"})
    out = with_sides(pairs, sizes, "text_key", "lex_key", "words", "lines").join(common, ["left_id", "right_id"], "left")
    for unit, name in (("lines", "line_pct"), ("words", "token_pct")):
        longest = F.greatest(f"l_{unit}", f"r_{unit}")
        share = F.floor(F.coalesce(F.col(f"same_{unit}"), F.lit(0)) * 100 / longest).cast("long")
        out = out.withColumn(name, F.when(longest == 0, F.lit(100).cast("long")).otherwise(share))
    pct = {"min": F.least("line_pct", "token_pct"), "max": F.greatest("line_pct", "token_pct"), "avg": F.floor((F.col("line_pct") + F.col("token_pct")) / 2)}[combine]
    kind = F.when(F.col("l_text_key") == F.col("r_text_key"), "T1").when(F.col("l_lex_key") == F.col("r_lex_key"), "T2").when(pct >= 90, "VST3").when(pct >= 70, "ST3").when(pct >= 50, "MT3").otherwise("WT3T4")
    drop = [f"{s}_{c}" for s in "lr" for c in ("text_key", "lex_key", "words", "lines")]
    return out.withColumn("category", kind).drop(*drop, "same_lines", "same_words")


def passages(documents: DataFrame, benchmark: DataFrame) -> DataFrame:
    """item_id, doc_id where a benchmark text stands verbatim in a document.

    The benchmark is a fixed evaluation set; its size is left to the engine's broadcast check.
    The words inside an item, between its first and its last when these touch its ends, are whole words of
    every text that holds it; up to five of them are looked up among the windows of that many words.  Items
    without such a word are searched in every document.
    """
    words = lambda c: F.regexp_extract_all(c, F.lit(r"[\p{L}\p{N}_]+"), F.lit(0))
    inner = F.regexp_replace("item", r"^[\p{L}\p{N}_]+|[\p{L}\p{N}_]+$", "")
    items = benchmark.select("item_id", F.col("text").alias("item")).where("item <> ''").withColumn("head", F.slice(words(inner), 1, 5)).withColumn("n", F.size("head"))
    sizes = sorted(r.n for r in items.where("n > 0").select("n").distinct().collect())
    docs = documents.select("doc_id", "text", words(F.col("text")).alias("w"))
    here = F.col("text").contains(F.col("item"))
    out = docs.join(items.where("n = 0"), here).select("item_id", "doc_id")
    for n in sizes:
        places = F.when(F.size("w") >= n, F.sequence(F.lit(1), F.size("w") - (n - 1)))
        window = lambda i: F.array_join(F.slice(F.col("w"), i, n), " ")  # noqa: B023, E731
        heads = docs.select("doc_id", "text", F.explode(F.array_distinct(F.transform(places, window))).alias("head"))
        listed = items.where(F.col("n") == n).select("item_id", "item", F.array_join("head", " ").alias("head"))
        out = out.unionByName(heads.join(listed, "head").where(here).select("item_id", "doc_id"))
    return out.distinct()
