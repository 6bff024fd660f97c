"""Fragments of natural-language text: whole documents, their lines, passages or turns of talk."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fragsim.config import METRICS
from fragsim.functions.hashing import metric_hash
from fragsim.functions.text import WORD, count_of, halstead, lexical_key, textual_key, tokens

ACTION_LETTERS = 6
SENTENCE = r"[^.!?]*[^.!?\s][^.!?]*"
MARK = r"[^\p{L}\p{N}_\s]"


def _long(c: Column) -> Column:
    return c.cast("long")


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use(value)`` with the value computed once: a lambda's argument is not evaluated again at each
    place where it stands."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def sorted_bag(words: Column) -> Column:
    """Map word -> frequency of an array of words, without a shuffle: sort, then one pass over the ends of runs."""

    def of_sorted(o: Column) -> Column:
        ends = F.filter(F.sequence(F.lit(1), F.size(o)), lambda i: (i == F.size(o)) | (F.get(o, i) != F.get(o, i - 1)))
        return let(ends, lambda e: F.map_from_arrays(F.transform(e, lambda i: F.get(o, i - 1)), F.transform(e, lambda i, n: _long(i - F.coalesce(F.get(e, n - 1), F.lit(0))))))

    empty = F.create_map().cast("map<string,bigint>")
    return F.when(F.size(words) > 0, let(F.sort_array(words), of_sorted)).otherwise(empty)


def prose_fragments(rows: DataFrame, id_col: str, text_col: str, origin: Column | None = None, lang: Column | None = None) -> DataFrame:
    """Canonical fragments without metrics: identifiers, sizes, action bag and normal-form keys."""
    base = rows.select(
        F.col(id_col).cast("long").alias("fragment_id"),
        (origin if origin is not None else F.lit(None)).cast("string").alias("origin"),
        (lang if lang is not None else F.lit(None)).cast("string").alias("lang"),
        F.coalesce(F.col(text_col), F.lit("")).alias("text"),
    )
    # A filter on what is generated is not moved before it, so a floor does not take the text apart a second time.
    base = base.select("*", F.explode(F.array(tokens(F.col("text")))).alias("words"))
    acts = F.filter("words", lambda w: F.length(w) >= ACTION_LETTERS)
    return base.select(
        "fragment_id", "origin", "lang", "text", "words",
        _long(F.size("words")).alias("n_tokens"),
        _long(F.size(F.split("text", "\n"))).alias("n_lines"),
        sorted_bag(acts).alias("actions"),
        _long(F.size(acts)).alias("action_total"),
        textual_key(F.col("text")).alias("text_key"),
        lexical_key(F.col("words"), "consistent").alias("lex_key"),
    )


def prose_metrics(fragments: DataFrame) -> DataFrame:
    """Adds the 24 metrics as columns, metric_vec and metric_hash.  None depends on blanks and line ends, as in the
    metrics of programs: texts that differ in layout alone have equal hashes."""
    t, w = F.col("text"), F.col("words")
    size = lambda a: _long(F.size(a))
    # Parts that several metrics read are columns of a step before, so that each is made once.
    parts = {
        "_marks": F.regexp_extract_all(t, F.lit(MARK), F.lit(0)),
        "_sentences": F.regexp_extract_all(t, F.lit(SENTENCE), F.lit(0)),
        "_middle": F.filter(w, lambda x: F.length(x).between(4, 5)),
        "_short": F.filter(w, lambda x: F.length(x).between(1, 2)),
        "_single": _long(F.size(F.filter(F.map_values("actions"), lambda n: n == 1))),
    }
    marks, sentences, middle, short, single = map(F.col, parts)
    original = F.regexp_extract_all(t, F.lit(WORD), F.lit(0))
    v = {
        "xmet": single,
        "vref": size(middle),
        "vdec": size(F.array_distinct(middle)),
        "nos": size(sentences),
        "nopr": size(marks),
        "noa": size(tokens(F.regexp_extract(t, "^[^.!?]*", 0))),
        "nexp": count_of(t, "[,;:]") + size(sentences),
        "nand": size(w),
        "mdn": _long(F.coalesce(F.array_max(F.transform(sentences, lambda s: count_of(s, "[,;:]") + 1)), F.lit(0))),
        "loop": size(sentences) - size(F.array_distinct(F.transform(sentences, lambda x: F.trim(F.regexp_replace(x, r"\s+", " "))))),
        "lmet": size(F.col("actions")) - single,
        "exct": count_of(t, "!"),
        "excr": count_of(t, "[?]"),
        "cref": count_of(t, r"\p{Lu}\p{Ll}+"),
        "comp": size(short) + 1,
        "cast": F.when(t.rlike(r"\p{Lu}{2}"), size(F.filter(original, lambda x: x.rlike(r"^\p{Lu}{2,}$")))).otherwise(F.lit(0).cast("long")),
        "nbltrl": size(F.filter(short, lambda x: F.length(x) == 1)),
        "ncltrl": count_of(t, r"[#$%&*@|]"),
        "nsltrl": count_of(t, '"[^"]*"'),
        "nnltrl": count_of(t, "[0-9]+"),
        "nnulltrl": size(F.filter(w, lambda x: x.startswith("0") & x.rlike("^0+$"))),
        "op_kinds": size(F.array_distinct(marks)),
        "operand_kinds": size(F.array_distinct(w)),
    }
    return add_metric_columns(fragments.withColumns(parts), v).drop(*parts)


def add_metric_columns(fragments: DataFrame, v: dict[str, Column]) -> DataFrame:
    """From whole-number columns to all metrics, the vector and the hash."""
    out = fragments.withColumns(v)
    held = {k: F.col(k) for k in v}
    vocabulary, difficulty, effort = halstead(held["op_kinds"], held["operand_kinds"], held["nopr"], held["nand"])
    out = out.withColumn("hvoc", vocabulary).withColumn("hdif", difficulty).withColumn("heff", effort)
    vector = F.array(*(F.col(m).cast("double") for m in METRICS))
    return out.withColumn("metric_vec", vector).withColumn("metric_hash", metric_hash(held))


def lines_of(documents: DataFrame) -> DataFrame:
    """One row per line of a document: fragment_id = doc_id * 10**6 + place."""
    lines = documents.select("doc_id", "lang", "source", F.posexplode(F.split(F.coalesce("text", F.lit("")), "\n")).alias("place", "line"))
    return lines.select((F.col("doc_id") * 1_000_000 + F.col("place")).alias("line_id"), "lang", "source", F.col("line").alias("text"))


def windows_of(fragments: DataFrame, window: int, stride: int) -> DataFrame:
    """Sliding windows of tokens: fragment_id, place, words."""
    places = F.when(F.size("words") >= window, F.sequence(F.lit(0), F.size("words") - window, F.lit(stride)))
    return fragments.select("fragment_id", "words", F.explode(places).alias("place")).select("fragment_id", "place", F.slice("words", F.col("place") + 1, F.lit(window)).alias("words"))


def apply_floor(fragments: DataFrame, min_tokens: int = 15, min_lines: int | None = None) -> DataFrame:
    out = fragments.where(F.col("n_tokens") >= min_tokens)
    return out if min_lines is None else out.where(F.col("n_lines") >= min_lines)
