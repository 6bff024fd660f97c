"""Column expressions on text: tokens, normal forms, Halstead measures."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = r"[\p{L}\p{N}_]+"


def tokens(text: Column, pattern: str = WORD) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(pattern), F.lit(0))


def count_of(text: Column, pattern: str) -> Column:
    """Number of matches of a pattern, as LONG."""
    return F.size(F.regexp_extract_all(text, F.lit(pattern), F.lit(0))).cast("long")


def token_count(text: Column) -> Column:
    return F.size(tokens(text)).cast("long")


def textual_key(text: Column) -> Column:
    """T1 normal form: blanks and layout collapsed; its MD5."""
    return F.md5(F.trim(F.regexp_replace(text, r"[ \t\n\r]+", " ")))


def lexical_key(words: Column, rename: str = "blind", literals: bool = True) -> Column:
    """T2 normal form of a token array; its MD5.

    ``blind`` replaces every identifier by one symbol, ``consistent`` by the place of its first
    occurrence; with ``literals`` numbers become one symbol too.
    """
    name = (lambda w: F.lit("v")) if rename == "blind" else (lambda w: F.concat(F.lit("v"), F.array_position(words, w).cast("string")))
    shown = F.transform(words, lambda w: F.when(w.rlike("^[0-9]+$"), F.lit("n") if literals else w).otherwise(name(w)))
    return F.md5(F.array_join(shown, " "))


def halstead(n1: Column, n2: Column, total1: Column, total2: Column) -> tuple[Column, Column, Column]:
    """Vocabulary, difficulty and effort from kinds and totals of operators and operands."""
    vocabulary = (n1 + n2).cast("long")
    difficulty = F.when(n2 == 0, F.lit(0.0)).otherwise(n1.cast("double") * total2 / (n2 * 2))
    effort = F.when(vocabulary == 0, F.lit(0.0)).otherwise(difficulty * (total1 + total2) * F.log2(vocabulary))
    return vocabulary, difficulty, effort


def literal_counts(words: Column) -> dict[str, Column]:
    """The five literal-kind metrics of a token array of program text."""
    n = lambda pattern: F.size(F.filter(words, lambda w: w.rlike(pattern))).cast("long")
    return {"nbltrl": n("^(true|false)$"), "ncltrl": n("^'.*'$"), "nsltrl": n('^".*"$'), "nnltrl": n("^[0-9]"), "nnulltrl": n("^null$")}
