"""Fragments of a small Java-like language: tokens, actions and literal counts of methods.

Tokens are keywords, types, identifiers and literals (a string literal counts once per word).  Actions are
called names, accessed fields and subscripts; a subscript whose index is a binary expression is marked
apart from a plain one, and an index in parentheses counts as plain.  The declared method's name and
constructors are not actions.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_LEX = re.compile(r"""//[^\n]*|/\*.*?\*/|(?P<str>"(?:\\.|[^"\\])*")|(?P<chr>'(?:\\.|[^'\\])*')|(?P<num>\d[\w.]*)|(?P<id>[A-Za-z_$][\w$]*)|(?P<op>[-+*/%&|^<>=!]=?|&&|\|\||[?:~])|(?P<p>[(){}\[\];,.@])""", re.S)
# Words of the language that cannot be called.
KEYWORDS = {"if", "for", "while", "switch", "catch", "return", "new", "throw", "synchronized", "else", "do", "try", "super", "this", "case", "instanceof"}


def lex(source: str) -> list[tuple[str, str]]:
    return [(m.lastgroup, m[0]) for m in _LEX.finditer(source) if m.lastgroup]


def size_in_tokens(tokens: list[tuple[str, str]]) -> int:
    return sum(max(0, len(v[1:-1].split())) if k == "str" else k in ("id", "num", "chr") for k, v in tokens)


def actions(tokens: list[tuple[str, str]]) -> dict[str, int]:
    """Bag of actions of one method (its declaration comes first)."""
    out: Counter[str] = Counter()
    body = next((i for i, (_, v) in enumerate(tokens) if v == "{"), 0)
    for i, (kind, value) in enumerate(tokens):
        after = tokens[i + 1][1] if i + 1 < len(tokens) else ""
        before = tokens[i - 1][1] if i else ""
        if kind == "id" and i > body and value not in KEYWORDS:
            if after == "(" and before != "new":
                out[value] += 1
            elif before == "." and after != "(":
                out[value] += 1
        if value == "[" and i > body and i and (tokens[i - 1][0] == "id" or before in ("]", ")")) and after != "]":
            depth, binary, j = 1, False, i + 1
            while j < len(tokens) and depth:
                v = tokens[j][1]
                depth += (v in "([") - (v in ")]")
                binary |= depth == 1 and tokens[j][0] == "op" and j > i + 1
                j += 1
            out["subscript_binary" if binary else "subscript"] += 1
    return dict(out)


def literals(tokens: list[tuple[str, str]]) -> dict[str, int]:
    n = Counter("nbltrl" if v in ("true", "false") else "nnulltrl" if v == "null" else {"str": "nsltrl", "chr": "ncltrl", "num": "nnltrl"}.get(k, "") for k, v in tokens)
    return {m: n[m] for m in ("nbltrl", "ncltrl", "nsltrl", "nnltrl", "nnulltrl")}


def _parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kind = pa.map_(pa.string(), pa.int64())
    for batch in batches:
        lexed = [lex(t or "") for t in batch.column(1).to_pylist()]
        bags, counts = [actions(t) for t in lexed], [literals(t) for t in lexed]
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array([size_in_tokens(t) for t in lexed], pa.int64()), pa.array([list(b.items()) for b in bags], kind), pa.array([sum(b.values()) for b in bags], pa.int64()), pa.array([list(c.items()) for c in counts], kind)],
            ["fragment_id", "n_tokens", "actions", "action_total", "literals"],
        )


def method_fragments(methods: DataFrame, id_col: str = "fragment_id", text_col: str = "text") -> DataFrame:
    """fragment_id, n_tokens, actions, action_total, literals of one method per row."""
    rows = methods.select(F.col(id_col).cast("long").alias("fragment_id"), F.col(text_col))
    return rows.mapInArrow(_parse, "fragment_id long, n_tokens long, actions map<string,bigint>, action_total long, literals map<string,bigint>")
