"""Language identification by a bidirectional gated recurrent network over bytes.

Texts are read as UTF-8 bytes in segments of fixed length; both directions start afresh in each segment,
so thousands of segments advance together as columns of matrices.  The network gives every byte position
a distribution over the learned languages; a document's distribution is the mean over all positions of
its whole text, its score the largest entry.

Training is backpropagation through time in numpy with the Adam rule, on a sample whose size does not
grow with the corpus: at most ``SAMPLE_DOCS`` labelled documents in all, equally many per language, each
seen through at most ``SAMPLE_SEGMENTS`` pieces spread evenly over it; of more languages than half the
sample the most frequent are learned.  Only rows with a language whose identifier has a CRC-32 not
divisible by five are learned from.

Defined results: null texts and texts without a letter are ``und`` with score 0, as is everything where
nothing could be learned; a null identifier is neither held out nor learned from; rows that repeat an
identifier are predicted each and learned from by text, once each; an empty table gives an empty result;
names of other columns do not matter.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType
from pyspark.sql.window import Window

from .common import unused
from .words import chunks

SAMPLE_DOCS, SAMPLE_SEGMENTS = 1200, 16
HIDDEN, TRAIN_LENGTH, LENGTH = 8, 64, 128
UPDATES, BATCH, RATE = 400, 256, 0.02
PAD = 256
#: Bytes of text that are in the network at once.
INFER_BYTES = 256 << 10


def held_out(id_col: str) -> Column:
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 5 == 0, F.lit(False))


@dataclass
class Model:
    """Weights: x (directions, 3 gates * hidden, bytes), u (directions, 3 * hidden, hidden), v (languages, 2 * hidden), b."""

    languages: list[str]
    x: np.ndarray
    u: np.ndarray
    v: np.ndarray
    b: np.ndarray


def new_model(languages: list[str], seed: int = 5, hidden: int = HIDDEN) -> Model:
    rng = np.random.default_rng(seed)
    normal = lambda *shape, scale: (rng.standard_normal(shape) * scale).astype(np.float32)
    n = len(languages)
    return Model(languages, normal(2, 3 * hidden, PAD + 1, scale=0.3), normal(2, 3 * hidden, hidden, scale=hidden**-0.5), normal(n, 2 * hidden, scale=0.3), np.zeros(n, np.float32))


def _steps(model: Model, codes: np.ndarray, keep: bool) -> tuple[np.ndarray, list]:
    """States (length, 2, hidden, columns) of both directions over ``codes`` (length, columns); the second
    direction reads backwards and its states are in reading order.  With ``keep``, what backpropagation needs."""
    length, columns = codes.shape
    hidden = model.u.shape[2]
    h = np.zeros((2, hidden, columns), np.float32)
    states, saved = np.empty((length, 2, hidden, columns), np.float32), []
    x = np.empty((2, 3 * hidden, columns), np.float32)
    for t in range(length):
        np.take(model.x[0], codes[t], axis=1, out=x[0])
        np.take(model.x[1], codes[length - 1 - t], axis=1, out=x[1])
        g = np.matmul(model.u, h)
        gates = x[:, : 2 * hidden] + g[:, : 2 * hidden]
        gates *= 0.5
        np.tanh(gates, out=gates)  # the logistic function through tanh
        gates += 1
        gates *= 0.5
        z, r = gates[:, :hidden], gates[:, hidden:]
        gn = g[:, 2 * hidden :]
        n = np.tanh(x[:, 2 * hidden :] + r * gn)
        if keep:
            saved.append((h, z, r, n, gn))
        h = n + z * (h - n)
        states[t] = h
    return states, saved


def _position_probabilities(model: Model, states: np.ndarray) -> np.ndarray:
    """(length, languages, columns): softmax of a linear map of both directions' states at each position."""
    hidden = model.u.shape[2]
    logits = np.matmul(model.v[:, :hidden], states[:, 0]) + np.matmul(model.v[:, hidden:], states[::-1, 1]) + model.b[:, None]
    logits -= logits.max(axis=1, keepdims=True)
    np.exp(logits, out=logits)
    logits /= logits.sum(axis=1, keepdims=True)
    return logits


def loss_and_gradients(model: Model, codes: np.ndarray, target: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
    """Mean cross-entropy over the positions that are text, and its gradients (backpropagation through time)."""
    length, columns = codes.shape
    hidden = model.u.shape[2]
    states, saved = _steps(model, codes, keep=True)
    p = _position_probabilities(model, states)
    live = (codes != PAD).astype(np.float32)
    total = max(1.0, float(live.sum()))
    chosen = p[:, target, np.arange(columns)]
    loss = float(-(np.log(chosen + 1e-12) * live).sum() / total)
    d = p.copy()
    d[:, target, np.arange(columns)] -= 1
    d *= live[:, None, :] / total
    forward, backward = states[:, 0], states[::-1, 1]
    dv = np.concatenate([np.einsum("tlc,thc->lh", d, forward, optimize=True), np.einsum("tlc,thc->lh", d, backward, optimize=True)], axis=1)
    from_output = np.stack([np.matmul(model.v[:, :hidden].T, d), np.matmul(model.v[:, hidden:].T, d)[::-1]], axis=1)
    du, dx = np.zeros_like(model.u), np.empty((length, 2, 3 * hidden, columns), np.float32)
    dh = np.zeros((2, hidden, columns), np.float32)
    ut = model.u.transpose(0, 2, 1)
    for t in range(length - 1, -1, -1):
        h, z, r, n, gn = saved[t]
        dh = dh + from_output[t]
        dz, dn = dh * (h - n) * z * (1 - z), dh * (1 - z) * (1 - n * n)
        dr = dn * gn * r * (1 - r)
        dx[t] = np.concatenate([dz, dr, dn], axis=1)
        dg = np.concatenate([dz, dr, dn * r], axis=1)
        du += np.matmul(dg, h.transpose(0, 2, 1))
        dh = dh * z + np.matmul(ut, dg)
    gx = np.zeros_like(model.x)
    for k, order in ((0, codes), (1, codes[::-1])):
        flat = order.ravel()
        for i in range(3 * hidden):
            gx[k, i] = np.bincount(flat, dx[:, k, i].ravel(), PAD + 1)
    return loss, {"x": gx, "u": du, "v": dv.astype(np.float32), "b": d.sum(axis=(0, 2)).astype(np.float32)}


def fit(pieces: list[bytes], labels: list[str], updates: int = UPDATES, batch: int = BATCH, rate: float = RATE, seed: int = 5) -> Model:
    """Train on labelled pieces of text."""
    languages = sorted(set(labels))
    model = new_model(languages, seed)
    if len(languages) < 2:
        return model
    number = {k: i for i, k in enumerate(languages)}
    codes = np.full((TRAIN_LENGTH, len(pieces)), PAD, np.int64)
    for i, piece in enumerate(pieces):
        codes[: min(len(piece), TRAIN_LENGTH), i] = np.frombuffer(piece[:TRAIN_LENGTH], np.uint8)
    target = np.array([number[x] for x in labels])
    rng = np.random.default_rng(seed)
    moments = {k: (np.zeros_like(getattr(model, k)), np.zeros_like(getattr(model, k))) for k in "xuvb"}
    for step in range(1, updates + 1):
        pick = rng.integers(0, len(pieces), min(batch, len(pieces)))
        _, gradients = loss_and_gradients(model, codes[:, pick], target[pick])
        now = rate * (1 - 0.9 * step / updates)
        for k, g in gradients.items():
            m, v = moments[k]
            m += 0.1 * (g - m)
            v += 0.01 * (g * g - v)
            getattr(model, k)[...] -= now * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return model


def training_pieces(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample: int = SAMPLE_DOCS) -> tuple[list[bytes], list[str]]:
    """The bounded sample, collected: pieces of text and their languages."""
    usable = F.col(lang_col).isNotNull() & F.col(id_col).isNotNull() & F.col(text_col).isNotNull() & ~held_out(id_col)
    marks = [F.col(lang_col).alias("lang"), F.xxhash64(id_col).alias("k"), F.xxhash64(text_col).alias("m")]
    last = F.greatest(F.length(text_col) - TRAIN_LENGTH, F.lit(0))
    piece = F.transform(F.sequence(F.lit(0), F.lit(SAMPLE_SEGMENTS - 1)), lambda i: F.substring(F.col(text_col), (F.floor(last * i / (SAMPLE_SEGMENTS - 1)) + 1).cast("int"), F.lit(TRAIN_LENGTH)))
    keys = docs.where(usable).select(*marks)
    kinds = [r["lang"] for r in keys.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(sample // 2).collect()]
    if not kinds:
        return [], []
    chosen = keys.where(F.col("lang").isin(kinds)).withColumn("n", F.row_number().over(Window.partitionBy("lang").orderBy("k", "m")))
    chosen = chosen.where(F.col("n") <= max(2, sample // len(kinds))).select("lang", "k", "m").distinct()
    # At most `sample` of (language, identifier, text); rows that repeat them all count once.
    rows = docs.where(usable).select(*marks, piece.alias("pieces")).join(F.broadcast(chosen), ["lang", "k", "m"], "left_semi")
    rows = rows.groupBy("lang", "k", "m").agg(F.min("pieces").alias("pieces")).collect()
    rows.sort(key=lambda r: (r.k, r.lang, r.m))
    pairs = [(p.encode(), r.lang) for r in rows for p in dict.fromkeys(r.pieces) if p]
    return [p for p, _ in pairs], [x for _, x in pairs]


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample: int = SAMPLE_DOCS, **options) -> Model:
    pieces, labels = training_pieces(docs, id_col, text_col, lang_col, sample)
    return fit(pieces, labels, **options)


def document_probabilities(model: Model, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Mean distribution of each document, and how many positions of it each language wins."""
    sizes = np.diff(offsets)
    parts = -(-sizes // LENGTH)
    document = np.repeat(np.arange(len(sizes)), parts)
    nth = np.arange(len(document)) - np.repeat(np.cumsum(parts) - parts, parts)
    start = offsets[document] + nth * LENGTH
    stop = offsets[document + 1]
    n = len(model.languages)
    sums, wins = np.zeros((len(sizes), n)), np.zeros((len(sizes), n), np.int64)
    padded = np.concatenate([data, np.zeros(LENGTH, np.uint8)])
    width = INFER_BYTES // LENGTH
    for at in range(0, len(document), width):
        s, e, d = start[at : at + width], stop[at : at + width], document[at : at + width]
        index = s[None, :] + np.arange(LENGTH)[:, None]
        live = index < e[None, :]
        codes = np.where(live, padded[np.minimum(index, len(padded) - 1)].astype(np.int64), PAD)  # bytes cannot hold PAD
        p = _position_probabilities(model, _steps(model, codes, keep=False)[0])
        np.add.at(sums, d, (p * live[:, None, :]).sum(axis=0, dtype=np.float64).T)
        best = p.argmax(axis=1)
        for k in range(n):
            np.add.at(wins[:, k], d, ((best == k) & live).sum(axis=0))
    return sums / np.maximum(sizes, 1)[:, None], wins


def _predict(batches: Iterator[pa.RecordBatch], shared, names: tuple[str, str, str]) -> Iterator[pa.RecordBatch]:
    """Adds language, score and position share (of positions labelled with it); text and the flag of letters come last."""
    model: Model = shared.value
    for batch in batches:
        own = batch.num_columns - 2
        for at, data, offsets in chunks(batch.column(own), INFER_BYTES):
            n = len(offsets) - 1
            known = np.array(batch.column(own + 1).slice(at, n).to_pylist(), bool)
            if len(model.languages):
                p, wins = document_probabilities(model, data, offsets)
                best = p.argmax(axis=1)
                found = [model.languages[b] if k else "und" for b, k in zip(best, known, strict=True)]
                rows = np.arange(n)
                score = np.where(known, np.clip(p[rows, best], 0, 1), 0.0)
                share = np.where(known, wins[rows, best] / np.maximum(np.diff(offsets), 1), 0.0)
            else:
                found, score, share = ["und"] * n, np.zeros(n), np.zeros(n)
            columns = [batch.column(i).slice(at, n) for i in range(own)]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(found, pa.string()), pa.array(score), pa.array(share)], [*batch.schema.names[:own], *names])


def identify(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", keep_columns: bool = False, names: tuple[str, str, str] = ("lang_pred", "score", "position_share")) -> DataFrame:
    """Language, score and position share of every row under ``names``, with its identifier and held_out, or
    with ``keep_columns`` with all its columns (but those that have one of the names: pass others to keep them)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    new = [n.lower() for n in names]
    own = [F.col(c) for c in docs.columns if c.lower() not in new] if keep_columns else [F.col(id_col).cast("long").alias("doc_id"), held_out(id_col).alias("held_out")]
    text, letter = unused(docs.columns, "_text", "_letter")
    rows = docs.select(*own, F.col(text_col).alias(text), F.coalesce(F.col(text_col).rlike(r"\p{L}"), F.lit(False)).alias(letter))
    schema = StructType([f for f in rows.schema if f.name not in (text, letter)])
    schema = schema.add(names[0], "string").add(names[1], "double").add(names[2], "double")
    return rows.mapInArrow(partial(_predict, shared=shared, names=tuple(names)), schema)
