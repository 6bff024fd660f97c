import zlib

import numpy as np
from pyspark.sql import functions as F

from fragsim.llm import langid, queries


def test_gradients_are_numerically_right():
    model = langid.new_model(["a", "b", "c"], seed=1, hidden=3)
    for k in "xuvb":
        setattr(model, k, getattr(model, k).astype(np.float64))
    rng = np.random.default_rng(2)
    codes, target = rng.integers(97, 103, (7, 5)), np.array([0, 1, 2, 1, 0])
    codes[5:, 1] = langid.PAD
    _, gradients = langid.loss_and_gradients(model, codes, target)
    for k in "xuvb":
        w = getattr(model, k)
        for _ in range(6):
            at = tuple(rng.integers(0, s) for s in w.shape) if k != "x" else (rng.integers(2), rng.integers(9), rng.integers(97, 103))
            old, step = w[at], 1e-2
            w[at] = old + step
            up = langid.loss_and_gradients(model, codes, target)[0]
            w[at] = old - step
            down = langid.loss_and_gradients(model, codes, target)[0]
            w[at] = old
            assert abs((up - down) / (2 * step) - gradients[k][at]) < 2e-3


def test_query_held_out_accuracy(spark, sf):
    truth = {r.doc_id: r.lang for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    out = queries.op5_byte_gru(spark, sf).collect()
    assert {r.doc_id for r in out} == set(truth) and len(out) == len(truth)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and 0 <= r.score <= 1 for r in out)
    held = [r for r in out if r.held_out]
    assert sum(r.lang_pred == truth[r.doc_id] for r in held) >= 0.93 * len(held)


def test_edge_cases(spark):
    train = [(i, ("der die und ist nicht ein " if i % 2 else "the and of is not a ") * 5, "de" if i % 2 else "en") for i in range(60)]
    rows = [*train, (100, None, "en"), (101, "", None), (102, "12 34 !?", "en"), (103, "the and of " * 100_000, None), (104, "x", None), (None, "the and of is", "en"), (101, "", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumn("score", F.lit("clash"))
    model = langid.train(df, updates=60)
    got = langid.identify(df, model).collect()
    by = {r.doc_id: r for r in got}
    assert len(got) == len(rows) and by[100].lang_pred == by[101].lang_pred == by[102].lang_pred == "und" and by[102].score == 0
    assert by[103].lang_pred == "en" and by[103].score > 0.9 and by[104].lang_pred in ("de", "en")
    kept = langid.identify(df, model, keep_columns=True)
    assert kept.columns == ["doc_id", "text", "lang", "lang_pred", "score", "position_share"] and kept.count() == len(rows)
    none = langid.identify(df, langid.train(df.where("lang is null"))).collect()
    assert {r.lang_pred for r in none} == {"und"}
    assert langid.identify(df.where(F.lit(False)), model).collect() == []


def test_identifiers_that_repeat_with_null_texts(spark):
    rows = [(i, t, "de" if i % 2 else "en") for i in range(30) for t in (("der die und " if i % 2 else "the and of ") * 4, None)] + [(1, "x" * n, "en") for n in range(2000)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumns({"_text": F.lit("own"), "_letter": F.lit("own"), "SCORE": F.lit(7.5)})
    pieces, labels = langid.training_pieces(df, sample=20)
    assert set(labels) == {"de", "en"} and len(pieces) <= 20 * langid.SAMPLE_SEGMENTS
    many = spark.createDataFrame([(i, f"text {i}", f"l{i % 500}") for i in range(3000)], "doc_id long, text string, lang string")
    assert len(langid.training_pieces(many, sample=40)[0]) <= 40 * langid.SAMPLE_SEGMENTS
    out = langid.identify(df, langid.fit(pieces, labels, updates=2), keep_columns=True, names=("l", "s", "p"))
    assert out.columns == [*df.columns, "l", "s", "p"] and {(r._text, r.SCORE) for r in out.collect()} == {("own", 7.5)}


def test_prediction_equals_plain_recurrence():
    """The segmented matrix form against one byte at a time with the same weights."""
    model = langid.new_model(["a", "b", "c"], seed=3)
    text = "Ünïcode and plain text, longer than one segment. " * 6
    data = np.frombuffer(text.encode(), np.uint8)
    got, _ = langid.document_probabilities(model, data, np.array([0, len(data)]))
    sigmoid = lambda v: 1 / (1 + np.exp(-v))
    total = np.zeros(3)
    for at in range(0, len(data), langid.LENGTH):
        codes = data[at : at + langid.LENGTH]
        padded = np.concatenate([codes, np.full(langid.LENGTH - len(codes), langid.PAD)])
        states = np.zeros((2, langid.LENGTH, langid.HIDDEN))
        for k in (0, 1):
            h = np.zeros(langid.HIDDEN)
            for t in range(langid.LENGTH) if k == 0 else reversed(range(langid.LENGTH)):
                x, g = model.x[k][:, padded[t]], model.u[k] @ h
                z, r = sigmoid(x[: len(h)] + g[: len(h)]), sigmoid(x[len(h) : 2 * len(h)] + g[len(h) : 2 * len(h)])
                h = z * h + (1 - z) * np.tanh(x[2 * len(h) :] + r * g[2 * len(h) :])
                states[k, t] = h
        for t in range(len(codes)):
            e = np.exp(model.v @ np.concatenate([states[0, t], states[1, t]]) + model.b)
            total += e / e.sum()
    assert np.allclose(got[0], total / len(data), atol=1e-4)
