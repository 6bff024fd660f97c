"""The trained method: what its shortcuts leave out changes no result."""

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from fragsim.nn import network as N
from fragsim.operators import pairs as P
from fragsim.operators.blocks import forest_of
from fragsim.queries import base, evaluation
from fragsim.sources.prose import prose_metrics


@pytest.mark.parametrize("net", [N.siamese(), N.Network(3, (4,), (), dropout=0), N.Network(3, (), (2,), dropout=0)])
def test_each_half_goes_through_the_trunk_once(net):
    rng = np.random.default_rng(1)
    half = rng.standard_normal((9, net.inputs))
    i, j = rng.integers(0, 9, (2, 200))
    x, swapped = np.concatenate([half[i], half[j]], axis=1), np.concatenate([half[j], half[i]], axis=1)
    want, back, rows = net.forward(x)[0], net.forward(swapped)[0], []
    net.forward = lambda x, masks=None: rows.append(len(x))
    assert np.allclose(net.predict(x), want, atol=1e-12) and np.allclose(net.predict(x, "average"), (want + back) / 2, atol=1e-12)
    assert not rows and net.predict(x).shape == (200,)


def test_forest_of_pairs_has_the_same_classes(spark):
    pairs = spark.range(0, 400).select((F.col("id") % 20).alias("left_id"), (F.col("id") % 20 + 20 * (1 + F.col("id") % 3)).alias("right_id")).repartition(3)
    forest = forest_of(pairs)
    assert forest.count() < 3 * 80 < pairs.count() and not forest.join(pairs, ["left_id", "right_id"], "left_anti").count()
    assert set(map(tuple, P.clone_classes(forest).collect())) == set(map(tuple, P.clone_classes(pairs).collect()))


def test_network_is_fitted_in_a_task_on_one_thread(spark, monkeypatch):
    rng = np.random.default_rng(3)
    x, y = rng.standard_normal((60, 48)), rng.integers(0, 2, 60).astype(float)
    monkeypatch.setattr(evaluation, "FIT", {"lr": 0.02, "batch": 30, "epochs": 2, "patience": 6})
    monkeypatch.setattr(N, "fit", None)  # of this process
    net, log = evaluation.fitted_twin(spark, x, y, (x, y))
    assert len(log) == 2 and log[0]["train_loss"] > 0 and net.predict(x).shape == (60,)
    threads = spark.range(0, 1, 1, 1).select(F.udf(lambda _: os.environ.get("OMP_NUM_THREADS"))("id")).first()[0]
    assert threads == "1"


def test_metrics_share_their_parts(spark, sf):
    plan = prose_metrics(base.documents(spark, sf)).select("metric_hash")._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("AS _sentences") == 1 and plan.count("AS _middle") == 1
