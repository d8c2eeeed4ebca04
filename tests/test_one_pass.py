"""Workloads compute a table once, keep no images of whole corpora and run the pixel chain once per image and setting."""

import numpy as np
import pytest

from chartrel.operators import cluster, learned, nn, raster
from chartrel.plans import experiments
from chartrel.sources.families import FAMILIES


@pytest.fixture
def kept(monkeypatch):
    """Columns of what a workload keeps."""
    out, held = [], experiments.held
    monkeypatch.setattr(experiments, "held", lambda df: out.append(df.columns) or held(df))
    return out


def test_what_is_held_has_no_lineage(spark, small):
    df = experiments.held(experiments.training_points(spark, small))
    assert "Window" not in df._jdf.queryExecution().withCachedData().toString() and df.count() > 0


def test_variants_are_the_single_predictions(spark, small):
    points = experiments.first_charts(FAMILIES["supplier"](spark, small), 6)
    images = experiments.held(experiments.rendered(points, "wide", noise=15))
    models = {"a": {"model": nn.Cnn(1, 1)}, "b": {"model": nn.Cnn(1, 2)}, "raw": {"clean": False}, "plain": {}}
    got = learned.predict_each(images, models)
    for name, how in models.items():
        rows = lambda df: sorted(map(str, df.withColumn("score", df["score"].cast("decimal(9,4)")).collect()))
        assert rows(got.filter(got["variant"] == name).drop("variant")) == rows(learned.predict(images, **how))


def test_cleaning_keeps_no_images(spark, small, kept):
    rows = experiments.cleaning_ablation(spark, small).collect()
    assert len(rows) == 6 and kept and not any("data" in c for c in kept)


def test_detectors_share_one_prediction(spark, small, monkeypatch):
    calls, predict = [], learned.predict
    monkeypatch.setattr(learned, "predict", lambda *a, **k: calls.append(1) or predict(*a, **k))
    assert len(experiments.detector_cost(spark, small).collect()) == 15 and len(calls) == 1


def test_a_colour_is_measured_once(monkeypatch):
    img = np.full((raster.H, raster.W, 3), 255, np.uint8)
    for k, c in enumerate(((255, 0, 0), (0, 160, 0), (250, 4, 4))):
        img[20 + 20 * k, 10:100] = c
    seen, hsv = [], cluster.np_hsv
    monkeypatch.setattr(cluster, "np_hsv", lambda a: seen.append(a.size // 3) or hsv(a))
    k, found = cluster.np_series(img)
    assert max(seen) <= 4 and [int(m.sum()) for _, m in found] == [180, 90]
    use = cluster.np_saturate(img)
    for rgb, mask in found:
        assert (mask == cluster.np_mask(hsv(use), cluster.np_boxes(np.array([rgb]))[0])).all()


def test_sizes_of_training_share_one_pass(spark, small, monkeypatch, kept):
    calls, each = [], learned.predict_each
    monkeypatch.setattr(experiments, "model_for", lambda points, n, seed=0, **_: nn.Cnn(1, seed))
    monkeypatch.setattr(learned, "predict_each", lambda images, variants: calls.append(len(variants)) or each(images, variants))
    assert len(experiments.training_size(spark, small).collect()) == 12 and calls == [6] and not any("data" in c for c in kept)
