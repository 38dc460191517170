"""The quality classifier against plain dense computations."""

import numpy as np
from mfaccel.llm import features, nbsvm, toxicity


def rows_of(seed, count=60, codes=40):
    dice = np.random.default_rng(seed)
    labels = (np.arange(count) % 3 == 0).astype(int)
    tilt = np.linspace(-1, 1, codes)
    rows = [np.flatnonzero(dice.random(codes) < 1 / (1 + np.exp(-(tilt if y else -tilt) * 1.5))) for y in labels]
    return [r if len(r) else np.array([0]) for r in rows], labels


def test_ratios_weights_and_margins_equal_dense_ones():
    rows, labels = rows_of(1)
    model = nbsvm.NbSvm(rows, labels, epochs=400, keep=True)
    x = np.zeros((len(rows), 40))
    for k, r in enumerate(rows):
        x[k, r] = 1
    up, down = 1 + x[labels == 1].sum(0), 1 + x[labels == 0].sum(0)
    ratio = np.log(up / (1 + (labels == 1).sum())) - np.log(down / (1 + (labels == 0).sum()))
    assert np.allclose(model.ratio[:40], ratio) and not model.ratio[40:].any()
    z = x * ratio
    z = np.hstack([z / np.linalg.norm(z, axis=1, keepdims=True), np.ones((len(rows), 1))])
    signs = np.where(labels == 1, 1.0, -1.0)
    cost = len(rows) / 2 / np.where(signs > 0, (signs > 0).sum(), (signs < 0).sum())
    w = np.append(model.fitted[:40], model.bias)
    primal = 0.5 * w @ w + (cost * np.maximum(0, 1 - signs * (z @ w))).sum()
    dual = model.dual.sum() - 0.5 * ((model.dual * signs) @ z) @ ((model.dual * signs) @ z)
    assert np.all((model.dual >= 0) & (model.dual <= cost + 1e-12)) and np.allclose(w, (model.dual * signs) @ z, atol=1e-4)
    assert primal - dual < 1e-3 * primal  # the least of the hinge problem
    size = np.abs(model.fitted[:40]).mean()
    drawn = 0.75 * model.fitted[:40] + 0.25 * size
    for k, r in enumerate(rows):
        assert abs(model.margin(r) - (z[k, :40] @ drawn + model.bias)) < 1e-5


def test_a_feature_of_class_0_lowers_the_score():
    good, bad = np.array([1, 2]), np.array([3, 4])
    model = nbsvm.NbSvm([good, good, bad, bad, np.array([1, 5]), np.array([3, 5])], np.array([1, 1, 0, 0, 1, 0]), beta=0.0)
    assert (model.gain[[1, 2]] > 0).all() and (model.gain[[3, 4]] < 0).all()
    assert model.margin(good) > model.margin(np.array([5])) > model.margin(bad)


def test_long_words_do_not_fill_the_cache():
    features._STEM_ROWS.clear()
    for _ in range(3):
        first = features.stems_view(b"x" * 5000 + b" stupid stupidity")
    assert len(features._STEM_ROWS) == 3 and len(first) == 5 + 3 + 5


def test_fits_leave_the_rows_to_a_task(spark, data, monkeypatch):
    docs, labels = (spark.read.parquet(f"{data}/{t}.parquet") for t in ("documents", "labels"))
    chosen = docs.join(labels.distinct(), "doc_id")
    rows = sorted(chosen.where(~nbsvm.held_out("doc_id")).select("doc_id", "text", "quality").distinct().collect())
    want = nbsvm.fit_rows([features.indicators(r.text.encode()) for r in rows], np.array([r.quality for r in rows])).packed()
    toxic = sorted(chosen.select("doc_id", "text", "toxic").distinct().collect())
    graded = toxicity._count([toxicity._counted_after_size(r.text.encode()) for r in toxic], np.array([r.toxic for r in toxic])).fitted()

    def in_driver(*_, **__):
        raise AssertionError("rows in the driver")

    monkeypatch.setattr(nbsvm.NbSvm, "__init__", in_driver)
    monkeypatch.setattr(toxicity.Ordinal, "__init__", in_driver)
    have, grades = nbsvm.fit(docs, labels), toxicity.fit(docs, labels)
    assert np.allclose(have.gain, want.gain) and np.isclose(have.bias, want.bias) and np.isclose(have.slope, want.slope)
    assert np.allclose(grades.weights, graded.weights) and np.allclose(grades.cuts, graded.cuts) and grades.counts is None
