"""How much work the serial fits do, and that it gives what plain sums over cells give."""

import numpy as np
from mfaccel import registry, workloads
from mfaccel.operators import normal, serial
from pyspark.sql import functions as F


def problem(seed=3, n_u=90, n_m=40, cells=700):
    dice = np.random.default_rng(seed)
    spot = dice.choice(n_u * n_m, cells, replace=False)
    return serial.Serial(spot // n_m, spot % n_m, dice.random(cells) * 5, 4, 0.1)


def test_a_point_has_its_residuals_taken_once_and_its_systems_solved_together(monkeypatch):
    p, calls = problem(), {"residual": 0, "_by_cholesky": 0}
    for name in calls:
        monkeypatch.setattr(normal, name, lambda *a, f=getattr(normal, name), n=name: (calls.__setitem__(n, calls[n] + 1), f(*a))[1])
    assert len(p.fit_als(*p.start(1), serial.Stop(gnorm=0, iterations=6)).trace) == 7
    assert calls == {"residual": 7, "_by_cholesky": 12}
    calls.update(residual=0, _by_cholesky=0)
    assert len(p.fit_accelerated(*p.start(1), serial.Stop(gnorm=0, iterations=6)).trace) == 7
    assert calls == {"residual": 7, "_by_cholesky": 14}


def test_loss_gradient_and_quartic_equal_plain_sums(monkeypatch):
    monkeypatch.setattr(normal, "PIECE", 64)  # many pieces and stacks
    monkeypatch.setattr(normal, "STACK", 64)
    p, dice = problem(), np.random.default_rng(8)
    (u, m), (pu, pm) = p.start(2), (dice.normal(size=(p.n_u, 4)), dice.normal(size=(p.n_m, 4)))
    full, known = np.zeros((p.n_u, p.n_m)), np.zeros((p.n_u, p.n_m))
    full[p.by_user.own, p.by_user.other], known[p.by_user.own, p.by_user.other] = p.by_user.rating, 1
    at = lambda a: known * ((u + a * pu) @ (m + a * pm).T - full)
    loss = lambda a: (at(a) ** 2).sum() + (p.cu * (u + a * pu) ** 2).sum() + (p.cm * (m + a * pm) ** 2).sum()
    left = p.residual(u, m)
    assert np.isclose(p.loss(u, m), loss(0)) and p.loss(u, m, left) == p.loss(u, m)
    for gu, gm in (p.gradient(u, m), p.look(u, m, left=left)[0], p.gradient(u, m, left)):
        assert np.allclose(gu, 2 * (at(0) @ m + p.cu * u)) and np.allclose(gm, 2 * (at(0).T @ u + p.cm * m))
    for q in (p.quartic(u, m, pu, pm), p.quartic(u, m, pu, pm, left)):
        assert np.allclose([np.polynomial.polynomial.polyval(a, q.c) for a in (0.0, 0.3, -1.0)], [loss(a) for a in (0.0, 0.3, -1.0)])
    new, rest = p.sweep(u, m)
    for k in (0, 17, p.n_u - 1):
        mine = m[known[k] > 0]
        assert np.allclose(new[k], np.linalg.solve(mine.T @ mine + p.ru[k] * np.eye(4), mine.T @ full[k][known[k] > 0]))
    assert np.isclose((at(0) ** 2).sum(), (left**2).sum()) and rest.shape == m.shape


def test_every_run_of_an_experiment_has_a_task_of_its_own(spark):
    p = problem()
    cells = spark.createDataFrame([(int(a), int(b), float(c)) for a, b, c in zip(p.by_user.own, p.by_user.other, p.by_user.rating, strict=True)], "user long, item long, rating double")
    runs = workloads.multi_start(cells, "s", 8, rank=3, iterations=2)
    places = runs.select("algo", "run", F.spark_partition_id().alias("task")).distinct().collect()
    assert len(places) == 16 == len({r.task for r in places}) and runs.count() == 48


def test_experiments_of_every_size_have_all_starts_and_keeping_places_changes_nothing(monkeypatch):
    monkeypatch.setattr(workloads, "convergence_table", lambda spark, d, size, starts=workloads.STARTS: (size, starts))
    sizes = [s for s in workloads.SUBSETS if s != "100x40"]
    assert [registry.queries()[f"convergence_{s}"](None, "") for s in sizes] == [(s, workloads.STARTS) for s in sizes]
    kept, made = problem(), problem()
    made.by_user.keep = made.by_item.keep = False
    runs = [p.fit_accelerated(*p.start(1), serial.Stop(gnorm=0, iterations=6)) for p in (kept, made)]
    assert np.array_equal(runs[0].users, runs[1].users) and [r["loss"] for r in runs[0].trace] == [r["loss"] for r in runs[1].trace]
    assert kept.by_user._kept and not made.by_user._kept
