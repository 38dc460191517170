"""Hand-computed cases, invariants of the methods, and agreement of the engines."""

import numpy as np
import pytest
from mfaccel.functions import vectors
from mfaccel.operators import baselines, distributed, linesearch, normal, recommend, serial, synthetic
from mfaccel.operators import relational as rel
from mfaccel.operators.conjugate import RULES, beta
from mfaccel.plans import blocks
from mfaccel.plans.cuts import numbered
from mfaccel.sources import ratings as src
from pyspark.sql import functions as F

#: Two users, two items, one missing cell; values found by hand.
H1 = (np.array([1, 1, 2]), np.array([1, 2, 1]), np.array([1.0, 2.0, 3.0]))


@pytest.fixture(scope="module")
def cells(spark, data):
    return src.view(spark, data, "cust_part").cache()


@pytest.fixture(scope="module")
def small(cells):
    pdf = cells.toPandas()
    return serial.Serial(pdf.user.values, pdf.item.values, pdf.rating.values, 3, 0.1)


def test_hand_case_sweep_and_quartic():
    s, one = serial.Serial(*H1, 1, 0.5), np.ones((2, 1))
    assert s.loss(one, one) == 8
    gu, gm = s.gradient(one, one)
    assert np.allclose(np.concatenate([gu, gm]).ravel(), [0, -3, -2, -1])
    u, m = s.sweep(one, one)
    assert np.allclose(u.ravel(), [1, 2]) and np.allclose(m.ravel(), [7 / 6, 4 / 3])
    q = s.quartic(one, one, u - one, m - one)
    assert np.allclose(q.c, [8, -11 / 3, 17 / 12, 7 / 18, 1 / 36])
    assert q.value(1) == pytest.approx(37 / 6)


def test_hand_case_accelerated_iterations():
    run = serial.Serial(*H1, 1, 0.5).fit_accelerated(np.ones((2, 1)), np.ones((2, 1)), serial.Stop(iterations=3), search="backtracking")
    assert [round(r["loss"], 6) for r in run.trace] == [8, 6.160534, 6.127202, 6.096494]
    assert [round(r["beta"], 6) for r in run.trace[1:]] == [0.069050, -0.022630, -0.047764]
    assert [round(r["gnorm"], 6) for r in run.trace] == [0.935414, 0.178165, 0.157790, 0.009951]
    assert run.trace[1]["alpha"] == pytest.approx(10 * 0.9**22)


def test_gradient_is_the_slope_of_the_loss(small):
    u, m = small.start(1)
    gu, gm = small.gradient(u, m)
    for side, at in ((0, (3, 1)), (1, (5, 2))):
        step, x = 1e-6, [u.copy(), m.copy()]
        x[side][at] += step
        up = small.loss(*x)
        x[side][at] -= 2 * step
        assert (up - small.loss(*x)) / (2 * step) == pytest.approx((gu, gm)[side][at], rel=1e-4)


def test_half_steps_zero_their_gradient_and_never_raise_the_loss(small):
    u, m = small.start(2)
    before = small.loss(u, m)
    for _ in range(3):
        u = normal.solve(small.by_user, m, small.ru)
        assert small.loss(u, m) <= before and np.abs(small.gradient(u, m)[0]).max() < 1e-8
        before = small.loss(u, m)
        m = normal.solve(small.by_item, u, small.rm)
        assert small.loss(u, m) <= before and np.abs(small.gradient(u, m)[1]).max() < 1e-8
        before = small.loss(u, m)


@pytest.mark.parametrize("alpha", [-0.7, 0.0, 0.3, 1.0, 4.0])
def test_quartic_is_the_loss_along_a_line(small, alpha):
    u, m = small.start(3)
    pu, pm = small.start(4)
    q = small.quartic(u, m, pu, pm)
    assert q.value(alpha) == pytest.approx(small.loss(u + alpha * pu, m + alpha * pm), rel=1e-10)
    g = small.gradient(u, m)
    assert q.slope(0) == pytest.approx((g[0] * pu).sum() + (g[1] * pm).sum(), rel=1e-9)
    assert q.c[4] >= 0


def test_backtracking_takes_the_first_step_that_decreases_enough():
    q = linesearch.Quartic((8, -11 / 3, 17 / 12, 7 / 18, 1 / 36))
    a, k = linesearch.backtracking(q)
    assert linesearch.enough(q, a, 0.5) and not linesearch.enough(q, a / 0.9, 0.5)
    assert linesearch.backtracking_direct(q.value, q.c[1]) == (a, k)
    assert linesearch.backtracking(linesearch.Quartic((0, 1, 1, 0, 0)), most=20)[0] == 0


def test_exact_and_more_thuente_find_the_minimum():
    q = linesearch.Quartic((3, -4, 2, -0.5, 0.25))
    grid = np.linspace(0, 5, 200_001)
    best = grid[np.argmin([q.gain(a) for a in grid])]
    assert linesearch.exact(q) == pytest.approx(best, abs=1e-4)
    step, _ = linesearch.more_thuente(q.gain, q.slope)
    assert abs(q.slope(step)) <= 1e-2 * 4 and q.gain(step) <= 1e-4 * step * -4
    assert linesearch.exact(linesearch.Quartic((0, 1, 0, 0, 0))) == 0


@pytest.mark.parametrize("slope", [-1e-3, -1.0, -500.0])
def test_more_thuente_holds_its_conditions(slope):
    dice = np.random.default_rng(5)
    for _ in range(50):
        c = (1.0, slope, *(dice.random(2) * [4, 2] - [1, 1]), dice.random() + 0.01)
        q = linesearch.Quartic(c)
        step, _ = linesearch.more_thuente(q.gain, q.slope, most=60)
        assert q.gain(step) <= 0


def test_first_step_of_one_is_a_sweep(small):
    u, m = small.start(6)
    bar = small.sweep(u, m)
    assert np.allclose(u + 1.0 * (bar[0] - u), bar[0])


def test_rules_agree_without_preconditioner_and_on_a_quadratic():
    dice = np.random.default_rng(0)
    a = dice.random((6, 6))
    a = a @ a.T + 6 * np.eye(6)
    b, x = dice.random(6), np.zeros(6)
    precond = np.diag(1 / np.diag(a))
    g = a @ x - b
    z = precond @ g
    p = -z
    for _ in range(6):
        alpha = -(g @ p) / (p @ a @ p)
        x = x + alpha * p
        g0, z0, g = g, z, a @ (x + 0) - b
        z = precond @ g
        d = {"g1g1": g @ g, "g1g0": g @ g0, "g0g0": g0 @ g0, "z1g1": z @ g, "z1g0": z @ g0, "z0g0": z0 @ g0, "z1z1": z @ z, "z1z0": z @ z0, "z0z0": z0 @ z0, "pg1": p @ g, "pg0": p @ g0}
        weight = beta("pr_pre", d)
        assert weight == pytest.approx((z @ g) / (z0 @ g0), abs=1e-6)
        p = -z + weight * p
    assert np.abs(a @ x - b).max() < 1e-8


@pytest.mark.parametrize("rule", RULES)
def test_every_rule_lowers_the_loss(small, rule):
    run = small.fit_accelerated(*small.start(1), serial.Stop(iterations=8), rule=rule, search="backtracking")
    losses = [r["loss"] for r in run.trace]
    assert all(b < a for a, b in zip(losses, losses[1:]))


@pytest.mark.parametrize("precond", ["als", "als_items_first", "coordinate", "gradient", "nonnegative"])
def test_every_preconditioner_runs(small, precond):
    run = small.fit_accelerated(*small.start(1), serial.Stop(iterations=5), precond=precond, search="exact")
    assert run.trace[-1]["loss"] < run.trace[0]["loss"]


def test_accelerated_needs_fewer_iterations(spark):
    from mfaccel import workloads

    sub = workloads.subset(spark, "/root/testdata/sf0.01", "400x80").toPandas()
    s = serial.Serial(sub.user.values, sub.item.values, sub.rating.values, 10, 0.1)
    stop = serial.Stop(gnorm=1e-5, iterations=3000)
    slow, fast = s.fit_als(*s.start(1), stop), s.fit_accelerated(*s.start(1), stop)
    assert slow.converged and fast.converged and len(slow.trace) > 4 * len(fast.trace)


@pytest.mark.parametrize("comm", ["fused", "paper"])
def test_distributed_equals_serial(spark, cells, comm):
    plan = blocks.layout(cells, 3)
    engine = distributed.Engine(plan, 3, 0.1)
    start = engine.start()
    at = [np.stack(start[s].orderBy("id").toPandas().x.values) for s in ("user", "item")]
    pdf = cells.toPandas()
    twin = serial.Serial(pdf.user.values, pdf.item.values, pdf.rating.values, 3, 0.1)
    want = twin.fit_accelerated(*at, serial.Stop(iterations=2), search="backtracking").trace
    have = engine.fit_accelerated(start, distributed.StopRule(0.0, 2), comm=comm).trace
    for a, b in zip(want, have, strict=True):
        for name in ("loss", "gnorm", "alpha", "beta"):
            assert b[name] == pytest.approx(a[name], rel=1e-8, abs=1e-12)


def test_plain_sweeps_equal_serial_and_relational(spark, cells):
    done = distributed.fit(cells, 2, 0.1, algo="als", stop=distributed.StopRule(0.0, 2), n_blocks=5)
    p = rel.Problem(cells, 2, 0.1)
    users, items = rel.fit_als(p, p.start()[1], 2)
    for mine, theirs in ((done.users, users), (done.items, items)):
        a, b = (np.stack(f.orderBy("id").toPandas().x.values) for f in (mine, theirs))
        assert np.allclose(a, b, atol=1e-9)


def test_routing_sends_a_vector_once_where_it_is_needed(cells):
    want = {(r.item, r.user % 4) for r in cells.collect()}
    have = [tuple(r) for r in blocks.routing(cells, "item", 4, "mod").collect()]
    assert len(have) == len(set(have)) and set(have) == want
    assert all(r.pairs <= r.bound for r in blocks.routing_volume(cells, 4).collect())


def test_edge_cases(spark):
    one = spark.createDataFrame([(-5, 9_000_000_000, 2.0)], src.SCHEMA)
    done = distributed.fit(one, 3, 0.1, stop=distributed.StopRule(1e-9, 3), n_blocks=2)
    assert done.trace[-1]["loss"] <= done.trace[0]["loss"]
    s = serial.Serial(np.array([1, 1, 2]), np.array([1, 2, 1]), np.array([3.0, 3.0, 3.0]), 4, 0.0)
    assert s.fit_als(*s.start(1), serial.Stop(iterations=20)).trace[-1]["loss"] < 1e-6


def test_validation_and_subsets(spark):
    rows = [(1, 1, 2.0), (1, 1, 4.0), (None, 1, 1.0), (2, 1, float("nan")), (2, 2, float("inf")), (3, None, 1.0), (3, 3, None), (4, 1, 1.0)]
    fine = src.validate(spark.createDataFrame(rows, src.SCHEMA))
    assert sorted(map(tuple, fine.collect())) == [(1, 1, 3.0), (4, 1, 1.0)]
    assert src.validate(spark.createDataFrame([], src.SCHEMA)).count() == 0
    order = numbered(spark.range(1000).select(((F.col("id") * 7919) % 1000).alias("id")), "id").collect()
    assert all(r.at == r.id + 1 for r in order) and len(order) == 1000


def test_csv_keeps_malformed_lines_apart(spark, tmp_path):
    (tmp_path / "r.csv").write_text("1,2,3.5\nx,2,1\n4,5\n6,7,8.0\n9,1,abc\n")
    good, bad = src.csv(spark, str(tmp_path))
    assert sorted(map(tuple, good.collect())) == [(1, 2, 3.5), (6, 7, 8.0)] and bad.count() == 3


def test_vectors(spark):
    x = spark.createDataFrame([("user", 1, [1.0, 2.0]), ("item", 1, [3.0, -1.0])], "side string, id long, x array<double>")
    assert {r.side: r.x for r in vectors.axpby(2, x, 1, x).collect()} == {"user": [3, 6], "item": [9, -3]}
    assert vectors.dot(x, x).first()[0] == 15 and vectors.norm(x).first()[0] == pytest.approx(15**0.5)


def test_top_k_in_chunks_leaves_out_what_was_seen(spark):
    dice = np.random.default_rng(0)
    users = spark.createDataFrame([(k, dice.random(3).tolist()) for k in range(5)], "id long, x array<double>")
    items = spark.createDataFrame([(k, dice.random(3).tolist()) for k in range(40)], "id long, x array<double>")
    seen = spark.createDataFrame([(0, 3), (0, 7)], "id long, other long")
    have = {(r.id, r.rk): r.other for r in recommend.top_k(users, items, 4, seen, block=9).collect()}
    u, m = (np.array([r.x for r in f.orderBy("id").collect()]) for f in (users, items))
    scores = u @ m.T
    scores[0, [3, 7]] = -np.inf
    want = np.argsort(-scores, axis=1)[:, :4]
    assert all(have[k, j + 1] == want[k, j] for k in range(5) for j in range(4)) and len(have) == 20
    whole = {(r.id, r.other): r.score for r in recommend.score_all(users, items, seen, block=3).collect()}
    assert len(whole) == 5 * 40 - 2 and all(v == pytest.approx(scores[k]) for k, v in whole.items())
    tied = items.select("id", F.array(F.lit(1.0), F.lit(0.0), F.lit(0.0)).alias("x"))
    assert [r.other for r in recommend.top_k(users.where("id = 2"), tied, 3, block=7).orderBy("rk").collect()] == [0, 1, 2]
    assert recommend.top_k(users.limit(0), items, 3).count() == 0 and recommend.top_k(users, items.limit(0), 3).count() == 0


def test_planted_factors_are_recovered_and_synthetic_marginals_hold(spark, cells):
    planted = synthetic.planted(cells, 2, 0.05)
    done = distributed.fit(planted, 2, 0.001, stop=distributed.StopRule(0.0, 6), n_blocks=2)
    p = rel.Problem(planted, 2, 0.001)
    assert rel.rmse(p, done.users, done.items).first()[0] < 0.25
    more = synthetic.expand(cells, 400)
    a, b = src.profile(cells).first(), src.profile(more).first()
    assert b.n_u == 400 and b.density == pytest.approx(a.density, rel=0.1) and b["mean"] == pytest.approx(a["mean"], rel=0.05)


def test_baselines(spark, cells, data):
    _, users, items = baselines.mllib_als(cells, 3, 0.1, 8)
    p = rel.Problem(cells, 3, 0.1)
    ours = distributed.fit(cells, 3, 0.1, algo="als", stop=distributed.StopRule(0.0, 8), n_blocks=2)
    assert ours.trace[-1]["loss"] == pytest.approx(rel.loss(p, users, items).first()[0], rel=0.1)
    u, m = baselines.sgd(cells, 2, 0.02, epochs=1, n_blocks=2)
    start = rel.Problem(cells, 2, 0.0)
    assert rel.loss(start, u, m).first()[0] < rel.loss(start, *start.start()).first()[0]
    full = src.view(spark, "/root/testdata/sf0.01", "nation_brand").toPandas().pivot(index="user", columns="item", values="rating").to_numpy()
    s = serial.Serial(*[x.ravel() for x in np.indices(full.shape)], full.ravel(), 2, 1e-9)
    assert s.fit_als(*s.start(0), serial.Stop(gnorm=1e-9, iterations=300)).trace[-1]["loss"] == pytest.approx(baselines.svd_loss(full, 2), rel=1e-3)


def test_meetings_give_their_pairs_piece_by_piece(spark):
    ids, x = np.arange(300), np.ones((300, 2))
    seen = np.arange(0, 300, 7)
    pieces = list(recommend._scores(ids, x, np.arange(1000), np.ones((1000, 2)), seen, seen, 4000))
    assert max(s.size for _, s in pieces) <= 4000 and sum(len(own) for own, _ in pieces) == 300
    gone = [(int(own[r]), int(c)) for own, s in pieces for r, c in zip(*np.nonzero(s == -np.inf), strict=True)]
    assert gone == [(k, k) for k in seen]


def test_top_k_leaves_out_groups_that_no_query_can_use():
    dice = np.random.default_rng(5)
    x, y = dice.normal(1, 0.2, (200, 2)), dice.normal(1, 0.2, (4000, 2))
    seen = dice.integers(0, 200, 3000), dice.integers(0, 4000, 3000)
    scores = x @ y.T
    scores[seen] = -np.inf
    want = np.argsort(-scores, axis=1, kind="stable")[:, :5]
    found = {}
    for ids, others, _ in recommend._best(np.arange(200), x, np.arange(4000), y, *seen, 5, group=16, leaf=32):
        for i, j in zip(ids.tolist(), others.tolist(), strict=True):
            found.setdefault(i, []).append(j)
    assert all(found[k] == want[k].tolist() for k in range(200))


def test_meetings_have_a_task_each(spark):
    side = spark.range(90).select("id", F.array(F.lit(1.0), F.col("id").cast("double")).alias("x"))
    pairs = recommend.score_all(side, side, block=15)
    tasks = pairs.groupBy(F.spark_partition_id().alias("task")).agg(F.count("*").alias("n")).collect()
    assert len(tasks) == 36 and sum(t.n for t in tasks) == 90 * 90


def test_seen_pairs_of_the_query_set_alone_are_kept(spark, data, monkeypatch):
    from mfaccel import registry

    given, every = [], recommend.score_all
    monkeypatch.setattr(recommend, "score_all", lambda users, parts, seen: (given.append(seen), every(users, parts, seen))[1])
    have = registry.queries()["seen_anti_join"](spark, data)
    assert given[0].where("id % 20 <> 0").count() == 0
    r = src.view(spark, data, "cust_part").where("user % 20 = 0").select("user", "item")
    part = spark.read.parquet(f"{data}/part.parquet").select(F.col("p_partkey").alias("item"))
    want = r.select("user").distinct().crossJoin(part).exceptAll(r)
    assert have.exceptAll(want).count() == 0 == want.exceptAll(have).count()


def test_scores_are_rounded_in_the_tasks_and_none_is_lost(spark, data):
    import duckdb
    import pyarrow as pa

    from mfaccel import registry

    dice = np.random.default_rng(3)
    values = np.r_[np.arange(-401, 402, 2) / 128, dice.normal(0, 0.3, 2000), 0.0, -0.0, -1e-9, 0.49999999999999994e-6, 1e300, np.inf, -np.inf, np.nan]
    given = pa.table({"id": np.arange(len(values)), "v": values})  # noqa: F841
    want = np.asarray(duckdb.sql("SELECT round(v, 6) + 0.0 AS r FROM given ORDER BY id").fetchnumpy()["r"], float)
    side = spark.createDataFrame([(k, [float(v)]) for k, v in enumerate(values)], "id long, x array<double>")
    one = spark.createDataFrame([(0, [1.0])], "id long, x array<double>")
    have = {r.other: r.score for r in recommend.score_all(one, side, block=700, digits=6).collect()}
    assert len(have) == len(values)  # minus infinity and what is no number are scores too
    have = np.array([have[k] for k in range(len(values))])
    assert np.array_equal(have, want, equal_nan=True) and not np.signbit(have[have == 0]).any()
    made = registry.queries()["score_given_items"](spark, data)
    assert "round(" not in made._jdf.queryExecution().optimizedPlan().toString()
    assert made.where("score <> round(score, 6)").count() == 0
