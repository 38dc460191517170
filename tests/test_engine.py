"""The block engine: entities in parts, precision, saved states, searches, schedules and measures, against the serial twin."""

import numpy as np
import pytest
from mfaccel.operators import distributed, linesearch, normal, serial
from mfaccel.plans import blocks
from mfaccel.sources import ratings as src


@pytest.fixture(scope="module")
def cells(spark, data):
    return src.view(spark, data, "cust_part").cache()


def twin_of(cells, engine, rank, lam, weighted=True):
    start = engine.start()
    at = [np.stack(start[s].where("lead").orderBy("id").toPandas().x.values).astype(float) for s in ("user", "item")]
    pdf = cells.toPandas()
    return start, at, serial.Serial(pdf.user.values, pdf.item.values, pdf.rating.values, rank, lam, weighted)


def same(have, want, names=("loss", "gnorm", "alpha", "beta"), **tolerance):
    assert len(have) == len(want)
    for a, b in zip(want, have, strict=True):
        for name in names:
            assert b[name] == pytest.approx(a[name], **(tolerance or {"rel": 1e-8, "abs": 1e-12}))


def test_every_block_has_a_partition_of_its_own(spark, cells):
    plan = blocks.layout(cells, 7)
    from pyspark.sql import functions as F

    held = plan.by_user.groupBy(F.spark_partition_id()).agg(F.count_distinct("blk").alias("n")).collect()
    assert len(held) == 7 and all(r.n == 1 for r in held)
    plan.close()


@pytest.mark.parametrize("weighted", [True, False])
def test_entities_in_parts_give_the_same_fit(spark, cells, weighted):
    plan = blocks.layout(cells, 4, heavy=35)
    assert plan.split == {"user": True, "item": True} and plan.users.where("parts > 1").count() > plan.n_u // 4
    engine = distributed.Engine(plan, 3, 0.1, weighted)
    start, at, twin = twin_of(cells, engine, 3, 0.1, weighted)
    for options in ({"comm": "fused"}, {"comm": "paper", "search_side": "item"}):
        want = twin.fit_accelerated(*at, serial.Stop(iterations=2), search="backtracking").trace
        same(engine.fit_accelerated(start, distributed.StopRule(0.0, 2), **options).trace, want)
    done, want = engine.fit_als(start, distributed.StopRule(0.0, 2)), twin.fit_als(*at, serial.Stop(0.0, iterations=2))
    same(done.trace, want.trace)
    assert np.allclose(np.stack(done.items.orderBy("id").toPandas().x.values), want.items) and done.users.count() == plan.n_u
    plan.close()


@pytest.mark.parametrize("precond", ["coordinate", "nonnegative", "als_items_first"])
def test_other_sweeps_measure_themselves_and_take_parts(spark, cells, precond):
    plan = blocks.layout(cells, 3, heavy=40)
    engine = distributed.Engine(plan, 2, 0.1, precond=precond)
    start, (u, m), twin = twin_of(cells, engine, 2, 0.1)
    trace = engine.fit_als(start, distributed.StopRule(0.0, 2)).trace
    for k, row in enumerate(trace):
        if k:
            u, m = twin.sweep(u, m, precond)
        assert row["loss"] == pytest.approx(twin.loss(u, m), rel=1e-8) and row["gnorm"] == pytest.approx(twin._norm(twin.gradient(u, m)), rel=1e-6)
    plan.close()


def test_single_precision_is_near_double(spark, cells):
    plan = blocks.layout(cells, 2)
    engine = distributed.Engine(plan, 3, 0.1, precision="float")
    start, at, twin = twin_of(cells, engine, 3, 0.1)
    done = engine.fit_accelerated(start, distributed.StopRule(0.0, 2))
    assert dict(done.users.dtypes)["x"] == "array<double>" or dict(done.users.dtypes)["x"] == "array<float>"
    same(done.trace, twin.fit_accelerated(*at, serial.Stop(iterations=2), search="backtracking").trace, ("loss", "gnorm"), rel=1e-4)
    plan.close()


@pytest.mark.parametrize("algo", ["als", "accelerated"])
def test_a_fit_goes_on_from_its_newest_save(spark, cells, tmp_path, algo):
    whole = distributed.fit(cells, 2, 0.1, algo=algo, stop=distributed.StopRule(0.0, 4), n_blocks=2)
    saves = distributed.Saves(str(tmp_path / algo), 2)
    first = distributed.fit(cells, 2, 0.1, algo=algo, stop=distributed.StopRule(0.0, 3), n_blocks=2, saves=saves)
    assert [r["ckpt"] for r in first.trace] == [False, False, True, False]
    rest = distributed.fit(cells, 2, 0.1, algo=algo, stop=distributed.StopRule(0.0, 4), n_blocks=2, saves=saves)
    same([r for r in rest.trace if r["iter"] > 2], whole.trace[3:], ("iter", "loss", "gnorm"), rel=1e-8)
    assert distributed.newest_save(spark, saves.folder)[1]["iter"] == 4


def test_plain_evaluation_finds_the_step_of_the_quartic(spark, cells):
    options = {"n_blocks": 2, "stop": distributed.StopRule(0.0, 1), "first": 2.0, "shrink": 0.6}
    a = distributed.fit(cells, 2, 0.1, search="backtracking", **options).trace
    b = distributed.fit(cells, 2, 0.1, search="backtracking_direct", **options).trace
    same(b, a, rel=1e-9)


def test_no_step_raises_the_loss(cells):
    pdf = cells.toPandas()
    twin = serial.Serial(pdf.user.values, pdf.item.values, pdf.rating.values, 2, 0.1)
    for precond, rule in (("gradient", "pr"), ("gradient", "zero"), ("coordinate", "pr_pre")):
        run = twin.fit_accelerated(*twin.start(3), serial.Stop(iterations=25), precond=precond, rule=rule, search="backtracking", first=1e-9, most=0)
        losses = [r["loss"] for r in run.trace]
        assert all(b <= a for a, b in zip(losses, losses[1:], strict=False))
    assert linesearch.plain_step(linesearch.Quartic((0, -1, 100, 0, 0))) == 2**-7 and linesearch.plain_step(linesearch.Quartic((0, 1, 1, 0, 0))) == 0


def test_batched_sums_equal_loops():
    dice = np.random.default_rng(3)
    own, other = dice.integers(0, 50, 700), dice.integers(0, 30, 700)
    cells = normal.BlockCells(own, other, dice.random(700), np.arange(52), np.arange(30))
    x, y, ridge = dice.random((52, 4)), dice.random((30, 4)), 0.1 + dice.random(52)
    new, g = normal.solve_and_look(cells, x, y, ridge)
    assert np.allclose(g, normal.gradient(cells, x, y, ridge)) and np.allclose(new, normal.solve(cells, y, ridge))
    for k in range(50):
        rows = slice(cells.edges[k], cells.edges[k + 1])
        m, r = y[cells.other[rows]], cells.rating[rows]
        assert np.allclose(new[k], np.linalg.solve(m.T @ m + ridge[k] * np.eye(4), r @ m))
        assert np.allclose(g[k], 2 * ((m @ x[k] - r) @ m + ridge[k] * x[k]))


def test_near_ids_that_rate_near_ones_send_few_vectors(spark):
    rows = [(g * 100 + u, g * 50 + (u * 7 + k) % 20, 1.0) for g in range(12) for u in range(40) for k in range(8)]
    near = spark.createDataFrame(rows, "user long, item long, rating double")
    plans = [blocks.layout(near, 12, how) for how in ("range", "hash")]
    volumes = [sum(p.volume.values()) for p in plans]
    assert volumes[0] < volumes[1] / 3 and all(p.nnz == len(rows) and p.n_u == 480 and p.n_m == 240 for p in plans)
    for p in plans:
        p.close()


def test_a_task_gathers_vectors_in_pieces(monkeypatch):
    dice = np.random.default_rng(3)
    own, other = np.repeat(np.arange(30), 9), dice.integers(0, 40, 270)
    cells = normal.BlockCells(own, other, dice.random(270), np.arange(30), np.arange(40))
    x, p, y, q = (dice.random((n, 3)) for n in (30, 30, 40, 40))
    whole = normal.quartic_sums(cells, x, p, y, q), normal.residual(cells, x, y), normal.gradient(cells, x, y, np.ones(30))
    monkeypatch.setattr(normal, "BATCH", 48)
    assert max(s.stop - s.start for s in normal.pieces(cells, 3)) == 16
    for a, b in zip(whole, (normal.quartic_sums(cells, x, p, y, q), normal.residual(cells, x, y), normal.gradient(cells, x, y, np.ones(30))), strict=True):
        assert np.allclose(a, b)


def test_routed_rows_have_no_null_lists_and_packed_ratings_are_whole(spark, cells):
    plan = blocks.layout(cells, 3)
    engine = distributed.Engine(plan, 2, 0.1)
    start = engine.start()
    routed = engine.route("user", start["user"], ["x"], start["item"], ["x"]).selectExpr("to", "mine", "dest", "x")
    assert routed.where("dest IS NULL OR x IS NULL").count() == 0
    rows = plan.by_user.toArrow()
    own, other, rating = blocks.unpacked(rows)
    assert rows.num_rows < plan.nnz == len(own) and sorted(zip(own, other, rating, strict=True)) == sorted(map(tuple, cells.collect()))
    plan.close()


def test_stacked_nonnegative_systems_are_minimised():
    dice = np.random.default_rng(3)
    m = dice.normal(size=(50, 8, 4))
    a, v = m.transpose(0, 2, 1) @ m, dice.normal(size=(50, 4))
    x = normal.nonnegative_solve(a, v, np.linalg.solve(a, v[..., None])[..., 0])
    slope = np.einsum("gij,gj->gi", a, x) - v
    assert (x >= 0).all() and (slope > -1e-6).all() and np.abs(slope * x).max() < 1e-6  # what holds at the minimum, and only there


def held_exchanges(frame):
    """The exchanges that the rows of a frame hold on to."""
    seen, todo, found = set(), [frame._jdf.queryExecution().toRdd()], set()
    while todo:
        rdd = todo.pop()
        if rdd.id() in seen:
            continue
        seen.add(rdd.id())
        for k in range(rdd.dependencies().size()):
            one = rdd.dependencies().apply(k)
            if "ShuffleDependency" in one.getClass().getName():
                found.add(one.shuffleId())
            todo.append(one.rdd())
    return found


def test_ratings_in_parts_hold_one_exchange_a_side(spark, cells):
    plan = blocks.layout(cells, 3, heavy=35)
    assert all(plan.split.values())
    for side in ("user", "item"):
        rows = plan.side(side)[0]
        assert len(held_exchanges(rows)) <= 1
    own, other, rating = blocks.unpacked(plan.by_item.toArrow())
    assert sorted(zip(other, own, rating, strict=True)) == sorted(map(tuple, cells.collect()))
    plan.close()


def test_a_pass_keeps_no_vector_twice_and_lets_old_rows_go(spark, cells):
    plan = blocks.layout(cells, 2)
    engine = distributed.Engine(plan, 3, 0.1)
    state = {s: v.selectExpr(*distributed.KEYS, "x", "x AS p", "transform(x, a -> 2 * a) AS g0", "transform(x, a -> 3 * a) AS z0") for s, v in engine.start().items()}
    old = {s: {r.id: np.array(r.x) for r in v.collect()} for s, v in state.items()}
    sides = engine._with_z(engine._look(state, [], 0.0, "fused"))
    assert "user" not in state and all({"g0", "z0"}.isdisjoint(v.columns) for v in sides.values())
    dots, rows = engine._dots(sides), {s: v.collect() for s, v in sides.items()}
    at = {c: np.concatenate([np.concatenate([np.array(r[c]) for r in rows[s]]) for s in rows]) for c in ("g", "z", "p")}
    at["p0"] = np.concatenate([np.concatenate([old[s][r.id] for r in rows[s]]) for s in rows])
    assert np.allclose(at["p"], at["p0"])
    at |= {"g0": 2 * at["p0"], "z0": 3 * at["p0"]}
    assert all(np.isclose(dots[n], at[a] @ at[b]) for n, (a, b) in distributed.DOTS.items())
    plan.close()
