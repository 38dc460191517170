"""Every query of the engine by name, with DuckDB SQL where SQL can express it.

A query of the methods runs them on the customer-part ratings at a small rank from the hashed start, which both engines can
make. Floats are rounded to six decimals on both sides.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from mfaccel import workloads
from mfaccel.functions import vectors
from mfaccel.operators import baselines, distributed, linesearch, ranking, recommend, synthetic, trace
from mfaccel.operators import relational as rel
from mfaccel.operators.conjugate import beta
from mfaccel.plans import blocks
from mfaccel.plans.cuts import cut, shared_folder
from mfaccel.replay import LAM, RATINGS, Chain, rounded, unit
from mfaccel.sources import ratings as src
from mfaccel.streaming import ratings as stream

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_ORACLES: dict[str, str] = {}


def _add(name: str, sql: str | None = None):
    def keep(f: Query) -> Query:
        _QUERIES[name] = f
        if sql:
            _ORACLES[name] = sql
        return f

    return keep


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_ORACLES)


def six(c: Column | str) -> Column:
    return F.round(c, 6) + F.lit(0.0)


def _problem(spark: SparkSession, sf_dir: str, rank: int = 2, view: str = "cust_part", weighted: bool = True) -> rel.Problem:
    return rel.Problem(src.view(spark, sf_dir, view), rank, LAM, weighted).held()


def _xs(df: DataFrame, rank: int = 2, col: str = "x", name: str = "x") -> list[Column]:
    return [six(F.col(col)[k]).alias(f"{name}{k}") for k in range(rank)]


def _both(users: DataFrame, items: DataFrame, rank: int = 2) -> DataFrame:
    return users.select(F.lit("user").alias("side"), "id", *_xs(users, rank)).unionByName(items.select(F.lit("item").alias("side"), "id", *_xs(items, rank)))


def _long(df: DataFrame, col: str, name: str, *keys: str) -> DataFrame:
    return df.select(*keys, F.posexplode(col).alias("k", "v")).select(*keys, "k", six("v").alias(name))


# --- ratings -------------------------------------------------------------------------------------------------------------

for _view, _sql in RATINGS.items():
    _add(f"ratings_{_view.removeprefix('cust_') if _view != 'cust_part' else _view}", f"SELECT u AS \"user\", CAST(i AS BIGINT) AS item, {rounded('v')} AS rating FROM ({_sql})")(
        lambda spark, d, v=_view: src.view(spark, d, v).select("user", F.col("item").cast("long").alias("item"), six("rating").alias("rating"))
    )

_R = f"WITH r AS ({RATINGS['cust_part']}) "


@_add("rating_profile", _R + f"SELECT n_u, n_m, nnz, {rounded('mean')} AS mean, {rounded('low')} AS low, {rounded('high')} AS high, {rounded('nnz / (n_u * n_m)')} AS density FROM (SELECT count(DISTINCT u) AS n_u, count(DISTINCT i) AS n_m, count(*) AS nnz, avg(v) AS mean, min(v) AS low, max(v) AS high FROM r)")
def _(spark, d):
    p = src.profile(src.view(spark, d, "cust_part"))
    return p.select("n_u", "n_m", "nnz", *[six(c).alias(c) for c in ("mean", "low", "high", "density")])


@_add("rating_histogram", _R + "SELECT round(v, 1) AS value, count(*) AS n FROM r GROUP BY 1")
def _(spark, d):
    return src.histogram(src.view(spark, d, "cust_part"))


@_add("entity_counts", _R + "SELECT 'user' AS side, u AS id, count(*) AS n FROM r GROUP BY u UNION ALL SELECT 'item', i, count(*) FROM r GROUP BY i")
def _(spark, d):
    return src.entity_counts(src.view(spark, d, "cust_part"))


def _subset_sql(view: str, n_u: int, n_m: int) -> str:
    def around(col: str, frm: str, k: int) -> str:
        ranked = f"SELECT {col}, row_number() OVER (ORDER BY count(*) DESC, {col}) AS spot, count(*) OVER () AS size FROM {frm} GROUP BY {col}"
        return f"SELECT {col} FROM ({ranked}) WHERE spot BETWEEN (size + 1) // 2 - {k // 2} AND (size + 1) // 2 + {(k + 1) // 2 - 1}"

    return (
        f"WITH r AS MATERIALIZED ({RATINGS[view]}), a AS MATERIALIZED (SELECT * FROM r WHERE u IN ({around('u', 'r', n_u)})), "
        f"b AS (SELECT * FROM a WHERE i IN ({around('i', 'a', n_m)})) SELECT u AS \"user\", CAST(i AS BIGINT) AS item, {rounded('v')} AS rating FROM b"
    )


for _size in workloads.SUBSETS:
    _u, _m, _v = workloads.SUBSETS[_size]
    _add(f"median_subset_{_size}", _subset_sql(_v, _u, _m))(
        lambda spark, d, s=_size: workloads.subset(spark, d, s).select("user", F.col("item").cast("long").alias("item"), six("rating").alias("rating"))
    )


@_add("routing_table", _R + "SELECT DISTINCT i AS item, CAST(u % 8 AS INTEGER) AS ublk FROM r")
def _(spark, d):
    return blocks.routing(src.view(spark, d, "cust_part"), "item", 8, "mod")


@_add("routing_volume", _R + "SELECT 'user' AS side, (SELECT count(*) FROM (SELECT DISTINCT u, i % 8 FROM r)) AS pairs, count(*) AS nnz, least(count(*), 8 * count(DISTINCT u)) AS bound FROM r UNION ALL SELECT 'item', (SELECT count(*) FROM (SELECT DISTINCT i, u % 8 FROM r)), count(*), least(count(*), 8 * count(DISTINCT i)) FROM r")
def _(spark, d):
    return blocks.routing_volume(src.view(spark, d, "cust_part"), 8, "mod")


@_add("communication", _R + "SELECT schedule, a * pi + b * pu AS vectors, passes FROM (SELECT (SELECT count(*) FROM (SELECT DISTINCT u, i % 8 FROM r)) AS pu, (SELECT count(*) FROM (SELECT DISTINCT i, u % 8 FROM r)) AS pi), (VALUES ('als', 1, 1, 2), ('paper', 4, 2, 5), ('fused', 2, 2, 3)) t(schedule, a, b, passes)")
def _(spark, d):
    return workloads.communication(spark, d)


# --- objective and half-steps ----------------------------------------------------------------------------------------------


def _chain(rank: int = 2) -> Chain:
    return Chain(rank=rank).start(0)


@_add("init_factors", _chain().sql(" UNION ALL ".join(f"SELECT '{s}' AS side, id, {k} AS k, {rounded(f'x{k}')} AS v FROM {t}0" for s, t in (("user", "u"), ("item", "m")) for k in (0, 1))))
def _(spark, d):
    u, m = _problem(spark, d).start()
    return _long(u.withColumn("side", F.lit("user")).unionByName(m.withColumn("side", F.lit("item"))), "x", "v", "side", "id")


@_add("loss_eq1", _chain().sql(f"SELECT {rounded('sse + reg_u + reg_m')} AS loss FROM ({_chain().loss('0')})"))
def _(spark, d):
    p = _problem(spark, d)
    return rel.loss(p, *p.start()).select(six("loss").alias("loss"))


@_add("loss_parts", _chain().sql(f"SELECT {rounded('sse')} AS sse, {rounded('reg_u')} AS reg_u, {rounded('reg_m')} AS reg_m FROM ({_chain().loss('0')})"))
def _(spark, d):
    p = _problem(spark, d)
    return rel.loss_parts(p, *p.start()).select(*[six(c).alias(c) for c in ("sse", "reg_u", "reg_m")])


@_add("loss_plain_reg", _chain().sql(f"SELECT {rounded(f'sse + {LAM} * (a + b)')} AS loss FROM ({_chain().loss('0')}), (SELECT sum(x0 * x0 + x1 * x1) AS a FROM u0), (SELECT sum(x0 * x0 + x1 * x1) AS b FROM m0)"))
def _(spark, d):
    p = _problem(spark, d, weighted=False)
    return rel.loss(p, *p.start()).select(six("loss").alias("loss"))


for _side, _t in (("user", "gu0"), ("item", "gm0")):
    _add(f"gradient_{_side}", _chain().gradient("0").sql(" UNION ALL ".join(f"SELECT id, {k} AS k, {rounded(f'g{k}')} AS g FROM {_t}" for k in (0, 1))))(
        lambda spark, d, s=_side: _long(rel.gradient(p := _problem(spark, d), *p.start(), s), "g", "g", "id")
    )


@_add("gnorm", _chain().gradient("0").sql(f"SELECT {rounded('gnorm')} AS gnorm FROM ({_chain().norm('0')})"))
def _(spark, d):
    p = _problem(spark, d)
    return rel.gradient_norm(p, *p.start()).select(six("gnorm").alias("gnorm"))


for _rank in (1, 2):
    for _side, _t in (("user", "m0"), ("item", "u0")):
        _xcols = ", ".join(f"{rounded(f'x{k}')} AS x{k}" for k in range(_rank))
        _add(f"half_step_{_side}_r{_rank}", _chain(_rank).half("h", _t, _side).sql(f"SELECT id, {_xcols} FROM h"))(
            lambda spark, d, s=_side, r=_rank: (lambda p: (lambda h: h.select("id", *_xs(h, r)))(rel.half_step(p, p.start()[1 if s == "user" else 0], s)))(_problem(spark, d, r))
        )


@_add("als_sweep_r2", (_c := _chain().sweep("0", "1")).sql(_c.both("1")))
def _(spark, d):
    p = _problem(spark, d)
    return _both(*rel.fit_als(p, p.start()[1], 1))


_THREE = _chain().sweep("0", "1").sweep("1", "2").sweep("2", "3")


@_add("als_3sweeps_r2", _THREE.sql(_THREE.both("3")))
def _(spark, d):
    p = _problem(spark, d)
    return _both(*rel.fit_als(p, p.start()[1], 3))


@_add("als_loss_by_sweep", _THREE.sql(" UNION ALL ".join(f"SELECT {k} AS iter, {rounded('sse + reg_u + reg_m')} AS loss FROM ({_THREE.loss(str(k))})" for k in (1, 2, 3))))
def _(spark, d):
    p = _problem(spark, d)
    items, out = p.start()[1], None
    for k in (1, 2, 3):
        users, items = rel.sweep(p, items)
        one = rel.loss(p, users, items).select(F.lit(k).alias("iter"), six("loss").alias("loss"))
        out = one if out is None else out.unionByName(one)
    return out


@_add("rmse", _THREE.sql(f"SELECT {rounded('sqrt(sse / n)')} AS rmse FROM ({_THREE.loss('3')}), (SELECT count(*) AS n FROM r)"))
def _(spark, d):
    p = _problem(spark, d)
    return rel.rmse(p, *rel.fit_als(p, p.start()[1], 3)).select(six("rmse").alias("rmse"))


_PRE = _chain().preconditioned("0")


@_add("precond_gradient_r2", _PRE.sql(" UNION ALL ".join(f"SELECT '{s}' AS side, id, {k} AS k, {rounded(f'z{k}')} AS gbar FROM z{t}0" for s, t in (("user", "u"), ("item", "m")) for k in (0, 1))))
def _(spark, d):
    p = _problem(spark, d)
    u, m = rel.preconditioned(p, *p.start())
    return _long(u.withColumn("side", F.lit("user")).unionByName(m.withColumn("side", F.lit("item"))), "gbar", "gbar", "side", "id")


# --- line search ---------------------------------------------------------------------------------------------------------------

_LINE = _chain().preconditioned("0").first_direction("0").quartic("0")


def _line(spark: SparkSession, d: str):
    p = _problem(spark, d)
    sides = tuple(f.select("id", "x", vectors.vscale(-1.0, "gbar").alias("p")) for f in rel.preconditioned(p, *p.start()))
    return p, sides


@_add("quartic_coeffs", _LINE.sql("SELECT " + ", ".join(f"{rounded(f'c{k}')} AS c{k}" for k in range(5)) + " FROM c0"))
def _(spark, d):
    p, sides = _line(spark, d)
    return rel.quartic(p, *sides).select(*[six(f"c{k}").alias(f"c{k}") for k in range(5)])


_ALPHAS = (0.1, 0.5, 1.0, 2.0)


def _direct_sql() -> str:
    c, rows = _chain().preconditioned("0").first_direction("0").quartic("0"), []
    for n, a in enumerate(_ALPHAS):
        c.add(f"s0_{n}", f"SELECT CAST({a} AS DOUBLE) AS alpha")
        for s in "um":
            c.add(f"{s}t{n}", f"SELECT a.id, a.x0 + alpha * p0 AS x0, a.x1 + alpha * p1 AS x1 FROM {s}0 a JOIN p{s}0 b ON a.id = b.id, s0_{n}")
        q = f"c0 + c1 * {a} + c2 * pow({a}, 2) + c3 * pow({a}, 3) + c4 * pow({a}, 4)"
        rows.append(f"SELECT CAST({a} AS DOUBLE) AS alpha, round({q}, 4) AS q, round(sse + reg_u + reg_m, 4) AS f FROM c0, ({c.loss(f't{n}')})")
    return c.sql(" UNION ALL ".join(rows))


@_add("quartic_vs_direct", _direct_sql())
def _(spark, d):
    p, sides = _line(spark, d)
    q = rel.quartic(p, *sides)
    out = None
    for a in _ALPHAS:
        f = rel.loss(p, *(rel.moved(s, a).select("id", "x") for s in sides))
        value = sum((F.col(f"c{n}") * a**n for n in range(1, 5)), F.col("c0"))
        one = q.crossJoin(f).select(F.lit(a).alias("alpha"), F.round(value, 4).alias("q"), F.round("loss", 4).alias("f"))  # one row each
        out = one if out is None else out.unionByName(one)
    return out


_STEP = _chain().preconditioned("0").first_direction("0").quartic("0").step("0")


@_add("backtracking_step", _STEP.sql(f"SELECT CAST(steps AS INTEGER) AS steps, {rounded('alpha')} AS alpha FROM s0"))
def _(spark, d):
    p, sides = _line(spark, d)
    steps = rel.quartic(p, *sides).select(linesearch.backtracking_columns([F.col(f"c{k}") for k in range(5)]).alias("steps"))
    return steps.select("steps", six(10.0 * F.pow(F.lit(0.9), "steps")).alias("alpha"))


@_add("line_steps", _LINE.sql(f"SELECT CAST(k AS INTEGER) AS k, {rounded('a')} AS alpha, round(c0 + c1 * a + c2 * pow(a, 2) + c3 * pow(a, 3) + c4 * pow(a, 4), 2) AS q FROM (SELECT *, CAST(10 AS DOUBLE) * pow(CAST(0.9 AS DOUBLE), k) AS a FROM c0, range(0, 41) t(k))"))
def _(spark, d):
    p, sides = _line(spark, d)
    return linesearch.line_steps(rel.quartic(p, *sides), most=40).select("k", six("alpha").alias("alpha"), F.round("q", 2).alias("q"))


def _searched(find) -> Query:
    def run(spark, d):
        p, sides = _line(spark, d)
        q = linesearch.Quartic.of(rel.quartic(p, *sides).first())
        return spark.createDataFrame([(round(find(q), 6),)], "alpha double")

    return run


def _exact_sql() -> str:
    """The lowest of the positive real roots of the quartic's slope, in closed form."""
    c = _chain().preconditioned("0").first_direction("0").quartic("0")
    c.add("cubic", "SELECT *, 3 * c3 / (4 * c4) AS a, c2 / (2 * c4) AS b, c1 / (4 * c4) AS c FROM c0")
    c.add("depressed", "SELECT *, (a * a - 3 * b) / 9 AS q, (2 * a * a * a - 9 * a * b + 27 * c) / 54 AS r FROM cubic")
    c.add("one", "SELECT *, -sign(r) * cbrt(abs(r) + sqrt(greatest(r * r - q * q * q, 0))) AS s FROM depressed")
    c.add("roots", "SELECT c1, c2, c3, c4, s + CASE WHEN s = 0 THEN 0 ELSE q / s END - a / 3 AS x FROM one WHERE r * r >= q * q * q UNION ALL SELECT c1, c2, c3, c4, -2 * sqrt(q) * cos((acos(r / sqrt(q * q * q)) + 2 * pi() * j) / 3) - a / 3 FROM one, range(0, 3) t(j) WHERE r * r < q * q * q")
    c.add("falls", "SELECT x, x * (c1 + x * (c2 + x * (c3 + x * c4))) AS gain FROM roots WHERE x > 0")
    return c.sql(f"SELECT {rounded('coalesce(arg_min(x, gain), 0)')} AS alpha FROM falls WHERE gain < 0")


_add("exact_step", _exact_sql())(_searched(linesearch.exact))
_add("more_thuente_step")(_searched(lambda q: linesearch.more_thuente(q.gain, q.slope)[0]))


# --- conjugate recurrence ---------------------------------------------------------------------------------------------------------

_ONE, _TWO = Chain().accelerate(1), Chain().accelerate(2)


def _weights_after_step(spark: SparkSession, d: str) -> dict[str, float]:
    p = _problem(spark, d)
    sides, _ = rel.fit_accelerated(p, *p.start(), 0)
    alpha = linesearch.backtracking(linesearch.Quartic.of(rel.quartic(p, *sides).first()))[0]
    new = rel._look(p, *(rel.moved(f, alpha).select("id", "x") for f in sides), "als")
    full = [n.join(o.select("id", F.col("g").alias("g0"), F.col("z").alias("z0"), "p"), "id") for n, o in zip(new, sides, strict=True)]
    return rel.dots(*full)


def _rules(*names: str) -> Query:
    def run(spark, d):
        dots = _weights_after_step(spark, d)
        return spark.createDataFrame([(n, round(beta(n, dots), 6) + 0.0) for n in names], "rule string, beta double")

    return run


def _rules_sql(*names: str) -> str:
    return _ONE.sql(" UNION ALL ".join(f"SELECT '{n}' AS rule, {rounded(n)} AS beta FROM w1" for n in names))


_add("beta_pr", _rules_sql("pr"))(_rules("pr"))
_add("beta_pr_pre", _rules_sql("pr_pre"))(_rules("pr_pre"))
_add("beta_variants", _rules_sql("pr_tilde", "fr", "fr_pre", "hs", "hs_pre"))(_rules("pr_tilde", "fr", "fr_pre", "hs", "hs_pre"))


def _accelerated(iterations: int) -> Query:
    def run(spark, d):
        p = _problem(spark, d)
        return _both(*rel.fit_accelerated(p, *p.start(), iterations)[0])

    return run


_add("accel_iter1_r2", _ONE.sql(_ONE.both("1")))(_accelerated(1))
_add("accel_iter2_r2", _TWO.sql(_TWO.both("2")))(_accelerated(2))


def _trace_sql(c: Chain, iterations: int, rule: str = "pr_pre") -> str:
    rows = []
    for k in range(iterations + 1):
        alpha, w = (f"(SELECT alpha FROM s{k - 1})", f"(SELECT {rule} FROM w{k})") if k else ("CAST(0 AS DOUBLE)", "CAST(0 AS DOUBLE)")
        rows.append(f"SELECT CAST({k} AS BIGINT) AS iter, {rounded('c0')} AS loss, {rounded('gnorm')} AS gnorm, {rounded(alpha)} AS alpha, {rounded(w)} AS beta FROM c{k}, ({c.norm(str(k))})")
    return c.sql(" UNION ALL ".join(rows))


def _trace_frame(spark: SparkSession, rows: list[dict], names: str = "iter loss gnorm alpha beta") -> DataFrame:
    cols = names.split()
    data = [tuple(r[c] if c == "iter" else round(r[c], 6) + 0.0 for c in cols) for r in rows]
    return spark.createDataFrame(data, ", ".join(f"{c} {'long' if c == 'iter' else 'double'}" for c in cols))


@_add("accel_trace_r2", _trace_sql(_TWO, 2))
def _(spark, d):
    p = _problem(spark, d)
    return _trace_frame(spark, rel.fit_accelerated(p, *p.start(), 2)[1])


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two accelerated iterations beside two plain sweeps: algo, iter, loss, gnorm, alpha, beta."""
    p = _problem(spark, sf_dir)
    start = p.start()
    fast = _trace_frame(spark, rel.fit_accelerated(p, *start, 2)[1]).select(F.lit("accelerated").alias("algo"), "*")
    users, items = start
    for k in (1, 2):
        users, items = rel.sweep(p, items)
        row = rel.loss(p, users, items).crossJoin(rel.gradient_norm(p, users, items))
        fast = fast.unionByName(row.select(F.lit("als").alias("algo"), F.lit(k).cast("long").alias("iter"), six("loss").alias("loss"), six("gnorm").alias("gnorm"), F.lit(0.0).alias("alpha"), F.lit(0.0).alias("beta")))
    return fast


for _name, _rule in (("plain_cg_iter2_r2", "pr"), ("descent_iter2_r2", "zero")):
    _cg = Chain().accelerate(2, _rule, "gradient")
    _add(_name, _cg.sql(" UNION ALL ".join(f"SELECT CAST({k} AS BIGINT) AS iter, {rounded('c0')} AS loss FROM c{k}" for k in range(3))))(
        lambda spark, d, r=_rule: _trace_frame(spark, rel.fit_accelerated(p := _problem(spark, d), *p.start(), 2, r, "gradient")[1], "iter loss")
    )


# --- vectors -----------------------------------------------------------------------------------------------------------------------


def _vector(spark: SparkSession, d: str, which: str) -> DataFrame:
    p, sides = _line(spark, d)
    return sides[0].select(F.lit("user").alias("side"), "id", F.col(which).alias("x")).unionByName(sides[1].select(F.lit("item").alias("side"), "id", F.col(which).alias("x")))


_VEC = _chain().preconditioned("0").first_direction("0")


@_add("vec_axpby", _VEC.sql(" UNION ALL ".join(f"SELECT '{s}' AS side, a.id, {k} AS k, {rounded(f'2 * x{k} + -0.5 * p{k}')} AS v FROM {t}0 a JOIN p{t}0 b ON a.id = b.id" for s, t in (("user", "u"), ("item", "m")) for k in (0, 1))))
def _(spark, d):
    return _long(vectors.axpby(2.0, _vector(spark, d, "x"), -0.5, _vector(spark, d, "p")), "x", "v", "side", "id")


_PAIRS = " UNION ALL ".join(f"SELECT x0, x1, p0, p1 FROM {t}0 a JOIN p{t}0 b ON a.id = b.id" for t in "um")


@_add("vec_dot", _VEC.sql(f"SELECT {rounded('sum(x0 * p0 + x1 * p1)')} AS value FROM ({_PAIRS})"))
def _(spark, d):
    return vectors.dot(_vector(spark, d, "x"), _vector(spark, d, "p")).select(six("value").alias("value"))


@_add("vec_norm", _VEC.sql(f"SELECT {rounded('sqrt(sum(p0 * p0 + p1 * p1))')} AS value FROM ({_PAIRS})"))
def _(spark, d):
    return vectors.norm(_vector(spark, d, "p")).select(six("value").alias("value"))


# --- scoring -----------------------------------------------------------------------------------------------------------------------

_GIVEN = "SELECT a.vec_id AS \"user\", b.vec_id AS item, list_dot_product(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) AS score FROM embeddings a, embeddings b WHERE a.vec_id % 20 = 0"


def _given(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    all_items = src.table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("x"))
    return all_items.where("id % 20 = 0"), all_items  # the query set of a search


@_add("score_given_items", f"SELECT \"user\", item, {rounded('score')} AS score FROM ({_GIVEN})")
def _(spark, d):
    return recommend.score_all(*_given(spark, d), digits=6).select(F.col("id").alias("user"), F.col("other").alias("item"), "score")


@_add("topk_given_items", f"SELECT \"user\", item, {rounded('score')} AS score, CAST(rk AS INTEGER) AS rk FROM (SELECT *, row_number() OVER (PARTITION BY \"user\" ORDER BY score DESC, item) AS rk FROM ({_GIVEN})) WHERE rk <= 10")
def _(spark, d):
    return recommend.recommend_items(*_given(spark, d), 10).select("user", "item", six("score").alias("score"), "rk")


@_add("similar_items", f"SELECT id, other, {rounded('score')} AS score, CAST(rk AS INTEGER) AS rk FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY score DESC, other) AS rk FROM (SELECT a.vec_id AS id, b.vec_id AS other, list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) AS score FROM embeddings a, embeddings b WHERE a.vec_id <> b.vec_id)) WHERE rk <= 3")
def _(spark, d):
    return recommend.similar_items(_given(spark, d)[1], 3).select("id", "other", six("score").alias("score"), "rk")


_FOLD = _chain().sweep("0", "1").half("f", "m1", "user")


@_add("fold_in_r2", _FOLD.sql(f"SELECT id AS \"user\", {rounded('x0')} AS x0, {rounded('x1')} AS x1 FROM f"))
def _(spark, d):
    p = _problem(spark, d)
    items = rel.sweep(p, p.start()[1])[1]
    new = recommend.fold_in(p.ratings, items, 2, LAM)
    return new.select(F.col("id").alias("user"), *_xs(new))


def _three(spark: SparkSession, d: str):
    p = _problem(spark, d)
    return p, rel.fit_als(p, p.start()[1], 3)


_SCORES = "SELECT u.id AS \"user\", m.id AS item, u.x0 * m.x0 + u.x1 * m.x1 AS score FROM u3 u, m3 m"


@_add("predict_pairs", _THREE.sql(f"SELECT r.u AS \"user\", r.i AS item, {rounded('u.x0 * m.x0 + u.x1 * m.x1')} AS score FROM r JOIN u3 u ON r.u = u.id JOIN m3 m ON r.i = m.id"))
def _(spark, d):
    p, (users, items) = _three(spark, d)
    return recommend.predict(p.ratings, users, items).select("user", "item", six("score").alias("score"))


@_add("recommend_topk", _THREE.sql(f"SELECT \"user\", item, {rounded('score')} AS score, CAST(rk AS INTEGER) AS rk FROM (SELECT *, row_number() OVER (PARTITION BY \"user\" ORDER BY score DESC, item) AS rk FROM ({_SCORES}) s WHERE NOT EXISTS (SELECT 1 FROM r WHERE r.u = s.\"user\" AND r.i = s.item)) WHERE rk <= 5"))
def _(spark, d):
    p, (users, items) = _three(spark, d)
    return recommend.recommend_items(users, items, 5, p.ratings).select("user", "item", six("score").alias("score"), "rk")


@_add("recommend_users_topk", _THREE.sql(f"SELECT item, \"user\", {rounded('score')} AS score, CAST(rk AS INTEGER) AS rk FROM (SELECT *, row_number() OVER (PARTITION BY item ORDER BY score DESC, \"user\") AS rk FROM ({_SCORES})) WHERE rk <= 5"))
def _(spark, d):
    _, (users, items) = _three(spark, d)
    return recommend.recommend_users(users, items, 5).select("item", "user", six("score").alias("score"), "rk")


# --- ranking -----------------------------------------------------------------------------------------------------------------------

_T = 20
_RANK = Chain("cust_brandtype").start(0).sweep("0", "1").sweep("1", "2").sweep("2", "3")
for _k in ("1", "3"):
    _RANK.add(f"pos{_k}", f"SELECT \"user\", item, row_number() OVER (PARTITION BY \"user\" ORDER BY score DESC, item) AS rk FROM (SELECT u.id AS \"user\", m.id AS item, u.x0 * m.x0 + u.x1 * m.x1 AS score FROM u{_k} u, m{_k} m)")
_RANK.add("placed", f"SELECT a.\"user\", a.item, a.rk AS k, b.rk AS pos FROM pos3 a JOIN pos1 b ON a.\"user\" = b.\"user\" AND a.item = b.item WHERE a.rk <= {_T}")
_RANK.add("swaps", "SELECT a.\"user\", sum(a.pos - 1) - sum((SELECT count(*) FROM placed b WHERE b.\"user\" = a.\"user\" AND b.k < a.k AND b.pos < a.pos)) AS s FROM placed a GROUP BY a.\"user\"")


def _ranked(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """Scores of all cells of the customers and brand types after three sweeps and after one."""
    p = _problem(spark, d, view="cust_brandtype")
    out = []
    for sweeps in (3, 1):
        users, items = rel.fit_als(p, p.start()[1], sweeps)
        pairs = users.select(F.col("id").alias("user")).crossJoin(F.broadcast(items.select(F.col("id").alias("item"))))  # 150 brand types
        out.append(recommend.predict(pairs, users, items))
    return tuple(out)


@_add("rank_distance", _RANK.sql('SELECT "user", CAST(s AS BIGINT) AS s FROM swaps'))
def _(spark, d):
    return ranking.distance(*_ranked(spark, d), _T)


@_add("rank_accuracy", _RANK.sql(f"SELECT {rounded(f'avg(1 - s / ({_T} * (2 * n - {_T} - 1) / 2))')} AS q FROM swaps, (SELECT count(*) AS n FROM m0)"))
def _(spark, d):
    return ranking.accuracy(*_ranked(spark, d), _T).select(six("q").alias("q"))


@_add("max_swaps", "SELECT t, CAST(t * (2 * n - t - 1) / 2 AS DOUBLE) AS most FROM (SELECT count(DISTINCT p_partkey) AS n FROM part), (VALUES (1), (5), (20)) v(t)")
def _(spark, d):
    n = src.table(spark, d, "part").agg(F.count_distinct("p_partkey")).first()[0]
    return spark.createDataFrame([(t, float(ranking.max_distance(n, t))) for t in (1, 5, 20)], "t int, most double")


@_add("stable_top_intersect", _RANK.sql(f'SELECT "user", item FROM pos3 WHERE rk <= {_T} INTERSECT SELECT "user", item FROM pos1 WHERE rk <= {_T}'))
def _(spark, d):
    return ranking.stable_top(*_ranked(spark, d), _T)


# --- traces ------------------------------------------------------------------------------------------------------------------------


def _tiny() -> list[tuple]:
    """Twelve iterations of two runs of both methods: run, algo, iter, t_sec, gnorm, q, checkpoint."""
    rows = []
    for run in (0, 1):
        for algo, pace, cost in (("als", 0.18 + 0.02 * run, 1.0), ("accelerated", 0.45 - 0.05 * run, 2.0)):
            for k in range(12):
                bump = 0.4 if algo == "accelerated" and k % 4 == 3 else 0.0
                rows.append((run, algo, k, round(cost * k + 0.5 * (k // 5) + 0.1 * run * k, 6), round(10 ** (-pace * k + bump), 9), round(min(1.0, 0.5 + pace * k / 4), 6), k % 5 == 0))
    return rows


_TINY = "SELECT * FROM (VALUES " + ", ".join(f"({r}, '{a}', {k}, CAST({t} AS DOUBLE), CAST({g} AS DOUBLE), CAST({q} AS DOUBLE), {str(c).lower()})" for r, a, k, t, g, q, c in _tiny()) + ") v(run, algo, iter, t_sec, gnorm, q, ckpt)"
#: Users of the events as runs, their events in the order of time as iterations: kinds of events are methods, hours since a run's first event its clock.
_RUNS = (
    "SELECT run, algo, row_number() OVER w - 1 AS iter, (us - first_value(us) OVER w) / CAST(3600000000 AS DOUBLE) AS t_sec, sqrt(value) / 100 AS gnorm, 1 / (1 + sqrt(value) / 25) AS q "
    "FROM (SELECT user_id AS run, CASE WHEN event_type IN ('click', 'purchase') THEN 'accelerated' ELSE 'als' END AS algo, epoch_us(ts) AS us, event_id, value FROM events) "
    "WINDOW w AS (PARTITION BY run, algo ORDER BY us, event_id, value)"
)
_W = f"WITH t AS ({_RUNS}) "


def _tiny_frame(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(_tiny(), "run int, algo string, iter int, t_sec double, gnorm double, q double, ckpt boolean")


def _runs(spark: SparkSession, d: str) -> DataFrame:
    """The traces of _RUNS."""
    algo = F.when(F.col("event_type").isin("click", "purchase"), "accelerated").otherwise("als").alias("algo")
    events = src.table(spark, d, "events").select(F.col("user_id").alias("run"), algo, F.unix_micros(F.col("ts").cast("timestamp")).alias("us"), "event_id", "value")
    w = Window.partitionBy("run", "algo").orderBy("us", "event_id", "value")
    since = (F.col("us") - F.first("us").over(w)) / F.lit(3.6e9)
    return events.select("run", "algo", (F.row_number().over(w) - 1).cast("long").alias("iter"), since.alias("t_sec"), (F.sqrt("value") / 100).alias("gnorm"), (1 / (1 + F.sqrt("value") / 25)).alias("q"))


def _stats(df: DataFrame, *cols: str) -> DataFrame:
    return df.select(*[six(c).alias(c) if c in cols else F.col(c) for c in df.columns])


def _hits_sql(cond: str, at: str, extra: str = "", group: str = "") -> str:
    return f"SELECT algo, run{group}, min(CASE WHEN {cond} THEN {at} END) AS hit FROM t{extra} GROUP BY algo, run{group}"


def _summary_sql(hits: str, group: str = "") -> str:
    return f"SELECT algo{group}, {rounded('avg(hit)')} AS mean, {rounded('stddev_samp(hit)')} AS std, count(hit) AS converged, count(*) - count(hit) AS nonconverged FROM ({hits}) GROUP BY algo{group}"


@_add("iterations_to", _W + _summary_sql(_hits_sql("gnorm < 0.01", "iter")))
def _(spark, d):
    return _stats(trace.iterations_to(_runs(spark, d), 0.01), "mean", "std")


@_add("time_to", _W + _summary_sql(_hits_sql("gnorm < 0.01", "t_sec")))
def _(spark, d):
    return _stats(trace.time_to(_runs(spark, d), 0.01), "mean", "std")


_LEVELS = ", (VALUES (CAST(0.7 AS DOUBLE)), (0.8), (0.9), (1.0)) l(threshold)"


@_add("time_to_accuracy", _W + _summary_sql(_hits_sql("q >= threshold", "t_sec", _LEVELS, ", threshold"), ", threshold"))
def _(spark, d):
    return _stats(trace.time_to_accuracy(_runs(spark, d), (0.7, 0.8, 0.9, 1.0)), "mean", "std")


@_add("acceleration_table", _W + f"SELECT threshold, {rounded('als')} AS als, {rounded('fast')} AS accelerated, {rounded('als / fast')} AS factor FROM (SELECT threshold, max(CASE WHEN algo = 'als' THEN mean END) AS als, max(CASE WHEN algo = 'accelerated' THEN mean END) AS fast FROM (SELECT algo, threshold, avg(hit) AS mean FROM ({_hits_sql('q >= threshold', 't_sec', _LEVELS, ', threshold')}) GROUP BY algo, threshold) GROUP BY threshold)")
def _(spark, d):
    return _stats(trace.acceleration(trace.time_to_accuracy(_runs(spark, d), (0.7, 0.8, 0.9, 1.0)), "threshold"), "als", "accelerated", "factor")


for _by, _col, _width in (("iter", "iter", 3), ("time", "t_sec", 5)):
    _add(f"trace_bands_{_by}", _W + f"SELECT algo, CAST(floor({_col} / {_width}) AS BIGINT) AS bucket, {rounded('avg(gnorm)')} AS mean, {rounded('stddev_samp(gnorm)')} AS std FROM t GROUP BY 1, 2")(
        lambda spark, d, b=_by, w=_width: _stats(trace.bands(_runs(spark, d), b, w), "mean", "std")
    )


@_add("trace_resample", _W + f"SELECT algo, CAST(g * 2.0 AS DOUBLE) AS t, {rounded('avg(q)')} AS mean FROM (SELECT k.algo, k.run, g, (SELECT arg_max(q, (t_sec, iter)) FROM t WHERE t.algo = k.algo AND t.run = k.run AND t_sec <= g * 2.0) AS q FROM (SELECT DISTINCT algo, run FROM t) k, range(0, 11) s(g)) GROUP BY 1, 2")
def _(spark, d):
    return _stats(trace.resample(_runs(spark, d), 2.0, 10), "mean")


@_add("trace_moving_avg", _W + f"SELECT run, algo, iter, {rounded('avg(gnorm) OVER (PARTITION BY algo, run ORDER BY iter ROWS BETWEEN 1 PRECEDING AND CURRENT ROW)')} AS smooth FROM t")
def _(spark, d):
    return trace.smoothed(_runs(spark, d)).select("run", "algo", "iter", six("smooth").alias("smooth"))


_HIT = "f AS (SELECT run, iter, avg(gnorm) OVER (PARTITION BY run ORDER BY iter ROWS BETWEEN 1 PRECEDING AND CURRENT ROW) AS smooth FROM t WHERE algo = 'accelerated'), h AS (SELECT *, (SELECT min(s.iter) FROM t s WHERE s.algo = 'als' AND s.run = f.run AND s.gnorm <= f.smooth) AS hit FROM f)"


@_add("trace_first_hit", f"WITH t AS ({_RUNS}), {_HIT} SELECT run, iter, {rounded('smooth')} AS smooth, coalesce(hit, -1) AS hit FROM h")
def _(spark, d):
    return _stats(trace.first_reach(_runs(spark, d)), "smooth").withColumn("hit", F.coalesce("hit", F.lit(-1)))


_SECONDS = "d AS (SELECT *, t_sec - lag(t_sec) OVER (PARTITION BY algo, run ORDER BY iter) AS seconds FROM t)"


@_add("trace_speedup", f"WITH t AS ({_TINY}), {_HIT}, {_SECONDS} SELECT h.run, iter, {rounded('smooth')} AS smooth, hit, {rounded('hit * ta / (iter * tf)')} AS factor FROM h JOIN (SELECT run, avg(CASE WHEN algo = 'als' THEN seconds END) AS ta, avg(CASE WHEN algo = 'accelerated' THEN seconds END) AS tf FROM d GROUP BY run) m ON h.run = m.run WHERE iter > 0 AND hit IS NOT NULL")
def _(spark, d):
    return _stats(trace.speedup(_tiny_frame(spark)), "smooth", "factor")


@_add("trace_time_per_iter", f"WITH t AS ({_TINY}), {_SECONDS} SELECT algo, {rounded('sum(total) / sum(n)')} AS mean, {rounded('sqrt(sum(n * var) / sum(n))')} AS std FROM (SELECT algo, ckpt, count(*) AS n, sum(seconds) AS total, coalesce(var_samp(seconds), 0) AS var FROM d WHERE seconds IS NOT NULL GROUP BY algo, ckpt) GROUP BY algo")
def _(spark, d):
    return _stats(trace.time_per_iteration(_tiny_frame(spark)), "mean", "std")


@_add("trace_cost_ratio", f"WITH t AS ({_RUNS}), {_SECONDS} SELECT {rounded('f')} AS accelerated, {rounded('a')} AS als, {rounded('f / a')} AS ratio FROM (SELECT avg(CASE WHEN algo = 'accelerated' THEN seconds END) AS f, avg(CASE WHEN algo = 'als' THEN seconds END) AS a FROM d)")
def _(spark, d):
    return _stats(trace.cost_ratio(_runs(spark, d)), "accelerated", "als", "ratio")


@_add("scaling_fit", _W + f"SELECT algo, {rounded('regr_slope(t_sec, iter)')} AS slope, {rounded('regr_intercept(t_sec, iter)')} AS intercept, {rounded('regr_r2(t_sec, iter)')} AS r2 FROM t GROUP BY algo")
def _(spark, d):
    return _stats(trace.linear_fit(_runs(spark, d), "iter", "t_sec", "algo"), "slope", "intercept", "r2")


# --- synthetic data and splits -----------------------------------------------------------------------------------------------------


def _law_sql(expr: str, frm: str = "r") -> str:
    return _R + f"SELECT value, n, {rounded('sum(n) OVER (ORDER BY value) / sum(n) OVER ()')} AS cum FROM (SELECT {expr} AS value, count(*) AS n FROM {frm} GROUP BY 1)"


for _name, _what, _sql in (("counts", "count", _law_sql("n", "(SELECT count(*) AS n FROM r GROUP BY u)")), ("items", "item", _law_sql("i")), ("values", "rating", _law_sql("round(v, 1)"))):
    _add(f"synth_{_name}_cdf", _sql)(lambda spark, d, w=_what: _stats(synthetic.laws(src.view(spark, d, "cust_part"))[w], "cum"))


def _spot_sql(what: str, size: str, *keys: str) -> str:
    return f"CAST(floor({unit(repr('42'), repr(what), *[f'CAST({k} AS VARCHAR)' for k in keys])} * {size}) AS BIGINT) + 1"


_EXPAND = f"""WITH r AS MATERIALIZED ({RATINGS['cust_part']}),
cells AS MATERIALIZED (SELECT row_number() OVER (ORDER BY i, u) AS spot, i, v FROM r), nc AS (SELECT count(*) AS c FROM r),
people AS MATERIALIZED (SELECT row_number() OVER (ORDER BY n, u) AS spot, n FROM (SELECT u, count(*) AS n FROM r GROUP BY u)), np AS (SELECT count(*) AS c FROM people),
new AS MATERIALIZED (SELECT g AS "user", n FROM (SELECT g, {_spot_sql('count', 'c', 'g')} AS spot FROM (SELECT unnest(range(0, c)) AS g FROM np), np) JOIN people USING (spot)),
draws AS MATERIALIZED (SELECT "user", n, draw, {_spot_sql('item', 'c', '"user"', 'draw')} AS spot FROM (SELECT "user", n, unnest(range(0, 2 * n + 4)) AS draw FROM new), nc),
found AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY "user" ORDER BY draw) AS k FROM (SELECT "user", i, min(draw) AS draw, any_value(n) AS n FROM draws JOIN cells USING (spot) GROUP BY "user", i)),
kept AS (SELECT "user", i FROM found WHERE k <= n)
SELECT "user", k.i AS item, {rounded('v')} AS rating FROM (SELECT "user", i, {_spot_sql('value', 'c', '"user"', 'i')} AS spot FROM kept, nc) k JOIN cells USING (spot)"""


def _expanded(spark: SparkSession, d: str):
    r = cut(src.view(spark, d, "cust_part"))
    return r, r.select("user").distinct().count()


@_add("synth_expand", _EXPAND)
def _(spark, d):
    return _stats(synthetic.expand(*_expanded(spark, d)), "rating")


_SHORT = _EXPAND[: _EXPAND.index('SELECT "user", k.i AS item')] + 'SELECT CAST(sum(n) AS BIGINT) AS wanted, CAST(sum(least(n, k)) AS BIGINT) AS made, count_if(k < n) AS short_users FROM (SELECT "user", any_value(n) AS n, max(k) AS k FROM found GROUP BY "user")'


@_add("synth_shortfall", _SHORT)
def _(spark, d):
    return synthetic.shortfall(*_expanded(spark, d))


_HELD = "CAST('0x' || substr(md5(concat_ws(':', '42', CAST(u AS VARCHAR), CAST(i AS VARCHAR))), 1, 8) AS BIGINT) % 10 < 2"


@_add("heldout_split", _R + f"SELECT {_HELD} AS held, count(*) AS n, {rounded('avg(v)')} AS mean FROM r GROUP BY 1")
def _(spark, d):
    return src.hash_split(src.view(spark, d, "cust_part")).groupBy("held").agg(F.count("*").alias("n"), six(F.avg("rating")).alias("mean"))


@_add("temporal_split", f"SELECT late, count(*) AS n, {rounded('avg(v)')} AS mean FROM (SELECT avg(l_quantity) / 10 AS v, min(l_shipdate) >= TIMESTAMP '1997-01-01' AS late FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey, l_partkey) GROUP BY 1")
def _(spark, d):
    return src.temporal_split(spark, d, "1997-01-01").groupBy("late").agg(F.count("*").alias("n"), six(F.avg("rating")).alias("mean"))


_HOLD = Chain()
_HOLD.parts = [("r0", RATINGS["cust_part"]), ("r", f"SELECT * FROM r0 WHERE NOT ({_HELD})")]
_HOLD.start(0).sweep("0", "1").sweep("1", "2")
_HOLD.parts.append(("test", f"SELECT * FROM r0 WHERE {_HELD}"))


@_add("heldout_rmse", _HOLD.sql(f"SELECT held, {rounded('sqrt(avg(pow(v - u.x0 * m.x0 - u.x1 * m.x1, 2)))')} AS rmse, count(*) AS n FROM (SELECT *, true AS held FROM test UNION ALL SELECT *, false FROM r) c JOIN u2 u ON c.u = u.id JOIN m2 m ON c.i = m.id GROUP BY held"))
def _(spark, d):
    split = src.hash_split(src.view(spark, d, "cust_part"))
    p = rel.Problem(split.where("NOT held").drop("held"), 2, LAM)
    fit = rel.fit_als(p, p.start()[1], 2)
    err = F.col("rating") - vectors.vdot("u_x", "m_x")
    return rel.Problem(split, 2, LAM).cells(*fit).groupBy("held").agg(six(F.sqrt(F.avg(err * err))).alias("rmse"), F.count("*").alias("n"))


# --- relational surroundings -------------------------------------------------------------------------------------------------------


@_add("seen_anti_join", _R + "SELECT a.u AS \"user\", p_partkey AS item FROM (SELECT DISTINCT u FROM r WHERE u % 20 = 0) a, part WHERE NOT EXISTS (SELECT 1 FROM r s WHERE s.u = a.u AND s.i = p_partkey)")
def _(spark, d):
    r = cut(src.view(spark, d, "cust_part").where("user % 20 = 0"))  # the query set of a search; what others have seen leaves out none of its pairs
    one = F.array(F.lit(1.0)).alias("x")
    users = r.select(F.col("user").alias("id")).distinct().select("id", one)
    parts = src.table(spark, d, "part").select(F.col("p_partkey").alias("id"), one)
    seen = r.select(F.col("user").alias("id"), F.col("item").alias("other"))
    return recommend.score_all(users, parts, seen).select(F.col("id").alias("user"), F.col("other").alias("item"))


@_add("cold_users", _R + "SELECT c_custkey AS id FROM customer WHERE c_custkey NOT IN (SELECT u FROM r)")
def _(spark, d):
    return src.table(spark, d, "customer").select(F.col("c_custkey").alias("id")).join(src.view(spark, d, "cust_part").select(F.col("user").alias("id")), "id", "left_anti")


@_add("active_semi", _R + "SELECT c_custkey AS id, c_mktsegment AS segment FROM customer WHERE c_custkey IN (SELECT u FROM r GROUP BY u HAVING count(*) >= 30)")
def _(spark, d):
    active = src.counts(src.view(spark, d, "cust_part"), "user").where("n >= 30")
    return src.table(spark, d, "customer").select(F.col("c_custkey").alias("id"), F.col("c_mktsegment").alias("segment")).join(active, "id", "left_semi")


_ERR = _THREE.sql("SELECT {} FROM (SELECT c_mktsegment AS segment, n_name AS nation, p_brand AS brand, pow(v - u.x0 * m.x0 - u.x1 * m.x1, 2) AS e FROM r JOIN u3 u ON r.u = u.id JOIN m3 m ON r.i = m.id JOIN customer ON c_custkey = r.u JOIN nation ON n_nationkey = c_nationkey JOIN part ON p_partkey = r.i) GROUP BY {}").replace("{}", "\x00")


def _errors_sql(cols: str, by: str) -> str:
    first, second, third = _ERR.split("\x00")
    return f"{first}{cols}, {rounded('sqrt(avg(e))')} AS rmse, count(*) AS n{second}{by}{third}"


def _errors(spark: SparkSession, d: str) -> DataFrame:
    p, (users, items) = _three(spark, d)
    err = F.col("rating") - vectors.vdot("u_x", "m_x")
    cells = p.cells(users, items).select("user", "item", (err * err).alias("e"))
    nation = src.table(spark, d, "nation").select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_name").alias("nation"))
    customer = src.table(spark, d, "customer").select(F.col("c_custkey").alias("user"), F.col("c_mktsegment").alias("segment"), "c_nationkey").join(F.broadcast(nation), "c_nationkey")  # 25 nations
    part = src.table(spark, d, "part").select(F.col("p_partkey").alias("item"), F.col("p_brand").alias("brand"))
    return cells.join(customer, "user").join(part, "item")


def _rmse_aggs():
    return six(F.sqrt(F.avg("e"))).alias("rmse"), F.count("*").alias("n")


@_add("rmse_rollup_segment", _errors_sql("segment, nation", "ROLLUP (segment, nation)"))
def _(spark, d):
    return _errors(spark, d).rollup("segment", "nation").agg(*_rmse_aggs())


@_add("rmse_cube_brand", _errors_sql("segment, brand", "CUBE (segment, brand)"))
def _(spark, d):
    return _errors(spark, d).cube("segment", "brand").agg(*_rmse_aggs())


@_add("rmse_grouping_sets", _errors_sql("nation, brand", "GROUPING SETS ((nation), (brand))"))
def _(spark, d):
    return _errors(spark, d).groupingSets([["nation"], ["brand"]], "nation", "brand").agg(*_rmse_aggs())


@_add("changed_cells_except", _R + f"SELECT u AS \"user\", i AS item, round(v, 0) AS rating FROM r EXCEPT ALL SELECT u, i, {rounded('v')} FROM r")
def _(spark, d):
    r = src.view(spark, d, "cust_part")
    return r.select("user", "item", F.round("rating", 0).alias("rating")).exceptAll(r.select("user", "item", six("rating").alias("rating")))


@_add("all_entities_union", _R + "SELECT u AS id FROM r UNION SELECT i FROM r")
def _(spark, d):
    r = src.view(spark, d, "cust_part")
    return r.select(F.col("user").alias("id")).union(r.select("item")).distinct()


@_add("events_tumbling", "SELECT date_trunc('day', ts) AS start, user_id AS \"user\", count(*) AS n FROM events GROUP BY 1, 2")
def _(spark, d):
    return stream.tumbling(src.table(spark, d, "events"))


@_add("events_sliding", "SELECT start - INTERVAL 12 HOUR * j AS start, user_id AS \"user\", count(*) AS n FROM (SELECT *, time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '2024-01-01') AS start FROM events), range(0, 2) t(j) GROUP BY 1, 2")
def _(spark, d):
    return stream.sliding(src.table(spark, d, "events"))


@_add("events_session", "SELECT min(ts) AS start, user_id AS \"user\", count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def _(spark, d):
    return stream.sessions(src.table(spark, d, "events"))


@_add("events_json_counts", "SELECT user_id AS \"user\", CAST(json_extract_string(props, '$.k') AS BIGINT) AS item, count(*) AS n FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY 1, 2")
def _(spark, d):
    return src.event_keys(src.table(spark, d, "events")).groupBy("user", "item").agg(F.count("*").alias("n"))


@_add("events_latest_rating", "SELECT user_id AS \"user\", CAST(json_extract_string(props, '$.k') AS BIGINT) AS item, arg_max(value, (ts, value)) AS rating FROM events GROUP BY 1, 2")
def _(spark, d):
    keyed = src.event_keys(src.table(spark, d, "events")).withColumn("at", F.struct("ts", "value")).withColumnRenamed("value", "rating")
    return src.validate(keyed, "latest", "at")


@_add("csv_roundtrip", f"SELECT u AS \"user\", i AS item, {rounded('v')} AS rating FROM ({RATINGS['cust_part']})")
def _(spark, d):
    folder = f"{shared_folder(spark)}/ratings-{uuid.uuid4().hex}"
    src.view(spark, d, "cust_part").write.csv(folder)
    return _stats(src.csv(spark, folder)[0], "rating")


# --- whole fits ----------------------------------------------------------------------------------------------------------------------


@_add("mllib_als")
def _(spark, d):
    r = src.view(spark, d, "cust_part")
    _, users, items = baselines.mllib_als(r, 10, LAM, 5)
    return rel.loss(rel.Problem(r, 10, LAM), users, items)


def _fit_trace(algo: str, iterations: int = 4, **options) -> Query:
    def run(spark, d):
        done = distributed.fit(src.view(spark, d, "cust_part"), 10, LAM, algo=algo, stop=distributed.StopRule(0.0, iterations), **options)
        return trace.frame(spark, done.trace).select("algo", "iter", "loss", "gnorm", "alpha", "beta")

    return run


_add("als_fit_r10")(_fit_trace("als"))
_add("accel_fit_r10")(_fit_trace("accelerated", 3))
_add("accel_fit_separate")(_fit_trace("accelerated", 2, comm="paper"))
_add("plain_cg_fit_r10")(_fit_trace("accelerated", 2, precond="gradient", rule="pr"))
_add("nonnegative_fit_r10")(_fit_trace("accelerated", 2, precond="nonnegative"))
_add("coordinate_fit_r10")(_fit_trace("als", 2, precond="coordinate"))


@_add("sgd_fit")
def _(spark, d):
    r = src.view(spark, d, "cust_part")
    return rel.rmse(rel.Problem(r, 5, 0.02), *baselines.sgd(r, 5, 0.02, epochs=2))


_add("accel_fit_exact")(_fit_trace("accelerated", 2, search="exact"))
_add("accel_fit_more_thuente")(_fit_trace("accelerated", 2, search="more_thuente"))
_add("accel_fit_direct")(_fit_trace("accelerated", 1, search="backtracking_direct", first=2.0, shrink=0.7))
_add("accel_fit_float")(_fit_trace("accelerated", 2, precision="float"))
_add("accel_fit_parts")(_fit_trace("accelerated", 2, heavy=40))
_add("accel_fit_items_first")(_fit_trace("accelerated", 2, precond="als_items_first"))
_add("descent_fit_r10")(_fit_trace("accelerated", 2, precond="gradient", rule="zero"))


# --- experiments ---------------------------------------------------------------------------------------------------------------------

for _size in ("400x80", "800x160", "1600x320", "3200x640"):
    _add(f"convergence_{_size}")(lambda spark, d, k=_size: workloads.convergence_table(spark, d, k))
for _size in ("400x80", "800x160"):
    _add(f"accuracy_{_size}")(lambda spark, d, k=_size: workloads.accuracy_table(spark, d, k))
_add("accuracy_curve_400x80")(lambda spark, d: workloads.accuracy_curve(spark, d, "400x80"))
_add("ablation_100x40")(lambda spark, d: workloads.ablation(spark, d, 30))
_add("search_cost")(lambda spark, d: workloads.search_cost(spark, d, first=2.0, shrink=0.7))
_add("full_run_bands")(lambda spark, d: trace.bands(workloads.full_run(spark, d, iterations=6), "iter", 3))
_add("full_run_time_bands")(lambda spark, d: trace.bands(workloads.full_run(spark, d, rank=10, iterations=6, seeds=(1, 2)), "time", 5))
_add("cost_ratio_measured")(lambda spark, d: trace.cost_ratio(workloads.full_run(spark, d, rank=10, iterations=4)))
_add("scaling_users")(lambda spark, d: workloads.scaling(spark, d))
_add("speedup_users")(lambda spark, d: workloads.speedups(spark, d))
_add("svd_reference")(lambda spark, d: workloads.svd_reference(spark, d))
_add("work_formula")(lambda spark, d: workloads.work(spark, d))
