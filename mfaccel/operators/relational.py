"""The methods as plain joins and sums, for small ranks: every vector component is a term of built-in aggregates.

Factors are frames (id, x). Ratings meet the factors in hash joins, sums are partial in each task, and the normal equations
of rank 1 to 4 are solved by an unrolled elimination. Nothing leaves the JVM, and any SQL engine can replay a query.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mfaccel.functions.vectors import hashed_start, vaxpby, vdot, vnorm2
from mfaccel.operators.conjugate import DOTS, beta
from mfaccel.operators.linesearch import Quartic, backtracking
from mfaccel.plans.cuts import cut


@dataclass(frozen=True)
class Problem:
    ratings: DataFrame
    rank: int
    lam: float
    weighted: bool = True  # the ridge term by the number of ratings, else plain

    def held(self) -> "Problem":
        """The same with its ratings cut, for methods that go over them more than once: a view of joined tables is made once."""
        return replace(self, ratings=cut(self.ratings))

    def ids(self, side: str) -> DataFrame:
        return self.ratings.groupBy(F.col(side).alias("id")).agg(F.count("*").alias("n"))

    def start(self, seed: int = 42) -> tuple[DataFrame, DataFrame]:
        return tuple(hashed_start(self.ids(s), s, self.rank, seed) for s in ("user", "item"))

    def cells(self, users: DataFrame, items: DataFrame, *more: str) -> DataFrame:
        """Ratings with the vectors of both sides: u_<name> and m_<name> for x and each further name."""
        u = users.select(F.col("id").alias("user"), *[F.col(c).alias(f"u_{c}") for c in ("x", *more)])
        m = items.select(F.col("id").alias("item"), *[F.col(c).alias(f"m_{c}") for c in ("x", *more)])
        return self.ratings.join(m, "item").join(u, "user")


def loss_parts(p: Problem, users: DataFrame, items: DataFrame) -> DataFrame:
    """sse, reg_u, reg_m. With the weighted ridge a cell carries its share of both terms, so one pass gives all."""
    cells = p.cells(users, items)
    err = F.col("rating") - vdot("u_x", "m_x")
    if p.weighted:
        return cells.agg(F.sum(err * err).alias("sse"), (p.lam * F.sum(vnorm2("u_x"))).alias("reg_u"), (p.lam * F.sum(vnorm2("m_x"))).alias("reg_m"))
    one = cells.agg(F.sum(err * err).alias("sse"))
    two, three = (f.agg((p.lam * F.sum(vnorm2("x"))).alias(n)) for f, n in ((users, "reg_u"), (items, "reg_m")))
    return one.crossJoin(two).crossJoin(three)  # one row each


def loss(p: Problem, users: DataFrame, items: DataFrame) -> DataFrame:
    return loss_parts(p, users, items).select((F.col("sse") + F.col("reg_u") + F.col("reg_m")).alias("loss"))


def rmse(p: Problem, users: DataFrame, items: DataFrame) -> DataFrame:
    err = F.col("rating") - vdot("u_x", "m_x")
    return p.cells(users, items).agg(F.sqrt(F.avg(err * err)).alias("rmse"))


def _solve(a: list[list[Column]], v: list[Column]) -> list[Column]:
    """Symmetric elimination without pivots, as column expressions; positive definite systems only."""
    n = len(v)
    a, v = [list(r) for r in a], list(v)
    for k in range(n):
        for i in range(k + 1, n):
            f = a[i][k] / a[k][k]
            v[i] = v[i] - f * v[k]
            a[i] = [a[i][j] - f * a[k][j] if j > k else a[i][j] for j in range(n)]
    x: list[Column] = [None] * n  # type: ignore[list-item]
    for k in reversed(range(n)):
        rest = v[k]
        for j in range(k + 1, n):
            rest = rest - a[k][j] * x[j]
        x[k] = rest / a[k][k]
    return x


def half_step(p: Problem, other: DataFrame, side: str) -> DataFrame:
    """(id, x): the exact minimiser of one side while the other side's vectors are fixed."""
    r, name = p.rank, {"user": "item", "item": "user"}[side]
    with_vectors = p.ratings.join(other.select(F.col("id").alias(name), F.col("x")), name)
    x = [F.col("x")[k] for k in range(r)]
    sums = [F.sum(x[k] * x[m]).alias(f"a{k}_{m}") for k in range(r) for m in range(k, r)]
    sums += [F.sum(x[k] * F.col("rating")).alias(f"v{k}") for k in range(r)]
    normal = with_vectors.groupBy(F.col(side).alias("id")).agg(F.count("*").alias("n"), *sums)
    ridge = p.lam * F.col("n") if p.weighted else F.lit(float(p.lam))
    a = [[F.col(f"a{min(k, m)}_{max(k, m)}") + (ridge if k == m else 0.0) for m in range(r)] for k in range(r)]
    return normal.select("id", F.array(*_solve(a, [F.col(f"v{k}") for k in range(r)])).alias("x"))


def sweep(p: Problem, items: DataFrame) -> tuple[DataFrame, DataFrame]:
    users = half_step(p, items, "user")
    return users, half_step(p, users, "item")


def gradient(p: Problem, users: DataFrame, items: DataFrame, side: str) -> DataFrame:
    """(id, g): the part of the gradient that belongs to one side."""
    own, other = ("u_x", "m_x") if side == "user" else ("m_x", "u_x")
    cells = p.cells(users, items).withColumn("e", vdot("u_x", "m_x") - F.col("rating"))
    share = [2 * (F.col("e") * F.col(other)[k] + (p.lam * F.col(own)[k] if p.weighted else 0.0)) for k in range(p.rank)]
    g = cells.groupBy(F.col(side).alias("id")).agg(F.array(*[F.sum(s) for s in share]).alias("g"))
    if p.weighted:
        return g
    mine = users if side == "user" else items
    return g.join(mine, "id").select("id", vaxpby(1.0, "g", 2 * p.lam, "x").alias("g"))


def with_gradient(p: Problem, users: DataFrame, items: DataFrame) -> tuple[DataFrame, DataFrame]:
    return users.join(gradient(p, users, items, "user"), "id"), items.join(gradient(p, users, items, "item"), "id")


def gradient_norm(p: Problem, users: DataFrame, items: DataFrame) -> DataFrame:
    """The gradient's length over the number of unknowns."""
    both = gradient(p, users, items, "user").unionByName(gradient(p, users, items, "item"))
    return both.agg((F.sqrt(F.sum(vnorm2("g"))) / (p.rank * F.count("*"))).alias("gnorm"))


def preconditioned(p: Problem, users: DataFrame, items: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Both sides (id, x, gbar): the present point less one sweep from it."""
    new = sweep(p, items)
    return tuple(old.join(n.withColumnRenamed("x", "xbar"), "id").select("id", "x", vaxpby(1.0, "x", -1.0, "xbar").alias("gbar")) for old, n in zip((users, items), new, strict=True))


def quartic(p: Problem, users: DataFrame, items: DataFrame) -> DataFrame:
    """c0..c4 of the loss along p from x, for frames (id, x, p): five sums over the cells in one pass."""
    cells = p.cells(users, items, "p")
    e, b, d = vdot("u_x", "m_x") - F.col("rating"), vdot("u_x", "m_p") + vdot("u_p", "m_x"), vdot("u_p", "m_p")
    cells = cells.select("*", e.alias("e"), b.alias("b"), d.alias("d"))
    e, b, d = F.col("e"), F.col("b"), F.col("d")
    ridge = [vnorm2("u_x") + vnorm2("m_x"), 2 * (vdot("u_x", "u_p") + vdot("m_x", "m_p")), vnorm2("u_p") + vnorm2("m_p")]
    terms = [e * e, 2 * e * b, b * b + 2 * e * d, 2 * b * d, d * d]
    if p.weighted:
        terms = [t + p.lam * ridge[k] if k < 3 else t for k, t in enumerate(terms)]
        return cells.agg(*[F.sum(t).alias(f"c{k}") for k, t in enumerate(terms)])
    out = cells.agg(*[F.sum(t).alias(f"s{k}") for k, t in enumerate(terms)])
    side = users.select("x", "p").unionByName(items.select("x", "p"))
    more = side.agg(*[(p.lam * F.sum(t)).alias(f"r{k}") for k, t in enumerate((vnorm2("x"), 2 * vdot("x", "p"), vnorm2("p")))])
    return out.crossJoin(more).select(*[(F.col(f"s{k}") + (F.col(f"r{k}") if k < 3 else 0.0)).alias(f"c{k}") for k in range(5)])


def moved(side: DataFrame, alpha: Column | float) -> DataFrame:
    """x + alpha p; other columns stay."""
    alpha = alpha if isinstance(alpha, Column) else F.lit(float(alpha))
    return side.withColumn("x", F.zip_with("x", "p", lambda s, t: s + alpha * t))


# --- whole methods, for small ranks ------------------------------------------------------------------------------------


def fit_als(p: Problem, items: DataFrame, sweeps: int) -> tuple[DataFrame, DataFrame]:
    """Both sides are cut in every sweep, so that no later use repeats the sweeps before it."""
    users = None
    for _ in range(sweeps):
        users = cut(half_step(p, items, "user"))
        items = cut(half_step(p, users, "item"))
    return users, items


def _look(p: Problem, users: DataFrame, items: DataFrame, precond: str) -> tuple[DataFrame, DataFrame]:
    """(id, x, g, z) of both sides: the gradient, and the point less one application of the preconditioner."""
    g = with_gradient(p, users, items)
    if precond == "gradient":
        return tuple(cut(f.select("id", "x", "g", F.col("g").alias("z"))) for f in g)
    new = sweep(p, items)
    return tuple(cut(f.join(n.withColumnRenamed("x", "xbar"), "id").select("id", "x", "g", vaxpby(1.0, "x", -1.0, "xbar").alias("z"))) for f, n in zip(g, new, strict=True))


def fit_accelerated(p: Problem, users: DataFrame, items: DataFrame, iterations: int, rule: str = "pr_pre", precond: str = "als") -> tuple[tuple[DataFrame, DataFrame], list[dict]]:
    """Both sides (id, x, g, z, p) after the iterations, and the trace. Five sums and the dot products reach the driver."""
    size = None
    sides = tuple(f.withColumn("p", vaxpby(0.0, "z", -1.0, "z")) for f in _look(p, users, items, precond))
    trace: list[dict] = []
    alpha = weight = 0.0
    for k in range(iterations + 1):
        both = sides[0].select("g").unionByName(sides[1].select("g"))
        squares = both.agg(F.sum(vnorm2("g")).alias("s"), F.count("*").alias("n")).first()
        size = p.rank * squares.n
        q = Quartic.of(quartic(p, *sides).first())
        if q.c[1] >= 0 and k:  # no descent: the preconditioned gradient alone
            sides = tuple(cut(f.withColumn("p", vaxpby(0.0, "z", -1.0, "z"))) for f in sides)
            q = Quartic.of(quartic(p, *sides).first())
        trace.append({"iter": k, "loss": q.c[0], "gnorm": math.sqrt(squares.s) / size, "alpha": alpha, "beta": weight})
        if k == iterations:
            break
        alpha = backtracking(q)[0]
        new = _look(p, *(moved(f, alpha).select("id", "x") for f in sides), precond)
        full = tuple(n.join(old.select("id", F.col("g").alias("g0"), F.col("z").alias("z0"), "p"), "id") for n, old in zip(new, sides, strict=True))
        weight = beta(rule, dots(*full))
        sides = tuple(cut(f.select("id", "x", "g", "z", vaxpby(-1.0, "z", weight, "p").alias("p"))) for f in full)
    return sides, trace


def dots(users: DataFrame, items: DataFrame) -> dict[str, float]:
    cols = ["g", "g0", "z", "z0", "p"]
    both = users.select(cols).unionByName(items.select(cols))
    return both.agg(*[F.sum(vdot(a, b)).alias(n) for n, (a, b) in DOTS.items()]).first().asDict()
