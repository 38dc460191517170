"""Plain and accelerated alternating least squares on block layouts of any size.

State is two frames of entity rows, users and items, with their vectors as array columns of one row, so that no vector
operation joins anything. A pass over one side sends each vector of the other side once to every block that needs it,
together with the own rows, and works block by block; its output is the new own rows.

The fused schedule has two exchanges an iteration: items' (x, p) to the user blocks, used for the line search and, once the
step is known, again for the user solve and gradient; and users' (x, xbar) to the item blocks, for the item solve and
gradient. The separate schedule makes the five exchanges of the plain layout: search, two for the sweep, two for the gradient; its search goes
over the side to which fewer vectors are sent. A search by plain evaluation makes an exchange for each trial step instead.

Plain sweeps measure themselves: the normal equations of a half-step give the gradient of its side, that of the other side is zero
after an exact solve, and the residuals give the loss, so gradient norms cost no pass of their own.

Only the five coefficients and a dozen dot products reach the driver in an iteration. Each pass ends in a checkpoint. An entity with more
ratings than `layout` lets one block hold is in parts: each part's block sums its share, and the shares are added up before the solve.
With precision "float" vectors are kept and sent in single precision, and computed with in double.

What a pass leaves behind is what a fit needs disk for: its rows hold their vectors in one list, the products that weigh the old direction are
taken in the pass, so that the old gradient and its z need not be written again, and rows that the next pass no longer needs are let go.
"""

from __future__ import annotations

import json
import time
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mfaccel.functions.vectors import start_vector, vaxpby, vdot, vnorm2, vzeros
from mfaccel.operators import normal
from mfaccel.operators.conjugate import DOTS, beta
from mfaccel.operators.linesearch import Quartic, backtracking, backtracking_direct, exact, more_thuente, plain_step
from mfaccel.plans.blocks import HEAVY, Layout, layout, unpacked
from mfaccel.plans.cuts import cut, release

KEYS = ["id", "blk", "n", "dest", "parts", "lead"]
STATIC = "id bigint, blk int, n int, dest array<int>, parts int, lead boolean"
PRECONDITIONERS = ("als", "als_items_first", "nonnegative", "coordinate", "gradient")


@dataclass
class StopRule:
    gnorm: float = 1e-6
    iterations: int = 100
    seconds: float = float("inf")


@dataclass
class Saves:
    """Where and how often the state is kept beyond the job, so that another can go on from it."""

    folder: str
    every: int = 10


@dataclass
class Fit:
    users: DataFrame
    items: DataFrame
    rank: int
    lam: float
    trace: list[dict] = field(default_factory=list)

    def factors(self) -> DataFrame:
        return self.users.select(F.lit("user").alias("side"), "id", "x").unionByName(self.items.select(F.lit("item").alias("side"), "id", "x"))


def _array(column: pa.ChunkedArray, rank: int) -> np.ndarray:
    column = column.combine_chunks()
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64, copy=False).reshape(-1, rank) if len(column) else np.zeros((0, rank))


def _lists(values: np.ndarray, kind: str = "double") -> pa.Array:
    flat = pa.array(values.reshape(-1).astype(np.float32 if kind == "float" else np.float64, copy=False))
    return pa.ListArray.from_arrays(pa.array(np.arange(0, values.size + 1, values.shape[1] or 1), pa.int32()), flat)


def _products(made: dict[str, np.ndarray], precond: str, kind: str) -> list[float]:
    """Over some rows, the products that the weight of the old direction is made of, of the vectors as they are kept."""
    at = {c: x.astype(np.float32).astype(np.float64) for c, x in made.items()} if kind == "float" else dict(made)
    at["z"] = at["g"] if precond == "gradient" else at["x"] - at["xbar"]
    return [float((at[a] * at[b]).sum()) for a, b in DOTS.values()]


def _ridge(cells: normal.BlockCells, own: pa.Table, lam: float, weighted: bool) -> np.ndarray:
    """Ridge of each own row; over the parts of an entity it adds up to the entity's."""
    return lam * (cells.counts if weighted else own["lead"].to_numpy().astype(float))


def _at_first(values: list[float], rows: int) -> pa.Array:
    """A column of lists: the values in the first row, nothing in the others."""
    return pa.ListArray.from_arrays(pa.array(np.r_[0, np.full(rows, len(values))], pa.int32()), pa.array(values, pa.float64())) if rows else pa.array([], pa.list_(pa.float64()))


def _parts_sums(cells: normal.BlockCells, others: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Upper triangles of the Gram matrices of some own rows, and their right-hand sides."""
    f = others.shape[1]
    upper, place = np.triu_indices(f), np.full(len(cells.counts), -1)
    place[rows] = np.arange(len(rows))
    out = np.zeros((len(rows), len(upper[0]) + f))
    for who, a, v in normal.normal_equations(cells, others):
        mine = np.flatnonzero(place[who] >= 0)
        out[place[who[mine]]] = np.hstack([a[mine][:, upper[0], upper[1]], v[mine]])
    return out


class Engine:
    def __init__(self, plan: Layout, rank: int, lam: float, weighted: bool = True, precond: str = "als", precision: str = "double"):
        if precond not in PRECONDITIONERS or precision not in ("double", "float"):
            raise ValueError(f"{precond}, {precision}")
        self.plan, self.rank, self.lam, self.weighted, self.precond, self.precision = plan, rank, lam, weighted, precond, precision
        self.first, self.second = ("item", "user") if precond == "als_items_first" else ("user", "item")

    def start(self, seed: int = 42) -> dict[str, DataFrame]:
        return {s: cut(self.plan.side(s)[1].select(*KEYS, self._kept(start_vector(s, self.rank, seed)).alias("x"))) for s in ("user", "item")}

    def _kept(self, vector: Column) -> Column:
        return vector.cast(f"array<{self.precision}>")

    def _cut(self, df: DataFrame) -> DataFrame:
        done = cut(df)
        release(done.sparkSession)
        return done

    # --- one pass ----------------------------------------------------------------------------------------------------

    def route(self, side: str, own: DataFrame, own_cols: list[str], other: DataFrame, other_cols: list[str]) -> DataFrame:
        """Own rows and the vectors that they need, by block: the exchange of a pass. Lists that a row does not have are empty, not null: Spark's
        Arrow writer goes over all nulls before a row again for each row."""
        null, none = F.lit(None), F.array()
        kind = f"array<{self.precision}>"
        names = [*dict.fromkeys([*own_cols, *other_cols])]
        mine = own.select(F.col("blk").alias("to"), F.lit(True).alias("mine"), "id", "n", "dest", "parts", "lead", *[(F.col(c).cast(kind) if c in own_cols else none.cast(kind)).alias(c) for c in names])
        absent = [x.cast(t).alias(c) for c, t, x in (("n", "int", null), ("dest", "array<int>", none), ("parts", "int", null), ("lead", "boolean", null))]
        sent = other.select(F.explode("dest").alias("to"), F.lit(False).alias("mine"), "id", *absent, *[(F.col(c).cast(kind) if c in other_cols else none.cast(kind)).alias(c) for c in names])
        return mine.unionByName(sent).repartition(self.plan.n_blocks, "to")

    def work(self, side: str, routed: DataFrame, each: Callable, schema: str) -> DataFrame:
        """`each` gets the cells of a block, the own table and the other side's table, and gives columns."""
        ratings, rank = self.plan.side(side)[0], self.rank

        def run(left: pa.Table, right: pa.Table) -> pa.Table:
            mine = right["mine"].to_numpy()
            own, others = (right.filter(pa.array(m)).sort_by("id") for m in (mine, ~mine))
            ids = [t["id"].to_numpy() for t in (own, others)]
            cells = normal.BlockCells(*unpacked(left), *ids)
            return each(cells, own, others, lambda t, c: _array(t[c], rank))

        return ratings.groupBy("blk").cogroup(routed.groupBy("to")).applyInArrow(run, schema)

    def _vectors(self, old: list[str], solve_with: str | None, with_gradient: bool) -> tuple[list[str], bool]:
        """The vectors that a pass gives, and whether it takes the products with the old gradient and its z, which it then gives no longer."""
        dotted = with_gradient and {"p", "g0", "z0"} <= {*old}
        return ["x", *(["xbar"] if solve_with else []), *(["g"] if with_gradient else []), *(c for c in old if not dotted or c not in ("g0", "z0"))], dotted

    def _apart(self, rows: DataFrame, old: list[str], solve_with: str | None, with_gradient: bool) -> DataFrame:
        """Rows of a pass with each vector in a column of its own."""
        names = self._vectors(old, solve_with, with_gradient)[0]
        return rows.select(*KEYS, *[F.slice("v", 1 + k * self.rank, self.rank).alias(c) for k, c in enumerate(names)], *[c for c in ("f", "dots") if c in rows.columns])

    def passed(self, side: str, routed: DataFrame, alpha: float, old: list[str], solve_with: str | None, with_gradient: bool) -> DataFrame:
        """A pass, kept: new own rows with a column for each vector."""
        return self._apart(self._cut(self.advance(side, routed, alpha, old, solve_with, with_gradient)), old, solve_with, with_gradient)

    def advance(self, side: str, routed: DataFrame, alpha: float, old: list[str], solve_with: str | None, with_gradient: bool) -> DataFrame:
        """New own rows: x moved by alpha along p (of both sides), xbar solved against a column of the other side, the gradient g, the own share f of
        the loss, and columns named in `old`, which are carried along; all vectors are one list v. Where old directions and gradients come along,
        `dots` has their products with the new ones, in one row for all of a block."""
        rank, lam, weighted, precond, kind, split = self.rank, self.lam, self.weighted, self.precond, self.precision, self.plan.split[side]
        moved_others = alpha if solve_with == "x" or side == self.first else 0.0
        outs, dotted = self._vectors(old, solve_with, with_gradient)
        wide = [*outs, *(["g0", "z0"] if dotted else [])]
        shares = ["f"] if with_gradient else []

        def each(in_parts):
            def run(cells, own, others, vectors):
                x, y = vectors(own, "x"), vectors(others, "x")
                if alpha:
                    x = x + alpha * vectors(own, "p")
                    if moved_others:
                        y = y + moved_others * vectors(others, "p")
                made, ridge = {"x": x}, _ridge(cells, own, lam, weighted)
                against = None if not solve_with else y if solve_with == "x" else vectors(others, solve_with)
                if with_gradient:
                    e = normal.residual(cells, x, y)
                    made["f"] = normal.sums_by_own(cells, (e**2)[:, None])[:, 0] + ridge * (x**2).sum(axis=1)
                if with_gradient and solve_with == "x" and precond != "coordinate" and not in_parts:
                    made["xbar"], made["g"] = normal.solve_and_look(cells, x, y, ridge, precond == "nonnegative")
                else:
                    if with_gradient:
                        made["g"] = 2 * (normal.weighed_sums(cells, e, y) + ridge[:, None] * x)
                    if solve_with and in_parts:
                        made["xbar"] = np.zeros_like(x)  # made of the sums of all parts
                    elif solve_with:
                        made["xbar"] = normal.coordinate_step(cells, x, against, ridge) if precond == "coordinate" else normal.solve(cells, against, ridge, precond == "nonnegative")
                made |= {c: vectors(own, c) for c in wide if c not in made}
                at = np.flatnonzero((own["parts"].to_numpy() > 1) == in_parts) if split else np.arange(own.num_rows)
                names = wide if in_parts else outs
                v = _lists(np.hstack([made[c][at] for c in names]), kind)
                columns = [*(own[c].take(pa.array(at)) for c in ("id", "to", "n", "dest", "parts", "lead")), v, *(pa.array(made[c][at]) for c in shares)]
                if in_parts:
                    sums = [ridge[at, None], made["g"][at] if with_gradient else np.zeros((len(at), rank))]
                    columns.append(_lists(np.hstack([*sums, *([_parts_sums(cells, against, at)] if solve_with else [])])))
                elif dotted:
                    columns.append(_at_first(_products({c: made[c][at] for c in wide}, precond, kind), len(at)))
                return pa.Table.from_arrays(columns, [*KEYS, "v", *shares, *(["sums"] if in_parts else ["dots"] if dotted else [])])

            return run

        schema = f"{STATIC}, v array<{kind}>" + "".join(f", {c} double" for c in shares)
        last = ", dots array<double>" * dotted
        done = self.work(side, routed, each(False), schema + last)
        if not split:
            return done
        parts = self.work(side, routed, each(True), schema + ", sums array<double>")
        parts = parts.groupBy(F.pmod(F.xxhash64("id"), F.lit(self.plan.n_blocks))).applyInArrow(self._add_parts(wide, outs, solve_with, with_gradient, dotted), schema + last)
        return done.unionByName(parts)

    def _add_parts(self, wide: list[str], outs: list[str], solve_with: str | None, with_gradient: bool, dotted: bool) -> Callable:
        """All parts of some entities, with what their sums make."""
        rank, precond, kind = self.rank, self.precond, self.precision
        upper = np.triu_indices(rank)
        half = len(upper[0])
        width = 1 + rank + (half + rank if solve_with else 0)

        def run(parts: pa.Table) -> pa.Table:
            parts = parts.sort_by("id")
            ids = parts["id"].to_numpy()
            first = np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]])
            which = np.repeat(np.arange(len(first)), np.diff(np.r_[first, len(ids)]))
            total = np.add.reduceat(_array(parts["sums"], width), first, axis=0)
            made, ridge = dict(zip(wide, np.hsplit(_array(parts["v"], len(wide) * rank), len(wide)), strict=True)), total[:, 0]
            if with_gradient:
                made["g"] = total[which, 1 : 1 + rank]
            if solve_with:
                a, v = np.zeros((len(first), rank, rank)), total[:, 1 + rank + half :]
                a[:, upper[0], upper[1]] = a[:, upper[1], upper[0]] = total[:, 1 + rank : 1 + rank + half]
                made["xbar"] = (normal.coordinate_systems(a, v, ridge, made["x"][first]) if precond == "coordinate" else normal.solve_systems(a, v, ridge, precond == "nonnegative"))[which]
            parts = parts.drop_columns(["sums"])
            parts = parts.set_column(parts.schema.get_field_index("v"), "v", _lists(np.hstack([made[c] for c in outs]), kind))
            if dotted:
                lead = parts["lead"].to_numpy()
                parts = parts.append_column("dots", _at_first(_products({c: made[c][lead] for c in wide}, precond, kind), len(ids)))
            return parts

        return run

    def coefficients(self, side: str, routed: DataFrame) -> Quartic:
        lam, weighted = self.lam, self.weighted

        def each(cells, own, others, vectors):
            x, p, y, q = vectors(own, "x"), vectors(own, "p"), vectors(others, "x"), vectors(others, "p")
            c = normal.quartic_sums(cells, x, p, y, q)
            if weighted:
                uses = np.bincount(cells.other, minlength=len(y))
                for n, a, b in ((cells.counts, x, p), (uses, y, q)):
                    c[:3] += lam * np.array([n @ (a * a).sum(1), 2 * n @ (a * b).sum(1), n @ (b * b).sum(1)])
            return pa.table({f"c{k}": [float(v)] for k, v in enumerate(c)})

        sums = self.work(side, routed, each, ", ".join(f"c{k} double" for k in range(5)))
        row = sums.agg(*[F.sum(f"c{k}").alias(f"c{k}") for k in range(5)]).first()
        return Quartic.of([row[k] for k in range(5)])

    def line(self, side: str, state: dict[str, DataFrame], keep: list[str]) -> tuple[DataFrame, Quartic]:
        """The routed rows of a side, and the loss along p as a quartic."""
        other = {"user": "item", "item": "user"}[side]
        routed = self.route(side, state[side], ["x", "p", *keep], state[other], ["x", "p"]).persist()
        q = self.coefficients(side, routed)
        if not self.weighted:
            both = state["user"].select("x", "p", "lead").unionByName(state["item"].select("x", "p", "lead")).where("lead")
            more = both.agg(F.sum(vnorm2("x")), F.sum(vdot("x", "p")), F.sum(vnorm2("p"))).first()
            c = q.c
            q = Quartic.of([c[0] + self.lam * more[0], c[1] + 2 * self.lam * more[1], c[2] + self.lam * more[2], c[3], c[4]])
        return routed, q

    # --- measures ----------------------------------------------------------------------------------------------------

    def gradients(self, state: dict[str, DataFrame]) -> dict[str, DataFrame]:
        """Both sides with their gradients: two exchanges, as much as a sweep."""
        out = {}
        for side, other in (("user", "item"), ("item", "user")):
            carried = [c for c in state[side].columns if c not in (*KEYS, "x", "g", "f")]
            routed = self.route(side, state[side], ["x", *carried], state[other], ["x"])
            out[side] = self.passed(side, routed, 0.0, carried, None, True)
        return out

    def loss(self, state: dict[str, DataFrame]) -> float:
        zero = {s: state[s].select(*KEYS, "x", vzeros(self.rank).alias("p")) for s in state}
        routed, q = self.line("user", zero, [])
        routed.unpersist()
        return q.c[0]

    def _squares(self, *sides: DataFrame) -> float:
        return sum(float(s.where("lead").agg(F.sum(vnorm2("g"))).first()[0] or 0.0) for s in sides)

    def norm(self, state: dict[str, DataFrame]) -> float:
        return self._squares(*state.values()) ** 0.5 / self.size

    @property
    def size(self) -> int:
        return self.rank * (self.plan.n_u + self.plan.n_m)

    # --- plain sweeps --------------------------------------------------------------------------------------------------

    def _half(self, side: str, state: dict[str, DataFrame], look: bool) -> DataFrame:
        other = {"user": "item", "item": "user"}[side]
        return self.passed(side, self.route(side, state[side], ["x"], state[other], ["x"]), 0.0, [], "x", look)

    def sweep(self, state: dict[str, DataFrame]) -> dict[str, DataFrame]:
        out = dict(state)
        for side in (self.first, self.second):
            out[side] = self._half(side, out, False).select(*KEYS, F.col("xbar").alias("x"))
        return out

    def fit_als(self, state: dict[str, DataFrame], stop: StopRule, measured: bool = True, saves: Saves | None = None, after: int = 0) -> Fit:
        """Plain sweeps, from iteration `after` on. An exact half-step tells the gradient and the loss of the point that it starts from; with other
        preconditioners, and at the start, the second side's gradient is measured by a pass that the clock leaves out."""
        a, b = self.first, self.second
        rows, clock, exact_solves = [], 0.0, self.precond in ("als", "als_items_first")
        state = {s: state[s].select(*KEYS, "x") for s in state}
        for k in range(after, stop.iterations + 1):
            at = time.perf_counter()
            saved = self._save(saves, k, state, {"algo": "als"}) if saves and k > after else None
            state, saving = saved or state, time.perf_counter() - at
            clock += saving
            last = k == stop.iterations
            row = {"algo": "als", "iter": k, "t_sec": clock, "loss": float("nan"), "gnorm": float("nan"), "alpha": 0.0, "beta": 0.0, "restart": False, "ckpt": bool(saved)}
            rows.append(row)
            if last and not measured:
                break
            at = time.perf_counter()
            half = self._half(a, state, measured)
            spent = time.perf_counter() - at
            if measured:
                ridge = F.sum(vnorm2("x") * (F.col("n") if self.weighted else F.col("lead").cast("int"))) * self.lam
                squares = self._squares(half)
                if k == after or not exact_solves:
                    routed = self.route(b, state[b], ["x"], state[a], ["x"])
                    squares += self._squares(self._apart(self.advance(b, routed, 0.0, [], None, True), [], None, True))
                row["loss"] = float(half.agg(F.sum("f")).first()[0] or 0.0) + float(state[b].agg(ridge).first()[0] or 0.0)
                row["gnorm"] = squares**0.5 / self.size
            if last or row["gnorm"] < stop.gnorm or clock > stop.seconds:
                break
            at = time.perf_counter()
            state = {**state, a: half.select(*KEYS, F.col("xbar").alias("x"))}
            state[b] = self._half(b, state, False).select(*KEYS, F.col("xbar").alias("x"))
            clock += spent + time.perf_counter() - at
        return Fit(*(state[s].where("lead") for s in ("user", "item")), self.rank, self.lam, rows)

    # --- accelerated ---------------------------------------------------------------------------------------------------

    def _look(self, state: dict[str, DataFrame], routed: list[DataFrame], alpha: float, comm: str) -> dict[str, DataFrame]:
        """Both sides at x + alpha p, with xbar, g, the old p and the products with the old g0, z0, p. Rows that a search has routed are taken out of the
        list, and old rows out of the state, once they are used."""
        a, b = self.first, self.second
        old = [c for c in ("p", "g0", "z0") if c in state[a].columns]
        if self.precond == "gradient":
            comm = "fused"
        if comm == "fused":
            mine = routed.pop() if routed else self.route(a, state[a], ["x", *old], state[b], ["x", "p"] if "p" in old else ["x"])
            first = cut(self.advance(a, mine, alpha, old, "x", True))
            mine.unpersist()
            del mine, state[a]  # the new rows have all that is still needed of the old
            release(first.sparkSession)
            first = self._apart(first, old, "x", True)
            moved = state[b].withColumn("x", vaxpby(1.0, "x", alpha, "p")) if alpha else state[b]
            rows = self.route(b, moved, ["x", *old], first, ["x", "xbar"])
            return {a: first, b: self.passed(b, rows, 0.0, old, "xbar", True)}
        moved = {s: state[s].withColumn("x", vaxpby(1.0, "x", alpha, "p")) if alpha else state[s] for s in state}
        first = self.passed(a, self.route(a, moved[a], ["x", *old], moved[b], ["x"]), 0.0, old, "x", False)
        del state[a], moved[a]
        rows = self.route(b, moved[b], ["x", *old], first, ["x", "xbar"])
        second = self.passed(b, rows, 0.0, old, "xbar", False)
        del rows, state[b], moved
        return self.gradients({a: first, b: second})

    def _with_z(self, sides: dict[str, DataFrame]) -> dict[str, DataFrame]:
        z = F.col("g") if self.precond == "gradient" else vaxpby(1.0, "x", -1.0, "xbar")
        return {s: sides[s].withColumn("z", z).drop("xbar", "f") for s in sides}

    def _dots(self, sides: dict[str, DataFrame]) -> dict[str, float]:
        found = [v.agg(*[F.sum(F.get("dots", F.lit(k))).alias(n) for k, n in enumerate(DOTS)]).first() for v in sides.values()]
        return {n: sum(row[n] or 0.0 for row in found) for n in DOTS}

    def _downhill(self, state: dict[str, DataFrame]) -> dict[str, DataFrame]:
        """The state with the preconditioned gradient alone as its direction."""
        return {s: v.withColumn("p", vaxpby(0.0, "z0", -1.0, "z0")) for s, v in state.items()}

    def fit_accelerated(
        self, state: dict[str, DataFrame], stop: StopRule, rule: str = "pr_pre", search: str = "backtracking", comm: str = "fused",
        search_side: str = "auto", saves: Saves | None = None, after: dict | None = None, **options,
    ) -> Fit:
        """`after`: the last row of a saved trace, if the state is one that a save holds (x, p, g0, z0). `search_side` matters to the separate
        schedule; the fused one uses the rows of its search again, so it searches over the side that it solves first."""
        began, a = time.perf_counter(), self.first
        direct = search.endswith("_direct")
        over = a if comm == "fused" or direct else search_side if search_side != "auto" else min(("user", "item"), key=lambda s: self.plan.volume[{"user": "item", "item": "user"}[s]])
        value, alpha, weight, restart, saved = None, 0.0, 0.0, False, None
        if after is None:
            state = {s: state[s].select(*KEYS, "x") for s in state}
            sides = self._with_z(self._look(state, [], 0.0, comm))
            squares = self._squares(*sides.values())
            state = {s: v.select(*KEYS, "x", vaxpby(0.0, "z", -1.0, "z").alias("p"), F.col("g").alias("g0"), F.col("z").alias("z0")) for s, v in sides.items()}
            del sides
        else:
            began -= after["t_sec"]
            squares, value = (after["gnorm"] * self.size) ** 2, after["loss"]
        rows: list[dict] = []
        keep = ["g0", "z0"] if over == a else []
        for k in range(after["iter"] if after else 0, stop.iterations + 1):
            norm, routed, q = float(squares) ** 0.5 / self.size, None, None
            last = norm < stop.gnorm or k == stop.iterations or time.perf_counter() - began > stop.seconds
            if value is None and direct:
                value = self.loss(state)
            elif not direct and (not last or value is None):
                routed, q = self.line(over, state, keep)
                value = q.c[0] if value is None else value
            row = {"algo": "accelerated", "iter": k, "t_sec": time.perf_counter() - began, "loss": value, "gnorm": norm, "alpha": alpha, "beta": weight, "restart": restart, "ckpt": bool(saved)}
            if not after or k > after["iter"]:
                rows.append(row)
            if last:
                if routed is not None:
                    routed.unpersist()
                break
            restart = False
            if direct:
                alpha, value, state, restart = self._direct_step(state, value, search, **options)
            else:
                if q.c[1] >= 0:  # no descent: begin anew from the preconditioned gradient
                    routed.unpersist()
                    state, restart = self._downhill(state), True
                    routed, q = self.line(over, state, keep)
                alpha = _search(q, search, **options)
                if q.c[1] >= 0 or alpha == 0.0:
                    if not restart:
                        routed.unpersist()
                        state, restart = self._downhill(state), True
                        routed, q = self.line(over, state, keep)
                    alpha = plain_step(q)
                value = q.value(alpha)
            if alpha == 0.0:  # nothing falls: a minimum as far as numbers tell
                break
            ready = [routed] if routed is not None and over == a and (comm == "fused" or self.precond == "gradient") else []
            if routed is not None and not ready:
                routed.unpersist()  # the separate schedule does not use the rows of its search again
            routed = None
            sides = self._with_z(self._look(state, ready, alpha, comm))
            dots = self._dots(sides)
            squares, weight = dots["g1g1"], beta(rule, dots)
            state = {s: v.select(*KEYS, "x", vaxpby(-1.0, "z", weight, "p").alias("p"), F.col("g").alias("g0"), F.col("z").alias("z0")) for s, v in sides.items()}
            del sides  # they would hold these rows through the next pass
            saved = self._save(saves, k + 1, state, {"algo": "accelerated", "loss": value, "gnorm": float(squares) ** 0.5 / self.size, "t_sec": time.perf_counter() - began}) if saves else None
            state = saved or state
        return Fit(*(state[s].where("lead") for s in ("user", "item")), self.rank, self.lam, rows)

    def _direct_step(self, state: dict[str, DataFrame], value: float, search: str, **options):
        """A step found by evaluating the whole loss at each trial, an exchange each: what the quartic saves."""
        def at(frames):
            return lambda step: self.loss({s: v.withColumn("x", vaxpby(1.0, "x", step, "p")) for s, v in frames.items()}) if step else value

        def slope_of(frames) -> float:
            return sum(float(v.where("lead").agg(F.sum(vdot("g0", "p"))).first()[0] or 0.0) for v in frames.values())

        if search != "backtracking_direct":
            raise ValueError(search)
        restart, slope = False, slope_of(state)
        if slope >= 0:
            state, restart = self._downhill(state), True
            slope = slope_of(state)
        step = backtracking_direct(at(state), slope, **options)[0] if slope < 0 else 0.0
        if step == 0.0:
            state, restart = self._downhill(state), True
            step = next((0.5**k for k in range(60) if at(state)(0.5**k) < value), 0.0)
        return step, (at(state)(step) if step else value), state, restart

    # --- saved states --------------------------------------------------------------------------------------------------

    def _save(self, saves: Saves, k: int, state: dict[str, DataFrame], about: dict) -> dict[str, DataFrame] | None:
        """Writes the state of every so many iterations and goes on from what was written; a save counts once its last file is there."""
        if k % saves.every:
            return None
        folder, out = f"{saves.folder.rstrip('/')}/{k:08d}", {}
        for s, v in state.items():
            v.write.mode("overwrite").parquet(f"{folder}/{s}")
            out[s] = v.sparkSession.read.parquet(f"{folder}/{s}")
        spark = state["user"].sparkSession
        spark.createDataFrame([(json.dumps(about | {"iter": k}),)], "value string").coalesce(1).write.mode("overwrite").text(f"{folder}/about")
        return out


def newest_save(spark, folder: str) -> tuple[dict[str, DataFrame], dict] | None:
    """(state, what is known of it) of the newest whole save in a folder."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
    names = sorted((x.getPath().getName() for x in fs.listStatus(path)), reverse=True) if fs.exists(path) else []
    for name in names:
        at = f"{folder.rstrip('/')}/{name}"
        if fs.exists(spark._jvm.org.apache.hadoop.fs.Path(f"{at}/about/_SUCCESS")):
            return {s: spark.read.parquet(f"{at}/{s}") for s in ("user", "item")}, json.loads(spark.read.text(f"{at}/about").first().value)
    return None


def _search(q: Quartic, search: str, **options) -> float:
    if search == "backtracking":
        return backtracking(q, **options)[0]
    if search == "exact":
        return exact(q, **options)
    if search == "more_thuente":
        return more_thuente(q.gain, q.slope, **options)[0]
    raise ValueError(search)


def fit(
    ratings: DataFrame, rank: int, lam: float, *, algo: str = "accelerated", seed: int = 42, stop: StopRule | None = None, n_blocks: int | None = None, weighted: bool = True,
    precond: str = "als", precision: str = "double", one_sweep: bool = False, heavy: int = HEAVY, saves: Saves | None = None, **options,
) -> Fit:
    """Fits a table of ratings (user, item, rating); entities without ratings are not part of the model. With `saves` a fit goes on from the newest
    state in their folder, which must be of the same ratings, rank and number of blocks."""
    plan = layout(ratings, n_blocks, heavy=heavy)
    try:
        engine = Engine(plan, rank, lam, weighted, precond, precision)
        found = newest_save(ratings.sparkSession, saves.folder) if saves else None
        held = [found[0] if found else engine.start(seed)]  # given away, so that the fit can let go of it
        if one_sweep and not found:
            held.append(engine.sweep(held.pop()))
        stop = stop or StopRule()
        if algo == "als":
            return engine.fit_als(held.pop(), stop, saves=saves, after=found[1]["iter"] if found else 0)
        return engine.fit_accelerated(held.pop(), stop, saves=saves, after=found[1] if found else None, **options)
    finally:
        plan.close()
