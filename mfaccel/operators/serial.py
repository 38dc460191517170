"""The whole method on one machine: numpy twin of the distributed engine, for subsets that fit a worker and for tests."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

from mfaccel.operators import normal
from mfaccel.operators.conjugate import beta as weight
from mfaccel.operators.linesearch import Quartic, backtracking, backtracking_direct, exact, more_thuente, plain_step


@dataclass
class Stop:
    gnorm: float = 1e-6
    iterations: int = 10_000
    evaluations: int = 10_000_000
    seconds: float = float("inf")


@dataclass
class Run:
    users: np.ndarray
    items: np.ndarray
    trace: list[dict] = field(default_factory=list)
    factors: list[tuple[np.ndarray, np.ndarray]] = field(default_factory=list)  # in single precision

    @property
    def converged(self) -> bool:
        return bool(self.trace) and self.trace[-1]["done"]


class Serial:
    def __init__(self, user: np.ndarray, item: np.ndarray, rating: np.ndarray, rank: int, lam: float, weighted: bool = True):
        self.user_ids, self.item_ids = np.unique(user), np.unique(item)
        self.by_user = normal.BlockCells(user, item, rating, self.user_ids, self.item_ids, keep=True)
        self.by_item = normal.BlockCells(item, user, rating, self.item_ids, self.user_ids, keep=True)
        place = np.empty(len(user), np.int64)
        place[np.argsort(user, kind="stable")] = np.arange(len(user))
        self.turn = place[np.argsort(item, kind="stable")]  # where the cells by item are among those by user
        self.rank, self.lam, self.weighted = rank, lam, weighted
        self.n_u, self.n_m = len(self.user_ids), len(self.item_ids)
        self.size = rank * (self.n_u + self.n_m)
        self.ru = (self.by_user.counts if weighted else np.ones(self.n_u)) * lam
        self.rm = (self.by_item.counts if weighted else np.ones(self.n_m)) * lam
        self.cu, self.cm = self.ru[:, None], self.rm[:, None]

    def start(self, seed: int) -> tuple[np.ndarray, np.ndarray]:
        dice = np.random.default_rng(seed)
        return dice.random((self.n_u, self.rank)) / np.sqrt(self.rank), dice.random((self.n_m, self.rank)) / np.sqrt(self.rank)

    def residual(self, u, m) -> np.ndarray:
        """Of the cells by user. What follows takes it, where it is known already."""
        return normal.residual(self.by_user, u, m)

    def loss(self, u, m, left: np.ndarray | None = None) -> float:
        left = self.residual(u, m) if left is None else left
        return float((left**2).sum()) + float((self.cu * u**2).sum() + (self.cm * m**2).sum())

    def gradient(self, u, m, left: np.ndarray | None = None):
        left = self.residual(u, m) if left is None else left
        return 2 * (normal.weighed_sums(self.by_user, left, m) + self.cu * u), self._item_gradient(u, m, left)

    def _item_gradient(self, u, m, left: np.ndarray) -> np.ndarray:
        return 2 * (normal.weighed_sums(self.by_item, left[self.turn], u) + self.cm * m)

    def sweep(self, u, m, kind: str = "als"):
        """One application of the preconditioner."""
        if kind == "als_items_first":
            m = normal.solve(self.by_item, u, self.rm)
            return normal.solve(self.by_user, m, self.ru), m
        if kind == "coordinate":
            u = normal.coordinate_step(self.by_user, u, m, self.ru)
            return u, normal.coordinate_step(self.by_item, m, u, self.rm)
        if kind == "gradient":
            gu, gm = self.gradient(u, m)
            return u - gu, m - gm
        u = normal.solve(self.by_user, m, self.ru, kind == "nonnegative")
        return u, normal.solve(self.by_item, u, self.rm, kind == "nonnegative")

    def look(self, u, m, kind: str = "als", left: np.ndarray | None = None):
        """The gradient and the point after the preconditioner; a sweep's first normal equations give its side's gradient too."""
        left = self.residual(u, m) if left is None else left
        if kind != "als":
            return self.gradient(u, m, left), self.sweep(u, m, kind)
        new, gu = normal.solve_and_look(self.by_user, u, m, self.ru)
        return (gu, self._item_gradient(u, m, left)), (new, normal.solve(self.by_item, new, self.rm))

    def quartic(self, u, m, pu, pm, left: np.ndarray | None = None) -> Quartic:
        c = normal.quartic_sums(self.by_user, u, pu, m, pm, left)
        c[0] += (self.cu * u**2).sum() + (self.cm * m**2).sum()
        c[1] += 2 * ((self.cu * u * pu).sum() + (self.cm * m * pm).sum())
        c[2] += (self.cu * pu**2).sum() + (self.cm * pm**2).sum()
        return Quartic.of(c)

    def fit_als(self, u, m, stop: Stop, keep_factors: bool = False) -> Run:
        """Plain sweeps. The clock runs during sweeps only: not during the gradient, which only the stopping rule needs, nor for
        anything that is only recorded."""
        run, clock = Run(u, m), 0.0
        for k in range(stop.iterations + 1):
            if k:
                at = time.perf_counter()
                run.users, run.items = self.sweep(run.users, run.items)
                clock += time.perf_counter() - at
            left = self.residual(run.users, run.items)
            norm = self._norm(self.gradient(run.users, run.items, left))
            run.trace.append({"iter": k, "t_sec": clock, "loss": self.loss(run.users, run.items, left), "gnorm": norm, "done": norm < stop.gnorm, "alpha": 0.0, "beta": 0.0, "restart": False})
            if keep_factors:
                run.factors.append((run.users.astype(np.float32), run.items.astype(np.float32)))
            if norm < stop.gnorm or clock > stop.seconds:
                break
        return run

    def fit_accelerated(self, u, m, stop: Stop, rule: str = "pr_pre", search: str = "more_thuente", precond: str = "als", keep_factors: bool = False, **options) -> Run:
        """The clock runs during all that the method needs, its gradients and searches too, and not for what is only recorded."""
        run, clock, evaluations = Run(u, m), 0.0, 0

        def look(u, m):
            left = self.residual(u, m)
            g, bar = self.look(u, m, precond, left)
            return left, g, (u - bar[0], m - bar[1])

        at = time.perf_counter()
        left, g, z = look(u, m)
        p, alpha, b, restart = tuple(-x for x in z), 0.0, 0.0, False
        norm = self._norm(g)
        clock += time.perf_counter() - at
        for k in range(stop.iterations + 1):
            run.trace.append({"iter": k, "t_sec": clock, "loss": self.loss(u, m, left), "gnorm": norm, "done": norm < stop.gnorm, "alpha": alpha, "beta": b, "restart": restart})
            if keep_factors:
                run.factors.append((u.astype(np.float32), m.astype(np.float32)))
            if norm < stop.gnorm or k == stop.iterations or evaluations > stop.evaluations or clock > stop.seconds:
                break
            at = time.perf_counter()
            q, restart = self.quartic(u, m, *p, left), False
            if q.c[1] >= 0:  # no descent: begin anew from the preconditioned gradient
                p, restart = tuple(-x for x in z), True
                q = self.quartic(u, m, *p, left)
            alpha, used = self._step(q, search, u, m, p, **options)
            evaluations += used
            if q.c[1] >= 0 or alpha == 0.0:
                alpha, p, restart = self._plain_step(u, m, p, z, q, restart)
                if alpha == 0.0:  # neither falls: a minimum as far as numbers tell
                    clock += time.perf_counter() - at
                    break
            u, m = u + alpha * p[0], m + alpha * p[1]
            g0, z0 = g, z
            left, g, z = look(u, m)
            b = 0.0 if restart and rule == "zero" else weight(rule, self._dots(g, g0, z, z0, p))
            p = tuple(-x + b * y for x, y in zip(z, p, strict=True))
            norm = self._norm(g)
            clock += time.perf_counter() - at
        run.users, run.items = u, m
        return run

    def _plain_step(self, u, m, p, z, q: Quartic, restart: bool):
        """(step, direction, True) without a searched step: the preconditioner itself if the loss falls by it, else the longest halved
        step along it that lessens the loss; step 0 if none does. An exact sweep always passes, a raw gradient step need not."""
        if not restart:
            p = tuple(-x for x in z)
            q = self.quartic(u, m, *p)
        return plain_step(q), p, True

    def _norm(self, g) -> float:
        return float(np.sqrt((g[0] ** 2).sum() + (g[1] ** 2).sum())) / self.size

    @staticmethod
    def _dots(g, g0, z, z0, p) -> dict[str, float]:
        from mfaccel.operators.conjugate import DOTS

        have = {"g": g, "g0": g0, "z": z, "z0": z0, "p": p}
        return {n: float(sum((s * t).sum() for s, t in zip(have[a], have[b], strict=True))) for n, (a, b) in DOTS.items()}

    def _step(self, q: Quartic, search: str, u, m, p, **options) -> tuple[float, int]:
        if search == "backtracking":
            return backtracking(q, **options)
        if search == "exact":
            return exact(q, **options), 1
        at: Callable[[float], float] = lambda a: self.loss(u + a * p[0], m + a * p[1])
        if search == "backtracking_direct":
            return backtracking_direct(at, q.c[1], **options)
        if search == "more_thuente_direct":
            def slope(a):
                g = self.gradient(u + a * p[0], m + a * p[1])
                return float((g[0] * p[0]).sum() + (g[1] * p[1]).sum())

            return more_thuente(at, slope, **options)
        return more_thuente(q.gain, q.slope, **options)
