"""Step lengths along a direction: the loss there is a quartic, so a search costs a few scalar operations.

`Quartic` holds the five coefficients; differences to the start are taken without the constant, which would cancel.
Direct variants take a function instead and evaluate the whole loss at each trial, which is what the quartic saves.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: First step, shrinking factor and decrease constant of the backtracking search.
FIRST, SHRINK, DECREASE = 10.0, 0.9, 0.5


@dataclass(frozen=True)
class Quartic:
    c: tuple[float, float, float, float, float]

    def value(self, a: float) -> float:
        return self.c[0] + self.gain(a)

    def gain(self, a: float) -> float:
        """Value at a less value at 0."""
        return a * (self.c[1] + a * (self.c[2] + a * (self.c[3] + a * self.c[4])))

    def slope(self, a: float) -> float:
        return self.c[1] + a * (2 * self.c[2] + a * (3 * self.c[3] + a * 4 * self.c[4]))

    @classmethod
    def of(cls, row: Sequence[float]) -> "Quartic":
        return cls(tuple(float(x) for x in row))  # type: ignore[arg-type]


def enough(q: Quartic, a: float, decrease: float) -> bool:
    """Sufficient decrease, divided by the step: no constant and no cancellation."""
    return q.c[2] * a + q.c[3] * a**2 + q.c[4] * a**3 <= (decrease - 1) * q.c[1]


def backtracking(q: Quartic, first: float = FIRST, shrink: float = SHRINK, decrease: float = DECREASE, most: int = 1000) -> tuple[float, int]:
    """(step, number of reductions): the largest first * shrink^k that decreases enough; step 0 if none of `most` does."""
    for k in range(most + 1):
        a = first * shrink**k
        if enough(q, a, decrease):
            return a, k
    return 0.0, most


def backtracking_direct(loss_at: Callable[[float], float], slope: float, first: float = FIRST, shrink: float = SHRINK, decrease: float = DECREASE, most: int = 1000) -> tuple[float, int]:
    start = loss_at(0.0)
    for k in range(most + 1):
        a = first * shrink**k
        if loss_at(a) - start <= a * decrease * slope:
            return a, k
    return 0.0, most


def backtracking_columns(c: Sequence[Column], first: float = FIRST, shrink: float = SHRINK, decrease: float = DECREASE, most: int = 400) -> Column:
    """The number of reductions as a column expression over coefficient columns; null if none of `most` is enough."""
    steps = F.sequence(F.lit(0), F.lit(most))
    a = lambda k: F.lit(first) * F.pow(F.lit(shrink), k)
    return F.array_min(F.filter(steps, lambda k: c[2] * a(k) + c[3] * a(k) * a(k) + c[4] * a(k) * a(k) * a(k) <= (decrease - 1) * c[1]))


def line_steps(coefficients: DataFrame, first: float = FIRST, shrink: float = SHRINK, most: int = 400) -> DataFrame:
    """A table of all trial steps with the quartic's value there."""
    steps = coefficients.select("*", F.explode(F.sequence(F.lit(0), F.lit(most))).alias("k")).withColumn("alpha", F.lit(first) * F.pow(F.lit(shrink), "k"))
    value = F.col("c0")
    for n in range(1, 5):
        value = value + F.col(f"c{n}") * F.pow("alpha", F.lit(n))
    return steps.select("k", "alpha", value.alias("q"))


def exact(q: Quartic, pick: str = "global") -> float:
    """The lowest of the positive stationary points, or the first minimum; 0 if the quartic does not fall."""
    coefficients = np.array([4 * q.c[4], 3 * q.c[3], 2 * q.c[2], q.c[1]])
    lead = int(np.argmax(np.abs(coefficients) > 0)) if np.any(coefficients) else 3
    found = np.roots(coefficients[lead:])
    real = sorted(float(z.real) for z in found if abs(z.imag) < 1e-9 * max(1.0, abs(z)) and z.real > 0)
    lower = [a for a in real if q.gain(a) < 0]
    if not lower:
        return 0.0
    return lower[0] if pick == "first" else min(lower, key=q.gain)


def plain_step(q: Quartic, most: int = 60) -> float:
    """1, halved until the quartic is lower there than at 0; 0 if it never is."""
    return next((0.5**k for k in range(most) if q.gain(0.5**k) < 0), 0.0)


def _cubic_min(a, fa, ga, b, fb, gb) -> float:
    """Minimiser of the cubic through two values and slopes."""
    d = ga + gb - 3 * (fa - fb) / (a - b)
    root = d * d - ga * gb
    if root < 0:
        return (a + b) / 2
    root = math.copysign(math.sqrt(root), b - a)
    below = gb - ga + 2 * root
    return b - (b - a) * (gb + root - d) / below if below else (a + b) / 2


def more_thuente(phi: Callable[[float], float], slope: Callable[[float], float], first: float = 1.0, ftol: float = 1e-4, gtol: float = 1e-2, most: int = 20, low: float = 0.0, high: float = 1e10) -> tuple[float, int]:
    """(step, evaluations) that meet sufficient decrease and the strong curvature condition, by safeguarded
    cubic and quadratic interpolation in a shrinking interval; the best step so far if `most` trials do not."""
    f0, g0 = phi(0.0), slope(0.0)
    if g0 >= 0:
        return 0.0, 1
    best, fbest, gbest = 0.0, f0, g0
    far, ffar, gfar = 0.0, f0, g0
    bracketed, first_stage, step = False, True, first
    width, before = high - low, 2 * (high - low)
    for k in range(1, most + 1):
        left, right = (min(best, far), max(best, far)) if bracketed else (best, step + 4 * (step - best))
        step = min(max(step, low), high)
        f, g = phi(step), slope(step)
        goal = f0 + ftol * step * g0
        if f <= goal and abs(g) <= gtol * abs(g0):
            return step, k
        if bracketed and (right - left) <= 1e-12 * max(1.0, right):
            break
        if first_stage and f <= goal and g >= min(ftol, gtol) * g0:
            first_stage = False
        shift = ftol * g0 if first_stage and f <= fbest and f > goal else 0.0
        fx, gx, fy, gy, ft, gt = fbest - best * shift, gbest - shift, ffar - far * shift, gfar - shift, f - step * shift, g - shift
        if ft > fx:
            cubic = _cubic_min(best, fx, gx, step, ft, gt)
            quad = best + gx / ((fx - ft) / (step - best) + gx) / 2 * (step - best)
            new = cubic if abs(cubic - best) < abs(quad - best) else cubic + (quad - cubic) / 2
            bracketed, bound = True, True
        elif gt * gx < 0:
            cubic = _cubic_min(best, fx, gx, step, ft, gt)
            secant = step + gt / (gt - gx) * (best - step)
            new = cubic if abs(cubic - step) > abs(secant - step) else secant
            bracketed, bound = True, False
        elif abs(gt) < abs(gx):
            cubic = _cubic_min(best, fx, gx, step, ft, gt)
            secant = step + gt / (gt - gx) * (best - step)
            if (cubic - step) * (step - best) <= 0:
                cubic = right if step > best else left
            near = abs(cubic - step) < abs(secant - step)
            new = cubic if near == bracketed else secant
            bound = True
        else:
            new = _cubic_min(step, ft, gt, far, fy, gy) if bracketed else (right if step > best else left)
            bound = False
        if ft > fx:
            far, ffar, gfar = step, f, g
        else:
            if gt * gx < 0:
                far, ffar, gfar = best, fbest, gbest
            best, fbest, gbest = step, f, g
        new = min(max(new, left), right) if not bracketed else new
        if bracketed and bound:
            edge = best + 0.66 * (far - best)
            new = min(edge, new) if far > best else max(edge, new)
        if bracketed:
            if abs(far - best) >= 0.66 * before:
                new = best + (far - best) / 2
            before, width = width, abs(far - best)
        step = new
    return best, most
