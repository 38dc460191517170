"""The conjugate recurrence: weights of the old direction from dot products, and the guard of a direction.

Every rule is a ratio of dot products of the true gradient g and the preconditioned one z (the point less one sweep from
it), new and old, and of the direction p. `pr_pre` is the rule that reduces to preconditioned linear conjugate
gradients on a quadratic; `pr` is its form without preconditioning.
"""

from __future__ import annotations

from collections.abc import Mapping

#: Names of the dot products, with the pair of vectors that each multiplies (1: new, 0: old).
DOTS = {
    "g1g1": ("g", "g"), "g1g0": ("g", "g0"), "g0g0": ("g0", "g0"),
    "z1g1": ("z", "g"), "z1g0": ("z", "g0"), "z0g0": ("z0", "g0"),
    "z1z1": ("z", "z"), "z1z0": ("z", "z0"), "z0z0": ("z0", "z0"),
    "pg1": ("p", "g"), "pg0": ("p", "g0"), "pz1": ("p", "z"), "pz0": ("p", "z0"), "z1p": ("z", "p"),
}

_RULES = {
    "pr": (("g1g1", "g1g0"), ("g0g0", None)),
    "pr_pre": (("z1g1", "z1g0"), ("z0g0", None)),
    "pr_tilde": (("z1z1", "z1z0"), ("z0z0", None)),
    "fr": (("g1g1", None), ("g0g0", None)),
    "fr_pre": (("z1g1", None), ("z0g0", None)),
    "hs": (("g1g1", "g1g0"), ("pg1", "pg0")),
    "hs_pre": (("z1g1", "z1g0"), ("pg1", "pg0")),
}
RULES = (*_RULES, "pr_plus", "zero")


def beta(rule: str, dots: Mapping[str, float], tiny: float = 1e-300) -> float:
    """The weight of the old direction; 0 where the denominator vanishes."""
    if rule == "zero":
        return 0.0
    top, below = _RULES["pr_pre" if rule == "pr_plus" else rule]
    value = lambda pair: dots[pair[0]] - (dots[pair[1]] if pair[1] else 0.0)
    bottom = value(below)
    out = value(top) / bottom if abs(bottom) > tiny else 0.0
    return max(0.0, out) if rule == "pr_plus" else out
