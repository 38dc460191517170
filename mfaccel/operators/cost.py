"""Work and communication by formula, for an iteration and for its parts."""

from __future__ import annotations


def solve_flops(n_entities: int, nnz: int, rank: int) -> float:
    """A half-step: Gram matrices of all ratings, then one factorisation and two triangular solves an entity."""
    return nnz * rank * (rank + 3) + n_entities * (rank**3 / 3 + 2 * rank**2)


def gradient_flops(n_entities: int, nnz: int, rank: int) -> float:
    """One side of the gradient: a dot product and a scaled sum a rating; the ridge an entity."""
    return 4 * nnz * rank + 2 * n_entities * rank


def search_flops(nnz: int, rank: int) -> float:
    return 10 * nnz * rank


def routed_vectors(pairs_users: int, pairs_items: int, schedule: str) -> int:
    """Vectors sent in an iteration; pairs are (entity, block) routes."""
    return {
        "als": pairs_items + pairs_users,
        "paper": 4 * pairs_items + 2 * pairs_users,
        "fused": 2 * pairs_items + 2 * pairs_users,
    }[schedule]


def passes(schedule: str) -> int:
    """Passes over the ratings in an iteration."""
    return {"als": 2, "paper": 5, "fused": 3}[schedule]
