"""What a block computes from its ratings and the vectors that were sent to it. Plain numpy, one block at a time."""

from __future__ import annotations

import numpy as np


#: Doubles that a batch of entities may gather at a time.
BATCH = 1 << 22
#: Doubles of Gram matrices that are solved as one stack, and doubles that sums over cells gather at a time (few enough to stay in a CPU's cache and in
#: memory that is used again).
STACK, PIECE = 1 << 18, 1 << 16


class BlockCells:
    """Ratings of a block, sorted by own entity, with positions in the sorted ids of both sides. With `keep` the places of the batches are
    made once, for callers that go over them again and again."""

    def __init__(self, own: np.ndarray, other: np.ndarray, rating: np.ndarray, own_ids: np.ndarray, other_ids: np.ndarray, keep: bool = False):
        order = np.argsort(own, kind="stable")
        self.rating = rating[order].astype(np.float64)
        self.own, self.other = np.searchsorted(own_ids, own[order]), np.searchsorted(other_ids, other[order])
        self.edges = np.searchsorted(self.own, np.arange(len(own_ids) + 1))
        self.counts = np.diff(self.edges)
        self.keep, self._kept = keep, {}

    def batches(self, rank: int):
        """(own entities, cells of each as a rectangle): entities of one count together, so that sums over their cells are one product."""
        if not self.keep:
            return self._batches(rank)
        if rank not in self._kept:
            self._kept = {rank: list(self._batches(rank))}
        return iter(self._kept[rank])

    def _batches(self, rank: int):
        order = np.argsort(self.counts, kind="stable")
        turns = np.flatnonzero(np.diff(self.counts[order], prepend=-1, append=-1))
        for a, b in zip(turns, turns[1:], strict=False):
            n = int(self.counts[order[a]])
            step = max(1, BATCH // max(1, n * rank, rank * rank))
            for k in range(a, b, step):
                who = order[k : min(b, k + step)]
                yield who, self.edges[who][:, None] + np.arange(n)


def normal_equations(cells: BlockCells, others: np.ndarray):
    """(own entities, Gram matrices, right-hand sides) in batches."""
    f = others.shape[1]
    for who, at in cells.batches(f):
        m = others[cells.other[at]]
        yield who, np.matmul(m.transpose(0, 2, 1), m), np.matmul(cells.rating[at][:, None, :], m)[:, 0]


def stacks(cells: BlockCells, others: np.ndarray):
    """normal_equations() with batches put together as far as a stack goes: small ones cost less in one call than in many."""
    held, size = [], 0
    for one in normal_equations(cells, others):
        held.append(one)
        size += one[1].size
        if size >= STACK:
            yield held[0] if len(held) == 1 else tuple(np.concatenate(x) for x in zip(*held, strict=True))
            held, size = [], 0
    if held:
        yield held[0] if len(held) == 1 else tuple(np.concatenate(x) for x in zip(*held, strict=True))


def solve(cells: BlockCells, others: np.ndarray, ridge: np.ndarray, nonnegative: bool = False) -> np.ndarray:
    """Each own entity's exact minimiser, with its own ridge; a singular system (no ridge) takes the shortest solution."""
    out = np.zeros((len(cells.counts), others.shape[1]))
    for who, a, v in stacks(cells, others):
        out[who] = solve_systems(a, v, ridge[who], nonnegative)
    return out


def solve_and_look(cells: BlockCells, own: np.ndarray, others: np.ndarray, ridge: np.ndarray, nonnegative: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """The minimisers, and the gradient at `own`, which the same normal equations give."""
    out, g = np.zeros_like(own), np.zeros_like(own)
    for who, a, v in stacks(cells, others):
        x = own[who]
        g[who] = 2 * (np.matmul(a, x[..., None])[..., 0] + ridge[who][:, None] * x - v)
        out[who] = solve_systems(a, v, ridge[who], nonnegative)
    return out, g


def solve_systems(a: np.ndarray, v: np.ndarray, ridge: np.ndarray, nonnegative: bool = False) -> np.ndarray:
    f = a.shape[1]
    a = a.copy()
    a[:, np.arange(f), np.arange(f)] += ridge[:, None]
    try:
        out = _by_cholesky(a, v)
    except np.linalg.LinAlgError:
        out = np.stack([np.linalg.lstsq(x, y, rcond=None)[0] for x, y in zip(a, v, strict=True)])
    if nonnegative:
        some = np.flatnonzero((out < 0).any(axis=1))
        out[some] = nonnegative_solve(a[some], v[some], out[some])
    return out


def _by_cholesky(a: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Stacked positive definite systems: one factor each, then both substitutions over the whole stack."""
    low, x = np.linalg.cholesky(a), v.copy()
    for k in range(v.shape[1]):
        x[:, k] = (x[:, k] - np.einsum("gj,gj->g", low[:, k, :k], x[:, :k])) / low[:, k, k]
    for k in reversed(range(v.shape[1])):
        x[:, k] = (x[:, k] - np.einsum("gj,gj->g", low[:, k + 1 :, k], x[:, k + 1 :])) / low[:, k, k]
    return x


def nonnegative_solve(a: np.ndarray, v: np.ndarray, free: np.ndarray, most: int = 200) -> np.ndarray:
    """min 1/2 xAx - vx with x >= 0 of stacked systems, by coordinate descent from their free minimisers; those that stand still are left alone."""
    out, open_ = np.maximum(free, 0), np.arange(len(v))
    for _ in range(most):
        x = out[open_]
        for k in range(v.shape[1]):
            curve = a[:, k, k]
            step = (np.einsum("gj,gj->g", a[:, k, :], x) - v[:, k]) / np.where(curve > 0, curve, 1.0)
            x[:, k] = np.where(curve > 0, np.maximum(0.0, x[:, k] - step), x[:, k])
        moves = np.abs(x - out[open_]).max(axis=1) >= 1e-12
        out[open_] = x
        if not moves.all():
            open_, a, v = open_[moves], a[moves], v[moves]
        if not len(open_):
            break
    return out


def coordinate_step(cells: BlockCells, own: np.ndarray, others: np.ndarray, ridge: np.ndarray) -> np.ndarray:
    """One pass over the components: each is set to its minimiser while the rest stays."""
    x = own.copy()
    for who, a, v in normal_equations(cells, others):
        x[who] = coordinate_systems(a, v, ridge[who], own[who])
    return x


def coordinate_systems(a: np.ndarray, v: np.ndarray, ridge: np.ndarray, own: np.ndarray) -> np.ndarray:
    y = own.copy()
    for k in range(v.shape[1]):
        curve = a[:, k, k] + ridge
        rest = v[:, k] - np.einsum("gj,gj->g", a[:, k, :], y) + a[:, k, k] * y[:, k]
        y[:, k] = rest / np.where(curve == 0, 1.0, curve)
    return y


def pieces(cells: BlockCells, rank: int):
    """Slices of the cells that a task gathers vectors for at a time."""
    step = max(1, min(PIECE, BATCH) // max(1, rank))
    return [slice(k, k + step) for k in range(0, len(cells.own), step)]


def residual(cells: BlockCells, own: np.ndarray, others: np.ndarray) -> np.ndarray:
    parts = [np.einsum("ij,ij->i", own.take(cells.own[at], axis=0), others.take(cells.other[at], axis=0)) for at in pieces(cells, own.shape[1])]
    return (np.concatenate(parts) if parts else np.zeros(0)) - cells.rating


def sums_by_own(cells: BlockCells, rows: np.ndarray) -> np.ndarray:
    """Sums of rows, one a cell, over the cells of each own entity."""
    out = np.zeros((len(cells.counts), rows.shape[1]))
    some = np.flatnonzero(cells.counts)
    if len(some):
        out[some] = np.add.reduceat(rows, cells.edges[some], axis=0)
    return out


def weighed_sums(cells: BlockCells, weights: np.ndarray, others: np.ndarray) -> np.ndarray:
    """Sums of the other side's vectors, each by the weight of its cell, over the cells of each own entity."""
    out = np.zeros((len(cells.counts), others.shape[1]))
    for who, at in cells.batches(others.shape[1]):
        out[who] = np.matmul(weights[at][:, None, :], others[cells.other[at]])[:, 0]
    return out


def gradient(cells: BlockCells, own: np.ndarray, others: np.ndarray, ridge: np.ndarray) -> np.ndarray:
    return 2 * (weighed_sums(cells, residual(cells, own, others), others) + ridge[:, None] * own)


def loss_sums(cells: BlockCells, own: np.ndarray, others: np.ndarray) -> float:
    return float((residual(cells, own, others) ** 2).sum())


def quartic_sums(cells: BlockCells, own: np.ndarray, own_p: np.ndarray, others: np.ndarray, others_p: np.ndarray, left: np.ndarray | None = None) -> np.ndarray:
    """The five data sums of the loss along (own_p, others_p); `left` are the residuals, if they are known."""
    dot = lambda s, t: np.einsum("ij,ij->i", s, t)
    out, f = np.zeros(5), own.shape[1]
    mine, theirs = np.hstack([own, own_p]), np.hstack([others_p, others])
    for at in pieces(cells, 4 * f):
        xp, qy = mine.take(cells.own[at], axis=0), theirs.take(cells.other[at], axis=0)
        e = left[at] if left is not None else dot(xp[:, :f], qy[:, f:]) - cells.rating[at]
        b, d = dot(xp, qy), dot(xp[:, f:], qy[:, :f])
        out += [e @ e, 2 * e @ b, b @ b + 2 * e @ d, 2 * b @ d, d @ d]
    return out
