"""What a fitted model is used for: predictions, best items and users, similar items, folding in new ratings."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mfaccel.functions.vectors import vdot, vnorm2
from mfaccel.operators.relational import Problem, half_step
from mfaccel.plans.blocks import block_of
from mfaccel.plans.cuts import cut

#: Rows of a block of queries or of the scored side.
BLOCK = 16_384
#: Most tasks that the meetings of blocks are dealt over.
MEETINGS = 4096
#: Scores that a task holds at a time.
CELLS = 1 << 18


def predict(pairs: DataFrame, users: DataFrame, items: DataFrame) -> DataFrame:
    """(user, item, score) of pairs whose user and item the model knows."""
    u = users.select(F.col("id").alias("user"), F.col("x").alias("u"))
    m = items.select(F.col("id").alias("item"), F.col("x").alias("m"))
    return pairs.select("user", "item").join(u, "user").join(m, "item").select("user", "item", vdot("u", "m").alias("score"))


def _meetings(queries: DataFrame, scored: DataFrame, seen: DataFrame | None, block: int, each, schema: str) -> DataFrame:
    """`each` applied where a block of queries meets a block of the scored side: ids and vectors of both, and the seen pairs among them.

    Both sides are cut into blocks of about `block` rows by a hash of their ids. A query goes to as many tasks as the other side has
    blocks and the other way round, a seen pair to the one task that it belongs to; nothing is collected or broadcast. `each` gives
    tables one after another, so a task holds two blocks and one such table, however many pairs a meeting has."""
    sizes = [max(1, -(-df.count() // block)) for df in (queries, scored)]
    own, other = block_of("id", sizes[0]), block_of("id", sizes[1])
    every = [F.explode(F.sequence(F.lit(0), F.lit(n - 1))) for n in sizes]
    no, vector = F.lit(None).cast("bigint"), F.transform("x", lambda v: v.cast("double")).alias("x")
    rows = queries.select(own.alias("q"), every[1].alias("s"), F.lit(0).alias("kind"), "id", no.alias("other"), vector)
    rows = rows.unionByName(scored.select(every[0].alias("q"), other.alias("s"), F.lit(1).alias("kind"), "id", no.alias("other"), vector))
    if seen is not None:
        pair = seen.select(own.alias("q"), block_of("other", sizes[1]).alias("s"), F.lit(2).alias("kind"), "id", "other", F.array().cast("array<double>").alias("x"))
        rows = rows.unionByName(pair)

    def side(parts: list[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray]:
        ids = np.concatenate([p.column(3).to_numpy() for p in parts]) if parts else np.zeros(0, np.int64)
        flat = np.concatenate([p.column(5).flatten().to_numpy(zero_copy_only=False) for p in parts]) if parts else np.zeros(0)
        order = np.argsort(ids, kind="stable")
        return ids[order], flat.reshape(len(ids), -1)[order] if len(ids) else np.zeros((0, 0))

    def met(held: list[list[pa.RecordBatch]]):
        if held[0] and held[1]:
            pairs = [np.concatenate([p.column(c).to_numpy() for p in held[2]]) if held[2] else np.zeros(0, np.int64) for c in (3, 4)]
            yield from each(*side(held[0]), *side(held[1]), *pairs)

    def run(batches):
        at, held = None, [[], [], []]
        for batch in batches:
            if not batch.num_rows:
                continue
            q, s, kind = (batch.column(k).to_numpy() for k in range(3))
            turns = (np.flatnonzero((np.diff(q) != 0) | (np.diff(s) != 0) | (np.diff(kind) != 0)) + 1).tolist()
            for a, b in zip([0, *turns], [*turns, len(q)], strict=True):
                now = int(q[a]), int(s[a])
                if now != at:
                    yield from met(held)
                    at, held = now, [[], [], []]
                held[int(kind[a])].append(batch.slice(a, b - a))
        yield from met(held)

    meetings = sizes[0] * sizes[1]
    parts = min(meetings, MEETINGS)  # one by one: a hash would give some tasks several meetings and others none
    at = F.pmod(F.col("q").cast("bigint") * F.lit(sizes[1]) + F.col("s"), F.lit(parts)).cast("int")
    return rows.repartitionById(parts, at).sortWithinPartitions("q", "s", "kind").mapInArrow(run, schema)


def _scores(ids, x, names, vectors, seen_ids, seen_names, cells: int = CELLS):
    """(ids, scores) of some queries at a time, by ascending name; seen pairs score minus infinity."""
    where = np.searchsorted(ids, seen_ids)
    spot = np.searchsorted(names, seen_names)
    real = (where < len(ids)) & (spot < len(names))
    if len(ids) and len(names):
        real &= (ids[np.minimum(where, len(ids) - 1)] == seen_ids) & (names[np.minimum(spot, len(names) - 1)] == seen_names)
    where, spot = where[real], spot[real]
    order = np.argsort(where, kind="stable")
    where, spot = where[order], spot[order]
    turn = max(1, cells // max(1, len(names)))
    for at in range(0, len(ids) if len(names) else 0, turn):
        scores = x[at : at + turn] @ vectors.T
        mine = slice(*np.searchsorted(where, (at, at + turn)))
        scores[where[mine] - at, spot[mine]] = -np.inf
        yield ids[at : at + turn], scores


def _pairs_batch(ids: np.ndarray, others: np.ndarray, scores: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c) for c in (ids, others, scores)], ["id", "other", "score"])


def _leaves(vectors: np.ndarray, most: int) -> list[np.ndarray]:
    """Positions of vectors in groups of at most `most`, halved along the component that spreads widest."""
    todo, done = [np.arange(len(vectors))], []
    while todo:
        at = todo.pop()
        if len(at) <= most:
            done.append(at)
            continue
        own = vectors[at]
        along = own[:, int(np.argmax(own.max(axis=0) - own.min(axis=0)))]
        order = np.argpartition(along, len(at) // 2)
        todo += [at[order[: len(at) // 2]], at[order[len(at) // 2 :]]]
    return done


def _best(ids, x, names, vectors, seen_ids, seen_names, k: int, group: int = 128, leaf: int = 512):
    """(ids, others, scores) of the k best of each query, ties by name. Near queries go together through groups of near vectors, in the order of
    the most that a query of theirs can score in a group's box; groups in which none can reach its k-th best so far are left out."""
    if not len(ids) or not len(names):
        return
    seen = np.sort(np.searchsorted(ids, seen_ids) * len(names) + np.searchsorted(names, seen_names)) if len(seen_ids) else np.zeros(0, np.int64)
    leaves, place_of = _leaves(vectors, leaf), np.full(len(names), -1)
    low, high = (np.stack([f(vectors[at], axis=0) for at in leaves]) for f in (np.min, np.max))
    slack = 1e-9 * np.abs(vectors).max()
    for mine in _leaves(x, group):
        mine.sort()
        own = x[mine]
        most = np.maximum(own, 0) @ high.T + np.minimum(own, 0) @ low.T + slack * np.abs(own).sum(axis=1)[:, None]
        edges = np.searchsorted(seen, np.stack([mine, mine + 1]) * len(names))
        whose = np.repeat(np.arange(len(mine)), edges[1] - edges[0])
        gone = np.concatenate([seen[a:b] for a, b in edges.T]) % len(names)
        row, col, score = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        least, order, at = np.full(len(mine), -np.inf), np.argsort(-most.max(axis=0), kind="stable"), 0
        while at < len(order):
            todo = order[at : at + 8]
            at += 8
            todo = todo[(most[:, todo] >= least[:, None]).any(axis=0)]
            if not len(todo):
                continue
            spots = np.concatenate([leaves[t] for t in todo])
            scores = own @ vectors[spots].T
            if len(gone):
                place_of[spots] = np.arange(len(spots))
                here = place_of[gone] >= 0
                scores[whose[here], place_of[gone[here]]] = -np.inf
                place_of[spots] = -1
            reach = np.maximum(least, np.partition(scores, -k, axis=1)[:, -k]) if len(spots) > k and np.isneginf(least).any() else least
            r, c = np.nonzero((scores >= reach[:, None]) & (scores > -np.inf))
            value, c = scores[r, c], spots[c]
            row, col, score = np.r_[row, r], np.r_[col, c], np.r_[score, value]
            by = np.lexsort((col, -score, row))
            row, col, score = row[by], col[by], score[by]
            place = np.arange(len(row)) - np.searchsorted(row, row)
            row, col, score, place = row[place < k], col[place < k], score[place < k], place[place < k]
            least[row[place == k - 1]] = score[place == k - 1]
        yield ids[mine[row]], names[col], score


def top_k(queries: DataFrame, scored: DataFrame, k: int, seen: DataFrame | None = None, block: int | None = None) -> DataFrame:
    """(id, other, score, rk): the k best of `scored` for every query by dot product, ties by id; pairs in `seen` (id, other) are left out.
    Each task keeps k a query, and a window over k rows a block merges them. Blocks hold more rows where vectors are short."""
    queries, scored = cut(queries.select("id", "x")), cut(scored.select("id", "x"))  # each is counted, and read for its blocks
    first = scored.select(F.size("x").alias("n")).first() if not block else None
    block = block or min(8 * BLOCK, max(BLOCK, (16 * BLOCK) // max(1, first.n if first else 1)))

    def best(ids, x, names, vectors, seen_ids, seen_names):
        if len(seen_ids):  # seen pairs of other queries or rows than these
            known = np.isin(seen_ids, ids) & np.isin(seen_names, names)
            seen_ids, seen_names = seen_ids[known], seen_names[known]
        for found in _best(ids, x, names, vectors, seen_ids, seen_names, k):
            yield _pairs_batch(*found)

    found = _meetings(queries, scored, seen, block, best, "id bigint, other bigint, score double")
    rank = F.row_number().over(Window.partitionBy("id").orderBy(F.desc("score"), "other"))
    return found.withColumn("rk", rank).where(F.col("rk") <= k)


def _rounded(x: np.ndarray, digits: int) -> np.ndarray:
    """Rounded half away from zero as SQL's round does, without negative zeros; what is not finite, or would not be, stays as it is."""
    with np.errstate(over="ignore", invalid="ignore"):
        size = np.abs(x) * 10.0**digits
        whole = np.floor(size)
        whole += size - whole >= 0.5
        whole /= 10.0**digits
    return np.where(np.isfinite(whole), np.copysign(whole, x), x) + 0.0


def score_all(queries: DataFrame, scored: DataFrame, seen: DataFrame | None = None, block: int = BLOCK // 4, digits: int | None = None) -> DataFrame:
    """(id, other, score) of a stated set of queries against all rows, without the pairs in `seen`: for sets whose whole result is wanted.
    Scores are rounded to `digits` where they are made: Spark's round would make a decimal, by way of a string, of each. Beside seen
    pairs, a score of minus infinity counts as one of them."""

    def every(ids, x, names, vectors, seen_ids, seen_names):
        for own, scores in _scores(ids, x, names, vectors, seen_ids, seen_names):
            at, others = np.repeat(own, len(names)), np.tile(names, len(own))
            scores = scores.ravel()
            if len(seen_ids):
                left = np.flatnonzero(scores != -np.inf)
                at, others, scores = at[left], others[left], scores[left]
            yield _pairs_batch(at, others, scores if digits is None else _rounded(scores, digits))

    return _meetings(queries.select("id", "x"), scored.select("id", "x"), seen, block, every, "id bigint, other bigint, score double")


def recommend_items(users: DataFrame, items: DataFrame, k: int, seen: DataFrame | None = None) -> DataFrame:
    seen = seen and seen.select(F.col("user").alias("id"), F.col("item").alias("other"))
    return top_k(users, items, k, seen).select(F.col("id").alias("user"), F.col("other").alias("item"), "score", "rk")


def recommend_users(users: DataFrame, items: DataFrame, k: int) -> DataFrame:
    return top_k(items, users, k).select(F.col("id").alias("item"), F.col("other").alias("user"), "score", "rk")


def similar_items(items: DataFrame, k: int) -> DataFrame:
    """The k nearest other items by cosine."""
    unit = items.select("id", F.expr("transform(x, v -> v / greatest(sqrt(aggregate(x, 0D, (s, w) -> s + w * w)), 1e-300))").alias("x"))
    return top_k(unit, unit, k + 1).where("id <> other").withColumn("rk", F.row_number().over(Window.partitionBy("id").orderBy(F.desc("score"), "other"))).where(F.col("rk") <= k)


def fold_in(ratings: DataFrame, items: DataFrame, rank: int, lam: float) -> DataFrame:
    """(id, x) of users from their ratings alone, items fixed."""
    return half_step(Problem(ratings, rank, lam), items, "user")


def norms(side: DataFrame) -> DataFrame:
    return side.select("id", F.sqrt(vnorm2("x")).alias("norm"))
