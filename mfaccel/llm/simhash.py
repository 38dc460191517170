"""SimHash fingerprints and near-duplicate classes by vantage-point trees.

A fingerprint bit is the strict majority over the XXH64 hashes (seed 42) of all word shingles. Distinct
fingerprints are searched, never documents, so a group of equal texts is one point. A tree of vantage
points, built from a bounded sample, cuts Hamming space into shards at median distances. Each fingerprint
lives in one shard, and its ball of radius `bits` may reach others by the triangle inequality; of two such shards one sends its
points to the other. In a shard a second tree finds the exact links. A shard gives a spanning forest of its links, not
all pairs, and star contraction joins the forests of all shards. No fingerprints or links reach the driver.

Cost: a level of the tree discards about a sixth of the candidates at 4 bits of 64, so work grows as about
n^1.75 for n distinct fingerprints; that is the method's, not the layout's.

Words: ASCII letters are lower-cased; space and tab to carriage return separate. Fewer words than a shingle
make one shingle; no word (null, empty) gives fingerprint zero, linked like any other.

Edge cases: repeated rows share a fingerprint and a component; a row without id takes the component of
its fingerprint if a row with id has it, else null, and links nothing; ids that are no whole numbers fail the query; empty tables
give no rows; other columns are ignored. Which documents stay, at the similarity that a corpus needs, is for `near_copies`.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mfaccel.llm.common import cut, first_by_hash, map_batches, raw, slices

SHINGLE, BITS, SEED = 4, 4, 42
#: Fingerprints in a shard, least and most rows of the sample that the shard tree is built from (four a shard between them), and points in a
#: leaf of a shard's own tree. Above MOST / 4 shards, a billion fingerprints, shards grow.
SHARD, SAMPLE, MOST, LEAF = 4096, 16384, 1 << 20, 128


def shingle_hashes(text: bytes | None, size: int) -> np.ndarray:
    """XXH64 of every shingle, with repeats."""
    words = text.lower().split() if text else []
    if not words:
        return np.zeros(0, np.uint64)
    joined = b" ".join(words)
    edges = np.zeros(len(words) + 1, np.int64)
    np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1, out=edges[1:])
    n, digest = max(1, len(words) - size + 1), xxhash.xxh64_intdigest
    spans = zip(edges[:n].tolist(), (edges[min(size, len(words)) :] - 1).tolist(), strict=True)
    return np.fromiter((digest(joined[a:b], SEED) for a, b in spans), np.uint64, n)


def majority(hashes: np.ndarray) -> int:
    votes = np.zeros(64, np.int64)
    for k in range(0, len(hashes), 1 << 16):
        votes += np.unpackbits(hashes[k : k + (1 << 16)].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * votes > len(hashes), bitorder="little").view("<u8")[0])


def fingerprint(text: bytes | None, shingle: int = SHINGLE) -> int:
    hashes = shingle_hashes(text, shingle)
    return majority(hashes) if len(hashes) else 0


def fingerprints(docs: DataFrame, *, doc_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """(id bigint, fp bigint), one row per document."""

    def make():
        def work(batch):
            for part in slices(batch, 1):
                found = np.array([fingerprint(t, shingle) for t in part.column(1).to_pylist()], np.uint64)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(found.view(np.int64))], ["id", "fp"])

        return work

    return map_batches(docs.select(F.col(doc_col).cast("long").alias("id"), raw(text_col).alias("text")), make, "id bigint, fp bigint")


def _apart(a: np.ndarray, b) -> np.ndarray:
    return np.bitwise_count(a ^ b).astype(np.int16)


def _split(points: np.ndarray, turn: int) -> tuple[np.uint64, int, np.ndarray] | None:
    """A vantage point, its median distance, and which points are inside; None if no trial splits them."""
    best = None
    for k in range(4):
        vantage = points[(turn * 7919 + k * 104729) % len(points)]
        away = _apart(points, vantage)
        for at in {int(np.median(away)), int(np.median(away)) - 1}:
            uneven = abs(2 * int((away <= at).sum()) - len(points))
            if uneven < len(points) and (best is None or uneven < best[0]):
                best = uneven, vantage, at, away <= at
    return best and best[1:]


class ShardTree:
    """Cuts the space into numbered shards; built once from a sample on the driver."""

    def __init__(self, sample: np.ndarray, shards: int, bits: int):
        self.bits, self.count = bits, 0
        self.root = self._grow(sample, shards, 0)

    def _grow(self, points: np.ndarray, shards: int, depth: int):
        cut_at = _split(points, depth) if shards > 1 and len(points) > 1 else None
        if cut_at is None:
            self.count += 1
            return self.count - 1
        vantage, at, inside = cut_at
        return vantage, at, self._grow(points[inside], shards // 2, depth + 1), self._grow(points[~inside], shards - shards // 2, depth + 1)

    def route(self, points: np.ndarray):
        """(shard, points that live there, points that only visit) for every shard that any of them reach."""
        home, visits, todo = np.zeros(len(points), np.int32), [], [(self.root, np.arange(len(points)), np.ones(len(points), bool))]
        while todo:
            node, who, lives = todo.pop()
            if not isinstance(node, tuple):
                home[who[lives]] = node
                visits.append((node, who, lives))
                continue
            vantage, at, near, far = node
            away = _apart(points[who], vantage)
            for child, reach, own in ((near, away - self.bits <= at, away <= at), (far, away + self.bits > at, away > at)):
                if reach.any():
                    todo.append((child, who[reach], (lives & own)[reach]))
        for node, who, lives in visits:
            # Of two shards, one sends its points to the other: the lower or the higher one, by the parity of their numbers.
            sends = ((home[who] ^ node) & 1) == (home[who] > node)
            yield node, points[who[lives]], points[who[~lives & sends]]


class LinkFinder:
    """The points of one shard in a vantage-point tree, and a forest of their links."""

    def __init__(self, points: np.ndarray, bits: int):
        self.points, self.bits, self.root = points, bits, np.arange(len(points))
        self.tree = self._grow(np.arange(len(points)), 0)
        for _, owns, leaf, hits in self._reached(points):
            own, theirs = self.root[owns], np.broadcast_to(self.root[leaf], hits.shape)
            low = np.where(hits, theirs, len(points)).min(axis=1)
            high = np.where(hits, theirs, -1).max(axis=1)
            for k in np.flatnonzero((low != own) | (high != own)):
                roots = self._linked_roots(leaf[hits[k]], owns[k])
                if len(roots):
                    self._unite(np.append(roots, self.root[owns[k]]))

    def _grow(self, which: np.ndarray, depth: int):
        cut_at = _split(self.points[which], depth) if len(which) > LEAF else None
        if cut_at is None:
            return which
        vantage, at, inside = cut_at
        return vantage, at, self._grow(which[inside], depth + 1), self._grow(which[~inside], depth + 1)

    def _reached(self, queries: np.ndarray):
        """(block of queries, its positions, points of a leaf, which are linked) where any link exists."""
        todo = [(self.tree, np.arange(len(queries)))]
        while todo:
            node, who = todo.pop()
            if isinstance(node, tuple):
                vantage, at, near, far = node
                away = _apart(queries[who], vantage)
                todo += [(c, who[m]) for c, m in ((near, away - self.bits <= at), (far, away + self.bits > at)) if m.any()]
                continue
            for k in range(0, len(who), 2048):
                part = who[k : k + 2048]
                hits = np.bitwise_count(queries[part][:, None] ^ self.points[node]) <= self.bits
                some = hits.any(axis=1)
                if some.any():
                    yield queries, part[some], node, hits[some]

    def _linked_roots(self, candidates: np.ndarray, own: int) -> np.ndarray:
        """Classes of points that are linked to an own one."""
        return np.unique(self.root[candidates])

    def _unite(self, roots: np.ndarray) -> None:
        roots = np.unique(roots)
        if len(roots) > 1:
            self.root[np.isin(self.root, roots[1:])] = roots[0]

    def forest(self) -> tuple[np.ndarray, np.ndarray]:
        own = np.flatnonzero(self.root != np.arange(len(self.points)))
        return self.points[own], self.points[self.root[own]]

    def visit(self, guests: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Links of guests, one to each class that they touch; touched classes become one."""
        left, right = [], []
        for _, owns, leaf, hits in self._reached(guests):
            for k, own in enumerate(owns):
                roots = np.unique(self.root[leaf[hits[k]]])
                left += [guests[own]] * len(roots)
                right += [self.points[r] for r in roots]
                self._unite(roots)
        return np.array(left, np.uint64), np.array(right, np.uint64)


def _edges(left: np.ndarray, right: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x.view(np.int64), pa.int64()) for x in (left, right)], ["a", "b"])


def links(points: DataFrame, *, bits: int = BITS, shard: int = SHARD, sample: int = SAMPLE) -> DataFrame:
    """(a, b): pairs of distinct fingerprints `fp` of one class that span it; a class is what links of `bits` or fewer
    differing bits connect."""
    spark = points.sparkSession
    count = points.count()
    shards = max(1, -(-count // shard))
    sample = min(max(sample, 4 * shards), MOST)
    drawn = first_by_hash(points.select("fp"), "fp", sample, count).toPandas()
    first = drawn.fp.to_numpy(np.int64).view(np.uint64)
    tree = spark.sparkContext.broadcast(ShardTree(first, min(shards, sample // 4), bits))

    def send(batches):
        def packed(held):
            for node, own, guests in tree.value.route(np.concatenate(held)):
                rows = [(node, g, x.tobytes()) for g, x in ((False, own), (True, guests)) if len(x)]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.bool_(), pa.binary()), strict=True)], ["shard", "guest", "fps"])

        held: list[np.ndarray] = []
        for batch in batches:
            held.append(batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64))
            if sum(map(len, held)) >= 1 << 18:
                yield from packed(held)
                held = []
        if held:
            yield from packed(held)

    def search(batches):
        at, own, finder = None, [], None
        for batch in batches:
            for node, guest, packed in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if node != at:
                    if own and finder is None:
                        yield _edges(*LinkFinder(np.concatenate(own), bits).forest())
                    at, own, finder = node, [], None
                if not guest:
                    own.append(np.frombuffer(packed, np.uint64))
                elif own:
                    if finder is None:
                        finder = LinkFinder(np.concatenate(own), bits)
                        yield _edges(*finder.forest())
                    yield _edges(*finder.visit(np.frombuffer(packed, np.uint64)))
        if own and finder is None:
            yield _edges(*LinkFinder(np.concatenate(own), bits).forest())

    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    sent = points.select("fp").mapInArrow(send, "shard int, guest boolean, fps binary")
    return sent.repartition(parts, "shard").sortWithinPartitions("shard", "guest").mapInArrow(search, "a bigint, b bigint")


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, root): every node of the edges (a, b) with the least node that it is connected to, by alternating
    large-star and small-star contraction; a few numbers a round reach the driver."""

    def tidy(df):
        return df.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()

    def state(df):
        return df.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()

    def to_least(both):
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        return both.join(least, "a")

    edges = cut(tidy(edges))
    before = state(edges)
    for _ in range(rounds):
        if not before[0]:
            break
        both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        large = to_least(both).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        down = tidy(large)
        small = to_least(down).select(F.explode(F.array("a", "b")).alias("a"), F.col("m").alias("b"))
        edges = cut(tidy(small))
        after = state(edges)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError(f"not contracted after {rounds} rounds")
    return edges.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("root")).unionByName(edges.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())


def near_duplicates(docs: DataFrame, *, doc_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, bits: int = BITS) -> DataFrame:
    """(id, fp, component): every document with its fingerprint and the least id of its class."""
    fps = cut(fingerprints(docs, doc_col=doc_col, text_col=text_col, shingle=shingle))
    points = cut(fps.where("id IS NOT NULL").groupBy("fp").agg(F.min("id").alias("least")))
    classes = cut(components(links(points, bits=bits)))
    joined = points.join(classes.withColumnRenamed("node", "fp"), "fp", "left")
    shared = joined.where("root IS NOT NULL").groupBy("root").agg(F.min("least").alias("own"))
    labels = joined.join(shared, "root", "left").select("fp", F.coalesce("own", "least").alias("component"))
    return fps.join(labels, "fp", "left").select("id", "fp", "component")
