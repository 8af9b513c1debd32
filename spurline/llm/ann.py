"""Approximate nearest neighbours by collision counting.

Each block of vectors has one sorted array for each random projection, built once and written. A query opens a window around its
own projection in each array and widens all windows together by virtual rehashing: only newly covered entries are counted. A
vector that lies in enough windows is verified with its exact distance. Widening ends once the k-th verified distance is within
the radius that the windows stand for.

Projections are the axes of random rotations, so that the counts of one vector vary less than those of independent directions
do; the collision threshold is set by a simulation of that very set of directions.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spurline.runtime import materialise

#: Rows of a block, which is what one set of sorted arrays covers (at most 65,536: places are 16 bits); bytes of queries that
#: are broadcast at a time; queries that are widened together.
BLOCK, QUERY_BYTES, TOGETHER = 16_384, 32 << 20, 128


def rotations(dim: int, projections: int, seed: int) -> np.ndarray:
    """``projections`` unit directions: the axes of as many random rotations as are needed."""
    rng = np.random.default_rng(seed)
    return np.concatenate([np.linalg.qr(rng.normal(size=(dim, dim)))[0] for _ in range(-(-projections // dim))], axis=1)[:, :projections]


def collision_threshold(directions: np.ndarray, half: float, miss: float, seed: int = 5, tries: int = 4_000) -> int:
    """The number of windows that a vector at exactly the radius lies in with probability 1 - ``miss``; ``half`` windows' half
    width for radius 1, in units of a direction's usual share of a length. Simulated with random vectors of length 1."""
    z = np.random.default_rng(seed).normal(size=(tries, len(directions)))
    z /= np.linalg.norm(z, axis=1)[:, None]
    counts = np.sort((np.abs(z @ directions) <= half / math.sqrt(len(directions))).sum(1))
    return max(1, int(counts[int(miss * tries)]))


class CollisionIndex:
    """Sorted projections of one block: ``order`` has the places of its vectors by projection, ``sorted`` the values."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, directions: np.ndarray, order: np.ndarray | None = None):
        self.ids, self.x, self.directions = ids, x, directions
        p = (x @ directions).T
        self.order = np.argsort(p, axis=1, kind="stable").astype(np.uint16) if order is None else order
        self.sorted = np.take_along_axis(p, self.order.astype(np.int64), axis=1)

    def search(self, own: np.ndarray, q: np.ndarray, k: int, half: float, needed: int, growth: float) -> list[tuple[np.ndarray, np.ndarray, int]]:
        """For each query (row of ``q``; ``own`` its id, which is left out): ids and distances of the k nearest found, nearest first,
        ties to the smaller id, and how many vectors were verified."""
        out = []
        for at in range(0, len(q), TOGETHER):
            out += self._search(own[at : at + TOGETHER], q[at : at + TOGETHER], k, half / math.sqrt(q.shape[1]), needed, growth)
        return out

    def _search(self, own, q, k, half, needed, growth):
        m, n = self.sorted.shape
        at = q @ self.directions
        low = np.stack([np.searchsorted(s, at[:, i]) for i, s in enumerate(self.sorted)], 1)
        high = low.copy()
        state = [_Query(self, int(o), v, k) for o, v in zip(own, q, strict=True)]
        radius = np.full(len(q), self._start(half))
        live = np.array([i for i, s in enumerate(state) if s.want], np.int64)
        while len(live):
            reach = half * radius[live]
            new_low = np.stack([np.searchsorted(s, at[live, i] - reach, "left") for i, s in enumerate(self.sorted)], 1)
            new_high = np.stack([np.searchsorted(s, at[live, i] + reach, "right") for i, s in enumerate(self.sorted)], 1)
            new_low, new_high = np.minimum(new_low, low[live]), np.maximum(new_high, high[live])
            going = []
            for j, i in enumerate(live):
                s = state[i]
                s.widen(self.order, new_low[j], low[i], high[i], new_high[j], needed)
                if s.done(radius[i], (new_low[j] == 0).all() and (new_high[j] == n).all()):
                    continue
                going.append(i)
                # Slowly once something is found, and never past the k-th distance of what is found.
                grown = radius[i] * (growth if len(s.found_d) else growth**4)
                radius[i] = min(grown, s.found_d[-1]) if len(s.found_d) >= s.want else grown
            low[live], high[live] = new_low, new_high
            live = np.array(going, np.int64)
        return [(s.found_i, s.found_d, s.verified) for s in state]

    def _start(self, half: float) -> float:
        """A first radius, below which next to nothing is found: half the usual distance of two vectors, or the least gap that shows."""
        spread = float(self.sorted.std(axis=1).mean()) * math.sqrt(2 * self.x.shape[1])
        return max(0.5 * spread, 1e-12 * float(np.abs(self.sorted).max(initial=0)) / half, 1e-300)


class _Query:
    """What is known of one query in one block."""

    def __init__(self, index: CollisionIndex, own: int, q: np.ndarray, k: int):
        self.index, self.q, self.k = index, q, k
        self.counts, self.seen = np.zeros(len(index.ids), np.int64), index.ids == own
        self.want, self.verified = min(k, int((~self.seen).sum())), 0
        self.found_i, self.found_d = np.empty(0, np.int64), np.empty(0)

    def widen(self, order: np.ndarray, low: np.ndarray, old_low: np.ndarray, old_high: np.ndarray, high: np.ndarray, needed: int) -> None:
        """Count the entries that the windows newly cover, and verify what has enough of them."""
        size = np.concatenate([old_low - low, high - old_high])
        total = int(size.sum())
        if not total:
            return
        rows = len(self.counts) * np.arange(len(order))
        first = np.concatenate([rows + low, rows + old_high])  # of each newly covered range, in the arrays laid end to end
        place = np.repeat((first - np.cumsum(size) + size).astype(np.int32), size) + np.arange(total, dtype=np.int32)
        touched = order.reshape(-1)[place]
        if 8 * total < len(self.counts):
            np.add.at(self.counts, touched, 1)
            touched = np.unique(touched[(self.counts[touched] >= needed) & ~self.seen[touched]])
        else:
            self.counts += np.bincount(touched, minlength=len(self.counts))
            touched = np.flatnonzero((self.counts >= needed) & ~self.seen)
        if len(touched):
            self._verify(touched)

    def _verify(self, new: np.ndarray) -> None:
        self.seen[new] = True
        self.verified += len(new)
        d = np.sqrt(((self.index.x[new] - self.q) ** 2).sum(1))
        ids, d = np.concatenate([self.found_i, self.index.ids[new]]), np.concatenate([self.found_d, d])
        best = np.lexsort((ids, d))[: self.k]
        self.found_i, self.found_d = ids[best], d[best]

    def done(self, radius: float, covered: bool) -> bool:
        """Whether the radius has reached the k-th distance; with all entries covered, what is left is verified."""
        if len(self.found_d) >= self.want and self.found_d[-1] <= radius:
            return True
        if covered and not self.seen.all():
            self._verify(np.flatnonzero(~self.seen))
        return covered


def usable(vectors: DataFrame, dim: int, id_col: str, vector_col: str) -> DataFrame:
    """``(vec_id, v)`` with ``v`` as doubles; without null ids, and vectors that are null, zero, of another length, or hold null or non-finite numbers."""
    v = F.col(vector_col).cast("array<double>")
    fine = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    return vectors.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull() & (F.size("v") == dim) & F.coalesce(fine, F.lit(False)))


def _matrix(batch: pa.RecordBatch, dim: int) -> tuple[np.ndarray, np.ndarray]:
    return batch.column(0).to_numpy(), batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)


def build_index(vectors: DataFrame, dim: int, projections: int = 192, seed: int = 3, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """``(ids, x, places)``, a row for each block of up to BLOCK vectors, written to the shared folder: ids, vectors as doubles, and
    the vectors' places in each sorted array (16 bits each). Vectors stay in their partitions; nothing is shuffled."""
    directions = rotations(dim, projections, seed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        for batch in batches:
            for at in range(0, batch.num_rows, BLOCK):
                held.append(_matrix(batch.slice(at, BLOCK), dim))
                while sum(len(h[0]) for h in held) >= BLOCK:
                    ids, x = (np.concatenate([h[i] for h in held]) for i in (0, 1))
                    yield packed(ids[:BLOCK], x[:BLOCK])
                    held = [(ids[BLOCK:], x[BLOCK:])]
        if sum(len(h[0]) for h in held):
            yield packed(*(np.concatenate([h[i] for h in held]) for i in (0, 1)))

    def packed(ids: np.ndarray, x: np.ndarray) -> pa.RecordBatch:
        order = CollisionIndex(ids, x, directions).order
        return pa.RecordBatch.from_arrays([pa.array([a.tobytes()], pa.binary()) for a in (ids.astype("<i8"), x.astype("<f8"), order.astype("<u2"))], names=["ids", "x", "places"])

    return materialise(usable(vectors, dim, id_col, vector_col).mapInArrow(run, "ids binary, x binary, places binary"), "ann-index")


def nearest(vectors: DataFrame, queries: DataFrame, dim: int, k: int = 10, projections: int = 192, half: float = 1.2, miss: float = 0.05, growth: float = 1.03, seed: int = 3, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """``(query_id, rank, vec_id, score, verified)``: for each query its k nearest in ``vectors`` other than itself, by Euclidean
    distance, and how many vectors were verified for it in all.

    ``half``: half a window's width for radius 1, in units of a direction's usual share of a length. A vector at exactly the radius
    lies in fewer windows than the collision threshold with probability ``miss`` at most.
    As every block stops only at its own k-th distance, which is larger than that of all, the recall over all is higher than
    1 - miss. Repeated query ids are searched once. Ties go to the smaller id; repeated rows of a vector are found as often
    as they stand there. Fewer candidates than k: all of them.

    The index is built once. Queries are written once, in chunks of a bounded size, and each chunk is sent to all blocks.
    """
    directions = rotations(dim, projections, seed)
    needed = collision_threshold(directions, half, miss)
    spark = vectors.sparkSession
    index = build_index(vectors, dim, projections, seed, id_col, vector_col)
    asked = materialise(usable(queries, dim, id_col, vector_col).groupBy("vec_id").agg(F.min("v").alias("v")), "ann-queries")
    chunks = -(-asked.count() * (dim + 1) * 8 // QUERY_BYTES) or 1
    parts = []
    for c in range(chunks):
        rows = asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(chunks)) == c).collect() if chunks > 1 else asked.collect()
        sent = spark.sparkContext.broadcast((np.array([r.vec_id for r in rows], np.int64), np.array([r.v for r in rows]).reshape(-1, dim)))

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in range(batch.num_rows):
                    ids, x, places = (np.frombuffer(batch.column(i)[row].as_buffer(), t) for i, t in enumerate(("<i8", "<f8", "<u2")))
                    yield search(CollisionIndex(ids, x.reshape(-1, dim), directions, places.reshape(projections, -1)), *sent.value)

        def search(block: CollisionIndex, own: np.ndarray, q: np.ndarray) -> pa.RecordBatch:
            got = block.search(own, q, k, half, needed, growth) if len(own) else []
            size = [len(i) for i, _, _ in got]
            # The verified vectors of a block are counted with its first row.
            verified = np.zeros(sum(size), np.int64)
            verified[np.cumsum([0, *size[:-1]])[np.array(size, bool)] if got else []] = [v for (_, _, v), s in zip(got, size, strict=True) if s]
            flat = [np.repeat(own, size), *(np.concatenate([g[j] for g in got]) if got else np.empty(0, t) for j, t in ((0, np.int64), (1, float))), verified]
            return pa.RecordBatch.from_arrays([pa.array(x) for x in flat], names=["query_id", "vec_id", "score", "seen"])

        found = index.mapInArrow(run, "query_id long, vec_id long, score double, seen long")
        whole = Window.partitionBy("query_id")
        best = found.withColumn("verified", F.sum("seen").over(whole)).withColumn("rank", F.row_number().over(whole.orderBy("score", "vec_id"))).where(F.col("rank") <= k)
        best = best.select("query_id", "rank", "vec_id", "score", "verified")
        if chunks > 1:
            best = materialise(best, "neighbours")
            sent.unpersist()
        parts.append(best)
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def brute_force(vectors: list[tuple[int, list[float] | None]], query_ids: set[int], k: int = 10) -> list[tuple[int, int, int, float]]:
    """The exact answer for small inputs, by which recall is measured."""
    rows = [(i, np.array(v, float)) for i, v in vectors if v is not None and all(x is not None and math.isfinite(x) for x in v) and any(v)]
    out = []
    for own, q in sorted((i, v) for i, v in rows if i in query_ids):
        near = sorted((float(np.sqrt(((v - q) ** 2).sum())), i) for i, v in rows if i != own)[:k]
        out += [(own, r, i, d) for r, (d, i) in enumerate(near, 1)]
    return out
