"""Approximate nearest neighbours by collision counting.

Vectors are projected on single random directions (orthonormal in groups), and each direction keeps its projections as a sorted array. A query
opens a window around its own place in every array; a vector collides with it in as many arrays as it lies in the window of. The
windows grow, the arrays staying as they are (virtual rehashing), and only the entries that newly enter a window are counted. Vectors that
collide often enough are verified: their inner products are computed on the original vectors.

Inner products become distances by one more coordinate, sqrt(M^2 - |x|^2) for a vector, M being the largest norm, and 0 for a query, which
is scaled to norm M. As that tells little of vectors much shorter than M, a block's vectors stand in groups of like norm, the
longest first, each with its own M and arrays; a group is left out when its M times the query's norm can't reach the k-th score found.

Windows stop growing when they are so wide that a vector as good as the k-th found so far would be expected to collide as often as asked but for
``SLACK`` standard deviations: any better one would have been found with high probability. So what is verified follows from the
query's own neighbours, not from a share of the table, and nothing is remembered between queries.

Every row is indexed. Rows are dealt into blocks of bounded size; a task builds the arrays of a block once and then streams all queries through
them, and the best of all blocks are ranked. Scores are in double precision.

Rows: vectors that are null, zero, or hold a null or non-finite component take no part, nor do those whose length isn't that of the most
common one (the longest, if several are). Rows with the query's own id are no candidates. Equal nearness goes to the smaller id. Repeated rows are
candidates each, and queries once. Null ids take no part. Other columns don't matter. An empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window as W

from .common import labelled, spread

K, DIRECTIONS, HALF_WIDTH, SLACK = 20, 64, 2.0, 0.8  # directions at least; window of a distance, in standard deviations of its projections
FIRST, GROWTH, SEEDS = 0.5, 1.6, 4  # first radius as a share of M; growth of windows; vectors verified for a first k-th score, in k
BLOCK_BYTES, LEAST_ROWS, GROUP_ROWS, SEED = 16 << 20, 16_384, 4_096, 11


def usable(vector: Column) -> Column:
    """Whether a vector can be compared: there, finite throughout, not zero."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.coalesce(~bad & F.exists(vector, lambda x: x != 0), F.lit(False))


def directions(dims: int, least: int = DIRECTIONS, seed: int = SEED) -> np.ndarray:
    """Unit directions as columns: as many orthonormal bases as give ``least``."""
    rng = np.random.default_rng(seed)
    return np.concatenate([np.linalg.qr(rng.standard_normal((dims, dims)))[0] for _ in range(-(-least // dims))], axis=1).astype(np.float32)


def collisions_asked(m: int, slack: float = SLACK) -> int:
    """How often a vector at a distance collides in windows made for that distance, less so many standard deviations. The projections on a basis
    have a fixed sum of squares, which makes their number in a window vary less than independent ones would."""
    inside = math.erf(HALF_WIDTH / math.sqrt(2))
    density = HALF_WIDTH * math.exp(-HALF_WIDTH**2 / 2) * math.sqrt(2 / math.pi)
    return max(1, math.floor(m * inside - slack * math.sqrt(m * (inside * (1 - inside) - density**2 / 2))))


class CollisionIndex:
    """Sorted arrays of the projections of a group of vectors."""

    def __init__(self, vectors: np.ndarray, ids: np.ndarray, axes: np.ndarray, slack: float = SLACK):
        self.vectors, self.ids, self.axes = vectors, ids, axes
        norms = np.einsum("ij,ij->i", vectors, vectors, dtype=np.float64)
        self.largest = float(np.sqrt(norms.max()))
        more = np.sqrt(np.maximum(self.largest**2 - norms, 0))
        projections = (np.column_stack([vectors, more]).astype(np.float32) @ axes).T
        m, n = projections.shape
        self.entries = np.argsort(projections, axis=1, kind="stable")  # of each array: the vectors in order
        # the arrays one after another, each moved by its number, so that one search serves them all
        self.reach = 2.02 * self.largest
        self.moved = np.arange(m) * 2 * self.reach
        self.sorted = (np.take_along_axis(projections, self.entries, axis=1) + self.moved[:, None]).ravel()
        self.entries = self.entries.ravel()
        self.begins = np.arange(m) * n
        self.asked = collisions_asked(m, slack)
        self.verified = 0  # how many inner products were computed, for reports

    def radius(self, score: float, norm: float) -> float:
        """Distance of a vector with this inner product."""
        return math.sqrt(max(2 * self.largest**2 - 2 * score * self.largest / norm, 0.0))

    def _counted(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """How often each vector lies in these stretches of the arrays."""
        some = np.flatnonzero(high > low)
        if not len(some):
            return np.zeros(len(self.ids), np.int64)
        return np.bincount(np.concatenate([self.entries[a:b] for a, b in zip(low[some].tolist(), high[some].tolist())]), minlength=len(self.ids))

    def search(self, query: np.ndarray, projected: np.ndarray, norm: float, own: int, best: Best) -> None:
        """Offers what the query's windows find to its best so far."""
        n, m, dims = len(self.ids), len(self.begins), self.axes.shape[0]
        if best.least() > self.largest * norm * (1 + 1e-6):  # no vector here can be as good
            return
        point = projected * (self.largest / norm)
        wide = lambda radius: HALF_WIDTH * radius / math.sqrt(dims)
        known = best.least() > -math.inf
        width = wide(self.radius(best.least(), norm)) if known else wide(FIRST * self.largest)
        ends = self.begins + n
        low = high = None
        seen = np.zeros(n, bool)
        while True:
            a = np.searchsorted(self.sorted, (point - width).clip(-self.reach, self.reach) + self.moved)
            b = np.searchsorted(self.sorted, (point + width).clip(-self.reach, self.reach) + self.moved, "right")
            a, b = np.clip(a, self.begins, ends), np.clip(b, self.begins, ends)
            entering = int((b - a).sum()) if low is None else int((low - a).sum() + (b - high).sum())
            if entering > n * m - int((b - a).sum()):  # fewer lie outside than enter: the same counts from the other side
                counts = m - self._counted(self.begins, a) - self._counted(b, ends)
            elif low is None:
                counts = self._counted(a, b)
            else:
                counts += self._counted(a, low) + self._counted(high, b)
            low, high = a, b
            fresh = np.flatnonzero((counts >= self.asked) & ~seen)
            if not known and len(fresh) < best.k and not seen.any():  # a first k-th score, from those that collide most
                fresh = np.argpartition(-counts, min(SEEDS * best.k, n - 1))[: SEEDS * best.k]
            seen[fresh] = True
            self.verified += len(fresh)
            fresh = fresh[self.ids[fresh] != own]
            best.offer(self.vectors[fresh], self.ids[fresh], self.largest)
            target = wide(self.radius(best.least(), norm)) if best.least() > -math.inf else wide(2 * self.largest)
            if width >= target or entering == 0 and (b - a == n).all():
                return
            width = min(target, GROWTH * width)


class Best:
    """The best vectors found for a query: rough scores decide what can't be among them, exact ones decide the rest."""

    def __init__(self, query: np.ndarray, norm: float, k: int):
        self.query, self.norm, self.k = query, norm, k
        self.rough = np.empty(0, query.dtype)
        self.vectors: list[np.ndarray] = []
        self.found: list[np.ndarray] = []
        self.scores: list[np.ndarray] = []
        self.error = 0.0

    def least(self) -> float:
        """A score that the k-th best reaches."""
        return float(self.rough.min()) - self.error if len(self.rough) == self.k else -math.inf

    def offer(self, vectors: np.ndarray, ids: np.ndarray, largest: float) -> None:
        if not len(ids):
            return
        rough = vectors @ self.query
        # of a sum of products in the vectors' own precision
        self.error = max(self.error, 2 * len(self.query) * float(np.finfo(vectors.dtype).eps) * largest * self.norm)
        top = np.concatenate([self.rough, rough])
        self.rough = np.partition(top, len(top) - self.k)[len(top) - self.k :] if len(top) > self.k else top
        near = rough >= self.least() - self.error
        self.vectors.append(vectors[near])
        self.found.append(ids[near])
        self.scores.append(rough[near])

    def ranked(self) -> tuple[np.ndarray, np.ndarray]:
        """Ids and scores of the k best, best first, of equal ones the smaller id first."""
        if not self.found:
            return np.empty(0, np.int64), np.empty(0)
        ids, rough, vectors = np.concatenate(self.found), np.concatenate(self.scores), np.concatenate(self.vectors)
        near = rough >= self.least() - self.error
        scores = vectors[near].astype(np.float64) @ self.query.astype(np.float64)
        order = np.lexsort((ids[near], -scores))[: self.k]
        return ids[near][order], scores[order]


class Block:
    """The groups of a block's vectors, those of the greatest norms first."""

    def __init__(self, vectors: np.ndarray, ids: np.ndarray, group_rows: int = GROUP_ROWS, least_directions: int = DIRECTIONS, slack: float = SLACK):
        norms = np.sqrt(np.einsum("ij,ij->i", vectors, vectors, dtype=np.float64))
        order = np.lexsort((ids, -norms))
        self.axes = directions(vectors.shape[1] + 1, least_directions)
        self.groups = [CollisionIndex(vectors[some], ids[some], self.axes, slack) for some in np.array_split(order, -(-len(ids) // group_rows))]

    def search(self, queries: np.ndarray, own: np.ndarray, k: int) -> list[tuple[np.ndarray, np.ndarray]]:
        """For every query the ids and scores of the k best vectors found."""
        projected = queries.astype(np.float32) @ self.axes[:-1]
        norms = np.sqrt(np.einsum("ij,ij->i", queries, queries, dtype=np.float64))
        results = []
        for query, point, norm, me in zip(queries, projected, norms.tolist(), own.tolist()):
            best = Best(query, norm, k)
            for group in self.groups:
                group.search(query, point, norm, me, best)
            results.append(best.ranked())
        return results


def _matrix(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    lists = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return lists.flatten().to_numpy(zero_copy_only=False).reshape(len(lists), -1)


def comparable(vectors: DataFrame, id_column: str, vector_column: str) -> tuple[DataFrame, int, int]:
    """The rows that take part as (id, vector), how many there are, and their length."""
    kind = vectors.schema[vector_column].dataType
    precise = isinstance(kind, T.ArrayType) and not isinstance(kind.elementType, T.FloatType)
    rows = vectors.select(F.col(id_column).cast("long").alias("id"), F.col(vector_column).cast("array<double>" if precise else "array<float>").alias("vector"))
    rows = rows.filter(F.col("id").isNotNull() & usable(F.col("vector")))
    top = rows.groupBy(F.size("vector").alias("dims")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), F.desc("dims")).first()
    return (rows.filter(F.size("vector") == top.dims), int(top.n), int(top.dims)) if top else (rows, 0, 0)


def nearest(
    vectors: DataFrame, queries: Column, id_column: str = "vec_id", vector_column: str = "embedding", k: int = K,
    block_bytes: int = BLOCK_BYTES, group_rows: int = GROUP_ROWS, least_directions: int = DIRECTIONS, slack: float = SLACK,
) -> DataFrame:
    """query_id, rank, vec_id and score of the k nearest rows found for every row that meets the condition ``queries`` on column ``id``."""
    rows, n, dims = comparable(vectors, id_column, vector_column)
    # blocks of bounded size, and on small tables as many as there are tasks
    blocks = max(1, -(-4 * n * dims // block_bytes), min(spread(vectors), n // LEAST_ROWS))
    label = lambda number: labelled(number, blocks).alias("block")
    data = rows.select(label(F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")), F.lit(0).alias("asks"), "id", "vector")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("number")
    asking = rows.filter(queries).dropDuplicates(["id"]).select("id", "vector", every).select(label(F.col("number")), F.lit(1).alias("asks"), "id", "vector")
    streams = data.union(asking).repartition(blocks, "block").sortWithinPartitions("block", "asks", "id")

    def searched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number, held, block = None, [], None
        for batch in batches:
            ends = np.flatnonzero(np.diff(batch.column(0).to_numpy()) | np.diff(batch.column(1).to_numpy())) + 1
            for a, b in zip([0, *ends.tolist()], [*ends.tolist(), batch.num_rows]):
                part = batch.slice(a, b - a)
                if not part.num_rows:
                    continue
                if part.column(0)[0].as_py() != number:
                    number, held, block = part.column(0)[0].as_py(), [], None
                if not part.column(1)[0].as_py():
                    held.append(part)
                    continue
                if held:  # the block is whole: its vectors come before its queries
                    block = Block(np.concatenate([_matrix(x.column(3)) for x in held]), np.concatenate([x.column(2).to_numpy() for x in held]), group_rows, least_directions, slack)
                    held = []
                if block:
                    own = part.column(2).to_numpy()
                    found = block.search(_matrix(part.column(3)), own, k)
                    yield pa.RecordBatch.from_arrays([np.repeat(own, [len(x) for x, _ in found]), np.concatenate([x for x, _ in found]), np.concatenate([s for _, s in found])], ["query_id", "vec_id", "score"])

    best = streams.mapInArrow(searched, "query_id long, vec_id long, score double")
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return best.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
