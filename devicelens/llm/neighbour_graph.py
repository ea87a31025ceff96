"""Near-duplicate vectors by NN-descent.

Vectors are compared within a label only. Equal ones are one class, with its number of rows. A label with more classes than a task should
hold is dealt into cells by the signs of projections on random directions, several times over with other directions (tables), so many
that a pair at the threshold shares a cell with probability ``1 - MISSED``; a pair counts in the first table it shares a cell in. A cell that is
still too large is cut into parts, and each pair of parts is a task.

In a task a neighbour graph begins with the leaves of random-projection trees and is refined: neighbours of neighbours are joined as
candidates and the nearest kept, until a round changes little. Where a list is saturated, all of it above the threshold, it is
enlarged to whatever hangs together with it: those vectors are compared by strips of rows, in which links are counted and components united as
they are found, so no pair is ever kept. An audit compares sampled vectors with all others of the task; where it finds a link
that the graph lacks, more trees and rounds follow, at last strips of all rows. Edges with cosine >= threshold, in double precision on the
original vectors, are the links.

Rows: vectors that are null, zero, or hold a null or non-finite component, and rows with a null label, link with nothing; so do vectors of
different length. Rows that repeat are vectors of their own, linked with their copies. Null ids keep their row. Other columns don't matter.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .ann import usable
from .common import cut
from .components import components
from .prefix_tree import UnionFind

THRESHOLD, LIST, LEAF, TREES, ROUNDS, AUDITED = 0.98, 8, 48, 4, 4, 1_024
CELL_ROWS, PART_ROWS, MISSED, SEED, STRIP, BAND = 6_000, 6_000, 1e-4, 5, 256, 1e-5


def tree_leaves(x: np.ndarray, leaf: int, rng: np.random.Generator) -> Iterator[np.ndarray]:
    """Leaves of a tree that halves a set at the median of its projections on the line through two of its members."""
    todo = [np.arange(len(x))]
    while todo:
        part = todo.pop()
        if len(part) <= leaf:
            yield part
            continue
        a, b = rng.choice(part, 2, replace=False)
        side = x[part] @ (x[a] - x[b])
        order = np.argpartition(side, len(part) // 2)
        todo += [part[order[: len(part) // 2]], part[order[len(part) // 2 :]]]


class NeighbourGraph:
    """Lists of the nearest neighbours found so far, by cosine."""

    def __init__(self, x: np.ndarray, size: int = LIST, seed: int = SEED):
        self.x, self.rng, n = x, np.random.default_rng(seed), len(x)
        self.size = min(size, max(1, n - 1))
        self.near = np.full((n, self.size), -1, np.int64)
        self.cosine = np.full((n, self.size), -2.0, np.float32)

    def offer(self, rows: np.ndarray, candidates: np.ndarray, cosine: np.ndarray) -> int:
        """Keeps the nearest distinct of each row's list and candidates; gives how many entries are new."""
        ids = np.concatenate([self.near[rows], candidates], axis=1)
        values = np.concatenate([self.cosine[rows], cosine], axis=1)
        values = np.where((ids == rows[:, None]) | (ids < 0), np.float32(-2), values)
        by_id = np.argsort(ids, axis=1, kind="stable")
        ids, values = np.take_along_axis(ids, by_id, 1), np.take_along_axis(values, by_id, 1)
        values[:, 1:][ids[:, 1:] == ids[:, :-1]] = -2
        best = np.argpartition(-values, self.size - 1, axis=1)[:, : self.size]
        old = self.cosine[rows].sum()
        self.near[rows], self.cosine[rows] = np.take_along_axis(ids, best, 1), np.take_along_axis(values, best, 1)
        self.near[rows] = np.where(self.cosine[rows] <= -2, -1, self.near[rows])
        return int(self.cosine[rows].sum() > old + 1e-4)

    def plant(self, trees: int) -> None:
        """Offers each vector its fellows in the leaves of some trees."""
        for _ in range(trees):
            by_size: dict[int, list[np.ndarray]] = {}
            for leaf in tree_leaves(self.x, LEAF, self.rng):
                by_size.setdefault(len(leaf), []).append(leaf)
            for size, leaves in by_size.items():
                if size > 1:
                    for a in range(0, len(leaves), 64):
                        at = np.array(leaves[a : a + 64])
                        v = self.x[at]
                        self.offer(at.ravel(), np.repeat(at, size, axis=0), (v @ v.transpose(0, 2, 1)).reshape(-1, size))

    def descend(self, rounds: int) -> None:
        """Joins neighbours of neighbours, both ways, while that changes lists."""
        for _ in range(rounds):
            n, changed = len(self.x), 0
            reverse = np.full((n, self.size), -1, np.int64)
            target, source = self.near.ravel(), np.repeat(np.arange(n), self.size)
            order = np.argsort(target, kind="stable")
            target, source = target[order], source[order]
            place = np.arange(len(target)) - np.searchsorted(target, target)
            fits = (target >= 0) & (place < self.size)
            reverse[target[fits], place[fits]] = source[fits]
            around = np.concatenate([self.near, reverse], axis=1)
            for a in range(0, n, 1_024):
                rows = np.arange(a, min(n, a + 1_024))
                mine = around[rows]
                candidates = np.where(mine[:, :, None] >= 0, self.near[mine], -1).reshape(len(rows), -1)
                candidates = np.concatenate([mine, candidates], axis=1)
                cosine = np.einsum("rcd,rd->rc", self.x[candidates], self.x[rows])
                changed += self.offer(rows, candidates, cosine)
            if not changed:
                break

    def links(self, threshold: float) -> tuple[np.ndarray, list[np.ndarray]]:
        """Pairs (a < b) of vectors in the lists whose cosine is at least the threshold, and sets of vectors that hang together and have saturated
        lists: within those any pair may be linked, and the pairs are those of no such set."""
        row, column = np.nonzero(self.cosine >= threshold)
        pairs = np.unique(np.sort(np.column_stack([row, self.near[row, column]]), axis=1), axis=0)
        saturated = self.cosine.min(axis=1) >= threshold
        if not saturated.any():
            return pairs, []
        root = united(len(self.x), pairs)
        full = np.isin(root, root[saturated])
        order = np.flatnonzero(full)[np.argsort(root[full], kind="stable")]
        return pairs[~full[pairs[:, 0]]], np.split(order, np.flatnonzero(np.diff(root[order])) + 1)

    def missed(self, pairs: np.ndarray, sets: list[np.ndarray], threshold: float, sample: int) -> bool:
        """Audit: whether a sampled vector has a link that neither the pairs nor the sets have."""
        n = len(self.x)
        chosen = np.sort(self.rng.choice(n, min(sample, n), replace=False))
        of = np.arange(n) - n  # a vector of no set is alone
        for k, members in enumerate(sets):
            of[members] = k
        known = np.sort(pairs[:, 0] * n + pairs[:, 1])
        for a in range(0, len(chosen), STRIP):
            some = chosen[a : a + STRIP]
            near = self.x[some] @ self.x.T >= threshold
            near &= of[some][:, None] != of[None, :]
            i, j = np.nonzero(near)
            ends = np.sort(np.column_stack([some[i], j]), axis=1)
            if not np.isin(ends[:, 0] * n + ends[:, 1], known).all():
                return True
        return False


def united(n: int, pairs: np.ndarray) -> np.ndarray:
    """The least member of each one's component, by the pairs."""
    forest = UnionFind(n)
    for a, b in pairs.tolist():
        forest.join(a, b)
    return np.array([forest.find(i) for i in range(n)], np.int64)


class Links:
    """Weights of the vectors each is linked to, and components, counted as links are found."""

    def __init__(self, vectors: np.ndarray, weights: np.ndarray, counts: Counts, threshold: float):
        self.vectors, self.weights, self.counts, self.threshold = vectors, weights, counts, threshold
        self.total, self.root = np.zeros(len(vectors), np.int64), np.arange(len(vectors))

    def exact(self, pairs: np.ndarray) -> np.ndarray:
        """Which pairs reach the threshold in double precision."""
        reached = np.empty(len(pairs), bool)
        for a in range(0, len(pairs), 65_536):
            u, v = (self.vectors[pairs[a : a + 65_536, k]].astype(np.float64) for k in (0, 1))
            reached[a : a + 65_536] = np.einsum("ij,ij->i", u, v) / np.sqrt(np.einsum("ij,ij->i", u, u) * np.einsum("ij,ij->i", v, v)) >= self.threshold
        return reached

    def unite(self, member: int, others: np.ndarray) -> None:
        found = self.root[others]
        if (found != self.root[member]).any():
            roots = np.unique(np.append(found, self.root[member]))
            self.root[np.isin(self.root, roots[1:])] = roots[0]

    def add(self, pairs: np.ndarray) -> None:
        pairs = pairs[self.exact(pairs)]
        pairs = pairs[self.counts(pairs[:, 0], pairs[:, 1])]
        for side in (0, 1):
            np.add.at(self.total, pairs[:, side], self.weights[pairs[:, 1 - side]])
        self.root = united(len(self.root), np.concatenate([np.column_stack([np.arange(len(self.root)), self.root]), pairs]))

    def scan(self, unit: np.ndarray, members: np.ndarray) -> None:
        """All links within a set, by strips of rows; of the pairs only those at the threshold's edge are looked at one by one."""
        x = unit[members]
        for a in range(0, len(members), STRIP):
            some = members[a : a + STRIP]
            cosine = x[a : a + STRIP] @ x.T
            near = cosine >= self.threshold + BAND
            i, j = np.nonzero((cosine >= self.threshold - BAND) & ~near)
            near[i, j] = self.exact(np.column_stack([some[i], members[j]]))
            near[np.arange(len(some)), a + np.arange(len(some))] = False
            near &= self.counts(some[:, None], members[None, :])
            self.total[some] += near @ self.weights[members]
            for row, member in zip(near, some.tolist()):
                self.unite(member, members[row])


Counts = Callable[[np.ndarray, np.ndarray], np.ndarray]


def find_links(vectors: np.ndarray, weights: np.ndarray, counts: Counts, threshold: float = THRESHOLD) -> Links:
    """Links between rows with cosine >= threshold, of those that ``counts`` says yes to; a row brings its weight to whom it is linked to."""
    links = Links(vectors, weights, counts, threshold)
    if len(vectors) < 2:
        return links
    unit = (vectors / np.linalg.norm(vectors.astype(np.float64), axis=1, keepdims=True)).astype(np.float32)
    graph, rough = NeighbourGraph(unit), threshold - BAND
    for extra in (0, 4, 8):
        graph.plant(TREES + extra)
        graph.descend(ROUNDS)
        pairs, sets = graph.links(rough)
        if not graph.missed(pairs, sets, rough, AUDITED):
            break
    else:  # the audits keep failing: compare them all
        pairs, sets = pairs[:0], [np.arange(len(unit))]
    links.add(pairs)
    for members in sets:
        links.scan(unit, members)
    return links


def cells(bits: int, tables: int, dims: int) -> np.ndarray:
    """Random directions of all tables, one after another."""
    return np.random.default_rng(SEED + 1).standard_normal((dims, max(1, bits * tables))).astype(np.float32)


def dealing(classes: int, threshold: float = THRESHOLD, cell_rows: int = CELL_ROWS) -> tuple[int, int]:
    """Bits of a cell's code, and tables, for a label with so many classes."""
    bits = max(0, math.ceil(math.log2(max(1, classes) / cell_rows)))
    together = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, 1 if not bits else math.ceil(math.log(MISSED) / math.log(1 - together))


def _matrix(column: pa.Array) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


def deal(batches: Iterator[pa.RecordBatch], threshold: float = THRESHOLD, cell_rows: int = CELL_ROWS) -> Iterator[pa.RecordBatch]:
    """Rows (class, label, rows, vector, classes of the label) once for each table, with the codes of all tables."""
    for batch in batches:
        counts = batch.column(4).to_numpy()
        for n in np.unique(counts).tolist():
            some = batch.filter(pa.array(counts == n))
            bits, tables = dealing(n, threshold, cell_rows)
            x = _matrix(some.column(3))
            codes = np.zeros((len(x), tables), np.int64)
            if bits:
                signs = (x @ cells(bits, tables, x.shape[1]) > 0).reshape(len(x), tables, bits)
                codes = (signs << np.arange(bits)).sum(axis=2)
            every = pa.array(codes.tolist(), pa.list_(pa.int64()))
            for t in range(tables):
                names = ["class", "label", "rows", "vector", "cell_table", "code", "codes"]
                yield pa.RecordBatch.from_arrays([*some.columns[:4], pa.array(np.full(len(x), t), pa.int32()), pa.array(codes[:, t]), every], names)


def link_cell(members: pa.Table, threshold: float) -> pa.Table:
    """Rows each class is linked to here, and the first class of its component here."""
    members = members.take(pa.array(np.argsort(np.array(members.column("class").to_pylist(), dtype=object), kind="stable")))
    ids, rows = members.column("class").to_pylist(), members.column("rows").to_numpy()
    codes, part = _matrix(members.column("codes")), members.column("part").to_numpy()
    table = members.column("cell_table")[0].as_py()
    apart = len(np.unique(part)) > 1

    def counts(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether a pair counts here: an earlier table counts what it has in one cell, and a task of two parts the pairs between them."""
        here = np.ones(np.broadcast_shapes(a.shape, b.shape), bool)
        for t in range(table):
            here &= codes[a, t] != codes[b, t]
        return here & (part[a] != part[b]) if apart else here

    links = find_links(_matrix(members.column("vector")), rows, counts, threshold)
    some = np.flatnonzero(links.total)
    return pa.table([pa.array([ids[i] for i in some], pa.binary()), pa.array(links.total[some]), pa.array([ids[links.root[i]] for i in some], pa.binary())], names=["class", "links", "first"])


def near_duplicate_vectors(
    vectors: DataFrame, threshold: float = THRESHOLD, id_column: str = "vec_id", vector_column: str = "embedding", label_column: str = "label", cell_rows: int = CELL_ROWS, part_rows: int = PART_ROWS
) -> DataFrame:
    """vec_id, n_links, component_id and kept of every row."""
    vector = F.col(vector_column).cast("array<float>")
    digest = F.unhex(F.concat(*(F.lpad(F.hex(F.xxhash64(F.lit(k), "label", "vector")), 16, "0") for k in (1, 2))))
    rows = vectors.select(F.col(id_column).alias("vec_id"), F.col(label_column).alias("label"), vector.alias("vector"))
    rows = rows.withColumn("class", F.when(usable(F.col("vector")) & F.col("label").isNotNull(), digest))
    classes = rows.filter("class IS NOT NULL").withColumn("dims", F.size("vector")).groupBy("class").agg(
        F.min("label").alias("label"), F.min("dims").alias("dims"), F.count("*").alias("rows"), F.min("vec_id").alias("least"), F.first("vector").alias("vector")
    )
    classes = cut(classes.withColumn("label", F.concat_ws("/", F.col("label").cast("string"), F.col("dims").cast("string"))).drop("dims"))
    sizes = classes.groupBy("label").agg(F.count("*").alias("classes"))
    dealt_row = "class binary, label string, rows long, vector array<float>, cell_table int, code long, codes array<long>"
    dealt = classes.join(sizes, "label").select("class", "label", "rows", "vector", "classes").mapInArrow(lambda b: deal(b, threshold, cell_rows), dealt_row)
    counts = dealt.groupBy("label", "cell_table", "code").agg(F.count("*").alias("n"))
    parts = counts.withColumn("parts", F.when(F.col("n") <= 2 * part_rows, F.lit(1).cast("long")).otherwise(F.ceil(F.col("n") * 2 / part_rows))).drop("n")
    placed = dealt.join(parts, ["label", "cell_table", "code"]).withColumn("part", F.pmod(F.xxhash64("class"), "parts"))
    tasks = placed.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1))).withColumn("i", F.least("part", "other")).withColumn("j", F.greatest("part", "other")).drop("other", "parts")
    linked = cut(tasks.groupBy("label", "cell_table", "code", "i", "j").applyInArrow(lambda m: link_cell(m, threshold), "class binary, links long, first binary"))
    roots = components(linked.select(F.col("class").alias("a"), F.col("first").alias("b")).distinct())
    links = linked.groupBy("class").agg(F.sum("links").alias("links"))
    known = classes.select("class", "rows", "least").join(links, "class", "left").join(roots.withColumnRenamed("node", "class"), "class", "left")
    known = known.select("class", (F.coalesce("links", F.lit(0)) + F.col("rows") - 1).alias("n_links"), F.coalesce("root", "class").alias("root"), "least")
    named = known.groupBy("root").agg(F.min("least").alias("component"))
    known = known.join(named, "root").select("class", "n_links", "component")
    component = F.coalesce("component", "vec_id")
    return rows.select("vec_id", "class").join(known, "class", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), (F.col("vec_id") == component).alias("kept"))
