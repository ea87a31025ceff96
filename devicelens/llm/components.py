"""Connected components by repeated contraction, finished in one task when little is left."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut
from .prefix_tree import UnionFind

EDGES_OF_A_TASK = 200_000  # as many edges as one task may unite


def _united(edges: pa.Table) -> pa.Table:
    """node and root (the smallest node reachable) of the nodes of a bounded number of edges."""
    a, b = edges.column("a").to_pylist(), edges.column("b").to_pylist()
    nodes = sorted({*a, *b})
    place = {x: i for i, x in enumerate(nodes)}
    forest = UnionFind(len(nodes))
    for x, y in zip(a, b):
        forest.join(place[x], place[y])
    kind = edges.schema.field("a").type
    return pa.table([pa.array(nodes, kind), pa.array([nodes[forest.find(i)] for i in range(len(nodes))], kind)], names=["node", "root"])


def components(edges: DataFrame, edges_of_a_task: int = EDGES_OF_A_TASK) -> DataFrame:
    """node and root (the smallest node reachable) of every node of the edges (a, b).

    As long as there are more edges than one task may unite, a round contracts the graph: every node takes the first of its closed
    neighbourhood, and edges go on between those. First is the smallest in the first round, which settles stars, and the first by a new
    random order in every later one, so a path of any order of names, and all that is denser, halves in a round or better. Rounds write to
    the shared folder. At the end each component is named by its smallest node.
    """
    edges = edges.select("a", "b").filter("a <> b")
    left = cut(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    roots, number = None, 0

    def after(roots: DataFrame | None, near: DataFrame) -> DataFrame:
        if roots is None:
            return cut(near)
        on = roots.withColumnRenamed("root", "via").join(near.select(F.col("node").alias("via"), F.col("root").alias("next")), "via", "left")
        return cut(on.select("node", F.coalesce("next", "via").alias("root")))

    while (n := left.count()) > edges_of_a_task:
        both = left.union(left.select(F.col("b").alias("a"), F.col("a").alias("b")))
        place = lambda c: F.struct(F.xxhash64(F.lit(number), F.col(c)).alias("h") if number else F.lit(0).alias("h"), F.col(c).alias("n"))  # noqa: B023, E731
        near = cut(both.groupBy("a").agg(F.min(place("b")).alias("first")).select(F.col("a").alias("node"), F.least("first", place("a"))["n"].alias("root")))
        roots = after(roots, near)
        to_a, to_b = near.select(F.col("node").alias("a"), F.col("root").alias("ra")), near.select(F.col("node").alias("b"), F.col("root").alias("rb"))
        moved = left.join(to_a, "a").join(to_b, "b").filter("ra <> rb")
        left = cut(moved.select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct())
        number += 1
    schema = T.StructType([T.StructField(name, left.schema["a"].dataType) for name in ("node", "root")])
    if n or roots is None:
        last = left.withColumn("task", F.lit(0)).groupBy("task").applyInArrow(_united, schema)
        if roots is None:
            return cut(last)
        roots = after(roots, last)
    names = roots.groupBy("root").agg(F.min("node").alias("least"))
    return cut(roots.join(names, "root").select("node", F.col("least").alias("root")))
