"""Jaccard similarity join of word n-gram sets with prefix trees, and the components it links.

A document's set holds the distinct runs of ``width`` words of its whole text (with fewer words, all of them as one run).
Documents with equal sets are one class; classes are joined, documents follow their class.

1. A text's n-grams are hashed twice: for its class and, one text a class and task, for its set, which is dealt into blocks as packed hashes.
   What each n-gram's document frequency is, blocks ask of key ranges, as for the language model. (frequency, hash) is the global order,
   rarest first.
2. A similar pair shares one of the first |set| - ceil(0.85 |set|) + 1 elements of both. Elements that one class alone has link
   nothing, so most classes end here; the others go on with their shared elements.
3. Sizes fall into bands as wide as similar sets may differ, so a similar pair lies in one band or two neighbouring ones. For every pair of
   neighbouring bands, classes that share an element of step 2 hang together; each such cluster is joined in one task by a prefix tree, in
   which subtrees share the overlap of their path and are pruned by the remaining lengths. A passage that is rare enough to count in many
   documents thus chains those of like length only. Clusters of more than ``bucket`` classes are cut into parts and every pair of parts is a
   task of its own, so no task grows with a cluster and no pair of a cluster is a row.
4. Tasks send a spanning forest of the links; its components are the result.

Rows: null texts and texts without words have an empty set, 0 n-grams, and are linked with nothing. A null doc_id keeps its row and names
no component unless all of the component are null. Rows that repeat are members like any other. Empty tables give no rows; other columns
don't matter. Hashes have 64 bits for a set's size, 128 for classes, and 48 for the elements that are joined: two unlike sets of 1,000 share
one by chance with probability 4e-9.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .blobs import merge, pack, pack_sorted, slices, unpack, unpack_sorted
from .common import cut, dealt, labelled, portions, text_or_empty
from .components import components
from .prefix_tree import PERCENT, linked
from .vectors_of_text import batches_of, mixed, words_by_text

WIDTH, BUCKET = 4, 4_000
BLOCK_BYTES, RANGE_BYTES = 4 << 20, 16 << 20
_SHIFT = np.uint64(16)  # the join tells elements apart by their upper 48 bits
_FACTORS = np.random.default_rng(8).integers(1, 1 << 63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def ngram_sets(texts: list[bytes], width: int = WIDTH) -> list[np.ndarray]:
    """The ascending hashes of each text's n-grams."""
    sets: list[np.ndarray] = []
    for low, high in batches_of(texts):  # besides the sets, no array grows with the number of texts
        words, first = words_by_text(texts[low:high])
        grams = np.zeros(len(words), np.uint64)
        for k in range(width):
            grams[: max(0, len(words) - k)] += words[k:] * _FACTORS[k]
        grams = mixed(grams)
        for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
            if b - a >= width:
                sets.append(np.unique(grams[a : b - width + 1]))
            elif b > a:  # a set of its own kind: no longer text has this n-gram
                sets.append(mixed(np.sum(words[a:b] * _FACTORS[8 : 8 + b - a], dtype=np.uint64, keepdims=True) + np.uint64(b - a)))
            else:
                sets.append(np.empty(0, np.uint64))
    return sets


def set_id(elements: np.ndarray) -> bytes | None:
    return xxhash.xxh3_128_digest(elements.tobytes()) if len(elements) else None


def sets_of(docs: DataFrame, width: int = WIDTH, carry: list[str] | None = None) -> DataFrame:
    """doc_id, the columns to carry, n_shingles and class of every row."""
    kept = docs.select(F.col("doc_id").cast("long"), *(carry or []))
    names, place = kept.columns, len(kept.columns)

    def classes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in portions(batches, place):
            sets = ngram_sets(batch.column(place).cast(pa.binary()).to_pylist(), width)
            yield pa.RecordBatch.from_arrays([*batch.columns[:place], pa.array(map(len, sets), pa.int64()), pa.array(map(set_id, sets), pa.binary())], [*names, "n_shingles", "class"])

    schema = T.StructType([*kept.schema.fields, *T.StructType.fromDDL("n_shingles long, class binary").fields])
    return docs.select(F.col("doc_id").cast("long"), *(carry or []), text_or_empty().alias("text")).mapInArrow(classes, schema)


def dealt_sets(docs: DataFrame, blocks: int, width: int = WIDTH) -> DataFrame:
    """block, class and its packed set; a task sends a class once only, so a block gets no more copies than there are tasks."""

    def sent(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        for batch in portions(batches, 0):
            found = {}
            for elements in ngram_sets(batch.column(0).cast(pa.binary()).to_pylist(), width):
                key = set_id(elements)
                if key and key not in seen:
                    seen.add(key)
                    found[key] = pack_sorted(elements >> _SHIFT)
            yield pa.RecordBatch.from_arrays([pa.array([int.from_bytes(k[:8], "big") % blocks for k in found], pa.int32()), pa.array(found.keys(), pa.binary()), pa.array(found.values(), pa.binary())], ["block", "class", "elements"])

    found = docs.select(text_or_empty().alias("text")).mapInArrow(sent, "block int, class binary, elements binary")
    return found.withColumn("block", labelled(F.col("block"), blocks)).repartition(blocks, "block")


def block_sets(block: pa.Table) -> dict[bytes, np.ndarray]:
    packed = dict(zip(block.column("class").to_pylist(), block.column("elements").to_pylist()))
    return {k: unpack_sorted(packed[k]) for k in sorted(packed)}


def ask(block: pa.Table, ranges: int) -> pa.Table:
    """A block's elements with the number of its classes that have them."""
    keys, counts = np.unique(np.concatenate([*block_sets(block).values()]), return_counts=True)
    at = slices(keys, ranges, 48)
    parts = [i for i in range(ranges) if at[i] < at[i + 1]]
    number = block.column("block")[0].as_py()
    return pa.table(
        {
            "part": pa.array(parts, pa.int32()), "block": pa.array([number] * len(parts), pa.int32()),
            "keys": pa.array([pack_sorted(keys[at[i] : at[i + 1]]) for i in parts], pa.binary()), "counts": pa.array([pack(counts[at[i] : at[i + 1]].astype(np.uint64)) for i in parts], pa.binary()),
        }
    )


def answer(asked: pa.Table) -> pa.Table:
    """The frequencies over all blocks, to each block in the order it asked."""
    keys = [unpack_sorted(x.as_py()) for x in asked.column("keys")]
    total, counts = merge(keys, [unpack(x.as_py()) for x in asked.column("counts")])
    return pa.table({"part": asked.column("part"), "block": asked.column("block"), "counts": pa.array([pack(counts[np.searchsorted(total, k)]) for k in keys], pa.binary())})


def band_of(size: int, percent: int) -> int:
    """Sets whose sizes differ as much as similar ones may lie in one band or in neighbouring ones."""
    return int(math.log(size) / (math.log(100 / percent) * (1 + 1e-9))) if percent < 100 else size


def prefixes(block: pa.Table, answers: pa.Table, percent: int) -> pa.Table:
    """The classes whose prefix holds shared elements: these, all their shared elements, and frequencies."""
    sets = block_sets(block)
    keys = np.unique(np.concatenate([*sets.values()]))
    frequency = np.concatenate([unpack(c) for _, c in sorted(zip(answers.column("part").to_pylist(), answers.column("counts").to_pylist()))]).astype(np.uint32)
    rows: list[tuple] = []
    for key, elements in sets.items():
        often = frequency[np.searchsorted(keys, elements)]
        n = len(elements)
        first = np.argsort(often, kind="stable")[: n - -(-percent * n // 100) + 1]  # ties by hash, as elements ascend
        shared = first[often[first] > 1]
        if len(shared):
            kept = often > 1
            rows.append((key, n, band_of(n, percent), elements[shared].view(np.int64).tolist(), pack_sorted(elements[kept]), pack(often[kept].astype(np.uint64))))
    names = ["class", "size", "band", "prefix", "elements", "frequencies"]
    types = [pa.binary(), pa.int64(), pa.int32(), pa.list_(pa.int64()), pa.binary(), pa.binary()]
    return pa.table([pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], names=names)


def join_bucket(members: pa.Table, percent: int) -> pa.Table:
    """Links within a bucket, or between its two parts: each class with the first of its component here."""
    order = np.argsort(np.array(members.column("class").to_pylist(), dtype=object), kind="stable")
    members = members.take(pa.array(order))
    ids, sizes, part = (members.column(c).to_pylist() for c in ("class", "size", "part"))
    elements = [unpack_sorted(x.as_py()) for x in members.column("elements")]
    often = [unpack(x.as_py()).astype(np.uint64) for x in members.column("frequencies")]
    every, where = np.unique(np.concatenate(elements), return_index=True)
    rank = np.empty(len(every), np.int64)
    rank[np.lexsort((every, np.concatenate(often)[where]))] = np.arange(len(every))
    sets = [np.sort(rank[np.searchsorted(every, e)]) for e in elements]
    queries = {i for i, p in enumerate(part) if p == max(part)} if len(set(part)) > 1 else None
    forest = linked(sets, sizes, percent, queries)
    found = [(ids[i], ids[forest.find(i)]) for i in range(len(ids)) if forest.find(i) != i]
    return pa.table([pa.array([x[k] for x in found], pa.binary()) for k in (0, 1)], names=["a", "b"])


def similar_classes(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT, bucket: int = BUCKET, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """a, b: a spanning forest of the links between classes."""
    size = docs.agg(F.sum(F.octet_length(text_or_empty()))).first()[0] or 0  # how much there is decides only how it is dealt
    blocks, ranges = dealt(size, block_bytes, RANGE_BYTES)
    sets = dealt_sets(docs, blocks, width)
    asked = sets.groupBy("block").applyInArrow(lambda b: ask(b, ranges), "part int, block int, keys binary, counts binary")
    answers = asked.groupBy("part").applyInArrow(answer, "part int, block int, counts binary")
    shared = cut(
        sets.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(lambda b, a: prefixes(b, a, percent), "class binary, size long, band int, prefix array<long>, elements binary, frequencies binary")
    )
    # a class stands in the space of its own band and the next, and in that of the band before and its own; a node is a class in a space
    node = lambda c, space: F.concat(c, F.unhex(F.lpad(F.hex(space), 16, "0")))
    spaces = F.explode(F.array(F.col("band"), F.col("band") + 1)).alias("space")
    firsts = shared.select("class", spaces, "prefix").select("class", "space", F.explode("prefix").alias("element"))
    lead = firsts.groupBy("element", "space").agg(F.min("class").alias("lead"), F.max("class").alias("last")).filter("lead < last").drop("last")
    stars = firsts.join(lead, ["element", "space"]).select(node(F.col("class"), F.col("space")).alias("a"), node(F.col("lead"), F.col("space")).alias("b"))
    clusters = components(stars.distinct()).select(F.substring("node", 1, 16).alias("class"), F.col("root").alias("cluster"))
    parts = clusters.groupBy("cluster").agg(F.count("*").alias("members")).select("cluster", F.greatest(F.lit(1), F.ceil(F.col("members") * 2 / bucket)).alias("parts"))
    parts = parts.withColumn("parts", F.when(F.col("parts") <= 2, 1).otherwise(F.col("parts")))
    placed = clusters.join(parts, "cluster").withColumn("part", F.pmod(F.xxhash64("class"), "parts"))
    dealt_out = placed.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)))
    dealt_out = dealt_out.select("class", "part", "cluster", F.least("part", "other").alias("i"), F.greatest("part", "other").alias("j"))
    members = dealt_out.join(shared.select("class", "size", "elements", "frequencies"), "class")
    return members.groupBy("cluster", "i", "j").applyInArrow(lambda m: join_bucket(m, percent), "a binary, b binary")


def classes_and_roots(docs: DataFrame, width: int, percent: int, bucket: int, carry: list[str] | None = None) -> tuple[DataFrame, DataFrame]:
    """The rows with their class, and class and root of every class that is linked."""
    return cut(sets_of(docs, width, carry)), components(similar_classes(docs, width, percent, bucket)).withColumnRenamed("node", "class")


def grouped_rows(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT, bucket: int = BUCKET, carry: list[str] | None = None) -> DataFrame:
    """doc_id, the columns to carry, n_shingles and root (one value a component, null for rows without words) of every row."""
    classes, roots = classes_and_roots(docs, width, percent, bucket, carry)
    return classes.join(roots, "class", "left").withColumn("root", F.coalesce("root", "class")).drop("class")


def near_duplicates(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT, bucket: int = BUCKET) -> DataFrame:
    """doc_id, n_shingles and component_id (the smallest doc_id reachable by links) of every row."""
    classes, roots = classes_and_roots(docs, width, percent, bucket)
    known = classes.filter("class IS NOT NULL").groupBy("class").agg(F.min("doc_id").alias("first"), F.count("*").alias("copies"))
    known = known.join(roots, "class", "left").filter("copies > 1 OR root IS NOT NULL").withColumn("root", F.coalesce("root", "class"))
    least = known.groupBy("root").agg(F.min("first").alias("least"))
    named = known.join(least, "root").select("class", "least")  # classes that are linked or have copies; the others are their own
    return classes.join(named, "class", "left").select("doc_id", "n_shingles", F.coalesce("least", "doc_id").alias("component_id"))
