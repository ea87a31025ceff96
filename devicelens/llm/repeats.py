"""Removal of byte strings that occur again anywhere in the corpus, found with enhanced suffix arrays.

Every window of ``least`` bytes that lies in one document has an anchor value, the least hash among its ``GRAM``-byte grams: equal windows
have equal anchors. Consecutive windows with one anchor value form a run, some 80 windows; so runs stand for all windows.

1. Blocks of documents ask key ranges about their runs, by (anchor, 128-bit digest of the run's bytes). Copies of a run are one run that is
   repeated as it stands. Anchors with several distinct runs need a closer look; one block, the owner, sends each such run's bytes.
2. Per range of anchors an enhanced suffix array is built over these bytes, and a stack scan of its common-prefix intervals, testing whether the
   bytes on the left differ, gives the maximal repeats with all occurrences; those of at least ``least`` bytes are spans to remove.
3. An anchor with more than ``hot`` distinct runs (a passage that ends in a different context in each of very many documents) is split, as one
   task couldn't hold it: its windows are dealt by their own digests, so that equal windows meet, whatever the size of the group. This
   changes where windows are compared, never what is found.
4. Each block unites the spans of its documents.

Rows: a null text is empty. Documents shorter than ``least`` lose nothing. Rows that repeat are documents of their own, so equal texts of
``least`` bytes or more go as a whole, each of them. A null doc_id is kept as it is. Empty tables give no rows. Other columns don't matter.
Equality is that of 128-bit digests in steps 1 and 3, and of bytes in step 2.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .blobs import pack, pack_sorted, slices, unpack, unpack_sorted
from .common import cut, dealt, labelled, text_or_empty
from .suffixes import EnhancedSuffixArray
from .vectors_of_text import _RANDOM, batches_of, mixed, powers

LEAST, GRAM, HOT = 200, 32, 2_000
BLOCK_BYTES, RANGE_BYTES, SEGMENT = 4 << 20, 16 << 20, 1 << 17
FINER = 12  # ranges of suffix arrays for each range of questions: an array takes some 60 bytes for each of its own
REPEATED, SENT, BUSY = 1, 2, 4  # what an answer says of a run
_ROW = "kind string, part int, block int, a binary, b binary, c binary, d binary"
_ROW_TYPES = pa.schema([("kind", pa.string()), ("part", pa.int32()), ("block", pa.int32()), *((c, pa.binary()) for c in "abcd")])


RESULT = "n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary, kept_text string, span_begins array<long>, span_ends array<long>"


@dataclass
class Runs:
    """Runs of windows: anchor, digest (two halves), document, first window, number of windows, and whether it can't repeat in itself."""

    anchor: np.ndarray
    digest: np.ndarray
    doc: np.ndarray
    begin: np.ndarray
    windows: np.ndarray
    alone: np.ndarray


def sliding_least(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every ``width`` neighbours, from minima over blocks that run forward and backward."""
    n = len(x) - width + 1
    padded = np.full(-(-len(x) // width) * width, x.max(), x.dtype)
    padded[: len(x)] = x
    blocks = padded.reshape(-1, width)
    forward = np.minimum.accumulate(blocks, axis=1).ravel()
    backward = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(backward[:n], forward[width - 1 : width - 1 + n])


def _segments(texts: list[bytes], least: int) -> list[tuple[int, int, bytes]]:
    """(document, offset, bytes); long texts in pieces that overlap so that each window lies in one piece."""
    return [(i, at, t[at : at + SEGMENT + least - 1]) for i, t in enumerate(texts) for at in range(0, max(1, len(t) - least + 1), SEGMENT) if len(t) >= least]


def digests(strings: Iterable[bytes]) -> np.ndarray:
    """128-bit digests, as two columns."""
    return np.frombuffer(b"".join(map(xxhash.xxh3_128_digest, strings)), np.uint64).reshape(-1, 2)


def runs_of(texts: list[bytes], least: int = LEAST) -> Runs:
    """All runs of the texts."""
    found: list[tuple] = []
    segments = _segments(texts, least)
    width = least - GRAM + 1
    for a, b in batches_of([s[2] for s in segments], SEGMENT):
        part = segments[a:b]
        raw = b"".join(s[2] for s in part)
        data = np.frombuffer(raw, np.uint8)
        edges = np.cumsum([0, *(len(s[2]) for s in part)])
        sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(_RANDOM[data] * powers()[0][: len(data)], out=sums[1:])
        grams = mixed((sums[GRAM:] - sums[:-GRAM]) * powers()[1][: len(data) - GRAM + 1])
        anchor = sliding_least(grams, width)
        segment = np.repeat(np.arange(len(part)), np.diff(edges))[: len(anchor)]
        valid = np.arange(len(anchor)) + least <= edges[1:][segment]
        new = valid.copy()
        new[1:] &= ~valid[:-1] | (anchor[1:] != anchor[:-1])
        begin = np.flatnonzero(new)
        ends = valid.copy()
        ends[:-1] &= ~valid[1:] | (anchor[1:] != anchor[:-1])
        windows = np.flatnonzero(ends) + 1 - begin
        # a run can only repeat in itself if its anchor's gram stands more than once in its segment
        shown = np.where(valid, anchor, np.uint64(0))
        padded = np.concatenate([np.zeros(width - 1, np.uint64), shown, np.zeros(width - 1, np.uint64)])
        most = ~sliding_least(~padded, width)[: len(grams)]
        picked = np.flatnonzero(most == grams)
        where = np.repeat(np.arange(len(part)), np.diff(edges))[picked].astype(np.uint64) * np.uint64(0x9FB21C651E98DF25)
        values, counts = np.unique(grams[picked] ^ where, return_counts=True)
        own = anchor[begin] ^ segment[begin].astype(np.uint64) * np.uint64(0x9FB21C651E98DF25)
        alone = counts[np.minimum(np.searchsorted(values, own), len(values) - 1)] < 2
        docs, offsets = np.array([s[0] for s in part]), np.array([s[1] for s in part])
        seg = segment[begin]
        # least hashes crowd at the low end; mixed once more they spread over the key ranges
        digest = digests(raw[i:j] for i, j in zip(begin.tolist(), (begin + windows + least - 1).tolist()))
        found.append((mixed(anchor[begin]), digest, docs[seg], offsets[seg] + begin - edges[:-1][seg], windows, alone))
    if not found:
        empty = np.zeros(0, np.int64)
        return Runs(empty.astype(np.uint64), np.zeros((0, 2), np.uint64), empty, empty, empty, empty.astype(bool))
    return Runs(*(np.concatenate(x) for x in zip(*found)))


def _ordered(block: pa.Table) -> tuple[pa.Table, list[bytes]]:
    """The block's rows in an order that doesn't depend on how they came."""
    block = block.sort_by([(c, "ascending") for c in ("doc_id", "text", *(c for c in block.column_names if c not in ("doc_id", "text", "block")))])
    return block, block.column("text").cast(pa.binary()).to_pylist()


def _distinct(runs: Runs) -> tuple[np.ndarray, np.ndarray]:
    """Order by (anchor, digest), and where each distinct pair begins in it."""
    order = np.lexsort((runs.digest[:, 1], runs.digest[:, 0], runs.anchor))
    a, d = runs.anchor[order], runs.digest[order]
    return order, np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (d[1:] != d[:-1]).any(axis=1)])) if len(order) else order


def _table(rows: list[tuple]) -> pa.Table:
    return pa.table([pa.array([r[i] for r in rows], t) for i, t in enumerate(_ROW_TYPES.types)], schema=_ROW_TYPES)


def ask(block: pa.Table, ranges: int, least: int) -> pa.Table:
    """The block's distinct runs, how often each occurs, and which may repeat in themselves."""
    number = block.column("block")[0].as_py()
    runs = runs_of(_ordered(block)[1], least)
    order, first = _distinct(runs)
    counts = np.diff(np.append(first, len(order)))
    anchor, digest = runs.anchor[order][first], runs.digest[order][first]
    alone = np.logical_and.reduceat(runs.alone[order], first) if len(first) else runs.alone
    at = slices(anchor, ranges)
    return _table([
        ("ask", i, number, pack_sorted(anchor[a:b]), digest[a:b].tobytes(), pack(np.minimum(counts[a:b], 2).astype(np.uint64)), pack(alone[a:b].astype(np.uint64)))
        for i, (a, b) in enumerate(zip(at[:-1], at[1:])) if a < b
    ])


def answer(asked: pa.Table, hot: int) -> pa.Table:
    """For every run asked about: is it repeated, are its bytes wanted from this block, has its anchor too many distinct runs."""
    asked = asked.sort_by("block")
    parts = [unpack_sorted(x.as_py()) for x in asked.column("a")]
    sizes = [len(p) for p in parts]
    anchor = np.concatenate(parts)
    digest = np.concatenate([np.frombuffer(x.as_py(), np.uint64).reshape(-1, 2) for x in asked.column("b")])
    counts = np.concatenate([unpack(x.as_py()) for x in asked.column("c")]).astype(np.int64)
    alone = np.concatenate([unpack(x.as_py()) for x in asked.column("d")]).astype(bool)
    order = np.lexsort((digest[:, 1], digest[:, 0], anchor))  # equal runs stay in the order of blocks: the first owns them
    a, d = anchor[order], digest[order]
    new_anchor = np.concatenate([[True], a[1:] != a[:-1]])
    new_run = new_anchor | np.concatenate([[True], (d[1:] != d[:-1]).any(axis=1)])
    run, group = np.cumsum(new_run) - 1, np.cumsum(new_anchor) - 1
    total = np.bincount(run, weights=counts[order])
    distinct = np.bincount(group, weights=new_run)
    closer = (distinct > 1) | (np.bincount(group, weights=~alone[order]) > 0)
    flags = np.zeros(len(a), np.uint8)
    flags[order] = REPEATED * (total[run] > 1) + SENT * (new_run & closer[group]) + BUSY * (distinct[group] > hot)
    return _table([("answer", asked.column("part")[i].as_py(), asked.column("block")[i].as_py(), pack(f.astype(np.uint64)), None, None, None) for i, f in enumerate(np.split(flags, np.cumsum(sizes)[:-1]))])


def _spans(block: int, doc: np.ndarray, begin: np.ndarray, end: np.ndarray) -> tuple:
    return ("spans", 0, block, pack(doc.astype(np.uint64)), pack(begin.astype(np.uint64)), pack((end - begin).astype(np.uint64)), None)


def sort_out(block: pa.Table, answers: pa.Table, ranges: int, least: int) -> pa.Table:
    """Spans of repeated runs, and what goes on: bytes of runs for the suffix arrays, window hashes of busy anchors."""
    number = block.column("block")[0].as_py()
    texts = _ordered(block)[1]
    runs = runs_of(texts, least)
    order, first = _distinct(runs)
    if not len(first):
        return _table([])
    flags = np.concatenate([unpack(x) for _, x in sorted(zip(answers.column("part").to_pylist(), answers.column("a").to_pylist()))])
    of_run = np.zeros(len(order), np.uint8)
    of_run[order] = np.repeat(flags, np.diff(np.append(first, len(order))))
    done = np.flatnonzero(of_run & REPEATED)
    rows = [_spans(number, runs.doc[done], runs.begin[done], runs.begin[done] + runs.windows[done] + least - 1)] if len(done) else []
    sent = order[first[(flags & SENT) > 0]]
    busy = (of_run[sent] & BUSY) > 0
    settled = (of_run[sent] & REPEATED) > 0
    doc, begin, size = runs.doc[sent], runs.begin[sent], runs.windows[sent] + least - 1
    at = slices(runs.anchor[sent], ranges * FINER)
    for i, (low, high) in enumerate(zip(at[:-1], at[1:])):
        chosen = np.arange(low, high)[~busy[low:high]]
        if len(chosen):
            raw = b"".join(texts[d][b : b + n] for d, b, n in zip(doc[chosen].tolist(), begin[chosen].tolist(), size[chosen].tolist()))
            rows.append(("bytes", i, number, pack(np.frombuffer(raw, np.uint8)), pack(np.concatenate([x[chosen].astype(np.uint64) for x in (size, doc, begin, settled)])), None, None))
    if busy.any():
        found, docs, begins = [], [], []
        for k in np.flatnonzero(busy).tolist():
            raw = texts[doc[k]][begin[k] : begin[k] + size[k]]
            start = np.arange(len(raw) - least + 1)
            found.append(digests(raw[i : i + least] for i in range(len(start))))
            docs.append(np.full(len(start), 0 if settled[k] else doc[k] + 1))  # 0: needs no answer
            begins.append(start + begin[k])
        every, docs, begins = (np.concatenate(x) for x in (found, docs, begins))
        by_digest = np.argsort(every[:, 0], kind="stable")
        every, docs, begins = every[by_digest], docs[by_digest], begins[by_digest]
        at = slices(every[:, 0], ranges)
        rows += [("windows", i, number, pack_sorted(every[a:b, 0]), pack(docs[a:b].astype(np.uint64)), pack(begins[a:b].astype(np.uint64)), every[a:b, 1].tobytes()) for i, (a, b) in enumerate(zip(at[:-1], at[1:])) if a < b]
    return _table(rows)


def look_closer(sent: pa.Table, least: int) -> pa.Table:
    """Spans found among the runs' bytes of one range of anchors, or among the window hashes of one range."""
    return _by_windows(sent, least) if sent.column("kind")[0].as_py() == "windows" else _by_suffixes(sent, least)


def _by_suffixes(sent: pa.Table, least: int) -> pa.Table:
    strings: list[bytes] = []
    blocks, docs, begins, settled = [], [], [], []
    for block, raw, packed in zip(*(sent.column(c).to_pylist() for c in ("block", "a", "b"))):
        size, doc, begin, known = unpack(packed).astype(np.int64).reshape(4, -1)
        raw = unpack(raw).tobytes()
        edges = np.cumsum([0, *size])
        strings += [raw[a:b] for a, b in zip(edges[:-1], edges[1:])]
        blocks.append(np.full(len(size), block)), docs.append(doc), begins.append(begin), settled.append(known)
    blocks, docs, begins, settled = (np.concatenate(x) for x in (blocks, docs, begins, settled))
    array = EnhancedSuffixArray(strings)
    change = np.zeros(len(array.data) + 1, np.int64)
    for length, positions in array.maximal_repeats(least):
        np.add.at(change, positions, 1)
        np.add.at(change, positions + length, -1)
    covered = np.cumsum(change[:-1]) > 0
    edge = np.zeros(len(covered) + 1, bool)
    edge[array.first] = True
    begin = np.flatnonzero(covered & (edge[:-1] | np.concatenate([[True], ~covered[:-1]])))
    end = np.flatnonzero(covered & (edge[1:] | np.concatenate([~covered[1:], [True]]))) + 1
    which = array.string[begin]
    keep = settled[which] == 0
    which, begin, end = which[keep], begin[keep], end[keep]
    start = begins[which] + begin - array.first[which]
    rows = [_spans(int(b), docs[which[mine]], start[mine], (start + end - begin)[mine]) for b in np.unique(blocks[which]) for mine in [blocks[which] == b]]
    return _table(rows)


def _by_windows(sent: pa.Table, least: int) -> pa.Table:
    found = [np.column_stack([unpack_sorted(x), np.frombuffer(y, np.uint64)]) for x, y in zip(sent.column("a").to_pylist(), sent.column("d").to_pylist())]
    every = np.concatenate(found)
    order = np.lexsort((every[:, 1], every[:, 0]))
    same = (every[order[1:]] == every[order[:-1]]).all(axis=1)
    again = np.zeros(len(every), bool)
    again[order[1:]] = same
    again[order[:-1]] |= same
    rows, edges = [], np.cumsum([0, *map(len, found)])
    for block, doc, begin, a, b in zip(sent.column("block").to_pylist(), sent.column("b").to_pylist(), sent.column("c").to_pylist(), edges[:-1], edges[1:]):
        doc, begin = unpack(doc).astype(np.int64), unpack(begin).astype(np.int64)
        mine = again[a:b] & (doc > 0)
        if mine.any():
            rows.append(_spans(block, doc[mine] - 1, begin[mine], begin[mine] + least))
    return _table(rows)


def united(doc: np.ndarray, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The same bytes as maximal spans, in order."""
    order = np.lexsort((begin, doc))
    doc, begin, end = doc[order], begin[order], end[order]
    if not len(doc):
        return doc, begin, end
    base = int(end.max()) + 2
    reach = np.maximum.accumulate(doc * base + end)
    new = np.concatenate([[True], doc[1:] * base + begin[1:] > reach[:-1]])
    first = np.flatnonzero(new)
    return doc[first], begin[first], reach[np.append(first[1:], len(doc)) - 1] - doc[first] * base


def remove(block: pa.Table, spans: pa.Table, carry: list[str], wanted: list[str]) -> pa.Table:
    """The block's documents with what is left of them; ``kept_text`` leaves out characters of which bytes went."""
    block, texts = _ordered(block)
    got = [[unpack(x.as_py()).astype(np.int64) for x in spans.column(c)] for c in ("a", "b", "c")] if spans.num_rows else [[], [], []]
    doc, begin, length = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in got)
    doc, begin, end = united(doc, begin, begin + length)
    edges = np.searchsorted(doc, np.arange(len(texts) + 1))
    columns: dict[str, list] = {name: [] for name in wanted}
    for i, text in enumerate(texts):
        starts, stops = begin[edges[i] : edges[i + 1]].tolist(), end[edges[i] : edges[i + 1]].tolist()
        left = b"".join(text[a:b] for a, b in zip([0, *stops], [*starts, len(text)])) if starts else text
        values = {
            "n_bytes": len(text), "n_removed": len(text) - len(left), "n_spans": len(starts), "kept": left, "span_begins": starts, "span_ends": stops,
            "kept_sha256": hashlib.sha256(left).hexdigest() if "kept_sha256" in columns else None, "kept_text": left.decode("utf-8", "ignore") if "kept_text" in columns else None,
        }
        for name, column in columns.items():
            column.append(values[name])
    types = {"kept_sha256": pa.string(), "kept": pa.binary(), "kept_text": pa.string(), "span_begins": pa.list_(pa.int64()), "span_ends": pa.list_(pa.int64())}
    return pa.table([*(block.column(c) for c in ("doc_id", *carry)), *(pa.array(v, types.get(n, pa.int64())) for n, v in columns.items())], names=["doc_id", *carry, *wanted])


def remove_repeats(docs: DataFrame, least: int = LEAST, hot: int = HOT, block_bytes: int = BLOCK_BYTES, carry: list[str] | None = None, wanted: list[str] | None = None) -> DataFrame:
    """doc_id, the columns to carry, and the ``wanted`` ones (all, if not said) of n_bytes, n_removed, n_spans, kept_sha256, kept (the
    remaining bytes), kept_text, span_begins and span_ends of every row."""
    carry = carry or []
    rows = docs.select("doc_id", *carry, text_or_empty().alias("text"))
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0  # how much there is decides only how it is dealt
    blocks, ranges = dealt(size, block_bytes, RANGE_BYTES)
    number = F.pmod(F.xxhash64("doc_id", F.octet_length("text")), F.lit(blocks)).cast("int")
    parted = rows.withColumn("block", labelled(number, blocks)).repartition(blocks, "block")
    asked = parted.groupBy("block").applyInArrow(lambda b: ask(b, ranges, least), _ROW)
    answers = asked.groupBy("part").applyInArrow(lambda a: answer(a, hot), _ROW)
    sorted_out = cut(parted.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(lambda b, a: sort_out(b, a, ranges, least), _ROW))
    found = sorted_out.filter("kind <> 'spans'").groupBy("kind", "part").applyInArrow(lambda s: look_closer(s, least), _ROW)
    spans = sorted_out.filter("kind = 'spans'").union(found)
    fields = [f for f in T.StructType.fromDDL(RESULT) if wanted is None or f.name in wanted]
    result = T.StructType([*docs.select(F.col("doc_id").cast("long"), *carry).schema.fields, *fields])
    return parted.groupBy("block").cogroup(spans.groupBy("block")).applyInArrow(lambda b, s: remove(b, s, carry, [f.name for f in fields]), result)
