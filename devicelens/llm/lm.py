"""Language-model scores from a weighted backoff automaton.

The model: smoothed trigrams. A state is a history that occurs in training: the last two tokens, the last one, or none. An arc reads a token that
was seen behind the history and leads to the longest history that its end is; it weighs (count + S * weight of the token one state
down) / (visits + S), S being the strength of that state's prior. The failure arc, taken only where no arc reads the token, weighs S / (visits + S)
and leads one state down, to the state without the oldest token; the state without history has an arc for every token,
weighing its smoothed share. So all that leaves a state sums to 1. A text is traversed once from left to right; its state is
carried along, and log-weights of arcs and failure arcs are added up. All texts of a block step together.

How it is spread: documents are dealt into blocks of bounded size. A block sends the distinct keys (64-bit hashes of tokens, pairs and
triples) that it needs with its own training counts, packed by key range; each range of keys is merged once, which both makes the counts and
answers every block; a block then holds the part of the automaton that its own documents can reach, and scores them. Nothing is
broadcast but two totals, and nothing is pruned or sampled: the model is that of all training documents.

Texts: null is empty; an empty text is one end token; every text ends in one. Rows whose id repeats are scored each; a null doc_id counts as
training (its remainder is null, thus held_out false). Empty tables give no rows. Other columns don't matter.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blobs import merge, pack, pack_sorted, slices, unpack, unpack_sorted
from .common import dealt, labelled, portions, remainder, text_or_empty
from .vectors_of_text import mixed, words_by_text

ADDED, STRENGTHS = 0.1, (300.0, 5.0)  # of the prior of states of one token and of two
BLOCK_BYTES, RANGE_BYTES, PACK_BYTES = 12 << 20, 16 << 20, 8 << 20  # text of a block, text whose keys one range holds, text packed at once
END, START = np.uint64(0x5EED0E4D), np.uint64(0x5EED57A7)  # keys of the end token and of the state that a text begins in
REQUEST = "kind string, part int, block int, keys binary, counts binary"
KINDS = ("token", "pair", "triple")


def tokens_of(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Keys of all tokens, each text closed by its end, and the first of each text (one more entry than texts)."""
    words, first = words_by_text(texts)
    tokens = np.insert(words, first[1:], END)
    return tokens, first + np.arange(len(first))


def histories_of(tokens: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Keys of each token behind the one before it (or the start), and behind the two before it. A text's first token has one history only, so the
    second key repeats the first."""
    before = np.empty_like(tokens)
    before[1:] = tokens[:-1]
    before[first[:-1]] = START
    with np.errstate(over="ignore"):
        pairs = mixed(before * np.uint64(0x9FB21C651E98DF25) + tokens)
        before[1:] = pairs[:-1]
        triples = mixed(before * np.uint64(0xC2B2AE3D27D4EB4F) + tokens)
    triples[first[:-1]] = pairs[first[:-1]]
    return pairs, triples


def ranked(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys, ascending, where one of each stands, and each key's place among them."""
    order = np.argsort(keys)
    ascending = keys[order]
    new = np.append(True, ascending[1:] != ascending[:-1]) if len(keys) else np.empty(0, bool)
    place = np.empty(len(keys), np.int32)
    place[order] = np.cumsum(new, dtype=np.int32) - 1
    return ascending[new], order[new], place


def packed(batches: Iterator[pa.RecordBatch], blocks: int) -> Iterator[pa.RecordBatch]:
    """Documents as one compressed row for each block that a portion of them goes to: less to shuffle, and to hold, than a row a document."""
    for batch in portions(batches, 1, PACK_BYTES, 1 << 20):
        number = batch.column(3).to_numpy()
        order = np.argsort(number, kind="stable")
        ends = np.searchsorted(number[order], np.arange(blocks + 1)) if blocks <= len(number) else np.append(np.flatnonzero(np.diff(number[order], prepend=-1)), len(number))
        rows = []
        for a, b in zip(ends[:-1].tolist(), ends[1:].tolist()):
            if a < b:
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, batch.schema) as stream:
                    stream.write_batch(batch.take(pa.array(order[a:b])))
                rows.append((int(number[order[a]]), pack(np.frombuffer(sink.getvalue(), np.uint8))))
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], ["block", "documents"])


def documents_of(block: pa.Table) -> pa.Table:
    """A block's documents, in an order that doesn't depend on how they came."""
    found = pa.concat_tables(pa.ipc.open_stream(unpack(x.as_py()).tobytes()).read_all() for x in block.column("documents"))
    return found.sort_by([("doc_id", "ascending"), ("text", "ascending")])


def texts_of(documents: pa.Table) -> list[bytes]:
    return documents.column("text").cast(pa.binary()).to_pylist()


_REQUEST = pa.schema([("kind", pa.string()), ("part", pa.int32()), ("block", pa.int32()), ("keys", pa.binary()), ("counts", pa.binary())])


def ask(block: pa.Table, ranges: int) -> pa.Table:
    """What one block needs and what it adds: its distinct tokens, pairs and triples with their training counts."""
    documents = documents_of(block)
    tokens, first = tokens_of(texts_of(documents))
    training = np.repeat(~np.array(documents.column("held_out").to_pylist(), bool), np.diff(first))
    rows: list[tuple] = []
    number = block.column("block")[0].as_py()
    for kind, keys in zip(KINDS, (tokens, *histories_of(tokens, first))):
        distinct, _, place = ranked(keys)
        counts = np.bincount(place[training], minlength=len(distinct)).astype(np.uint64)
        at = slices(distinct, ranges)
        rows += [(kind, i, number, pack_sorted(distinct[a:b]), pack(counts[a:b])) for i, (a, b) in enumerate(zip(at[:-1], at[1:])) if a < b]
    return pa.table([pa.array([r[i] for r in rows], t) for i, t in enumerate(_REQUEST.types)], schema=_REQUEST)


def answer(asked: pa.Table) -> pa.Table:
    """One range of keys: what all blocks have counted, given back to each in the order it asked."""
    keys = [unpack_sorted(x.as_py()) for x in asked.column("keys")]
    total, counts = merge(keys, [unpack(x.as_py()) for x in asked.column("counts")])
    return asked.select(["kind", "part", "block"]).append_column("counts", pa.array([pack(counts[np.searchsorted(total, k)]) for k in keys], pa.binary()))


def tokens_counted(asked: pa.Table) -> pa.Table:
    """One range of keys: how many tokens there are in training, and how many distinct ones."""
    seen = distinct = 0
    if asked.column("kind")[0].as_py() == "token":
        _, counts = merge([unpack_sorted(x.as_py()) for x in asked.column("keys")], [unpack(x.as_py()) for x in asked.column("counts")])
        seen, distinct = int(counts.sum()), int(np.count_nonzero(counts))
    return pa.table({"seen": [seen], "distinct": [distinct]}, schema=pa.schema([("seen", pa.int64()), ("distinct", pa.int64())]))


class Automaton:
    """States and arcs that a block's documents can reach, numbered as its tokens, pairs and triples are.

    A token is also the state of one token, and a pair the state of two. An arc is there if its count isn't 0. ``below`` and ``state`` give the
    pair that a triple ends with and the state it leaves; ``last`` and ``token`` the same for a pair.
    """

    ROOT = 0

    def __init__(self, counts: dict[str, np.ndarray], visits: np.ndarray, n: int, v: int, last: np.ndarray, token: np.ndarray, state: np.ndarray, below: np.ndarray, strengths: tuple[float, float] = STRENGTHS):
        one, two = strengths
        self.known, self.pairs, self.triples = (counts[k] > 0 for k in KINDS)
        plain = (counts["token"] + ADDED) / (n + ADDED * (v + 1))
        pair = (counts["pair"] + one * plain[token]) / (visits[last] + one)
        triple = (counts["triple"] + two * pair[below]) / (counts["pair"][state] + two)
        self.arcs = tuple(np.log10(x) for x in (plain, pair, triple))
        self.failing = (np.log10(one / (visits + one)), np.log10(two / (counts["pair"] + two)))

    def step(self, order: np.ndarray, one: np.ndarray, two: np.ndarray, token: np.ndarray, pair: np.ndarray, triple: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """From states of so many tokens (numbers ``one`` and ``two``) by a token each: log-weights of what is passed, and how many tokens the states
        have that are reached."""
        weight = np.zeros(len(order))
        at, fits = order == 2, self.triples[triple]
        read = at & fits
        weight[read] = self.arcs[2][triple[read]]
        fail = at & ~fits
        weight[fail] = self.failing[1][two[fail]]
        at, fits = fail | (order == 1), self.pairs[pair]
        read = at & fits
        weight[read] += self.arcs[1][pair[read]]
        fail = at & ~fits
        weight[fail] += self.failing[0][one[fail]]
        read = fail | (order == self.ROOT)
        weight[read] += self.arcs[0][token[read]]
        return weight, np.where(fits, 2, self.known[token])


def traverse(automaton: Automaton, token: np.ndarray, pair: np.ndarray, triple: np.ndarray, first: np.ndarray, start: int) -> np.ndarray:
    """Log10 probability of each text: all texts read a token at a time, from left to right, each carrying its state."""
    lengths = np.diff(first)
    longest = np.argsort(-lengths, kind="stable")
    total = np.zeros(len(lengths))
    begin, still = first[:-1][longest], np.searchsorted(-lengths[longest], -np.arange(1, lengths.max(initial=0) + 1), "right")
    order = np.ones(len(lengths), np.int64)  # the state that a text begins in is one of one token
    one, two = np.full(len(lengths), start), np.zeros(len(lengths), np.int64)
    for t, n in enumerate(still.tolist()):
        at = begin[:n] + t
        read, passed = token[at], pair[at]
        weight, order = automaton.step(order[:n], one[:n], two[:n], read, passed, triple[at])
        total[:n] += weight
        one, two = read, passed
    scores = np.empty(len(lengths))
    scores[longest] = total
    return scores


def score_block(block: pa.Table, answers: pa.Table, strengths: tuple[float, float] = STRENGTHS) -> pa.Table:
    """Builds the block's part of the automaton and traverses its documents."""
    parts = sorted(zip(answers.column("kind").to_pylist(), answers.column("part").to_pylist(), answers.column("counts").to_pylist()))
    counts = {kind: np.concatenate([unpack(c) for k, _, c in parts if k == kind]).astype(float) for kind in KINDS}
    totals = answers.column("totals")[0].as_py()
    documents = documents_of(block)
    tokens, first = tokens_of(texts_of(documents))
    pairs, triples = histories_of(tokens, first)
    keys, _, token = ranked(tokens)
    _, at_pair, pair = ranked(pairs)
    _, at_triple, triple = ranked(triples)
    del tokens, pairs, triples
    start = len(keys)  # the state that texts begin in: visited as often as texts end
    visits = np.append(counts["token"], counts["token"][np.searchsorted(keys, END)])
    before = np.empty_like(token)
    before[1:] = token[:-1]
    before[first[:-1]] = start
    automaton = Automaton(counts, visits, totals["n"], totals["v"], before[at_pair], token[at_pair], pair[np.maximum(at_triple - 1, 0)], pair[at_triple], strengths)
    by_text = lambda x: np.add.reduceat(x, first[:-1])  # noqa: E731  every text has a token, its end
    rows = documents.num_rows
    return pa.table(
        {
            "doc_id": documents.column("doc_id"), "held_out": documents.column("held_out"), "n_tokens": np.diff(first), "n_known": by_text(automaton.known[token].astype(np.int64)), "train_tokens": np.full(rows, totals["n"], np.int64),
            "base_score": by_text(automaton.arcs[0][token]), "score": traverse(automaton, token, pair, triple, first, start),
        },
        schema=pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64())]),
    )


def language_model_scores(docs: DataFrame, folds: int = 10, block_bytes: int = BLOCK_BYTES, strengths: tuple[float, float] = STRENGTHS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score of every row; rows of remainder 0 are held out."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"), F.coalesce(remainder("doc_id", folds) == 0, F.lit(False)).alias("held_out"))
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0  # how much there is decides only how it is dealt
    blocks, ranges = dealt(size, block_bytes, RANGE_BYTES)
    numbered = rows.withColumn("block", F.pmod(F.xxhash64("doc_id", F.octet_length("text")), F.lit(blocks)).cast("int"))
    texts = numbered.mapInArrow(lambda b: packed(b, blocks), "block int, documents binary").withColumn("block", labelled(F.col("block"), blocks)).repartition(blocks, "block")

    requests = texts.groupBy("block").applyInArrow(lambda block: ask(block, ranges), REQUEST).repartition(len(KINDS) * ranges, "kind", "part")  # some range a task, whatever the size
    answers = requests.groupBy("kind", "part").applyInArrow(answer, "kind string, part int, block int, counts binary")
    totals = requests.groupBy("kind", "part").applyInArrow(tokens_counted, "seen long, distinct long").agg(F.struct(F.sum("seen").alias("n"), F.sum("distinct").alias("v")).alias("totals"))
    return texts.groupBy("block").cogroup(answers.withColumn("totals", totals.scalar()).groupBy("block")).applyInArrow(
        lambda block, answered: score_block(block, answered, strengths), "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    )
