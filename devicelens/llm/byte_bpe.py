"""Byte-level BPE encoding and decoding with a minimal acyclic transducer of frequent words as the lexicon.

The corpus's most frequent words, up to a bound (``LEXICON_WORDS``), are counted over all texts and encoded once on the driver. An automaton that
shares suffixes holds them with their id sequences as outputs; executors get it as a file and memory-map it. A word that it doesn't
know is merged exactly, by rank. Words are what lies between places where the pattern must begin a new one (a blank before a visible
character), so that the ids of a word depend on nothing else. A worker remembers words up to a bound in bytes.

Null texts count as empty; the empty text has no ids, and decodes to itself; repeated rows are encoded each; other columns don't matter. A
long text is worked on in stretches; a word of any length is merged in n log n steps.
"""

from __future__ import annotations

import codecs
import hashlib
import heapq
import json
import os
import tempfile
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark import SparkFiles
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window as W

from .common import cut, portions, text_or_empty
from .lexicon import Lexicon, compile_lexicon
from .token_counts import pieces

LEXICON_WORDS, LONGEST_WORD = 50_000, 64  # words of the lexicon at most, and characters of one
_NEVER = 1 << 40
REMEMBERED_BYTES, LONG, STRETCH = 24 << 20, 512, 1 << 20  # of a worker's memory; characters of a word that isn't remembered; characters worked on at once
#: The pattern of words of this vocabulary's library.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"

_CODECS: dict[tuple[str, str], BpeCodec] = {}
_SHIPPED: set[tuple[str, str]] = set()


def byte_letters() -> dict[str, int]:
    """The letter that the vocabulary file writes for each byte: printable Latin-1 stands for itself, the rest is numbered from 256."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    others = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(others)}


class Vocabulary:
    """Ids of bytes, of merged pairs with their ranks, and of the special strings."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = byte_letters()
        vocab = spec["model"]["vocab"]
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        self.bytes_of = {i: bytes(map(letters.__getitem__, w)) for w, i in vocab.items() if all(c in letters for c in w)} | {i: s.encode() for s, i in self.special.items()}
        self.byte_ids = np.array([vocab[c] for c, _ in sorted(letters.items(), key=lambda x: x[1])], np.int64)
        pairs = (m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"])
        self.merges = {(vocab[a], vocab[b]): (rank, vocab[a + b]) for rank, (a, b) in enumerate(pairs)}
        keys = np.array([a << 32 | b for a, b in self.merges], np.int64)
        order = np.argsort(keys)
        # the last entries stand for a pair that never merges
        self.keys, self.ranks = np.append(keys[order], np.int64(-1)), np.append(order, _NEVER)
        self.merged = np.append(np.array([m for _, m in self.merges.values()], np.int64)[order], -1)

    def _pair(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Places of pairs among the merges."""
        key = left << 32 | right
        at = np.searchsorted(self.keys[:-1], key)
        return np.where(self.keys[at] == key, at, len(self.keys) - 1)

    def merge(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words of the pattern, one after another, and how many each has. In every round each word merges its pair of the least rank, of
        equal ones the leftmost, until none can; the rounds are made for all words together."""
        lengths = np.array([len(w) for w in words], np.int64)
        ended: list[tuple[np.ndarray, np.ndarray]] = []  # (word, its ids)
        for i in np.flatnonzero(lengths > LONGEST_WORD).tolist():
            found = np.array(self._merge_long(self.byte_ids[np.frombuffer(words[i], np.uint8)].tolist()))
            ended.append((np.full(len(found), i), found))
        short = np.flatnonzero((lengths > 0) & (lengths <= LONGEST_WORD))
        ids = self.byte_ids[np.frombuffer(b"".join([words[i] for i in short.tolist()]), np.uint8)]
        word, none = np.repeat(short, lengths[short]), len(self.keys) - 1
        pair = np.full(len(ids), none)
        inner = np.flatnonzero(word[1:] == word[:-1])
        pair[inner] = self._pair(ids[inner], ids[inner + 1])
        while len(ids):
            first = np.flatnonzero(np.append(True, word[1:] != word[:-1]))
            rank = self.ranks[pair]
            least = np.repeat(np.minimum.reduceat(rank, first), np.diff(np.append(first, len(ids))))
            over = least == _NEVER
            if over.any():
                ended.append((word[over], ids[over]))
                ids, word, pair, rank, least = (x[~over] for x in (ids, word, pair, rank, least))
            here = np.flatnonzero(rank == least)
            here = here[np.append(True, word[here[1:]] != word[here[:-1]])] if len(here) else here
            ids[here] = self.merged[pair[here]]
            keep = np.ones(len(ids), bool)
            keep[here + 1] = False
            ids, word, pair = ids[keep], word[keep], pair[keep]
            here -= np.arange(len(here))  # one id went before each
            for side in (here - 1, here):  # the pairs on both sides are new
                side = side[side >= 0]
                pair[side] = none
                side = side[side + 1 < len(ids)]
                side = side[word[side] == word[side + 1]]
                pair[side] = self._pair(ids[side], ids[side + 1])
        word, ids = (np.concatenate([np.empty(0, np.int64), *(x[k] for x in ended)]) for k in (0, 1))
        order = np.argsort(word, kind="stable")
        return ids[order].astype(np.int32), np.bincount(word, minlength=len(words))

    def _merge_long(self, ids: list[int]) -> list[int]:
        """The same with a heap of pairs over linked places."""
        n, get = len(ids), self.merges.get
        at, after, before = array("i", ids), array("i", range(1, n + 1)), array("i", range(-1, n - 1))
        heap = [found[0] * n + i for i in range(n - 1) if (found := get((ids[i], ids[i + 1])))]
        heapq.heapify(heap)
        while heap:
            rank, i = divmod(heapq.heappop(heap), n)
            j = after[i]
            found = get((at[i], at[j])) if at[i] >= 0 and j < n else None
            if not found or found[0] != rank:  # one of the two was merged meanwhile
                continue
            at[i], at[j], after[i] = found[1], -1, after[j]
            if after[j] < n:
                before[after[j]] = i
                if pair := get((at[i], at[after[i]])):
                    heapq.heappush(heap, pair[0] * n + i)
            if before[i] >= 0 and (pair := get((at[before[i]], at[i]))):
                heapq.heappush(heap, pair[0] * n + before[i])
        return [i for i in at if i >= 0]

    def ids(self, texts: list[str], pieces: bool = True) -> list[bytes]:
        """Ids of texts without special strings, as 32-bit numbers. If they are pieces, words end where they do, so that they can stand together."""
        words = _WORDS.findall("".join(texts)) if pieces else [w for t in texts for w in words_of(t)]
        distinct = {w: i for i, w in enumerate(dict.fromkeys(words))}
        flat, counts = self.merge([w.encode("utf-8") for w in distinct])
        which = np.fromiter(map(distinct.__getitem__, words), np.int64, len(words))
        # the ids of every word in the order of words
        begins = np.cumsum(counts) - counts
        sizes = counts[which]
        at = np.repeat(begins[which] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())
        raw = flat[at].tobytes()
        # the ids of every text
        word_ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)))
        text_ends = np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)))
        ends = 4 * np.append(0, np.append(0, np.cumsum(sizes))[np.searchsorted(word_ends, text_ends, "right")])
        return [raw[a:b] for a, b in zip(ends[:-1].tolist(), ends[1:].tolist())]


_WORDS = regex.compile(PATTERN)


def words_of(piece: str) -> list[str]:
    return [piece] if piece[1:].isalpha() and piece[0] == " " else _WORDS.findall(piece)


def stretches(text: str, at_most: int = STRETCH) -> Iterator[str]:
    """The text in parts of some length, each but the first beginning with a blank before a visible character."""
    start = 0
    while len(text) - start > at_most:
        cut = start + at_most
        while (cut := text.find(" ", cut)) >= 0 and (cut + 1 == len(text) or text[cut + 1].isspace()):
            cut += 1
        if cut < 0:
            break
        yield text[start:cut]
        start = cut
    yield text[start:]


class BpeCodec:
    """Ids of texts and texts of ids. A worker remembers the ids of pieces, as 32-bit numbers: those of the lexicon, which are bounded, and others up
    to a bound in bytes."""

    def __init__(self, path: str, lexicon_path: str | None = None):
        self.vocabulary = Vocabulary(path)
        self.lexicon = Lexicon(lexicon_path) if lexicon_path else None
        self.special = self.vocabulary.special
        self.marks = regex.compile("|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True))) if self.special else None
        size = max(self.vocabulary.bytes_of, default=-1) + 1
        self.bytes_of = [self.vocabulary.bytes_of.get(i, b"") for i in range(size)]
        self.decimal_of = [b"%d," % i for i in range(size)]
        self.known: dict[str, bytes] = {}
        self.steady: dict[str, bytes] = {}
        self.held = 0

    @classmethod
    def of(cls, path: str, lexicon_path: str) -> BpeCodec:
        if (path, lexicon_path) not in _CODECS:
            _CODECS.clear()  # a worker keeps one
            _CODECS[path, lexicon_path] = cls(path, lexicon_path)
        return _CODECS[path, lexicon_path]

    def segments(self, text: str) -> Iterator[tuple[str, int | None]]:
        """The text between special strings, and these with their ids; the earliest goes first, of several the longest."""
        at = 0
        for found in self.marks.finditer(text) if self.marks else ():
            if found.start() > at:
                yield text[at : found.start()], None
            yield found.group(), self.special[found.group()]
            at = found.end()
        if at < len(text):
            yield text[at:], None

    def learn(self, cut: set[str]) -> None:
        """Remembers the pieces that aren't yet, those of the lexicon by one walk of its automaton for all, the others by merges; they come without
        the blank before them."""
        if self.held > REMEMBERED_BYTES:
            self.known, self.held = dict(self.steady), 0
        unseen = [" " + p for p in cut.difference(self.known)]
        if self.lexicon:
            places = self.lexicon.find([p.encode("utf-8") for p in unseen])
            found = {p[1:]: self.lexicon.output(place) for p, place in zip(unseen, places) if place >= 0}
            self.steady |= found
            self.known |= found
            unseen = [p for p, place in zip(unseen, places) if place < 0]
        raw = self.vocabulary.ids(unseen)
        self.known.update(zip((p[1:] for p in unseen), raw))
        self.held += sum(map(len, unseen)) + sum(map(len, raw)) + 200 * len(raw)

    def parts(self, texts: list[str]) -> Iterator[tuple[int, bytes, list[str]]]:
        """The texts in order as (number of the text, ids, remembered pieces after them), some of these for each; learns as much text at once as is
        worked on at once."""
        group: list[tuple[int, bytes | str, list[str]]] = []
        size = 0

        def flushed() -> Iterator[tuple[int, bytes, list[str]]]:
            self.learn({p for _, _, rest in group for p in rest})
            firsts = iter(self.vocabulary.ids([first for _, first, _ in group if isinstance(first, str)], False))
            for number, first, rest in group:
                yield number, next(firsts) if isinstance(first, str) else first, rest
            group.clear()

        for number, text in enumerate(texts):
            for segment, special in self.segments(text):
                if special is not None:
                    group.append((number, array("i", [special]).tobytes(), []))
                    continue
                for stretch in stretches(segment):
                    first, *rest = pieces(stretch)
                    at = 0
                    if max(map(len, rest), default=0) > LONG:  # long pieces aren't remembered
                        for i, piece in enumerate(rest):
                            if len(piece) > LONG:
                                group.append((number, first, rest[at:i]))
                                first, at = " " + piece, i + 1
                    group.append((number, first, rest[at:]))
                    size += len(stretch)
                    if size >= STRETCH:
                        yield from flushed()
                        size = 0
        yield from flushed()

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        joined: list[list[bytes]] = [[] for _ in texts]
        for number, ids, known in self.parts(texts):
            joined[number].append(ids)
            joined[number] += map(self.known.__getitem__, known)
        return [np.frombuffer(b"".join(x), np.int32) for x in joined]

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", "replace")

    def digests(self, texts: list[str]) -> list[tuple[int, str, str]]:
        """Number of ids, SHA-256 of the ids joined by commas, and SHA-256 of the decoded text, of each text."""
        counts, ids_sha, text_sha = [0] * len(texts), [hashlib.sha256() for _ in texts], [hashlib.sha256() for _ in texts]
        readers = [codecs.getincrementaldecoder("utf-8")("replace") for _ in texts]
        for number, first, known in self.parts(texts):
            ids = np.frombuffer(first + b"".join(map(self.known.__getitem__, known)), np.int32).tolist()
            if ids:
                decimals = b"".join(map(self.decimal_of.__getitem__, ids))
                ids_sha[number].update(b"," + decimals[:-1] if counts[number] else decimals[:-1])
                counts[number] += len(ids)
                text_sha[number].update(readers[number].decode(b"".join(map(self.bytes_of.__getitem__, ids))).encode("utf-8"))
        for reader, sha in zip(readers, text_sha):
            sha.update(reader.decode(b"", True).encode("utf-8"))
        return [(n, a.hexdigest(), b.hexdigest()) for n, a, b in zip(counts, ids_sha, text_sha)]


def frequent_words(docs: DataFrame, most: int = LEXICON_WORDS) -> list[str]:
    """The words between blanks that occur most often, at least twice, counted over all texts: those of the least count with which no more than
    ``most`` occur as often, so that only these come to the driver."""
    words = docs.select(F.explode(F.split(text_or_empty(), " ")).alias("word")).filter(F.length("word").between(1, LONGEST_WORD))
    counts = cut(words.groupBy("word").agg(F.count("*").alias("n")).filter("n > 1"))
    often = counts.groupBy("n").agg(F.count("*").alias("words")).withColumn("above", F.sum("words").over(W.orderBy(F.desc("n"))))
    least = often.filter(F.col("above") <= most).agg(F.min("n")).first()[0]
    return sorted(r.word for r in counts.filter(F.col("n") >= least).select("word").collect()) if least else []


def ship_lexicon(docs: DataFrame, path: str, most: int = LEXICON_WORDS) -> str:
    """Compiles the lexicon of these texts and hands it to all executors; gives the name to look it up by."""
    codec, context = BpeCodec(path), docs.sparkSession.sparkContext
    plain = [" " + w for w in frequent_words(docs, most) if not (codec.marks and codec.marks.search(w))]
    plain = [w for w in plain if len(pieces(w)) == 2]
    compiled = compile_lexicon({w.encode("utf-8"): np.frombuffer(raw, np.int32).tolist() for w, raw in zip(plain, codec.vocabulary.ids(plain))})
    name = f"lexicon-{hashlib.sha256(compiled).hexdigest()[:16]}.bin"
    if (context.applicationId, name) not in _SHIPPED:
        at = os.path.join(tempfile.mkdtemp(prefix="devicelens-lexicon-"), name)
        with open(at, "wb") as f:
            f.write(compiled)
        context.addFile(at)  # Spark hands the driver's file out to all executors
        _SHIPPED.add((context.applicationId, name))
    return name


def encode_ids_of(docs: DataFrame, tokenizer_path: str, keep: list[str]) -> DataFrame:
    """The named columns, ids and n_tokens of every row; map-only, after the count of words."""
    name = ship_lexicon(docs, tokenizer_path)
    kept = docs.select(*keep)

    def encoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = BpeCodec.of(tokenizer_path, SparkFiles.get(name))
        for batch in portions(batches, len(keep)):
            ids = codec.encode(batch.column(len(keep)).to_pylist())
            counts = np.array([len(x) for x in ids], np.int64)
            lists = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *counts]), pa.int32()), pa.array(np.concatenate([np.empty(0, np.int32), *ids])))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], lists, pa.array(counts)], [*keep, "ids", "n_tokens"])

    schema = T.StructType(kept.schema.fields + T.StructType.fromDDL("ids array<int>, n_tokens long").fields)
    return docs.select(*keep, text_or_empty().alias("_text")).mapInArrow(encoded, schema)


def encode_ids(docs: DataFrame, tokenizer_path: str) -> DataFrame:
    """doc_id and the ids of every row."""
    return encode_ids_of(docs, tokenizer_path, ["doc_id"]).drop("n_tokens")


def decode_ids(encoded: DataFrame, tokenizer_path: str) -> DataFrame:
    """doc_id and the text of every row of ids; null ids decode to the empty text."""

    def decoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = BpeCodec.of(tokenizer_path, "")
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([codec.decode(x.as_py() or []) for x in batch.column(1)], pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(decoded, "doc_id long, text string")


def round_trip(docs: DataFrame, tokenizer_path: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of every row, without ids crossing to Spark."""
    name = ship_lexicon(docs, tokenizer_path)

    def digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = BpeCodec.of(tokenizer_path, SparkFiles.get(name))
        for batch in portions(batches, 1):
            n, ids, text = zip(*codec.digests(batch.column(1).to_pylist())) if batch.num_rows else ((), (), ())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(text, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", text_or_empty().alias("text")).mapInArrow(digests, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
