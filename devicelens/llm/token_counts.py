"""Token counts of whole texts by overlap resynchronisation.

A text of at most ``chunk_chars`` characters is encoded as it stands. A longer one is cut into chunks that overlap; every chunk is encoded
with the offsets of its tokens. Two neighbours are spliced at a place inside their overlap that both have as a boundary between tokens,
from which on, up to the last stable place of the overlap, both have the same tokens at the same offsets, and that is proven stable: white space
stands right before it and a character that is none stands at it. No token of this kind of tokenizer spans white space, and what it
does on one side of such a place can't depend on the other side, so the splice yields the tokens of the whole text. Where an
overlap holds no such place (one endless word) or the two don't align, it is widened, and so is the chunk, at last up to the whole text.

Short texts come to the library in pieces between blanks, many at once, and a worker remembers what it gave for each, up to a bound in bytes.

Null texts count as empty; an empty text has 0 tokens; repeated rows are counted each; other columns don't matter.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import portions, quiet_tokenizers, text_or_empty

CHUNK_CHARS, OVERLAP_CHARS = 32_768, 512
REMEMBERED_BYTES, LONG = 64 << 20, 512  # of a worker's memory; characters of a piece that isn't remembered
JOINED = 16_384  # characters of unseen pieces that are handed to the library at once

_BLANK = re.compile(r" (?=\S)")
_DOUBTFUL = re.compile(r" (?=\s|$)")
_ENCODERS: dict[str, PieceEncoder] = {}


def pieces(text: str) -> list[str]:
    """The text cut at every single blank that a visible character follows."""
    return _BLANK.split(text) if _DOUBTFUL.search(text) else text.split(" ")


class PieceEncoder:
    """Counts and offsets of the library's tokens, remembered by piece."""

    def __init__(self, path: str):
        quiet_tokenizers()
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.counts: dict[str, int] = {}
        self.held = 0

    @classmethod
    def of(cls, path: str) -> PieceEncoder:
        if path not in _ENCODERS:
            _ENCODERS[path] = cls(path)
        return _ENCODERS[path]

    def learn(self, unseen: list[str]) -> None:
        """Counts of pieces that aren't remembered yet, many of them in one call of the library."""
        group: list[str] = []
        size = 0
        for piece in unseen:
            group.append(piece)
            size += len(piece)
            if size >= JOINED:
                self._learn_joined(group)
                group, size = [], 0
        if group:
            self._learn_joined(group)

    def _learn_joined(self, group: list[str]) -> None:
        offsets = self.library.encode(" ".join(group), add_special_tokens=False).offsets
        starts = np.cumsum([0, *(len(p) + 1 for p in group)])
        first = np.fromiter((a for a, _ in offsets), np.int64, len(offsets))
        counts = np.bincount(np.searchsorted(starts, first, "right") - 1, minlength=len(group))
        self.counts.update(zip(group, counts.tolist()))
        self.held += sum(150 + 4 * len(p) for p in group)

    def count(self, text: str) -> int:
        """Tokens of a text, from its pieces between blanks."""
        if self.held > REMEMBERED_BYTES:
            self.counts.clear()
            self.held = 0
        cut = pieces(text)
        try:
            return sum(map(self.counts.__getitem__, cut))
        except KeyError:
            unseen = {*cut}.difference(self.counts)
        alone = {p: len(self.spans(p)) for p in unseen if len(p) > LONG}
        self.learn([p for p in unseen if p not in alone])
        return sum(map((self.counts | alone if alone else self.counts).__getitem__, cut))

    def spans(self, chunk: str) -> list[tuple[int, int]]:
        """Where each token of the chunk begins and ends, by character."""
        return self.library.encode(chunk, add_special_tokens=False).offsets


def stable(text: str, at: int) -> bool:
    """Whether the tokens before and after this place are the same whatever lies beyond it."""
    return 0 < at < len(text) and text[at - 1] in " \n\t\r" and not text[at].isspace()


def splice(left: np.ndarray, right: np.ndarray, text: str, low: int, high: int) -> int | None:
    """A place in [low, high) where tokens of a left chunk (rows of begin and end) give way to those of a right one, which begins at low; or none."""
    places = [at for at in range(low + 1, high) if stable(text, at)]
    if len(places) < 2:
        return None
    last = places[-1]  # what follows it may differ, as the left chunk ends within a word
    of = lambda spans, at: spans[np.searchsorted(spans[:, 0], at) : np.searchsorted(spans[:, 0], last)]
    for at in places[:-1]:
        a, b = of(left, at), of(right, at)
        before = left[: np.searchsorted(left[:, 0], at)]
        if np.array_equal(a, b) and not (len(before) and before[-1, 1] > at):
            return at
    return None


def spliced_count(text: str, encoder: PieceEncoder, chunk: int = CHUNK_CHARS, overlap: int = OVERLAP_CHARS) -> int:
    """Tokens of a long text, encoded in overlapping chunks."""
    offsets = lambda a, b: np.array(encoder.spans(text[a:b]), np.int64).reshape(-1, 2) + a
    total, start, stop, width = 0, 0, min(chunk, len(text)), overlap
    spans, counted = offsets(start, stop), 0  # the chunk's tokens that begin before ``counted`` are part of the sum
    while stop < len(text):
        low = stop - width
        if low <= counted:  # the overlap would reach behind the last splice: take a longer chunk
            stop = min(len(text), stop + (stop - start))
            spans = offsets(start, stop)
            continue
        end = min(len(text), low + max(chunk, 2 * width))
        following = offsets(low, end)
        at = splice(spans, following, text, low, stop)
        if at is None:
            width *= 2
            continue
        total += int(np.count_nonzero((spans[:, 0] >= counted) & (spans[:, 0] < at)))
        start, stop, spans, counted, width = low, end, following, at, overlap
    return total + int(np.count_nonzero(spans[:, 0] >= counted))


def count_tokens(text: str | None, encoder: PieceEncoder, chunk: int = CHUNK_CHARS, overlap: int = OVERLAP_CHARS) -> int:
    if not text:
        return 0
    return spliced_count(text, encoder, chunk, overlap) if len(text) > chunk else encoder.count(text)


def token_counts(docs: DataFrame, tokenizer_path: str, limit: int = 2048, chunk_chars: int = CHUNK_CHARS, overlap_chars: int = OVERLAP_CHARS) -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit of every row; map-only."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = PieceEncoder.of(tokenizer_path)
        for batch in portions(batches, 2):
            counts = [count_tokens(t.as_py(), encoder, chunk_chars, overlap_chars) for t in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(counts, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    rows = docs.select("doc_id", F.octet_length(text_or_empty()).cast("long").alias("n_bytes"), text_or_empty().alias("text"))
    return rows.mapInArrow(counted, "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)
