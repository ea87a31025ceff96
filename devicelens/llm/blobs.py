"""Sorted 64-bit keys packed into binary columns, so that a shuffle moves a few bytes a key and a few rows a task."""

from __future__ import annotations

import numpy as np
import zstandard

_SQUEEZE, _UNSQUEEZE = zstandard.ZstdCompressor(level=1), zstandard.ZstdDecompressor()


def pack(values: np.ndarray) -> bytes:
    """An array of numbers, compressed, in the least width that holds them."""
    if values.dtype.kind == "u" and len(values):
        top = int(values.max())
        values = values.astype(np.uint8 if top < 1 << 8 else np.uint16 if top < 1 << 16 else np.uint32 if top < 1 << 32 else np.uint64)
    return values.dtype.char.encode() + _SQUEEZE.compress(values.tobytes())


def unpack(blob: bytes) -> np.ndarray:
    return np.frombuffer(_UNSQUEEZE.decompress(blob[1:]), np.dtype(blob[:1].decode()))


def pack_sorted(keys: np.ndarray) -> bytes:
    """Ascending unsigned keys, by their differences; those are split into bytes of equal weight, which compress better."""
    steps = np.diff(keys, prepend=keys[:1] * 0).astype("<u8")
    return _SQUEEZE.compress(steps.view(np.uint8).reshape(-1, 8).T.tobytes())


def unpack_sorted(blob: bytes) -> np.ndarray:
    raw = np.frombuffer(_UNSQUEEZE.decompress(blob), np.uint8)
    return np.cumsum(np.ascontiguousarray(raw.reshape(8, -1).T).view("<u8").ravel(), dtype=np.uint64)


def slices(sorted_keys: np.ndarray, parts: int, bits: int = 64) -> np.ndarray:
    """Where each of ``parts`` equal ranges of the key space begins among sorted keys (one more entry than parts)."""
    edges = np.array([(i << bits) // parts for i in range(1, parts)], np.uint64)
    return np.concatenate([[0], np.searchsorted(sorted_keys, edges), [len(sorted_keys)]])


def merge(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys of all, ascending, with their summed counts."""
    every = np.concatenate(keys)
    order = np.argsort(every, kind="stable")
    every, amount = every[order], np.concatenate(counts).astype(np.uint64)[order]
    first = np.flatnonzero(np.concatenate([[True], every[1:] != every[:-1]])) if len(every) else np.empty(0, np.int64)
    return every[first], np.add.reduceat(amount, first) if len(first) else amount
