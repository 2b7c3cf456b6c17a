"""Vectorised word splitting and hashing over Arrow-sized batches of texts.

A word is a maximal run of bytes outside the six ASCII blanks (0x20, 0x09-0x0D);
on UTF-8 bytes this is the same as on code points.  Hashes are 64-bit polynomial
sums taken from one prefix sum over the whole batch, then mixed, so a batch costs a
handful of numpy passes and no per-word Python work.  They depend on the word's
bytes alone: reruns, executors and partitionings agree.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np

_BASE = 0x9E3779B97F4A7C15 | 1
_BASE_INV = pow(_BASE, -1, 1 << 64)
_BLANK = np.zeros(256, dtype=bool)
_BLANK[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Texts are hashed in blocks of about so many bytes; a longer text is a block of its own.
BLOCK_BYTES = 1 << 21

_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse up to n - 1, kept between calls."""
    if len(_powers[0]) < n:
        for slot, base in ((0, _BASE), (1, _BASE_INV)):
            steps = np.full(n, base, np.uint64)
            steps[0] = 1
            _powers[slot] = np.multiply.accumulate(steps)
    return _powers[0], _powers[1]


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser, so that every bit of a hash depends on every other."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _span_hash(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int) -> np.ndarray:
    power, inverse = _power_tables(len(data) + 1)
    prefix = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(seed)) * power[: len(data)], out=prefix[1:])
    raw = (prefix[ends] - prefix[starts]) * inverse[starts]
    return mix(raw + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


class Words:
    """Words of a block of texts: hash, byte span, and per text the range [first[i], first[i+1])."""

    __slots__ = ("data", "ends", "first", "hash", "starts", "text_start")

    def __init__(self, texts: list[bytes], lower: bool = False, seed: int = 1):
        joined = np.frombuffer(b" ".join(texts) + b" ", np.uint8)
        data = _LOWER[joined] if lower else joined
        inside = np.zeros(len(data) + 1, dtype=np.int8)
        inside[1:] = ~_BLANK[data]
        change = np.diff(inside)
        self.data = data
        self.starts = np.flatnonzero(change == 1)
        self.ends = np.flatnonzero(change == -1)
        lengths = np.fromiter((len(t) + 1 for t in texts), np.int64, len(texts))
        self.text_start = np.concatenate(([0], np.cumsum(lengths)))
        self.first = np.searchsorted(self.starts, self.text_start)
        self.hash = _span_hash(data, self.starts, self.ends, seed)

    def owner(self) -> np.ndarray:
        """Index of each word's text in the block."""
        return np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))


def blocks(texts: Iterable[str | None], size: int = BLOCK_BYTES) -> Iterator[tuple[int, list[bytes]]]:
    """(index of the first text, encoded texts) in blocks of about `size` bytes; null counts as empty."""
    held: list[bytes] = []
    first = total = 0
    for i, text in enumerate(texts):
        raw = b"" if text is None else text.encode("utf-8", "surrogatepass")
        if held and total + len(raw) > size:
            yield first, held
            held, first, total = [], i, 0
        held.append(raw)
        total += len(raw) + 1
    if held:
        yield first, held


def gram_hash(word_hash: np.ndarray, n: int) -> np.ndarray:
    """Hash of the n words from each word on; the last n - 1 places of the block are not windows."""
    count = len(word_hash) - n + 1
    if count <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(count, np.uint64)
    for i in range(n):
        out *= np.uint64(_BASE)
        out += word_hash[i : i + count]
    return mix(out)


def window_mask(first: np.ndarray, n: int, total: int) -> np.ndarray:
    """True where the n words from a word on lie within one text."""
    count = total - n + 1
    if count <= 0:
        return np.zeros(0, bool)
    end_of_text = np.repeat(first[1:], np.diff(first))
    return np.arange(count) + n <= end_of_text[:count]
