"""Vectorised words of many texts: byte offsets and 64-bit hashes, without a Python loop per word."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BASE = 0x9E3779B97F4A7C15
_WORD = np.zeros(256, bool)
_WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE**i and its inverse modulo 2**64 for i < n."""
    if len(powers.kept[0]) < n:
        room = 1 << max(16, (n - 1).bit_length())
        inverse = pow(BASE, -1, 1 << 64)
        with np.errstate(over="ignore"):
            powers.kept = tuple(np.concatenate([[np.uint64(1)], np.cumprod(np.full(room - 1, b, np.uint64))]) for b in (BASE, inverse))
    return powers.kept


powers.kept = (np.zeros(0, np.uint64), np.zeros(0, np.uint64))


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(29))


class Words:
    """Words of the texts laid end to end: hash, first and last byte, text of each."""

    def __init__(self, texts: list[bytes]):
        self.data = b"\x00".join(texts)
        raw = np.frombuffer(self.data, np.uint8)
        inside = _WORD[raw]
        edge = np.diff(np.concatenate([[False], inside, [False]]).astype(np.int8))
        self.starts, self.ends = np.nonzero(edge == 1)[0], np.nonzero(edge == -1)[0]
        up, down = powers(len(raw) + 1)
        total = np.concatenate([[np.uint64(0)], np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up[: len(raw)])])
        self.hash = mixed((total[self.ends] - total[self.starts]) * down[self.starts])
        self.text_starts = np.cumsum([0, *(len(t) + 1 for t in texts)])
        self.text = np.searchsorted(self.text_starts, self.starts, "right") - 1
        self.first = np.searchsorted(self.text, np.arange(len(texts) + 1))

    def grams(self, q: int) -> tuple[np.ndarray, np.ndarray]:
        """Positions at which q words of one text start, and the hashes of those q words."""
        n = len(self.hash) - q + 1
        if n <= 0:
            return np.zeros(0, np.int64), np.zeros(0, np.uint64)
        at = np.nonzero(self.text[: n] == self.text[q - 1 :])[0]
        h = np.full(len(at), q, np.uint64)
        for k in range(q):
            h = mixed(h * np.uint64(BASE) + self.hash[at + k])
        return at, h


def lowered_slices(batch: pa.RecordBatch, column: int, most: int = 1 << 21) -> Iterator[tuple[int, list[bytes]]]:
    """(first row, texts as lower-cased bytes) in slices of about `most` bytes; null becomes empty."""
    texts, start, room = [], 0, 0
    for row, text in enumerate(pc.utf8_lower(pc.fill_null(batch.column(column).cast(pa.string()), ""))):
        raw = text.as_buffer()
        raw = raw.to_pybytes() if raw is not None else b""
        if texts and room + len(raw) > most:
            yield start, texts
            texts, start, room = [], row, 0
        texts.append(raw)
        room += len(raw)
    if texts:
        yield start, texts
