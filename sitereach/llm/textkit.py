"""Vectorised text kernels shared by the corpus operators (numpy over the bytes of Arrow batches)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U64 = np.uint64
#: Bytes of text that a kernel call works on at once (one longer document is a call of its own).
SLICE_BYTES = 2 << 20

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_ALNUM = np.zeros(256, dtype=bool)
_ALNUM[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (xor-shift and odd multipliers)."""
    with np.errstate(over="ignore"):
        h = h ^ (h >> U64(30))
        h = h * U64(0xBF58476D1CE4E5B9)
        h = h ^ (h >> U64(27))
        h = h * U64(0x94D049BB133111EB)
        return h ^ (h >> U64(31))


def stream(n: int, seed: int = 0) -> np.ndarray:
    """n pseudo-random 64-bit values, the same on every machine."""
    with np.errstate(over="ignore"):
        return mix((np.arange(1, n + 1, dtype=U64) + U64(seed) * U64(1 << 32)) * U64(0x9E3779B97F4A7C15))


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string column, end to end, and the offsets of its rows. A null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    _, off, data = column.buffers()
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(off, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, offsets - offsets[0]


def slices(batches: Iterator[pa.RecordBatch], column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut batches so that the texts of each piece hold about ``limit`` bytes."""
    for batch in batches:
        if not batch.num_rows:
            continue
        _, off = text_bytes(batch.column(batch.schema.get_field_index(column)))
        at = 0
        while at < batch.num_rows:
            to = max(at + 1, int(np.searchsorted(off, off[at] + limit, "right")) - 1)
            yield batch.slice(at, to - at)
            at = to


class Words:
    """Words of the texts of a batch: start and end byte, row, and a 64-bit hash of the (A-Z lower-cased) bytes."""

    def __init__(self, raw: np.ndarray, offsets: np.ndarray, separator: str = "space"):
        inside = ~_SPACE[raw] if separator == "space" else _ALNUM[raw]
        n = len(raw)
        before = np.zeros(n, bool)
        before[1:] = inside[:-1]
        heads = offsets[:-1][offsets[:-1] < n]
        before[heads] = False
        after = np.zeros(n, bool)
        after[:-1] = inside[1:]
        after[heads[heads > 0] - 1] = False
        self.start = np.flatnonzero(inside & ~before)
        self.end = np.flatnonzero(inside & ~after) + 1
        self.row = np.searchsorted(offsets, self.start, "right") - 1
        self.rows = len(offsets) - 1
        length = self.end - self.start
        self.first = np.searchsorted(self.row, np.arange(self.rows + 1))
        self.hash = np.zeros(0, U64)
        if len(self.start):
            head = np.cumsum(length) - length
            with np.errstate(over="ignore"):
                part = (_LOWER[raw[inside]].astype(U64) + U64(1)) * stream(int(length.max()), 7)[np.arange(int(length.sum())) - np.repeat(head, length)]
                self.hash = mix(np.add.reduceat(part, head) + length.astype(U64) * U64(0xD6E8FEB86659FD93))
            self._part, self._head, self._length = part, head, length

    def stems(self, size: int) -> np.ndarray:
        """Hash of the first ``size`` bytes of each word; of the whole word where it is no longer."""
        out = np.zeros(len(self.hash), U64)
        with np.errstate(over="ignore"):
            for j in range(size):
                long = self._length > j
                out[long] += self._part[self._head[long] + j]
            return mix(out)

    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def runs(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """(hash of every run of exactly ``size`` words, its row), hashed as ``shingles`` does."""
        m = len(self.hash) - size + 1
        if m <= 0:
            return np.zeros(0, U64), np.zeros(0, np.int64)
        acc = np.zeros(m, U64)
        with np.errstate(over="ignore"):
            for j in range(size):
                acc = mix(acc * U64(0x9FB21C651E98DF25) + self.hash[j : j + m])
        same = self.row[:m] == self.row[size - 1 :]
        return acc[same], self.row[:m][same]

    def shingles(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """(hash of every run of ``size`` words, its row). A text of fewer words gives its whole sequence, an empty one nothing."""
        n = len(self.hash)
        keep_h, keep_r = [], []
        with np.errstate(over="ignore"):
            acc = np.zeros(n, U64)
            for j in range(size):
                m = n - j
                if m <= 0:
                    break
                acc = mix(acc[:m] * U64(0x9FB21C651E98DF25) + self.hash[j:])
                if j + 1 < size:
                    short = np.flatnonzero(self.counts() == j + 1)
                    keep_h.append(acc[self.first[short]])
                    keep_r.append(short)
                else:
                    same = self.row[:m] == self.row[j:]
                    keep_h.append(acc[same])
                    keep_r.append(self.row[:m][same])
        if not keep_h:
            return np.zeros(0, U64), np.zeros(0, np.int64)
        return np.concatenate(keep_h), np.concatenate(keep_r)


def sets_by_row(h: np.ndarray, row: np.ndarray, rows: int) -> list[np.ndarray]:
    """Sorted distinct hashes of each row."""
    order = np.argsort(row, kind="stable")
    h, cut = h[order], np.searchsorted(row[order], np.arange(rows + 1))
    return [np.unique(h[cut[i] : cut[i + 1]]) for i in range(rows)]
