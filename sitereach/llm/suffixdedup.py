"""Removal of long repeated byte strings with a sparse, range-partitioned suffix array.

A byte goes if it is covered by a string of ``LENGTH`` bytes that also starts in a document with a smaller
doc_id. Sorting every suffix would move dozens of times the text, so only the suffixes at anchors are
sorted: the ``KMER``-byte string of smallest hash in each window of LENGTH bytes. Equal windows choose the
same anchor, so every repeated window is seen from an anchor of both documents, and nothing is lost.

1. Each anchor sends its leading two 8-byte symbols, a 128-bit digest of the bytes within reach of the windows
   that hold it (its surroundings) and its document to a bucket. Sampled splitters of two symbols
   range-partition the suffixes, so a frequent first symbol is split by the second one; equal pairs never
   straddle a boundary, so buckets need no neighbour. A bucket sorts its suffixes by multikey quicksort.
   Anchors whose surroundings also occur in a smaller document are settled. Anchors of equal leading bytes
   but differing surroundings stay open. Copies within a task are settled before anything is sent, so a text
   that fills the corpus loads no bucket.
2. Open anchors send the surroundings themselves, again by leading symbols. A bucket sorts them to the right
   of the anchor and, reversed, to the left, with the lengths of common prefixes; two windows are equal
   where both ranks agree, and the smallest document of each group of equal windows is found by sorting,
   never pair by pair.
3. The settled stretches meet the texts again and are cut out.

Contract of rows: a null text counts as empty; a null doc_id counts as larger than all others; rows of the
same doc_id and text are one document (each gives a row, neither removes from the other), rows of the same
doc_id with different texts are two that do not remove from each other; an empty table gives an empty one;
further columns are not read.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import store, textkit
from .textkit import U64, mix

LENGTH, KMER = 50, 16
#: Bytes before an anchor, and from it on, that windows around it can reach; windows of k-mers.
LEFT, RIGHT, WIDTH = LENGTH - KMER, LENGTH, LENGTH - KMER + 1
SLICE, FLUSH = 1 << 20, 8 << 20
_LAST = (1 << 63) - 1
_OPEN = 255
#: One in so many documents is read for the splitters, and about so many of their suffixes reach the driver at most.
SAMPLE, DRAWN = 64, 100_000
#: Rows that the quicksort leaves to a sort by one symbol after the other.
SMALL = 2048


def pack(*arrays: np.ndarray) -> bytes:
    """Arrays in one compressed blob, each laid out by byte planes."""
    head = [struct.pack("<i", len(arrays))]
    body = []
    for a in arrays:
        a = np.ascontiguousarray(a)
        head.append(struct.pack("<4sqq", a.dtype.str[1:].encode().ljust(4), len(a), a.shape[1] if a.ndim == 2 else 0))
        flat = a.view(np.uint8).reshape(len(a), -1) if len(a) else np.zeros((0, 1), np.uint8)
        body.append((flat if a.ndim == 2 else flat.T).tobytes())
    return zstandard.ZstdCompressor(level=1).compress(b"".join(head + body))


def unpack(blob: bytes) -> list[np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(blob)
    (n,), at, heads, out = struct.unpack_from("<i", raw), 4, [], []
    for _ in range(n):
        heads.append(struct.unpack_from("<4sqq", raw, at))
        at += struct.calcsize("<4sqq")
    for code, rows, columns in heads:
        kind = np.dtype("<" + code.decode().strip()) if code.strip() not in (b"u1",) else np.dtype(np.uint8)
        size = rows * max(columns, 1) * kind.itemsize
        flat = np.frombuffer(raw, np.uint8, size, at)
        at += size
        out.append(flat.reshape(rows, columns) if columns else np.ascontiguousarray(flat.reshape(kind.itemsize, rows).T).view(kind).ravel())
    return out


def symbols(raw: np.ndarray) -> np.ndarray:
    """The eight bytes from each place on as one number in text order (places with fewer bytes left out)."""
    w = raw.astype(U64)
    for step in (1, 2, 4):
        w = (w[:-step] << U64(8 * step)) | w[step:]
    return w


def _sliding(x: np.ndarray, width: int, best: np.ufunc) -> np.ndarray:
    """best over x[i : i + width]."""
    have = 1
    while have * 2 <= width:
        x = best(x[:-have], x[have:])
        have *= 2
    return best(x[: len(x) - (width - have)], x[width - have :]) if width > have else x


def anchors(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(place, row, first and second symbol) of the anchors of texts laid end to end."""
    none = np.zeros(0, np.int64)
    if len(raw) < LENGTH:
        return none, none, none.astype(U64), none.astype(U64)
    w = symbols(raw)
    with np.errstate(over="ignore"):
        h = mix(w[:-8] * U64(0x9FB21C651E98DF25) + w[8:]) | U64(1)
    low = _sliding(h, WIDTH, np.minimum)
    # a window counts if it ends in the text in which it starts
    ok = np.zeros(len(low), bool)
    size = np.diff(off)
    for r in np.flatnonzero(size >= LENGTH):
        ok[off[r] : off[r + 1] - LENGTH + 1] = True
    low[~ok] = 0
    edge = np.zeros(WIDTH - 1, U64)
    place = np.flatnonzero(_sliding(np.concatenate([edge, low, edge]), WIDTH, np.maximum) == h)
    return place, np.searchsorted(off, place, "right") - 1, w[place], w[place + 8]


def surroundings(raw: np.ndarray, off: np.ndarray, place: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes from LEFT before to RIGHT after each place, zero outside of its text, and how many lie inside on each side."""
    left, right = np.minimum(place - off[row], LEFT), np.minimum(off[row + 1] - place, RIGHT)
    padded = np.concatenate([np.zeros(LEFT, np.uint8), raw, np.zeros(RIGHT, np.uint8)])
    around = np.lib.stride_tricks.sliding_window_view(padded, LEFT + RIGHT)[place]
    column = np.arange(LEFT + RIGHT)[None, :]
    short = np.flatnonzero((left < LEFT) | (right < RIGHT))
    around[short] *= (column >= LEFT - left[short][:, None]) & (column < LEFT + right[short][:, None])
    return around, left, right


def _words(bytes_: np.ndarray) -> np.ndarray:
    """Rows of bytes as rows of 8-byte symbols in text order."""
    wide = -(-bytes_.shape[1] // 8) * 8
    full = np.zeros((len(bytes_), wide), np.uint8)
    full[:, : bytes_.shape[1]] = bytes_
    return full.view(">u8").astype(U64)


def _by_symbols(keys: list[np.ndarray], rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``rows`` sorted by the symbols of ``keys`` one after the other, only what they leave tied being sorted again; and where a new group begins."""
    first = keys[0][rows]
    rows = rows[np.argsort(first, kind="stable")]
    new = np.ones(len(rows), bool)
    new[1:] = keys[0][rows][1:] != keys[0][rows][:-1]
    for key in keys[1:]:
        tied = np.flatnonzero(~new | np.append(~new[1:], False))
        if not len(tied):
            break
        group, some = np.cumsum(new)[tied], rows[tied]
        rows[tied] = some[np.lexsort((key[some], group))]
        value = key[rows[tied]]
        differs = np.ones(len(tied), bool)
        differs[1:] = (value[1:] != value[:-1]) | (group[1:] != group[:-1])
        new[tied] |= differs
    return rows, new


def multikey_order(keys: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Multikey quicksort by the symbols of ``keys``: the order of the rows, and the group of each sorted row.

    A part is split into the rows whose symbol is smaller than, equal to and larger than a pivot; the equal ones
    go on with the next symbol, the others with the same one.
    """
    n = len(keys[0])
    order, new = np.arange(n), np.zeros(n, bool)
    new[:1] = True
    parts = [(0, n, 0)]
    while parts:
        lo, hi, depth = parts.pop()
        if hi - lo < 2 or depth == len(keys):
            continue
        rows = order[lo:hi]
        if hi - lo <= SMALL:
            order[lo:hi], heads = _by_symbols(keys[depth:], rows.copy())
            new[lo + 1 : hi] |= heads[1:]
            continue
        symbol = keys[depth][rows]
        pivot = np.sort(symbol[:: max(1, len(symbol) // 63)])[31]
        less, more = symbol < pivot, symbol > pivot
        order[lo:hi] = np.concatenate([rows[less], rows[~(less | more)], rows[more]])
        a, b = lo + int(less.sum()), hi - int(more.sum())
        new[[x for x in (a, b) if x < hi]] = True
        parts += [(lo, a, depth), (a, b, depth + 1), (b, hi, depth)]
    return order, np.cumsum(new) - 1


def bucket_of(edges: np.ndarray, w0: np.ndarray, w1: np.ndarray) -> np.ndarray:
    """How many of the splitters (rows of two symbols, ascending) are no larger than each suffix."""
    lo, hi = (np.searchsorted(edges[:, 0], w0, side) for side in ("left", "right"))
    out = lo.copy()
    tied = np.flatnonzero(hi > lo)
    for a in np.unique(lo[tied]):
        at = tied[lo[tied] == a]
        out[at] = a + np.searchsorted(edges[a : hi[at[0]], 1], w1[at], "right")
    return out


def home_of(ids: np.ndarray, n: int) -> np.ndarray:
    """The partition in which a document meets its stretches; ``home_column`` is the same for Spark."""
    y = np.mod(ids, 2147483629) * 48271
    return ((y ^ (y >> 15)) % n).astype(np.int32)


def home_column(doc: Column, n: int) -> Column:
    y = F.pmod(F.coalesce(doc, F.lit(_LAST)).cast("long"), F.lit(2147483629)) * F.lit(48271)
    return (y.bitwiseXOR(F.shiftright(y, 15)) % n).cast("int")


def _doc_ids(column: pa.Array) -> np.ndarray:
    return column.cast(pa.int64()).fill_null(_LAST).to_numpy(zero_copy_only=False)


def _tags(raw: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Tells texts of the same doc_id apart."""
    view = memoryview(np.ascontiguousarray(raw))
    return np.array([zlib.crc32(view[off[i] : off[i + 1]]) for i in range(len(off) - 1)], np.uint32)


_ROW = "part int, kind int, blob binary"


def _batch(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
    part, kind, blob = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(kind, pa.int32()), pa.array(blob, pa.binary())], names=["part", "kind", "blob"])


def _grouped(target: np.ndarray, n: int) -> Iterator[tuple[int, np.ndarray]]:
    order = np.argsort(target, kind="stable")
    cut = np.searchsorted(target[order], np.arange(n + 1))
    for p in np.flatnonzero(np.diff(cut)):
        yield int(p), order[cut[p] : cut[p + 1]]


def _to_homes(doc: np.ndarray, tag: np.ndarray, pos: np.ndarray, low: np.ndarray, high: np.ndarray, n: int) -> list[tuple[int, int, bytes]]:
    """Stretches (low before, high from pos on; open anchors marked) on their way to their documents."""
    out = []
    for p, at in _grouped(home_of(doc, n), n):
        at = at[np.lexsort((pos[at], tag[at], doc[at]))]
        first = np.ones(len(at), bool)
        first[1:] = (doc[at][1:] != doc[at][:-1]) | (tag[at][1:] != tag[at][:-1])
        count = np.diff(np.append(np.flatnonzero(first), len(at))).astype(np.uint32)
        out.append((p, 0, pack(doc[at][first], tag[at][first], count, pos[at].astype(np.uint32), low[at], high[at])))
    return out


def splitters(docs: DataFrame, n: int) -> np.ndarray:
    """Up to n - 1 pairs of leading symbols that part the suffixes evenly, from a sample of bounded size."""
    some = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(SAMPLE)) == 0).select("text")
    size = some.agg(F.sum(F.octet_length("text")).alias("size")).first()["size"] or 0
    # an anchor comes about every (WIDTH + 1) / 2 bytes
    least = U64(min((1 << 64) - 1, int((1 << 64) * DRAWN * (WIDTH + 1) / 2 / max(size, 1))))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in textkit.slices(batches, "text", SLICE):
            place, _, first, second = anchors(*textkit.text_bytes(part.column(0)))
            with np.errstate(over="ignore"):
                use = mix(first ^ (second * U64(0x9E3779B97F4A7C15)) ^ mix(place.astype(U64))) <= least
            yield pa.RecordBatch.from_arrays([pa.array(x[use].view(np.int64)) for x in (first, second)], names=["first", "second"])

    drawn = some.mapInArrow(work, "first long, second long").toPandas()
    pairs = np.stack([drawn[c].to_numpy(np.int64).view(U64) for c in ("first", "second")], 1)
    pairs = pairs[np.lexsort((pairs[:, 1], pairs[:, 0]))]
    return np.unique(pairs[[len(pairs) * i // n for i in range(1, n)]], axis=0) if len(pairs) else pairs


def _digest(words: np.ndarray, sides: np.ndarray, seed: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mix((mix(words * textkit.stream(words.shape[1], seed)[None, :]) * textkit.stream(words.shape[1], seed + 1)[None, :]).sum(axis=1, dtype=U64) + sides)


def _first_map(edges: np.ndarray, n: int):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        size = 0

        def flush() -> Iterator[pa.RecordBatch]:
            doc, tag, pos, w0, w1, around, again = (np.concatenate(x) for x in zip(*held, strict=True))
            # copies met in this task: all but the smallest document's are settled here
            order = np.lexsort((pos, tag, doc, again, around))
            key, more = around[order], again[order]
            first = np.ones(len(order), bool)
            first[1:] = (key[1:] != key[:-1]) | (more[1:] != more[:-1]) | (w0[order][1:] != w0[order][:-1]) | (w1[order][1:] != w1[order][:-1])
            least = doc[order][np.flatnonzero(first)][np.cumsum(first) - 1]
            settled, sent = order[doc[order] > least], order[doc[order] == least]
            rows = _to_homes(doc[settled], tag[settled], pos[settled], np.full(len(settled), LEFT, np.uint8), np.full(len(settled), RIGHT, np.uint8), n)
            rows = [(p, 1, blob) for p, _, blob in rows]
            for p, at in _grouped(bucket_of(edges, w0[sent], w1[sent]), n):
                at = sent[at]
                at = at[np.argsort(w0[at], kind="stable")]
                names, index = np.unique(np.stack([doc[at], tag[at].astype(np.int64)], 1), axis=0, return_inverse=True)
                rows.append((p, 0, pack(w0[at].byteswap(), w1[at].byteswap(), around[at], again[at], index.ravel().astype(np.uint32), pos[at].astype(np.uint32), names[:, 0].copy(), names[:, 1].astype(np.uint32))))
            for i in range(0, len(rows), 256):
                yield _batch(rows[i : i + 256])

        for part in textkit.slices(batches, "text", SLICE):
            raw, off = textkit.text_bytes(part.column(1))
            size += len(raw)
            place, row, w0, w1 = anchors(raw, off)
            if len(place):
                around, left, right = surroundings(raw, off, place, row)
                words = _words(around)
                sides = (left * 64 + right).astype(U64)
                held.append((_doc_ids(part.column(0))[row], _tags(raw, off)[row], place - off[row], w0, w1, _digest(words, sides, 5), _digest(words, sides, 15)))
            if held and size >= FLUSH:
                yield from flush()
                held, size = [], 0
        if held:
            yield from flush()

    return work


def _first_reduce(n: int):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = []
        for batch in batches:
            through = []
            for part, kind, blob in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                if kind:
                    through.append((part, 0, blob))
                else:
                    w0, w1, around, again, index, pos, ids, tags = unpack(blob)
                    held.append((w0.byteswap(), w1.byteswap(), around, again, ids[index], tags[index], pos))
            if through:
                yield _batch(through)
        if not held:
            return
        w0, w1, around, again, doc, tag, pos = (np.concatenate(x) for x in zip(*held, strict=True))
        held.clear()
        order, group = multikey_order([w0, w1, around, again])
        doc, tag, pos, w0, w1 = doc[order], tag[order], pos[order], w0[order], w1[order]
        new = np.ones(len(order), bool)
        new[1:] = (w0[1:] != w0[:-1]) | (w1[1:] != w1[:-1])
        same = np.ones(len(order), bool)
        same[1:] = group[1:] != group[:-1]
        head, copy = np.flatnonzero(same), np.cumsum(same) - 1
        least = np.minimum.reduceat(doc, head)
        gone = doc > least[copy]
        # open: the group has another surrounding whose smallest document is a smaller or larger one
        start = np.flatnonzero(new)
        low, high = np.minimum.reduceat(least, copy[start]), np.maximum.reduceat(least, copy[start])
        which = np.cumsum(new) - 1
        open_ = ~gone & (low != high)[which]
        use = gone | open_
        mark = np.where(gone, LEFT, _OPEN).astype(np.uint8)[use]
        rows = _to_homes(doc[use], tag[use], pos[use], mark, np.full(int(use.sum()), RIGHT, np.uint8), n)
        for i in range(0, len(rows), 256):
            yield _batch(rows[i : i + 256])

    return work


class Stretches:
    """What a partition has been told of its documents."""

    def __init__(self):
        self.blobs: list[list[np.ndarray]] = []
        self.of: dict[tuple[int, int], list[tuple[int, int, int]]] | None = None

    def add(self, blob: bytes) -> None:
        self.blobs.append(unpack(blob))

    def get(self, doc: int, tag: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if self.of is None:
            self.of = {}
            for b, (ids, tags, count, *_) in enumerate(self.blobs):
                end = np.cumsum(count.astype(np.int64))
                for d, t, lo, hi in zip(ids.tolist(), tags.tolist(), (end - count).tolist(), end.tolist(), strict=True):
                    self.of.setdefault((d, t), []).append((b, lo, hi))
        at = self.of.get((doc, tag), [])
        take = lambda i: np.concatenate([self.blobs[b][i][lo:hi] for b, lo, hi in at]).astype(np.int64) if at else np.zeros(0, np.int64)
        return take(3), take(4), take(5)


def _with_texts(docs: DataFrame, told: DataFrame, n: int) -> DataFrame:
    """Stretches, then the texts, of the documents of each partition."""
    rows = docs.select(home_column(F.col("doc_id"), n).alias("part"), F.lit(1).alias("kind"), F.lit(None).cast("binary").alias("blob"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    both = told.select("part", "kind", "blob", F.lit(None).cast("long").alias("doc_id"), F.lit(None).cast("string").alias("text")).union(rows)
    return both.repartitionById(n, F.col("part")).sortWithinPartitions("kind")


def _documents(batches: Iterator[pa.RecordBatch], told: Stretches) -> Iterator[pa.RecordBatch]:
    """The text rows, after the stretches that come first have been kept."""
    for batch in batches:
        kind = batch.column(1).to_numpy(zero_copy_only=False)
        texts = int(np.searchsorted(kind, 1))
        for blob in batch.column(2).slice(0, texts):
            told.add(blob.as_py())
        if texts < batch.num_rows:
            yield batch.slice(texts).select(["doc_id", "text"])


def _second_map(edges: np.ndarray, n: int):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        told, held, size = Stretches(), [], 0

        def flush() -> Iterator[pa.RecordBatch]:
            doc, tag, pos, left, right, around = (np.concatenate(x) for x in zip(*held, strict=True))
            w0, w1 = _words(around[:, LEFT : LEFT + KMER]).T
            rows = [(p, 0, pack(doc[at], tag[at], pos[at].astype(np.uint32), left[at], right[at], around[at])) for p, at in _grouped(bucket_of(edges, w0, w1), n)]
            for i in range(0, len(rows), 256):
                yield _batch(rows[i : i + 256])

        for part in textkit.slices(_documents(batches, told), "text", SLICE):
            raw, off = textkit.text_bytes(part.column(1))
            for r, (d, t) in enumerate(zip(_doc_ids(part.column(0)).tolist(), _tags(raw, off).tolist(), strict=True)):
                pos, low, _ = told.get(d, t)
                pos = np.unique(pos[low == _OPEN])
                if len(pos):
                    around, left, right = surroundings(raw, off, off[r] + pos, np.full(len(pos), r))
                    held.append((np.full(len(pos), d), np.full(len(pos), t, np.uint32), pos, left.astype(np.uint8), right.astype(np.uint8), around))
                    size += around.size
            if size >= FLUSH:
                yield from flush()
                held, size = [], 0
        if held:
            yield from flush()

    return work


def _common(sorted_bytes: np.ndarray) -> np.ndarray:
    """Length of the common prefix of each row and the one before it (0 for the first)."""
    out = np.zeros(len(sorted_bytes), np.int64)
    if len(sorted_bytes) > 1:
        differ = sorted_bytes[1:] != sorted_bytes[:-1]
        out[1:] = np.where(differ.any(axis=1), differ.argmax(axis=1), sorted_bytes.shape[1])
    return out


def window_stretches(doc: np.ndarray, left: np.ndarray, right: np.ndarray, around: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each anchor how far before it and after it repeated windows reach; (0, 0) where there are none."""
    n = len(doc)
    low, high = np.zeros(n, np.int64), np.zeros(n, np.int64)
    to_right = around[:, LEFT:]
    to_left = np.ascontiguousarray(around[:, LEFT - 1 :: -1]) if LEFT else around[:, :0]
    orders = []
    for side in (to_right, to_left):
        order, _ = multikey_order(list(_words(side).T))
        orders.append((order, _common(side[order])))
    for o in range(LEFT + 1):
        ranks = []
        for (order, common), need in zip(orders, (LENGTH - o, o), strict=True):
            rank = np.empty(n, np.int64)
            rank[order] = np.cumsum(common < need)
            ranks.append(rank)
        use = np.flatnonzero((left >= o) & (right >= LENGTH - o))
        if not len(use):
            continue
        key = ranks[0][use] * (n + 1) + ranks[1][use]
        by = np.argsort(key, kind="stable")
        new = np.ones(len(by), bool)
        new[1:] = key[by][1:] != key[by][:-1]
        least = np.minimum.reduceat(doc[use][by], np.flatnonzero(new))[np.cumsum(new) - 1]
        hit = use[by[doc[use][by] > least]]
        low[hit] = o
        high[hit] = np.where(high[hit] == 0, LENGTH - o, high[hit])
    return low, high


def _second_reduce(n: int):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [unpack(blob.as_py()) for batch in batches for blob in batch.column(2)]
        if not held:
            return
        doc, tag, pos, left, right, around = (np.concatenate(x) for x in zip(*held, strict=True))
        low, high = window_stretches(doc, left.astype(np.int64), right.astype(np.int64), around)
        use = high > 0
        rows = _to_homes(doc[use], tag[use], pos[use], low[use].astype(np.uint8), high[use].astype(np.uint8), n)
        if rows:
            yield _batch(rows)

    return work


def _cut_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    told = Stretches()
    for part in textkit.slices(_documents(batches, told), "text", SLICE):
        raw, off = textkit.text_bytes(part.column(1))
        removed, runs, kept, places = [], [], [], []
        for r, (d, t) in enumerate(zip(_doc_ids(part.column(0)).tolist(), _tags(raw, off).tolist(), strict=True)):
            text = raw[off[r] : off[r + 1]]
            pos, low, high = told.get(d, t)
            use = low != _OPEN
            edge = np.zeros(len(text) + 1, np.int32)
            np.add.at(edge, np.maximum(pos[use] - low[use], 0), 1)
            np.add.at(edge, np.minimum(pos[use] + high[use], len(text)), -1)
            gone = np.cumsum(edge[:-1]) > 0
            starts = np.flatnonzero(gone & ~np.append(False, gone[:-1])) if len(text) else np.zeros(0, np.int64)
            ends = np.flatnonzero(gone & ~np.append(gone[1:], False)) + 1 if len(text) else starts
            removed.append(int(gone.sum()))
            runs.append(len(starts))
            places.append(np.stack([starts, ends], 1).ravel().tolist())
            kept.append(text[~gone].tobytes())
        yield pa.RecordBatch.from_arrays(
            [part.column(0), pa.array(np.diff(off)), pa.array(removed, pa.int64()), pa.array(runs, pa.int64()), pa.array([hashlib.sha256(k).hexdigest() for k in kept]), pa.array(places, pa.list_(pa.int64())), pa.array(kept, pa.binary())],
            names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans", "kept"],
        )


def remove_repeats(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans (start, end, start, end, ... in bytes) and the kept bytes."""
    docs = docs.select("doc_id", "text")
    n = store.parts(docs.sparkSession)
    edges = splitters(docs, n)
    sent = docs.mapInArrow(_first_map(edges, n), _ROW).repartitionById(n, F.col("part"))
    first = store.cut_and_free(sent.mapInArrow(_first_reduce(n), _ROW), "stretches")
    opened = _with_texts(docs, first, n).mapInArrow(_second_map(edges, n), _ROW).repartitionById(n, F.col("part"))
    second = store.cut_and_free(opened.mapInArrow(_second_reduce(n), _ROW), "stretches")
    return _with_texts(docs, first.union(second), n).mapInArrow(_cut_out, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<long>, kept binary")


def op1_repeated_strings(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet")).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
