"""Token ids in Arrow stream files of fixed-size lists.

``write`` encodes every whole text with the tokenizers library, appends an end id to each document and
lays the ids out in ascending doc_id order: documents are ranged into shards by doc_id, each shard is a run of
Arrow stream files of bounded size whose batches hold two fixed-size-list columns, ``ids`` and ``mask`` (one
bit an id, false in the padding of the file's last sequence). Equal-length rows make the place of every id a
matter of arithmetic, so a memory-mapped file gives zero-copy random access to sequences and masks.
``read_documents`` goes back from the files to documents.

Ids are those of the library object as it is loaded from its file: the string of a special token in a text
gives that token's id. The library's model encodes pieces; as it spends most of its time on pieces that it has
met before, a worker keeps their ids (a bounded number), and cuts texts with the same pattern itself.

A null text counts as empty (its document holds the end id alone), a null doc_id comes after all others,
repeated rows are repeated in the files, an empty table gives no file and no row; further columns of the
input are not carried along. A file is written under a name of its attempt and then renamed, so a lost
or repeated task leaves whole files only.
"""

from __future__ import annotations

import re
import uuid
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import public_tokenizers
import regex
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from . import store, textkit

#: Ids in a sequence, and sequences in a record batch; ids after which a new file begins (at the next document).
LENGTH, ROWS, FILE_IDS = 2048, 256, 1 << 26
_LAST = (1 << 63) - 1
#: White space, and the byte-level split pattern with it, as the library's tables have them.
_WHITE = r"\t-\r\x20\x85\xa0  -     　"
_PIECE = regex.compile(rf"'(?:[sdmt]|ll|re|ve)| ?\p{{L}}+| ?\p{{N}}+| ?[^{_WHITE}\p{{L}}\p{{N}}]+|[{_WHITE}]+(?![^{_WHITE}])|[{_WHITE}]+")
#: The same cut for texts without a character beyond these, in the standard library's faster engine.
_LATIN = re.compile("[^\\t\\n\\r\\x20-\\x7e\\u00a1-\\u00a9\\u00ab-\\u00b1\\u00b6-\\u00b8\\u00bb\\u00bf-\\u024f\\u2010-\\u2027]")
_LATIN_PIECE = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+")
#: Code points (first, last) that are letters or numbers here but not yet in the library's tables; it cuts texts that hold one.
_NEWER = [
    (0x558, 0x558), (0x58B, 0x58C), (0x88F, 0x88F), (0xC5C, 0xC5C), (0xCDC, 0xCDC), (0x208F, 0x208F), (0x209D, 0x209F), (0xA7CE, 0xA7CF), (0xA7D2, 0xA7D2),
    (0xA7D4, 0xA7D4), (0xA7DD, 0xA7DD), (0xA7E2, 0xA7E2), (0xA7F1, 0xA7F1), (0xAB6C, 0xAB6D), (0x107BB, 0x107BF), (0x10940, 0x10959), (0x10EC5, 0x10EC7),
    (0x10ED9, 0x10EEE), (0x11B0A, 0x11B0A), (0x11DB0, 0x11DDB), (0x11DE0, 0x11DE9), (0x11DF1, 0x11DF1), (0x1246F, 0x1246F), (0x12475, 0x1247F),
    (0x12550, 0x12686), (0x16EA0, 0x16EB8), (0x16EBB, 0x16ED3), (0x16FF2, 0x16FF6), (0x187F8, 0x187FF), (0x18CD6, 0x18CDA), (0x18D09, 0x18D20),
    (0x18D80, 0x18DF2), (0x18E00, 0x19191), (0x191A0, 0x191D2), (0x1B123, 0x1B128), (0x1B168, 0x1B168), (0x1D6A6, 0x1D6A6), (0x1DF1F, 0x1DF24),
    (0x1DF2B, 0x1DF81), (0x1DF90, 0x1DF96), (0x1DFCD, 0x1DFFF), (0x1E6C0, 0x1E6DE), (0x1E6E0, 0x1E6E2), (0x1E6E4, 0x1E6E5), (0x1E6E7, 0x1E6ED),
    (0x1E6F0, 0x1E6F4), (0x1E6FE, 0x1E6FF), (0x2B73A, 0x2B73F), (0x2B81E, 0x2B81E), (0x2CEA2, 0x2CEAD), (0x323B0, 0x33479), (0x3D000, 0x3FC3F),
]
_UNKNOWN = re.compile("[" + "".join(f"{chr(a)}-{chr(b)}" for a, b in _NEWER) + "]")
_OPEN: dict[str, "Pieces"] = {}


class Pieces(dict):
    """Id bytes of the pieces met so far; a new piece is encoded by the library's model."""

    LIMIT = 400_000

    def __init__(self, path: str):
        self.tokenizer = Tokenizer.from_file(path)
        self.kind = np.uint16 if self.tokenizer.get_vocab_size(with_added_tokens=True) <= 1 << 16 else np.uint32
        self.code, t = np.dtype(self.kind).char, self.tokenizer
        self.byte_level = t.normalizer is None and t.post_processor is None and type(t.pre_tokenizer).__name__ == "ByteLevel" and not t.pre_tokenizer.add_prefix_space and type(t.model).__name__ == "BPE"
        added = t.get_added_tokens_decoder()
        self.byte_level &= not any(x.lstrip or x.rstrip or x.single_word for x in added.values())
        # the string of a token that was added stands for its id, the longest first
        self.added = {x.content: np.array([i], self.kind).tobytes() for i, x in added.items()}
        self.cut = re.compile("|".join(f"({re.escape(x)})" for x in sorted(self.added, key=len, reverse=True)) or r"(?!)")
        if self.byte_level:
            # fixed rule of byte-level vocabularies: printable bytes stand for themselves, the others follow from 256 on
            shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
            hidden = [b for b in range(256) if b not in shown]
            self.table = {b: chr(b) for b in shown} | {b: chr(256 + i) for i, b in enumerate(hidden)}
            self.model = t.model

    def __missing__(self, piece: str) -> bytes:
        shown = piece.replace(" ", self.table[32]) if piece.isascii() and piece.isprintable() else piece.encode().decode("latin-1").translate(self.table)
        self[piece] = out = array(self.code, [x.id for x in self.model.tokenize(shown)]).tobytes()
        return out

    def cut_up(self, text: str) -> bytes:
        if not _LATIN.search(text):
            return b"".join(map(self.__getitem__, _LATIN_PIECE.findall(text)))
        if _UNKNOWN.search(text):
            return array(self.code, self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()
        return b"".join(map(self.__getitem__, _PIECE.findall(text)))

    def encode(self, text: str) -> bytes:
        if not self.byte_level:
            return array(self.code, self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()
        if not any(x in text for x in self.added):
            return self.cut_up(text)
        return b"".join(self.added[x] if x in self.added else self.cut_up(x) for x in self.cut.split(text) if x)


def pieces(path: str) -> Pieces:
    if path not in _OPEN:
        _OPEN[path] = Pieces(path)
    if len(_OPEN[path]) > Pieces.LIMIT:
        _OPEN[path].clear()
    return _OPEN[path]


def _file(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri)


def encoded(docs: DataFrame, tokenizer_file: str, end_id: int, bounds: list[int]) -> DataFrame:
    """shard, doc_id, n_tokens and the compressed ids (little-endian, 16 bits where the vocabulary fits)."""
    edges = np.array(bounds, np.int64)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=1)
        for part in textkit.slices(batches, "text"):
            known = pieces(tokenizer_file)
            end = np.array([end_id], known.kind).tobytes()
            ids = [known.encode(t or "") + end for t in part.column(1).to_pylist()]
            doc = part.column(0).cast(pa.int64())
            shard = np.searchsorted(edges, doc.fill_null(_LAST).to_numpy(zero_copy_only=False), "left")
            width = np.dtype(known.kind).itemsize
            yield pa.RecordBatch.from_arrays([pa.array(shard, pa.int32()), doc, pa.array([len(x) // width for x in ids], pa.int64()), pa.array([pack.compress(x) for x in ids], pa.binary())], names=["shard", "doc_id", "n_tokens", "ids"])

    return docs.select("doc_id", "text").mapInArrow(work, "shard int, doc_id long, n_tokens long, ids binary")


class _Writer:
    """One file, from the id bytes of documents in order; memory holds one batch."""

    def __init__(self, uri: str, kind: type, length: int):
        (self.fs, self.path), self.kind, self.length = _file(uri), kind, length
        self.schema = pa.schema([("ids", pa.list_(pa.from_numpy_dtype(kind), length)), ("mask", pa.list_(pa.bool_(), length))])
        self.trial, self.whole = f"{self.path}.{uuid.uuid4().hex}", length * ROWS * np.dtype(kind).itemsize
        self.sink = self.fs.open_output_stream(self.trial)
        self.out, self.held = pa.ipc.new_stream(self.sink, self.schema), bytearray()
        self.n, self.docs, self.counts, self.places = 0, [], [], []

    def _put(self, raw: bytes) -> None:
        ids = np.frombuffer(raw, self.kind)
        n = -(-len(ids) // self.length) * self.length
        full, mask = np.zeros(n, self.kind), np.zeros(n, bool)
        full[: len(ids)], mask[: len(ids)] = ids, True
        self.out.write_batch(pa.RecordBatch.from_arrays([pa.FixedSizeListArray.from_arrays(pa.array(x), self.length) for x in (full, mask)], schema=self.schema))

    def add(self, doc: int | None, count: int, raw: bytes) -> None:
        self.docs.append(doc)
        self.counts.append(count)
        self.places.append(self.n)
        self.n += count
        self.held += raw
        while len(self.held) >= self.whole:
            self._put(bytes(self.held[: self.whole]))
            del self.held[: self.whole]

    def close(self, shard: int, number: int) -> pa.RecordBatch:
        """Finish the file; the index rows of its documents."""
        if self.held:
            self._put(bytes(self.held))
        self.out.close()
        self.sink.close()
        self.fs.move(self.trial, self.path)
        k = len(self.docs)
        columns = [pa.array([shard] * k, pa.int32()), pa.array([number] * k, pa.int32()), *(pa.array(x, pa.int64()) for x in (self.docs, self.counts, self.places))]
        return pa.RecordBatch.from_arrays(columns, names=["shard", "file", "doc_id", "n_tokens", "place"])


def file_name(folder: str, shard: int, number: int) -> str:
    return f"{folder}/shard-{shard:06d}-{number:05d}.arrows"


def write(docs: DataFrame, folder: str, tokenizer_file: str | None = None, end_id: int = 2, length: int = LENGTH, file_ids: int = FILE_IDS) -> DataFrame:
    """Write the files and return the index: shard, file (in the shard), doc_id, n_tokens, place (ids before it in its file), start (ids before it at all)."""
    spark = docs.sparkSession
    tokenizer_file = tokenizer_file or public_tokenizers.path("byte_bpe_50k.json")
    n = store.parts(spark)
    # n - 1 quantiles of doc_id: as many values as there are partitions, from a scan of that column alone
    found = docs.select(F.percentile_approx("doc_id", [i / n for i in range(1, n)] or [0.5], 20 * n).alias("q")).first()["q"]
    fs, path = _file(folder)
    fs.create_dir(path, recursive=True)
    kind = pieces(tokenizer_file).kind

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack, now, number = zstandard.ZstdDecompressor(), None, 0
        for batch in batches:
            for shard, doc, count, x in zip(*(batch.column(i).to_pylist() for i in range(3)), batch.column(3), strict=True):
                if now is not None and now.n >= file_ids:
                    yield now.close(shard, number)
                    now, number = None, number + 1
                now = now or _Writer(file_name(folder, shard, number), kind, length)
                now.add(doc, count, unpack.decompress(x.as_buffer()))
        if now is not None:
            yield now.close(shard, number)

    ranged = encoded(docs, tokenizer_file, end_id, sorted(set(found or []))).repartitionById(n, F.col("shard"))
    ordered = ranged.sortWithinPartitions(F.coalesce("doc_id", F.lit(_LAST)), "n_tokens", "ids")
    index = store.cut_and_free(ordered.mapInArrow(work, "shard int, file int, doc_id long, n_tokens long, place long"), "token-index")
    # one row a file, which holds FILE_IDS ids
    before = Window.orderBy("shard", "file").rowsBetween(Window.unboundedPreceding, -1)
    bases = index.groupBy("shard", "file").agg(F.sum("n_tokens").alias("held")).select("shard", "file", F.coalesce(F.sum("held").over(before), F.lit(0)).alias("base"))
    return index.join(F.broadcast(bases), ["shard", "file"]).select("shard", "file", "doc_id", "n_tokens", "place", (F.col("base") + F.col("place")).alias("start"))


class Shard:
    """Zero-copy access to one file: sequence(i), mask(i) and the ids between two places."""

    def __init__(self, uri: str):
        fs, path = _file(uri)
        source = pa.memory_map(path) if isinstance(fs, pafs.LocalFileSystem) else fs.open_input_file(path)
        self.batches = list(pa.ipc.open_stream(source))
        self.values = [b.column(0).flatten().to_numpy() for b in self.batches]
        self.masks = [b.column(1).flatten() for b in self.batches]
        self.length = self.batches[0].schema.field(0).type.list_size
        self.rows = self.batches[0].num_rows

    def sequence(self, i: int) -> np.ndarray:
        at = i % self.rows * self.length
        return self.values[i // self.rows][at : at + self.length]

    def mask(self, i: int) -> pa.BooleanArray:
        at = i % self.rows * self.length
        return self.masks[i // self.rows].slice(at, self.length)

    def ids(self, place: int, n: int) -> Iterator[np.ndarray]:
        size = self.rows * self.length
        while n > 0:
            got = self.values[place // size][place % size : place % size + n]
            yield got
            place, n = place + len(got), n - len(got)


def read_documents(index: DataFrame, folder: str) -> DataFrame:
    """doc_id, start, n_tokens and the CRC-32 of the ids that the files hold for each document."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        opened: dict[tuple[int, int], Shard] = {}
        for batch in batches:
            sums = []
            for shard, number, place, n in zip(*(batch.column(i).to_pylist() for i in (0, 1, 4, 3)), strict=True):
                if (shard, number) not in opened:
                    opened.clear()
                    opened[shard, number] = Shard(file_name(folder, shard, number))
                crc = 0
                for ids in opened[shard, number].ids(place, n):
                    crc = zlib.crc32(ids.astype("<u4").tobytes(), crc)
                sums.append(crc)
            yield pa.RecordBatch.from_arrays([batch.column(2), batch.column(5), batch.column(3), pa.array(sums, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    together = index.select("shard", "file", "doc_id", "n_tokens", "place", "start").repartitionById(store.parts(index.sparkSession), F.col("shard")).sortWithinPartitions("shard", "file", "place")
    return together.mapInArrow(work, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op2_token_files(spark, sf_dir: str) -> DataFrame:
    folder = store.new_path(spark, "token-files")
    return read_documents(write(spark.read.parquet(f"{sf_dir}/documents.parquet"), folder), folder)
