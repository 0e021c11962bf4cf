"""Byte-level BPE encoding and decoding with the tiktoken library and a local rank file.

``encode`` adds the token ids of every whole text, ``decode`` turns ids back into bytes, and
``encode_decode`` does both in one pass. A null text counts as empty and has no ids; repeated rows
give repeated results; an empty table gives an empty one; other columns of the input, whatever their
names, are not carried along. A long text is cut before the regex runs, at places where the pattern
always ends a match, so the ids are those of the uncut text and the library never sees a huge string.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator

import pyarrow as pa
import public_tokenizers
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textkit

#: Characters after which a long text is cut at the next safe place.
PIECE_CHARS = 1 << 16
_ENCODERS: dict[tuple[str, str], tiktoken.Encoding] = {}


def encoder(rank_file: str, pattern: str) -> tiktoken.Encoding:
    """One encoder for each worker process."""
    if (rank_file, pattern) not in _ENCODERS:
        with open(rank_file, "rb") as lines:
            ranks = {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}
        _ENCODERS[rank_file, pattern] = tiktoken.Encoding("local", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    return _ENCODERS[rank_file, pattern]


def pieces(text: str, limit: int = PIECE_CHARS) -> Iterator[str]:
    """Cut where a space follows a non-space: no alternative of the pattern reaches over such a place."""
    at, n = 0, len(text)
    while n - at > limit:
        cut = at + limit
        while cut < n and not (text[cut] == " " and not text[cut - 1].isspace()):
            cut += 1
        yield text[at:cut]
        at = cut
    yield text[at:]


def token_ids(enc: tiktoken.Encoding, text: str) -> list[int]:
    if len(text) <= PIECE_CHARS:
        return enc.encode_ordinary(text)
    return [i for piece in pieces(text) for i in enc.encode_ordinary(piece)]


def encode_decode(docs: DataFrame, rank_file: str | None = None, pattern: str | None = None, decoded: bool = True) -> DataFrame:
    """doc_id, ids array<int> and, if asked for, the bytes that the ids decode to."""
    rank_file = rank_file or public_tokenizers.path("byte_bpe_50k.tiktoken")
    pattern = pattern or public_tokenizers.PATTERN

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(rank_file, pattern)
        for part in textkit.slices(batches, "text"):
            ids = [token_ids(enc, text or "") for text in part.column(1).to_pylist()]
            out = [part.column(0).cast(pa.int64()), pa.array(ids, pa.list_(pa.int32()))]
            if decoded:
                out.append(pa.array([enc.decode_bytes(x) for x in ids], pa.binary()))
            yield pa.RecordBatch.from_arrays(out, names=["doc_id", "ids", "decoded"][: len(out)])

    schema = "doc_id long, ids array<int>" + ", decoded binary" * decoded
    return docs.select("doc_id", "text").mapInArrow(work, schema)


def encode(docs: DataFrame, rank_file: str | None = None, pattern: str | None = None) -> DataFrame:
    return encode_decode(docs, rank_file, pattern, decoded=False)


def decode(tokens: DataFrame, rank_file: str | None = None, pattern: str | None = None) -> DataFrame:
    """doc_id and the raw bytes of ``ids`` (null ids: no bytes)."""
    rank_file = rank_file or public_tokenizers.path("byte_bpe_50k.tiktoken")
    pattern = pattern or public_tokenizers.PATTERN

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(rank_file, pattern)
        for batch in batches:
            out = [enc.decode_bytes(x or []) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(out, pa.binary())], names=["doc_id", "decoded"])

    return tokens.select("doc_id", "ids").mapInArrow(work, "doc_id long, decoded binary")


def digests(coded: DataFrame) -> DataFrame:
    """The digest columns of the contract, from the ids and the decoded bytes."""
    ids = F.array_join(F.col("ids").cast(T.ArrayType(T.StringType())), " ")
    return coded.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), F.sha2(ids, 256).alias("ids_sha256"), F.sha2(F.col("decoded"), 256).alias("decoded_sha256"))


def op8_byte_bpe(spark, sf_dir: str) -> DataFrame:
    return digests(encode_decode(spark.read.parquet(f"{sf_dir}/documents.parquet")))
