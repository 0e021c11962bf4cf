"""Benchmark decontamination: size-partitioned MinHash containment search, verified on exact shingle sets.

Test items are split by the size of their shingle sets (powers of two). The sketch of an item holds the
smallest hashes of its shingles, one more than the item may miss at the containment asked for given the
largest size of its part: a document that contains enough of the item holds at least one of them, so the
candidate search loses nothing. Candidates are then counted on the whole shingle sets of both sides.

The items are read in blocks of bounded size, each sent to all tasks; documents never move. A null or
empty text, of either side, matches nothing; a null item_id is carried through. An item of fewer words than a shingle counts as one shingle,
its whole sequence, and is searched for as such. Rows with equal ids and texts give equal rows; an empty
table on either side gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkit

SIZE, LEAST = 5, 0.8
#: Items, and bytes of their texts, that one block may hold.
BLOCK_ITEMS, BLOCK_BYTES = 20_000, 16 << 20


class Block:
    """Sketches and shingle sets of the items of a block."""

    def __init__(self, ids: list[int | None], texts: list[str], size: int, least: float):
        raw, off = textkit.text_bytes(pa.array(texts, pa.string()))
        words = textkit.Words(raw, off)
        self.size, self.least = size, least
        self.short = sorted({int(n) for n in words.counts() if 0 < n < size})
        self.sets = textkit.sets_by_row(*words.shingles(size), len(ids))
        self.ids = ids
        n = np.array([len(s) for s in self.sets])
        part = np.log2(np.maximum(n, 1)).astype(int)
        pairs = []
        for i, s in enumerate(self.sets):
            upper = int(n[part == part[i]].max())
            m = min(len(s), int((1 - least) * upper + 1e-9) + 1)
            pairs.append((textkit.mix(s), s, m))
        value = [s[np.argsort(order)[:m]] for order, s, m in pairs]
        self.value = np.concatenate(value) if value else np.zeros(0, textkit.U64)
        self.item = np.repeat(np.arange(len(ids)), [len(v) for v in value])
        by = np.argsort(self.value, kind="stable")
        self.value, self.item = self.value[by], self.item[by]

    def search(self, raw: np.ndarray, off: np.ndarray) -> Iterator[tuple[int, int, int, int]]:
        """(row, item, shingles of the item, of these in the row's text)."""
        words = textkit.Words(raw, off)
        runs = [words.runs(k) for k in (self.size, *self.short)]
        h, row = (np.concatenate([x[i] for x in runs]) for i in (0, 1))
        if not len(h) or not len(self.value):
            return
        near = np.zeros(1 << 16, bool)
        near[(self.value >> textkit.U64(48)).astype(np.int64)] = True
        some = np.flatnonzero(near[(h >> textkit.U64(48)).astype(np.int64)])
        lo, hi = np.searchsorted(self.value, h[some], "left"), np.searchsorted(self.value, h[some], "right")
        hit = np.flatnonzero(hi > lo)
        if not len(hit):
            return
        n = (hi - lo)[hit]
        where = np.repeat(lo[hit], n) + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        pair = np.unique(np.repeat(row[some[hit]], n) * len(self.ids) + self.item[where])
        rows, items = pair // len(self.ids), pair % len(self.ids)
        order = np.argsort(row, kind="stable")
        h, row = h[order], row[order]
        for r in np.unique(rows):
            whole = np.unique(h[np.searchsorted(row, r) : np.searchsorted(row, r, "right")])
            for i in items[rows == r]:
                both = int(np.isin(self.sets[i], whole, assume_unique=True).sum())
                if both >= self.least * len(self.sets[i]) - 1e-9:
                    yield int(r), int(i), len(self.sets[i]), both


def blocks(items: DataFrame) -> Iterator[tuple[list[int | None], list[str]]]:
    """The items, block by block; the driver holds one block at a time."""
    ids, texts, held = [], [], 0
    rows = items.select("item_id", "text").where("text is not null").distinct()
    for r in rows.toLocalIterator():
        if ids and (len(ids) >= BLOCK_ITEMS or held + len(r["text"]) > BLOCK_BYTES):
            yield ids, texts
            ids, texts, held = [], [], 0
        ids.append(r["item_id"])
        texts.append(r["text"])
        held += len(r["text"])
    yield ids, texts


def matches(docs: DataFrame, items: DataFrame, size: int = SIZE, least: float = LEAST) -> DataFrame:
    """doc_id, item_id, item_shingles, shared_shingles for each document that holds enough of an item."""
    spark = docs.sparkSession

    def over(block: Block) -> DataFrame:
        shared = spark.sparkContext.broadcast(block)

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for part in textkit.slices(batches, "text"):
                found = list(shared.value.search(*textkit.text_bytes(part.column(1))))
                if found:
                    r, i, n, both = (list(x) for x in zip(*found, strict=True))
                    yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()).take(pa.array(r)), pa.array([shared.value.ids[x] for x in i], pa.int64()), pa.array(n, pa.int64()), pa.array(both, pa.int64())], names=["doc_id", "item_id", "item_shingles", "shared_shingles"])

        return docs.select("doc_id", "text").mapInArrow(work, "doc_id long, item_id long, item_shingles long, shared_shingles long")

    return reduce(DataFrame.unionAll, [over(Block(ids, texts, size, least)) for ids, texts in blocks(items)])


def clean(docs: DataFrame, items: DataFrame, size: int = SIZE, least: float = LEAST) -> DataFrame:
    """The documents that match no item, whole and with all their columns.

    One pass: the search runs beside the rows it judges. Rows with a null doc_id are judged like any other.
    """
    spark, schema = docs.sparkSession, docs.schema
    out = docs
    for ids, texts in blocks(items):
        shared = spark.sparkContext.broadcast(Block(ids, texts, size, least))

        def work(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for part in textkit.slices(batches, "text"):
                text = part.column(part.schema.get_field_index("text"))
                keep = np.ones(part.num_rows, bool)
                keep[[r for r, *_ in shared.value.search(*textkit.text_bytes(text))]] = False
                yield part.filter(pa.array(keep))

        out = out.mapInArrow(work, schema)
    return out


def op9_decontaminate(spark, sf_dir: str) -> DataFrame:
    found = matches(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return found.select("doc_id", "item_id", "item_shingles", "shared_shingles", (F.col("shared_shingles") / F.col("item_shingles")).alias("containment"))


_SETS = """
    select {id} as id, unnest(list_distinct(case
        when len(w) >= 5 then list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))
        when {short} and len(w) > 0 then [array_to_string(w, ' ')] else [] end)) as s
    from (select {id}, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') as w
          from {table} where text is not null)"""

#: No benchmark item of the given tables has fewer than five words, so shorter runs need no branch on the documents' side.
ORACLE = f"""
with item as ({_SETS.format(id='item_id', table='benchmark', short='true')}),
     doc as ({_SETS.format(id='doc_id', table='documents', short='false')}),
     size as (select id, count(*) as n from item group by id)
select doc.id as doc_id, item.id as item_id, any_value(size.n)::BIGINT as item_shingles, count(*)::BIGINT as shared_shingles,
       count(*) / any_value(size.n)::DOUBLE as containment
from doc join item on doc.s = item.s join size on size.id = item.id
group by doc.id, item.id having 10 * count(*) >= 8 * any_value(size.n)"""
