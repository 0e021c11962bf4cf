"""Near-duplicate groups: fast similarity sketches, banding and exact verification.

A document's set holds its distinct word shingles (A-Z lower-cased words between ASCII white space; fewer
words than a shingle: the whole sequence as one; no word: the empty set, linked with nothing).

1. Sketch. In round i every element of a set is thrown into a hashed bin, and a bin keeps the smallest
   hash of the first round that reached it; after as many rounds as there are bins, round i fills bin
   i - bins, so that every coordinate is filled. Two sets agree in a coordinate with the probability of
   their Jaccard similarity, and the share of agreeing coordinates is concentrated as for independent ones.
2. Banding. Bands of ``ROWS`` coordinates; as many bands as make a pair at the threshold meet in none
   with a probability of at most ``MISS``. Documents of equal sets form one class, and only the smallest
   doc_id of a class goes on.
3. Verification on whole sets. Each bucket is first compared with its most central member, the one whose
   buckets hold most texts. Pairs still in different components are then compared one by one in small
   buckets; large buckets with the same centre are taken together and compared block by block, a block
   pair giving no more links than it needs to join its components. No pair of a bucket is left out unless
   it is linked already, and no task holds more than two blocks.

Results: rows that share a doc_id count as one document; a row with a null doc_id is linked with nothing
and kept; a null or empty text has no shingle; an empty table gives an empty one; further columns are not
read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import store, textkit
from .components import components
from .textkit import U64, mix

ROWS, MISS = 5, 1e-9
#: Texts of a bucket up to which all its pairs are compared one by one; texts of a block beyond.
SMALL, BLOCK = 12, 256
#: Rounds that all sets of a batch go through together.
TOGETHER = 24


def n_bands(percent: int) -> int:
    return math.ceil(math.log(MISS) / math.log(1 - (percent / 100) ** ROWS))


def _round(h: np.ndarray, i: int | np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mix(h ^ (np.asarray(i).astype(U64) + U64(1)) * U64(0x9E3779B97F4A7C15))


def sketches(sets: list[np.ndarray], bins: int) -> np.ndarray:
    """One row of ``bins`` coordinates a set; the sets must not be empty."""
    none = U64(0xFFFFFFFFFFFFFFFF)
    out = np.full((len(sets), bins), none)
    if not sets:
        return out
    flat = out.ravel()
    h, row = np.concatenate(sets), np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    for i in range(TOGETHER):
        value = _round(h, i)
        at = row * bins + ((value >> U64(32)).astype(np.int64) * bins >> 32)
        open_ = flat[at] == none
        np.minimum.at(flat, at[open_], value[open_])
        todo = (out == none).any(axis=1)
        if not todo.any():
            return out
        keep = todo[row]
        h, row = h[keep], row[keep]
    for r in np.flatnonzero(todo):
        for first in range(TOGETHER, 2 * bins, 64):
            rounds = np.arange(first, min(first + 64, 2 * bins))
            value = _round(sets[r][None, :], rounds[:, None])
            at = np.where(rounds[:, None] < bins, (value >> U64(32)).astype(np.int64) * bins >> 32, rounds[:, None] - bins)
            # the smallest hash of the earliest round wins a bin
            order = np.lexsort((value.ravel(), np.repeat(rounds, value.shape[1])))
            bin_, where = np.unique(at.ravel()[order], return_index=True)
            free = out[r, bin_] == none
            out[r, bin_[free]] = value.ravel()[order[where[free]]]
            if (out[r] != none).all():
                break
    return out


def band_keys(sketch: np.ndarray, bands: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        key = np.tile(textkit.stream(bands, 3), (len(sketch), 1))
        for j in range(ROWS):
            key = mix(key * U64(0x9FB21C651E98DF25) + sketch[:, j * bands : (j + 1) * bands])
    return key


def shingle_sets(column: pa.Array, size: int) -> list[np.ndarray]:
    words = textkit.Words(*textkit.text_bytes(column))
    return textkit.sets_by_row(*words.shingles(size), words.rows)


def sketch_table(docs: DataFrame, size: int, percent: int) -> DataFrame:
    """doc_id, n_shingles, a 128-bit digest of the set and the keys of its bands (none for an empty set)."""
    bands = n_bands(percent)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in textkit.slices(batches, "text"):
            sets = shingle_sets(part.column(1), size)
            some = [i for i, s in enumerate(sets) if len(s)]
            keys: list = [None] * len(sets)
            digest = np.zeros((2, len(sets)), np.int64)
            for i, k in zip(some, band_keys(sketches([sets[i] for i in some], bands * ROWS), bands).view(np.int64), strict=True):
                keys[i] = k
            with np.errstate(over="ignore"):
                for i in some:
                    digest[0, i], digest[1, i] = (int(mix(sets[i] ^ textkit.stream(1, seed)).sum().view(np.int64)) for seed in (11, 12))
            yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array(digest[0]), pa.array(digest[1]), pa.array(keys, pa.list_(pa.int64()))], names=["doc_id", "n_shingles", "d1", "d2", "keys"])

    return docs.select("doc_id", "text").mapInArrow(work, "doc_id long, n_shingles long, d1 long, d2 long, keys array<long>")


def _linked(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def verified(pairs: DataFrame, texts: DataFrame, size: int, percent: int) -> DataFrame:
    """The (a, b) pairs whose whole sets are similar enough."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in textkit.slices(batches, "text_a"):
            first, second = (shingle_sets(part.column(i), size) for i in (2, 3))
            good = [i for i in range(part.num_rows) if _linked(first[i], second[i], percent)]
            yield part.select(["a", "b"]).take(pa.array(good, pa.int64()))

    left = texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a"))
    right = texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "text_a", "text_b").mapInArrow(work, "a long, b long")


def block_links(ids: np.ndarray, side: np.ndarray, sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Links between texts of the two sides (all pairs if there is one side), no more than join the same components.

    Counts of common shingles come from one product of 0/1 matrices over the shingles that occur twice.
    """
    n = np.array([len(s) for s in sets])
    value, where, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(len(sets)), n)
    left, right = (np.flatnonzero(side == 0), np.flatnonzero(side == side.max()))
    both = np.zeros((len(left), len(right)), np.int64)
    column = np.cumsum(times > 1) - 1
    wide = int((times > 1).sum())
    for at in range(0, wide, 8192):
        use = (times > 1)[where] & (column[where] >= at) & (column[where] < at + 8192)
        m = np.zeros((len(sets), min(8192, wide - at)), np.float32)
        m[row[use], column[where[use]] - at] = 1
        # a product over so few columns is exact in 32 bits; the sum is not
        both += (m[left] @ m[right].T).astype(np.int64)
    union = n[left][:, None] + n[right][None, :] - both
    i, j = np.nonzero(100 * both >= percent * union)
    parent = list(range(len(ids)))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    out = []
    for x, y in zip(left[i].tolist(), right[j].tolist(), strict=True):
        rx, ry = root(x), root(y)
        if rx != ry:
            parent[max(rx, ry)] = min(rx, ry)
            out.append((int(ids[x]), int(ids[y])))
    return out


def _family_links(buckets: DataFrame, state: DataFrame, texts: DataFrame, size: int, percent: int) -> DataFrame:
    """Links inside the large buckets of one centre, taken together, where they span components."""
    large = buckets.where(F.col("size") > SMALL)
    family = large.select("hub", "rep").union(large.select("hub", F.col("hub").alias("rep"))).distinct()
    family = family.join(state, family["rep"] == state["node"], "left").select("hub", "rep", F.coalesce("label", "rep").alias("label"))
    split = family.groupBy("hub").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.count("*").alias("n")).where("lo <> hi")
    placed = family.join(split.select("hub", F.ceil(F.col("n") / BLOCK).cast("int").alias("blocks")), "hub").withColumn("block", F.floor((F.row_number().over(Window.partitionBy("hub").orderBy("label", "rep")) - 1) / BLOCK).cast("int"))
    blocks = placed.groupBy("hub", "block").agg(F.min("label").alias("lo"), F.max("label").alias("hi"))
    pairs = blocks.alias("x").join(blocks.alias("y"), (F.col("x.hub") == F.col("y.hub")) & (F.col("x.block") <= F.col("y.block"))).where(F.least("x.lo", "y.lo") != F.greatest("x.hi", "y.hi"))
    pairs = pairs.select(F.col("x.hub").alias("hub"), F.col("x.block").alias("left"), F.col("y.block").alias("right"))
    sides = pairs.select("hub", "left", "right", F.col("left").alias("block"), F.lit(0).alias("side")).union(pairs.where("left <> right").select("hub", "left", "right", F.col("right").alias("block"), F.lit(1).alias("side")))
    rows = sides.join(placed.select("hub", "block", "rep"), ["hub", "block"]).join(texts, F.col("rep") == F.col("doc_id")).select("hub", "left", "right", "side", "rep", "text")

    def work(group: pa.Table) -> pa.Table:
        links = block_links(group["rep"].to_numpy(), group["side"].to_numpy(), shingle_sets(group["text"], size), percent)
        return pa.table({"a": pa.array([a for a, _ in links], pa.int64()), "b": pa.array([b for _, b in links], pa.int64())})

    return rows.groupBy("hub", "left", "right").applyInArrow(work, "a long, b long")


def groups(docs: DataFrame, size: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id and kept for each row: documents whose sets overlap by ``percent`` of their union are linked."""
    sketch = store.cut_and_free(sketch_table(docs, size, percent), "sketches")
    known = sketch.where("n_shingles > 0 and doc_id is not null")
    classes = known.groupBy("d1", "d2").agg(F.min("doc_id").alias("rep"))
    reps = known.groupBy("d1", "d2").agg(F.min("doc_id").alias("rep"), F.first("keys").alias("keys"))
    keyed = reps.select("rep", F.explode("keys").alias("key"))
    met = keyed.withColumn("size", F.count("*").over(Window.partitionBy("key"))).where("size > 1")
    met = store.cut_and_free(met, "buckets")
    central = met.groupBy("rep").agg(F.sum("size").alias("weight"))
    weighed = met.join(central, "rep")
    hubs = weighed.groupBy("key").agg(F.max(F.struct("weight", (-F.col("rep")).alias("minus"))).alias("top")).select("key", (-F.col("top.minus")).alias("hub"))
    buckets = store.cut_and_free(met.join(hubs, "key"), "buckets")
    texts = store.cut_and_free(docs.select("doc_id", "text").join(central.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi"), "texts")

    star = buckets.where("rep <> hub").select(F.col("rep").alias("a"), F.col("hub").alias("b")).distinct()
    links = store.cut_and_free(verified(star, texts, size, percent), "links")
    state = components(links)

    labelled = buckets.join(state, buckets["rep"] == state["node"], "left").select("key", "rep", "size", "hub", F.coalesce("label", "rep").alias("label"))
    small = labelled.where((F.col("size") > 2) & (F.col("size") <= SMALL) & (F.col("rep") != F.col("hub")))
    rest = small.alias("x").join(small.alias("y"), F.col("x.key") == F.col("y.key")).where("x.rep < y.rep and x.label <> y.label").select(F.col("x.rep").alias("a"), F.col("y.rep").alias("b")).distinct()
    more = store.cut_and_free(verified(rest, texts, size, percent).union(_family_links(buckets, state, texts, size, percent)), "links")
    final = components(state.select(F.col("node").alias("a"), F.col("label").alias("b")).union(more))

    owners = classes.join(final, classes["rep"] == final["node"], "left").select("d1", "d2", F.coalesce("label", "rep").alias("found"))
    out = sketch.join(owners, ["d1", "d2"], "left").withColumn("component_id", F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.col("found")).otherwise(F.col("doc_id")))
    return out.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def deduplicated(docs: DataFrame, size: int = 5, percent: int = 80) -> DataFrame:
    """The documents that stay, one of each group, with all their columns."""
    gone = groups(docs, size, percent).where(~F.col("kept")).select(F.col("doc_id").alias("__gone")).distinct()
    return docs.join(gone, docs["doc_id"] == gone["__gone"], "left_anti")


def op3_near_duplicates(spark, sf_dir: str) -> DataFrame:
    return groups(spark.read.parquet(f"{sf_dir}/documents.parquet"), 3, 85)


#: Links from an inverted list of shingles, components by repeated minima over the links.
ORACLE = """
with recursive word as (
    select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') as w from documents),
listed as (select doc_id, list_distinct(case when len(w) >= 3 then list_transform(range(1, len(w) - 1), lambda i: array_to_string(w[i:i + 2], ' '))
    when len(w) > 0 then [array_to_string(w, ' ')] else [] end) as s from word),
size as (select doc_id, len(s)::BIGINT as n from listed),
shingle as (select doc_id, unnest(s) as h from listed),
link as (select x.doc_id as a, y.doc_id as b from shingle x join shingle y on x.h = y.h and x.doc_id <> y.doc_id
    join size m on m.doc_id = x.doc_id join size n on n.doc_id = y.doc_id
    group by x.doc_id, y.doc_id having 100 * count(*) >= 85 * (any_value(m.n) + any_value(n.n) - count(*))),
reach as (select doc_id as a, doc_id as b from size union select r.a, l.b from reach r join link l on l.a = r.b)
select size.doc_id, size.n as n_shingles, min(reach.b) as component_id, size.doc_id = min(reach.b) as kept
from size join reach on reach.a = size.doc_id group by size.doc_id, size.n"""
