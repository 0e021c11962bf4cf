"""Approximate nearest neighbours with a permutation index.

A vector is represented by its nearest pivots in order. The index deals the vectors into shards of ``SHARD``
rows by hash; a shard holds one inverted file per pivot (numbers of its vectors, and the position that the
pivot takes in each). It is written once to the shared folder and read by every block of queries. A query
visits the files of its own pivots only and adds up, for each vector met there, how far the footrule distance
of the two prefixes falls below that of disjoint ones. Prefixes tell angles only, so that sum times the
vector's length stands for the inner product; the share of a shard's vectors where it is largest (never fewer
than the 2 k + 2 that k neighbours can need) is ranked again by the exact inner product in double precision.
Where lengths are equal, these are the vectors of least footrule distance.

Pivots are the ``pivots`` vectors of smallest hash (a bounded sample); every vector is indexed. Vectors
that are equal are indexed once with their ``k + 1`` smallest ids, which is all that a result of k rows
can show. Queries are sent to all shards in blocks of bounded size; a shard answers with k rows a query.

Rows with a null id or vector, a zero vector, or a null, NaN or infinite component take no part, nor do
vectors whose length is not the commonest one. Rows of the same id and vector count once; rows of the same id
and different vectors are candidates each, and as queries each brings its own neighbours, ranked together
under the id, which is never its own neighbour. Equal scores go by the smaller vec_id; an empty table gives an
empty result; further columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import store

#: Pivots, length of the prefixes, share of a shard's vectors that is ranked again, and vectors of a shard.
PIVOTS, PREFIX, SHARE, SHARD = 1024, 96, 0.2, 8192
#: Queries in a block.
BLOCK = 20_000


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id and embedding of the rows that take part, without repeated rows."""
    odd = F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    rows = vectors.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>").alias("embedding"))
    rows = rows.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull()).where(~odd).where(F.exists("embedding", lambda x: x != 0))
    length = rows.groupBy(F.size("embedding").alias("n")).count().orderBy(F.desc("count"), "n").limit(1).collect()
    return rows.where(F.size("embedding") == (length[0]["n"] if length else 0)).dropDuplicates(["vec_id", "embedding"])


def distinct_vectors(rows: DataFrame, k: int) -> DataFrame:
    """One row for each different vector with its k + 1 smallest ids."""
    first = F.row_number().over(Window.partitionBy("embedding").orderBy("vec_id"))
    return rows.withColumn("nth", first).where(F.col("nth") <= k + 1).groupBy("embedding").agg(F.sort_array(F.collect_list("vec_id")).alias("ids"))


def _matrix(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1).astype(np.float64)


class InvertedFiles:
    """The posting lists of one shard: for each pivot, vectors and the position that the pivot takes in their prefix."""

    def __init__(self, n: int, prefix: int, cut: np.ndarray, vector: np.ndarray, place: np.ndarray):
        self.n, self.prefix, self.cut, self.vector, self.place = n, prefix, cut, vector, place

    @staticmethod
    def of(x: np.ndarray, pivots: np.ndarray, prefix: int) -> InvertedFiles:
        flat = prefixes(x, pivots, prefix).ravel()
        order = np.argsort(flat, kind="stable")
        cut = np.searchsorted(flat[order], np.arange(len(pivots) + 1))
        return InvertedFiles(len(x), prefix, cut.astype(np.int32), (order // prefix).astype(np.int32), (order % prefix).astype(np.int16))

    def footrule_gain(self, query: np.ndarray) -> np.ndarray:
        """How far the footrule distance of each vector is below that of two prefixes without a common pivot."""
        lo, hi = self.cut[query], self.cut[query + 1]
        met = np.concatenate([self.vector[a:b] for a, b in zip(lo, hi, strict=True)])
        place = np.concatenate([self.place[a:b] for a, b in zip(lo, hi, strict=True)])
        later = np.maximum(place, np.repeat(np.arange(len(query), dtype=np.int16), hi - lo))
        return 2 * np.bincount(met, self.prefix - later, self.n)


def prefixes(x: np.ndarray, pivots: np.ndarray, prefix: int) -> np.ndarray:
    """The nearest pivots of each vector, nearest first."""
    s = x @ pivots.T
    part = np.argpartition(-s, prefix - 1, axis=1)[:, :prefix] if prefix < len(pivots) else np.tile(np.arange(len(pivots)), (len(x), 1))
    return np.take_along_axis(part, np.argsort(-np.take_along_axis(s, part, 1), axis=1, kind="stable"), 1)


_PARTS = "shard int, prefix int, vectors binary, width int, owners binary, counts binary, cut binary, vector binary, place binary"


def build(rows: DataFrame, k: int, pivots: int, prefix: int, shard: int) -> tuple[DataFrame, np.ndarray]:
    """The index, one row a shard, and the pivots."""
    index = store.cut_and_free(distinct_vectors(rows, k), "vectors")
    n_shards = max(1, -(-index.count() // shard))
    sample = index.select("embedding").orderBy(F.xxhash64("embedding"), "embedding").limit(pivots).toPandas()["embedding"]
    # lengths do not matter to an order of pivots by angle, so long vectors do not attract every prefix
    base = np.array([np.asarray(v, float) for v in sample]) if len(sample) else np.zeros((0, 1))
    base = base / np.maximum(np.linalg.norm(base, axis=1, keepdims=True), 1e-300) if len(base) else base
    prefix = min(prefix, max(1, len(base)))
    shared = index.sparkSession.sparkContext.broadcast(base)

    def work(group: pa.Table) -> pa.Table:
        x = _matrix(group["embedding"].combine_chunks())
        owners = group["ids"].combine_chunks()
        files = InvertedFiles.of(x, shared.value, prefix)
        blobs = (x, owners.flatten().to_numpy(), np.diff(owners.offsets.to_numpy()), files.cut, files.vector, files.place)
        raw = [pa.array([a.tobytes()], pa.binary()) for a in blobs]
        return pa.Table.from_arrays([pa.array([group["shard"][0].as_py()], pa.int32()), pa.array([prefix], pa.int32()), raw[0], pa.array([x.shape[1]], pa.int32()), *raw[1:]], names=[c.split()[0] for c in _PARTS.split(", ")])

    dealt = index.withColumn("shard", F.pmod(F.xxhash64("embedding"), F.lit(n_shards)).cast("int"))
    return store.cut_and_free(dealt.groupBy("shard").applyInArrow(work, _PARTS), "inverted-files"), base


def nearest(vectors: DataFrame, every: int, k: int, pivots: int = PIVOTS, prefix: int = PREFIX, share: float = SHARE, shard: int = SHARD) -> DataFrame:
    """query_id, rank, vec_id, score: k neighbours of each row whose vec_id is divisible by ``every``."""
    spark, rows = vectors.sparkSession, usable(vectors)
    index, base = build(rows, k, pivots, prefix, shard)
    prefix = min(prefix, max(1, len(base)))
    asked = rows.where(F.col("vec_id") % every == 0)
    n_blocks, tasks = -(-asked.count() // BLOCK), min(4 * store.parts(spark), max(1, index.count()))

    def block(b: int) -> DataFrame:
        # bounded by BLOCK up to the spread of the hash
        found = asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(n_blocks)) == b).orderBy("vec_id").toPandas()
        q = np.array([np.asarray(v, float) for v in found["embedding"]]) if len(found) else np.zeros((0, 1))
        shared = spark.sparkContext.broadcast((found["vec_id"].to_numpy(np.int64), q, prefixes(q, base, prefix) if len(q) else q))

        def answers(part: dict) -> pa.RecordBatch:
            ids, q, views = shared.value
            x = np.frombuffer(part["vectors"]).reshape(-1, part["width"])
            owner, size = np.frombuffer(part["owners"], np.int64), np.frombuffer(part["counts"], np.int32).astype(np.int64)
            first = np.cumsum(size) - size
            files = InvertedFiles(len(x), part["prefix"], np.frombuffer(part["cut"], np.int32), np.frombuffer(part["vector"], np.int32), np.frombuffer(part["place"], np.int16))
            length = np.linalg.norm(x, axis=1)
            take = min(len(x), max(2 * k + 2, int(np.ceil(share * len(x)))))
            best = []
            for i in range(len(ids)):
                gain = (files.footrule_gain(views[i]) + 1) * length
                near = np.argpartition(-gain, take - 1)[:take] if take < len(x) else np.arange(len(x))
                if len(near) > 2 * k + 2:
                    s = x[near] @ q[i]
                    near = near[np.argpartition(-s, 2 * k + 1)[: 2 * k + 2]]
                s = (x[near] * q[i]).sum(axis=1)
                n = size[near]
                v = owner[np.repeat(first[near] - np.cumsum(n) + n, n) + np.arange(int(n.sum()))]
                s = np.repeat(s, n)
                v, s = v[v != ids[i]], s[v != ids[i]]
                order = np.lexsort((v, -s))[:k]
                best.append((s[order], v[order]))
            n = [len(v) for _, v in best]
            return pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, n)), pa.array(np.concatenate([v for _, v in best])), pa.array(np.concatenate([s for s, _ in best]))], names=["query_id", "vec_id", "score"])

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i in range(batch.num_rows if len(shared.value[0]) else 0):
                    yield answers({name: batch.column(j)[i].as_py() for j, name in enumerate(batch.schema.names)})

        # shards are few rows in few files, which would be read as one partition
        return index.repartition(tasks, "shard").mapInArrow(work, "query_id long, vec_id long, score double")

    found = reduce(DataFrame.unionAll, [block(b) for b in range(n_blocks)]) if n_blocks else spark.createDataFrame([], "query_id long, vec_id long, score double")
    # rows of one id with different vectors may bring the same neighbour twice
    best = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op10_nearest(spark, sf_dir: str) -> DataFrame:
    return nearest(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), 20, 20)
