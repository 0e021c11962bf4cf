"""The engine from SQL: table functions and a data source.

``register(spark, sf_dir)`` makes the relations of the parts city views named ``city_*``, registers the
function ``coin32`` and the table function ``reverse_walk``, and the data source ``reach_city``.
"""

from __future__ import annotations

from hashlib import md5

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.functions import udtf

from .model import parts_city


@udtf(returnType="step int, usr bigint")
class ReverseWalk:
    """Vertices of a walk back over in-neighbours given as a map usr -> array of predecessors, by the coins of a sample."""

    def eval(self, rid: int, target: int, before: dict, seed: int):
        seen, layer, step = {target}, [target], 0
        while layer:
            for u in layer:
                yield step, u
            following = []
            for v in layer:
                sources = before.get(v) or []
                for u in sources:
                    draw = int(md5(f"{rid}|{u}|{v}|{seed}".encode()).hexdigest()[:8], 16)
                    if draw * len(sources) < 1 << 32 and u not in seen:
                        seen.add(u)
                        following.append(u)
            layer, step = following, step + 1


class GridSource(DataSource):
    """``spark.read.format("reach_city").option("side", n)``: the edges of an n x n street grid of unit lengths, a block of rows a partition."""

    @classmethod
    def name(cls) -> str:
        return "reach_city"

    def schema(self) -> str:
        return "src bigint, dst bigint, len bigint"

    def reader(self, schema) -> DataSourceReader:
        return GridReader(int(self.options.get("side", "10")), int(self.options.get("blocks", "4")))


class GridReader(DataSourceReader):
    def __init__(self, side: int, blocks: int):
        self.side, self.blocks = side, blocks

    def partitions(self):
        return [InputPartition((self.side * i // self.blocks, self.side * (i + 1) // self.blocks)) for i in range(self.blocks)]

    def read(self, partition):
        lo, hi = partition.value
        n = self.side
        for y in range(lo, hi):
            for x in range(n):
                v = y * n + x
                for to in ([v + 1] if x + 1 < n else []) + ([v + n] if y + 1 < n else []):
                    yield v, to, 1
                    yield to, v, 1


def register(spark: SparkSession, sf_dir: str) -> None:
    city = parts_city(spark, sf_dir)
    for name in city.__dataclass_fields__:
        getattr(city, name).createOrReplaceTempView(f"city_{name}")
    spark.sql("create or replace temporary function coin32(t string) returns bigint return cast(conv(substring(md5(t), 1, 8), 16, 10) as bigint)")
    spark.udtf.register("reverse_walk", ReverseWalk)
    spark.dataSource.register(GridSource)
