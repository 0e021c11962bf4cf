"""Scans of the given tables, other formats, and tables kept in the shared folder."""

from __future__ import annotations

import atexit
import json
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; filters and columns are pushed into its scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Any built-in format (parquet, orc, csv, json, text, jdbc); a schema spares inference."""
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", by: list[str] | None = None, sort: list[str] | None = None, **options) -> None:
    """Write, clustered by ``sort`` so that readers prune row groups, and partitioned by ``by``."""
    if sort:
        df = df.repartitionByRange(*sort).sortWithinPartitions(*sort)
    writer = df.write.format(kind).options(**options)
    (writer.partitionBy(*by) if by else writer).save(path)


def store_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``, which all executors share. In local mode a new folder, gone at exit, where it is unset; an error on a cluster."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="sitereach-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        at = f"file://{folder}"
        spark.conf.set("spark.checkpoint.dir", at)
    return at.rstrip("/")


def keep(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read back: cuts lineage, survives lost executors, is computed once. What is kept already is given back."""
    if getattr(df, "_kept", False):
        return df
    spark, path = df.sparkSession, f"{store_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._kept = True
    return out


def stored_bytes(df: DataFrame) -> int:
    """Bytes of the files of a kept table."""
    spark, total = df.sparkSession, 0
    for name in df.inputFiles():
        path = spark._jvm.org.apache.hadoop.fs.Path(name)
        total += path.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(path).getLen()
    return total


def manifest(components: dict[str, DataFrame], **params) -> str:
    """JSON of the rows and stored bytes of an index's kept components."""
    return json.dumps({"params": params, "components": {k: {"rows": v.count(), "bytes": stored_bytes(v)} for k, v in components.items()}})
