"""Tables in, tiles, models and runs out."""

from __future__ import annotations

import json
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own: str | None = None


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """User data in any of Spark's file formats: parquet, orc, csv, json, text, libsvm."""
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; an own temporary one where none is set and all runs on this machine, else an error."""
    global _own
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    if _own is None:
        _own = tempfile.mkdtemp(prefix="kernmill-")
    return _own


def materialize(df: DataFrame, path: str | None = None) -> DataFrame:
    """Write and read again: cuts lineage and survives lost executors."""
    path = path or f"{shared_dir(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def write_tiles(tiles: DataFrame, path: str) -> DataFrame:
    """A kernel tile store, partitioned by tile column so that a reader of one column prunes the rest."""
    tiles.write.mode("overwrite").option("compression", "none").partitionBy("bj").parquet(path)
    return read_tiles(tiles.sparkSession, path)


def read_tiles(spark: SparkSession, path: str, column: int | None = None) -> DataFrame:
    tiles = spark.read.parquet(path)
    return tiles if column is None else tiles.where(tiles.bj == column)


def latest_sweep(spark: SparkSession, path: str, n: int):
    """(sweep, labels int32 by idx) of the last whole checkpoint under ``path``; (0, None) without one."""
    import numpy as np

    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = hadoop.getFileSystem(spark._jsc.hadoopConfiguration())
    found = [f.getPath() for f in fs.listStatus(hadoop)] if fs.exists(hadoop) else []
    whole = [int(f.getName()[6:]) for f in found if f.getName().startswith("sweep=") and fs.exists(spark._jvm.org.apache.hadoop.fs.Path(f, "_SUCCESS"))]
    if not whole:
        return 0, None
    labels = np.zeros(n, np.int32)
    rows = spark.read.parquet(f"{path}/sweep={max(whole)}").toPandas()
    if len(rows) != n:
        raise ValueError(f"{path} holds labels of {len(rows)} points, not {n}")
    labels[rows["idx"].to_numpy()] = rows["cl"].to_numpy()
    return max(whole), labels


def write_runs(runs: DataFrame, path: str) -> None:
    runs.write.mode("append").parquet(path)


def export_csv(df: DataFrame, path: str) -> None:
    df.coalesce(1).write.mode("overwrite").option("header", True).csv(path)


def write_json_row(spark: SparkSession, row: dict, path: str) -> None:
    spark.createDataFrame([(json.dumps(row, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(path)


def read_json_row(spark: SparkSession, path: str) -> dict:
    return json.loads(spark.read.text(path).first()[0])
