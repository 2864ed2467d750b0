"""Folders that driver and executors share, and repositories from a folder of files."""

from __future__ import annotations

import atexit
import contextlib
import uuid

from pyspark.sql import DataFrame, SparkSession


#: Folders that this driver made; results are read from them until it ends.
_made: list[tuple[SparkSession, str]] = []


def _sweep() -> None:
    """Removes the folders of this driver when it ends, as far as its sessions still live."""
    with contextlib.suppress(Exception):  # the virtual machine may be gone
        for spark, path in _made:
            place = spark._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def shared_folder(spark: SparkSession, name: str) -> str:
    """A fresh folder below spark.checkpoint.dir (below the warehouse where that is unset); it goes when the driver ends."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_shared"
    path = f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    if not _made:
        atexit.register(_sweep)
    _made.append((spark, path))
    return path


def written(df: DataFrame, name: str) -> DataFrame:
    """The frame written to the shared folder and read again, which cuts its lineage and outlives lost executors."""
    path = shared_folder(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def read_folder(spark: SparkSession, folder: str) -> dict[str, DataFrame]:
    """Candidate tables of a folder by name: parquet, orc, json, csv and text files or folders.

    Listing goes through Hadoop's file systems, so any store that Spark reads will do.
    """
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
    out = {}
    for status in fs.listStatus(path):
        name, _, kind = status.getPath().getName().rpartition(".")
        if kind in ("parquet", "orc", "json", "csv", "text"):
            reader = spark.read.format(kind)
            out[name] = (reader.option("header", True).option("inferSchema", True) if kind == "csv" else reader).load(status.getPath().toString())
    return out


def read_jdbc(spark: SparkSession, url: str, table: str, *, key: str | None = None, parts: int = 16, **options) -> DataFrame:
    """A table of a database by JDBC, read in ``parts`` ranges of a numeric key if one is given.

    The driver class has to be on Spark's class path; bounds come from one query.
    """
    reader = spark.read.format("jdbc").option("url", url).options(**options)
    if key is None:
        return reader.option("dbtable", table).load()
    low, high = reader.option("query", f"SELECT min({key}) AS low, max({key}) AS high FROM {table}").load().first()
    return reader.option("dbtable", table).option("partitionColumn", key).option("lowerBound", str(low or 0)).option("upperBound", str((high or 0) + 1)).option("numPartitions", str(parts)).load()
