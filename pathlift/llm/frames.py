"""Small helpers shared by the corpus operators."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import gc
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, read by Spark from wherever ``sf_dir`` points."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def held_out(doc_id: Column | str = "doc_id") -> Column:
    """True where crc32 of the id's decimal text is 2 modulo 4; false for a null id."""
    column = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.coalesce(F.pmod(F.crc32(column.cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def without(df: DataFrame, names: list[str]) -> DataFrame:
    """The frame without columns of these names, whatever their case."""
    gone = {n.lower() for n in names}
    return df.select(*[F.col(f"`{c}`") for c in df.columns if c.lower() not in gone])


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Names like these, each with a number at its end if a column has it already (in any case)."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        own, k = name, 0
        while own.lower() in taken:
            k += 1
            own = f"{name}_{k}"
        taken.add(own.lower())
        out.append(own)
    return out


def tidied(run: Callable) -> Callable:
    """A function over batches that gives its memory back to the system when it ends.

    Workers outlive their task: Spark hands them to later stages, in which the heap
    that malloc and Arrow's pool kept from this one counts against the executor's
    memory beside the JVM's own.  This is the one place where memory is given back.
    """

    def wrapped(batches: Iterator) -> Iterator:
        yield from run(batches)
        gc.collect()
        pa.default_memory_pool().release_unused()
        with contextlib.suppress(OSError, AttributeError):  # not glibc
            ctypes.CDLL("libc.so.6").malloc_trim(0)

    return wrapped


def add_columns(df: DataFrame, fields: list[tuple[str, T.DataType]], make: Callable[[pa.RecordBatch], list]) -> DataFrame:
    """The frame with columns that ``make`` computes from each Arrow batch.

    Columns of the same names (in any case) are replaced; others are carried on.
    """
    kept = without(df, [n for n, _ in fields])
    schema = T.StructType([*kept.schema.fields, *[T.StructField(n, t) for n, t in fields]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, *make(batch)], names=[*batch.schema.names, *[n for n, _ in fields]])

    return kept.mapInArrow(tidied(run), schema)


def shared_dir(spark: SparkSession, purpose: str) -> str:
    """A fresh folder that driver and executors share, below spark.checkpoint.dir.

    Where that setting is absent (local tests), a folder below the warehouse serves.
    """
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_shared"
    path = f"{root.rstrip('/')}/{purpose}-{uuid.uuid4().hex}"
    if not _made:
        atexit.register(_sweep)
    _made.append((spark, path))
    return path


#: Folders that this driver made; results are read from them until it ends.
_made: list[tuple[SparkSession, str]] = []


def _sweep() -> None:
    """Removes the folders of this driver when it ends, as far as its sessions still live."""
    with contextlib.suppress(Exception):  # the virtual machine may be gone
        for spark, path in _made:
            place = spark._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


@contextlib.contextmanager
def small_batches(spark: SparkSession, rows: int = 1000) -> Iterator[None]:
    """Arrow batches of fewer rows while a step runs: texts are long, and batches are held twice."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(min(rows, int(before)) if int(before) > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)


class Workspace:
    """Written intermediate tables of one run, in the folder all machines share.

    ``keep`` writes a frame and reads it again, which cuts its lineage: a lost
    executor costs no recomputation.  After large steps (``release``) the shuffle files
    behind them go at once rather than at the next garbage collection of the driver.
    """

    def __init__(self, spark: SparkSession, purpose: str):
        self.spark, self.base, self.kept = spark, shared_dir(spark, purpose), set()

    def _path(self, name: str):
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.base}/{name}")
        return path, path.getFileSystem(self.spark._jsc.hadoopConfiguration())

    def keep(self, df: DataFrame, name: str, *, release: bool = False) -> DataFrame:
        with small_batches(self.spark):
            df.write.parquet(f"{self.base}/{name}")
        self.kept.add(name)
        schema = df.schema
        if release:
            del df
            self.release()
        return self.spark.read.schema(schema).parquet(f"{self.base}/{name}")

    def release(self) -> None:
        """Lets the driver notice which shuffles nothing refers to any more."""
        gc.collect()
        self.spark._jvm.System.gc()

    def forget(self, *names: str) -> None:
        """Removes tables that nothing reads any more."""
        for name in names:
            path, fs = self._path(name)
            fs.delete(path, True)
            self.kept.discard(name)

    def forget_all_but(self, *names: str) -> None:
        """Removes all tables but those of these names."""
        self.forget(*(self.kept - set(names)))
