"""Helpers shared by the operators: scratch tables, byte-level words, joins safe against hot keys."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import kept as written
from ..session import scratch as scratch_dir
from ..session import workers as on_workers

__all__ = ["WORD", "batch", "boxed", "crc", "driver_gives_back", "give_back", "join_groups", "map_batches", "on_workers", "quoted", "scratch_dir", "table", "unboxed", "without", "written"]

MOST_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"
BATCH_BYTES = 4 << 20

WORD = r"[^\x20\x09-\x0D]+"


def map_batches(df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema) -> DataFrame:
    """fn over all batches of a partition. A worker process serves many tasks, so each gives back what it no longer
    needs: otherwise the freed memory of every earlier stage stays with the process. Batches are bounded in bytes,
    where the session sets no bound of its own: they are held several times over, by executor and worker."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from fn(batches)
        give_back()

    on_workers(df.sparkSession)
    if df.sparkSession.conf.get(MOST_BYTES, None) is None:
        df.sparkSession.conf.set(MOST_BYTES, str(BATCH_BYTES))
    return df.mapInArrow(run, schema)


def give_back() -> None:
    """Return freed memory to the system, where the C library can."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def driver_gives_back(spark: SparkSession) -> None:
    """Return freed memory of the driver, its Python and its JVM, to the system: each of many small jobs leaves garbage,
    and memory of the threads that planned and broadcast it. JVMs that can't trim what they freed outside the heap only
    collect garbage."""
    give_back()
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway
    jvm.java.lang.System.gc()

    def array(kind, *values):
        out = gateway.new_array(kind, len(values))
        for k, v in enumerate(values):
            out[k] = v
        return out

    of, lang = jvm.java.lang.Class.forName, jvm.java.lang
    kinds = map(of, ("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;"))
    command = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
    try:  # by reflection: the server's own class isn't open to callers
        invoke = of("javax.management.MBeanServer").getMethod("invoke", array(lang.Class, *kinds))
        invoke.invoke(lang.management.ManagementFactory.getPlatformMBeanServer(), array(lang.Object, command, "systemTrimNativeHeap", array(lang.Object), array(lang.String)))
    except Py4JJavaError:
        pass


def batch(**columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict(columns)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def without(names: list[str], *made: str) -> list[str]:
    """Columns to carry: those an operator makes replace input columns of the same name (any case)."""
    lower = {x.lower() for x in made}
    return [c for c in names if c.lower() not in lower]


def boxed(df: DataFrame, columns: list[str] | None = None) -> Column:
    """Input columns in one struct, so that their names never meet an operator's own."""
    return F.struct(*quoted(df.columns if columns is None else columns)).alias("_row")


def unboxed(names: list[str]) -> list[Column]:
    return [F.col(f"_row.`{c.replace('`', '``')}`").alias(c) for c in names]


def quoted(names: list[str]) -> list[Column]:
    return [F.col(f"`{c.replace('`', '``')}`") for c in names]


def crc(col: str) -> Column:
    return F.crc32(F.col(col).cast("string").cast("binary"))


def join_groups(rows: DataFrame, groups: DataFrame, key: str, size: str, total: int) -> DataFrame:
    """rows JOIN groups on key, where groups has one row per key and the number of its rows.

    Keys with at least max(1000, total / 20000) rows are at most 20,000, so they are broadcast and their rows
    never move; the others are shuffled and none of them is large enough to weigh on a task. groups should be written:
    it is asked first whether there are such keys, since the driver keeps threads and memory for each broadcast.
    """
    least = max(1000, total // 20_000)
    heavy, light = groups.where(F.col(size) >= least), groups.where(F.col(size) < least)
    if heavy.isEmpty():
        return rows.join(groups, key)
    hot = rows.join(F.broadcast(heavy), key)
    rest = rows.join(F.broadcast(heavy.select(key)), key, "left_anti").join(light, key)
    return hot.unionByName(rest)
