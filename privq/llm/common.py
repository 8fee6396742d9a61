"""Small helpers that the operators of this subpackage share."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of the word rule; everything else belongs to a word.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_or_empty(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))


def is_held_out(id_column: str = "doc_id") -> Column:
    """True where crc32 of the id's decimal text leaves 0 modulo 5; a null id is never held out."""
    return F.coalesce(F.crc32(F.col(id_column).cast("string").cast("binary")) % 5 == 0, F.lit(False))


def give_back() -> None:
    """Returns freed memory of a Python worker to the system: idle workers count against an executor's memory."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library keeps its own rules
        pass


def give_back_executors(spark: SparkSession) -> None:
    """Asks the executors' JVMs for a full collection, after which they return the heap that shuffles grew and dead classes.

    One task a core; with free cores each executor has one. A task that is dealt otherwise costs nothing but the effect.
    """
    cores = spark.sparkContext.defaultParallelism
    spark.range(0, cores, 1, cores).select(F.expr("reflect('java.lang.System', 'gc')")).collect()


def give_back_driver(spark: SparkSession) -> bool:
    """Has the driver collect its garbage and return freed memory to the system; whether the JVM's allocator did so too.

    That allocator keeps what compiling and planning freed in many arenas, so without this it grows with every stage. A
    JVM that doesn't know the command (it came with 17.0.9) keeps its own rules.
    """
    jvm = spark.sparkContext._jvm
    jvm.System.gc()
    give_back()
    try:
        given = spark.sparkContext._gateway.new_array(jvm.java.lang.Object, 4)  # bean, command, and no arguments
        given[0], given[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        methods = jvm.java.lang.Class.forName("javax.management.MBeanServerConnection").getMethods()  # the server's own class is closed
        next(m for m in methods if m.getName() == "invoke").invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), given)
    except Py4JError:
        return False
    return True


Batches = Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]


def tidy(run: Batches) -> Batches:
    """``run``, which gives memory back when a task ends."""

    def batches(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(stream)
        finally:
            give_back()

    return batches


@contextlib.contextmanager
def small_batches(spark: SparkSession, rows: int = 1000) -> Iterator[None]:
    """Arrow batches of fewer rows for what runs inside: rows that hold texts or arrays are long."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(min(rows, int(before)) if int(before) > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)
