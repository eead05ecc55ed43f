"""Python workers are kept between tasks: what a task held goes back to the system at its end."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from functools import wraps

import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import SparkSession


def release() -> None:
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def tidy(fn: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """fn of batches, with memory returned at the end of the task."""

    @wraps(fn)
    def run(batches: Iterator) -> Iterator:
        yield from fn(batches)
        release()

    return run


BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"
BATCH_MB = 4  # of the rows that go to a Python worker at once


def short_batches(spark: SparkSession) -> None:
    """Batches to Python of few MB, whatever the texts' lengths, from here on in this session: an executor holds several copies of one
    for each of its cores, in Python, in the JVM's direct memory and in what the allocators keep of both. A given setting stays."""
    if spark.conf.get(BATCH, None) is None:
        spark.conf.set(BATCH, f"{BATCH_MB}m")


def release_driver(spark: SparkSession) -> None:
    """What the driver holds for finished jobs goes: its own memory, its JVM's heap and what the JVM's allocator keeps for threads
    that ended, and the shuffle files that Spark keeps as long as a plan is reachable."""
    jvm = spark.sparkContext._jvm
    jvm.java.lang.System.gc()
    release()
    try:  # the virtual machine's own command; older ones lack it
        call = next(m for m in jvm.java.lang.Class.forName("javax.management.MBeanServer").getMethods() if m.getName() == "invoke")
        args = spark.sparkContext._gateway.new_array(jvm.java.lang.Object, 4)
        args[0] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        args[1] = "systemTrimNativeHeap"
        call.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), args)
    except Py4JError:
        pass
