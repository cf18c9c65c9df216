"""What a session that somebody else started needs before it can run this library."""

from __future__ import annotations

import functools
import os
import tempfile
import time
import uuid
import zipfile
from collections.abc import Callable

from py4j.protocol import Py4JError
from pyspark.sql import SparkSession

#: Seconds from one ``relieve`` to the next at least.
RELIEVE_SECONDS = 3.0
_relieved = [0.0]


def ship(spark: SparkSession) -> None:
    """Give the library's own files to the workers, once for each context; they may not have it installed."""
    sc = spark.sparkContext
    if getattr(sc, "_seqcount_shipped", False):
        return
    top = os.path.dirname(os.path.abspath(__file__))
    path = os.path.join(tempfile.mkdtemp(prefix="seqcount-"), "seqcount_library.zip")
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for folder, _, names in sorted(os.walk(top)):
            for name in sorted(names):
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    z.write(full, os.path.relpath(full, os.path.dirname(top)))
    sc.addPyFile(path)
    sc._seqcount_shipped = True


def work_folder(spark: SparkSession) -> str:
    """The folder that the driver and all executors see, without a trailing slash.

    It's the checkpoint folder of the context, else the one that spark.checkpoint.dir names. Only a
    session whose executors are threads of the driver may do without and gets a temporary one.
    """
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors see")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="seqcount-checkpoint-"))
    return sc.getCheckpointDir().rstrip("/")


def new_folder(spark: SparkSession, name: str) -> str:
    """A path in the work folder that nothing has yet."""
    return f"{work_folder(spark)}/{name}-{uuid.uuid4().hex}"


def delete_folder(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def relieve(spark: SparkSession, every: float = RELIEVE_SECONDS) -> bool:
    """Let the driver's JVM give back what finished plans have left; whether it was asked to.

    For operators that run plan after plan: broadcasts, shuffles and generated classes of a
    finished plan go only with a collection, which a heap with room puts off, and memory
    that native code has freed (map statuses are compressed there) stays with the
    allocator until it's trimmed. A JVM without that command is only collected.
    """
    if time.monotonic() - _relieved[0] < every:
        return False
    _relieved[0] = time.monotonic()
    jvm, java = spark._jvm, spark._jvm.java.lang
    java.System.gc()
    try:
        beans = java.management.ManagementFactory.getPlatformMBeanServer()
        (invoke,) = [m for m in java.Class.forName("javax.management.MBeanServer").getMethods() if m.getName() == "invoke"]
        asked = spark.sparkContext._gateway.new_array(java.Object, 4)
        asked[0], asked[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        invoke.invoke(beans, asked)
    except Py4JError:
        pass
    return True


def shipped(query: Callable) -> Callable:
    """A query (spark, ...) that sees to it that workers have the library."""

    @functools.wraps(query)
    def run(spark, *args):
        ship(spark)
        return query(spark, *args)

    return run
