"""Sessions, and this package's way to the executors."""

from __future__ import annotations

import atexit
import os
import re
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path
from urllib.parse import urlparse

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()


def local_session(cores: int | str = "*", partitions: int = 8, **conf: str) -> SparkSession:
    """A session for tests and benchmarks. On a cluster the caller brings its own."""
    build = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(partitions))
    for k, v in {"spark.ui.enabled": "false", "spark.sql.session.timeZone": "UTC", "spark.ui.showConsoleProgress": "false"}.items():
        build = build.config(k, v)
    for k, v in conf.items():
        build = build.config(k, v)
    return build.getOrCreate()


def ship_package(spark: SparkSession) -> None:
    """Send this package to the executors' Python workers, once for each application; they need not have it installed."""
    sc = spark.sparkContext
    if sc.applicationId in _SHIPPED:
        return
    _SHIPPED.add(sc.applicationId)
    root = Path(__file__).resolve().parent
    out = os.path.join(tempfile.mkdtemp(prefix="halograph-"), "halograph_package.zip")
    with zipfile.ZipFile(out, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    sc.addPyFile(out)


#: Used only where the session names no shared folder (tests, a laptop).
FALLBACK_SHARED_DIR = "/tmp/checkpoints"
_RUN = uuid.uuid4().hex[:12]
_MADE: set[str] = set()


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors see: spark.checkpoint.dir, or on one machine the fallback where it is unset."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.fullmatch(r"local(\[[^]]*\])?", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return (named or FALLBACK_SHARED_DIR).rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    """A new path under the shared folder. It is removed when this Python process ends."""
    root = f"{shared_dir(spark)}/halograph-{_RUN}"
    if root not in _MADE:
        _MADE.add(root)
        atexit.register(_remove, spark, root)
    return f"{root}/{name}-{uuid.uuid4().hex[:10]}"


def store(path: str):
    """A pyarrow file system and the path in it, for tasks that write or read a shared file themselves. Paths without a scheme are local."""
    from pyarrow import fs

    scheme = urlparse(path).scheme
    return (fs.LocalFileSystem(), "/" + path.removeprefix("file:").lstrip("/")) if scheme in ("", "file") else fs.FileSystem.from_uri(path)


def _remove(spark: SparkSession, path: str) -> None:
    try:
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # noqa: BLE001 - the session may be gone; the folder is only scratch space
        pass


def release(spark: SparkSession) -> bool:
    """Give back what finished jobs leave in the driver: its heap, which is else grown rather than collected, with it shuffle files of plans
    that are gone, and freed native memory that the system's allocator keeps. False where this JVM can't return the latter."""
    try:
        jvm, array = spark.sparkContext._jvm, spark.sparkContext._gateway.new_array
        jvm.System.gc()

        def of(kind, *values):
            out = array(kind, len(values))
            for k, v in enumerate(values):
                out[k] = v
            return out

        # through the interface, since the server's own class is not open to callers
        named = jvm.Class.forName
        kinds = of(jvm.Class, *map(named, ("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")))
        invoke = named("javax.management.MBeanServer").getMethod("invoke", kinds)
        bean = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        invoke.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), of(jvm.Object, bean, "systemTrimNativeHeap", of(jvm.Object), of(jvm.String)))
        return True
    except Exception:  # noqa: BLE001 - no such JVM or command; results don't depend on it
        return False


#: of a batch of rows on its way to Python
BATCH_BYTES = 64 << 20
_BATCH_ROWS, _BATCH_LIMIT = "spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.execution.arrow.maxBytesPerBatch"


@contextmanager
def batches_by_rows(spark: SparkSession, row_bytes: int) -> Iterator[None]:
    """Within it, batches of rows of at most row_bytes are held to BATCH_BYTES by counting rows. Under a limit of bytes, Spark weighs the whole
    batch again with each row it adds, which takes many times as long as the rows themselves."""
    before = {k: spark.conf.get(k, None) for k in (_BATCH_ROWS, _BATCH_LIMIT)}
    asked = int(before[_BATCH_ROWS] or 10_000)
    rows = max(1, BATCH_BYTES // row_bytes)
    spark.conf.set(_BATCH_ROWS, str(min(asked, rows) if asked > 0 else rows))
    spark.conf.set(_BATCH_LIMIT, str(2**31 - 1))  # the value that stands for none
    try:
        yield
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)


def stage(df: DataFrame, name: str = "stage") -> DataFrame:
    """Write to shared storage and read again: cuts lineage, and outlives a lost executor."""
    spark = df.sparkSession
    ship_package(spark)
    path = fresh_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def bucketed(df: DataFrame, key: str, buckets: int | None = None) -> DataFrame:
    """Write to shared storage in sorted buckets of the key and read again, as a table that joins and groups by the key don't exchange. The
    table's files lie in the shared folder; only its name is in the session's catalog."""
    spark = df.sparkSession
    ship_package(spark)
    n = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
    path = fresh_path(spark, "buckets")
    name = f"halograph_{uuid.uuid4().hex}"
    df.repartition(n, key).write.format("parquet").option("path", path).bucketBy(n, key).sortBy(key).saveAsTable(name)
    return spark.table(name)
