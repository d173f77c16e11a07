"""Scratch tables in the folder that driver and executors share, and tables that are kept for a session."""

from __future__ import annotations

import hashlib
import tempfile
import uuid
from collections.abc import Callable
from concurrent.futures import Future, ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession

_kept: dict[tuple[str, str], tuple[str, Callable[[SparkSession], DataFrame]]] = {}
PART = 1 << 20


def scratch_root(spark: SparkSession) -> str:
    """The shared folder of ``spark.checkpoint.dir``; in local mode, a folder of our own if that is unset."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root
    if not spark.conf.get("spark.master", "local").startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    root = tempfile.mkdtemp(prefix="factlake-")
    spark.conf.set("spark.checkpoint.dir", root)
    return root


def folder(spark: SparkSession, name: str) -> str:
    """A new path under the shared folder."""
    return f"{scratch_root(spark)}/factlake/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str, narrow: bool = False) -> DataFrame:
    """Write ``df`` to the shared scratch folder and read it back: cuts lineage and survives lost executors.

    ``narrow``: rows are short and few beside the texts, so a few files for every core will do.
    """
    spark = df.sparkSession
    if narrow:
        df = df.coalesce(4 * spark.sparkContext.defaultParallelism)
    path = folder(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def later(spark: SparkSession, make: Callable) -> Future:
    """``make()`` in a thread of its own, beside what follows."""
    pool = ThreadPoolExecutor(1)
    out = pool.submit(inheritable_thread_target(spark)(make))
    pool.shutdown(wait=False)
    return out


def stamp(spark: SparkSession, sf_dir: str, *tables: str) -> str:
    """What identifies the present content of tables: path, bytes, files and time of the last change."""
    out = []
    for t in tables:
        path = spark._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/{t}.parquet")
        fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
        sum_ = fs.getContentSummary(path)
        out.append(f"{path}|{sum_.getLength()}|{sum_.getFileCount()}|{fs.getFileStatus(path).getModificationTime()}")
    return ";".join(out)


def fitted(spark: SparkSession, sf_dir: str, *tables: str) -> SparkSession:
    """A session with the settings of ``spark`` and a shuffle partition (and bucket) for every PART bytes of these tables.

    Their number is a multiple of the cores, and at most what ``spark`` has or the cores, whichever is more: small
    tables in hundreds of partitions cost more to start tasks for than to work on.
    """
    scratch_root(spark)
    cores, size = max(1, spark.sparkContext.defaultParallelism), 0
    for t in tables:
        path = spark._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/{t}.parquet")
        size += path.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(path).getLength()
    most = max(cores, int(spark.conf.get("spark.sql.shuffle.partitions")))
    own = SparkSession(spark.sparkContext, spark._jsparkSession.cloneSession())
    own.conf.set("spark.sql.shuffle.partitions", str(min(most, cores * max(1, -(-size // (PART * cores))))))
    own.conf.set("spark.sql.codegen.hugeMethodLimit", "8000")  # the JVM never compiles longer methods
    return own


def _exists(spark: SparkSession, path: str) -> bool:
    """Whether a kept table is still there; scratch folders may be cleared between jobs."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)


def kept(spark: SparkSession, key: str, build: Callable[[], DataFrame], bucket: str | None = None) -> DataFrame:
    """The table of ``key``: built by the first call in a session, read by the others.

    ``bucket``: rows are stored in buckets of this column, so that joins on it need not move them; as many as the
    session of what is built has shuffle partitions.
    """
    own = (spark.sparkContext.applicationId, key)
    if own not in _kept or not _exists(spark, _kept[own][0]):
        df, path = build(), folder(spark, "kept")
        if bucket:
            n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
            name = f"factlake_{hashlib.md5(path.encode()).hexdigest()}"
            df.repartition(n, bucket).write.bucketBy(n, bucket).option("path", path).saveAsTable(name)
            _kept[own] = path, lambda s: s.table(name)
        else:
            df.write.parquet(path)
            schema = df.schema
            _kept[own] = path, lambda s: s.read.schema(schema).parquet(path)
    return _kept[own][1](spark)
