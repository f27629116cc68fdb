"""Lineage cuts: tables written once to the folder that driver and executors share.

The folder is the session's ``spark.checkpoint.dir``; a temporary one is set only where
that is unset and the master is local (tests). On a cluster an unset folder is an error,
since executors would write to disks of their own."""

from __future__ import annotations

import atexit
import contextlib
import os
import tempfile
import threading
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Folders made here, with the session and the thread that made them; and the tables that lie in some of them.
_written: dict[str, tuple[SparkSession, int]] = {}
_tables: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """URI of the folder that all executors and the driver can read and write."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        holder = spark.sparkContext._jsc.sc().getCheckpointDir()
        if holder.isDefined():
            base = holder.get()
        elif is_local(spark):
            base = f"file://{tempfile.mkdtemp(prefix='pathmeet-')}"
            spark.sparkContext.setCheckpointDir(base)
        else:
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if "://" not in base and not base.startswith("file:"):
        base = f"file://{base}" if is_local(spark) else _qualified(spark, base)
    return base.rstrip("/")


def is_local(spark: SparkSession) -> bool:
    """True where driver and executors are one process."""
    master = spark.sparkContext.master
    return master == "local" or master.startswith("local[")


def _qualified(spark: SparkSession, path: str) -> str:
    """The path with the scheme of the file system that Spark itself would use for it."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).makeQualified(target).toString()


def new_path(spark: SparkSession, name: str) -> str:
    """A fresh folder name below the shared folder; removed when the process ends."""
    path = f"{shared_dir(spark)}/pathmeet-{name}-{uuid.uuid4().hex[:12]}"
    _written[path] = spark, threading.get_ident()
    return path


@contextmanager
def _swept(spark: SparkSession) -> Iterator[None]:
    """The shuffle files of a write made inside are deleted when it ends, not when the driver collects garbage."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, "false")
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def staged(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Writes ``df`` once as Parquet and returns a scan of it.

    Cuts lineage, survives the loss of executors, and freezes anything that
    depends on how rows were dealt to tasks."""
    spark = df.sparkSession
    path = new_path(spark, name)
    writer = df.write.option("compression", "zstd")
    with _swept(spark):
        (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def made() -> set[str]:
    """The folders that this thread has made and that still exist."""
    mine = threading.get_ident()
    return {path for path, (_, thread) in list(_written.items()) if thread == mine}


def settled(name: str, build: Callable[[], DataFrame]) -> DataFrame:
    """Builds a table, writes it, and deletes the tables that were written on the way to it."""
    before = made()
    out = staged(build(), name)
    for path in made() - before - paths_of(out):
        drop_path(out.sparkSession, path)
    return out


def paths_of(df: DataFrame) -> set[str]:
    """The folders made here that ``df`` reads."""
    roots = {f.rpartition("/")[0].rpartition("/")[2] for f in df.inputFiles()}
    return {p for p in list(_written) if p.rpartition("/")[2] in roots}


def drop_path(spark: SparkSession, path: str) -> None:
    """Deletes a folder made by ``new_path``, and the table in it."""
    if path in _tables:
        spark.sql(f"DROP TABLE IF EXISTS {_tables.pop(path)}")
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    _written.pop(path, None)


def _opened(spark: SparkSession, path: str):
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target, target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def read_file(spark: SparkSession, path: str) -> bytes | None:
    """A small file, or None if there is none."""
    target, fs = _opened(spark, path)
    if not fs.exists(target):
        return None
    stream = fs.open(target)
    try:
        return bytes(stream.readAllBytes())
    finally:
        stream.close()


def replace_file(spark: SparkSession, path: str, content: bytes) -> None:
    """Gives a file new content in one step: written aside, then renamed over the old one."""
    draft, fs = _opened(spark, f"{path}.{uuid.uuid4().hex}")
    out = fs.create(draft, False)
    out.write(content)
    out.close()
    target, _ = _opened(spark, path)
    if target.toUri().getScheme() in (None, "file"):
        os.replace(draft.toUri().getPath(), target.toUri().getPath())
        side = os.path.join(os.path.dirname(draft.toUri().getPath()), f".{draft.getName()}.crc")
        stale = os.path.join(os.path.dirname(target.toUri().getPath()), f".{target.getName()}.crc")
        for checksum in (side, stale):  # checksums of the draft and of the content before
            with contextlib.suppress(FileNotFoundError):
                os.unlink(checksum)
        return
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway
    kind = getattr(jvm.org.apache.hadoop.fs, "Options$Rename")
    over = gateway.new_array(kind, 1)
    over[0] = kind.OVERWRITE
    jvm.org.apache.hadoop.fs.FileContext.getFileContext(target.toUri(), spark.sparkContext._jsc.hadoopConfiguration()).rename(draft, target, over)


def delete_folder(spark: SparkSession, path: str) -> None:
    target, fs = _opened(spark, path)
    fs.delete(target, True)


def discard(df: DataFrame) -> None:
    """Deletes the files below a ``staged`` table that nothing reads any more."""
    for path in paths_of(df):
        drop_path(df.sparkSession, path)


@atexit.register
def _clean() -> None:
    for path, (spark, _) in list(_written.items()):
        with contextlib.suppress(Exception):
            drop_path(spark, path)


#: Rows that a bucket is meant to hold where their number is known.
BUCKET_ROWS = 200_000


def bucketed(df: DataFrame, name: str, key: str, buckets: int | None = None, rows: int | None = None) -> DataFrame:
    """Writes ``df`` once as a table bucketed and sorted by ``key``, and returns a scan of it.

    Joins on the key read it in place while the other side is shuffled to its buckets. Rows are dealt to their buckets
    first, so that each is one file. ``rows``, their number or a bound of it, gives fewer buckets to small tables."""
    spark = df.sparkSession
    path = new_path(spark, name)
    table = path.rpartition("/")[2].replace("-", "_")
    most = int(spark.conf.get("spark.sql.shuffle.partitions", "200"))
    if rows is not None:
        most = min(most, max(spark.sparkContext.defaultParallelism, -(-rows // BUCKET_ROWS)))
    buckets = buckets or most
    _tables[path] = table
    with _swept(spark):
        df.repartition(buckets, key).write.format("parquet").option("path", path).option("compression", "zstd").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
    return spark.table(table)
