"""Edge lists as text: one ``src<TAB>dst`` (or ``src<TAB>dst<TAB>w``) per line, ``#`` begins a comment.

``read_edge_list`` parses with built-in functions and is the way for large inputs.
``EdgeListSource`` makes ``spark.read.format("edgelist")`` work, reading in byte ranges."""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator
from dataclasses import dataclass
from urllib.parse import urlparse

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage


def read_edge_list(spark: SparkSession, path: str, weighted: bool = False) -> DataFrame:
    """(src, dst[, w]); comments, blank lines and lines that hold no two integers are left out."""
    part = F.split(F.trim("value"), r"\s+")
    rows = spark.read.text(path).where(~F.col("value").rlike(r"^\s*(#|$)"))
    columns = [F.get(part, 0).try_cast("long").alias("src"), F.get(part, 1).try_cast("long").alias("dst")]
    if weighted:
        columns.append(F.get(part, 2).try_cast("double").alias("w"))
    return rows.select(*columns).where("src is not null and dst is not null")


def write_edge_list(edges: DataFrame, path: str) -> None:
    """Writes (src, dst[, w]) as text, one line per row."""
    names = [c for c in ("src", "dst", "w") if c in edges.columns]
    edges.select(F.concat_ws("\t", *(F.col(c).cast("string") for c in names)).alias("value")).write.text(path)


def _local(path: str) -> str:
    return urlparse(path).path if path.startswith("file:") else path


@dataclass
class ByteRange(InputPartition):
    file: str
    begin: int
    end: int


class EdgeListReader(DataSourceReader):
    def __init__(self, path: str, weighted: bool, split_bytes: int):
        self.path, self.weighted, self.split_bytes = _local(path), weighted, split_bytes

    def partitions(self) -> list[ByteRange]:
        if os.path.isfile(self.path):
            files = [self.path]
        else:
            files = sorted(os.path.join(self.path, f) for f in os.listdir(self.path) if not f.startswith((".", "_")))
        sizes = [(f, os.path.getsize(f)) for f in files]
        return [ByteRange(f, at, min(at + self.split_bytes, size)) for f, size in sizes for at in range(0, size, self.split_bytes)]

    def read(self, partition: ByteRange) -> Iterator[tuple]:
        """Lines that begin in the range; the one that its start cuts belongs to the range before."""
        with open(partition.file, "rb") as lines:
            if partition.begin:
                lines.seek(partition.begin - 1)
                lines.readline()
            while lines.tell() < partition.end:
                line = lines.readline().split()
                if len(line) < 2 or line[0].startswith(b"#"):
                    continue
                try:
                    ends = int(line[0]), int(line[1])
                    yield (*ends, float(line[2]) if len(line) > 2 else None) if self.weighted else ends
                except ValueError:
                    continue


@dataclass
class Written(WriterCommitMessage):
    file: str


class EdgeListWriter(DataSourceWriter):
    """Each task writes a hidden file; the commit gives all of them their names, an abort deletes them."""

    def __init__(self, path: str, overwrite: bool):
        self.path, self.overwrite = _local(path), overwrite

    def write(self, rows: Iterator) -> Written:
        os.makedirs(self.path, exist_ok=True)
        file = os.path.join(self.path, f".part-{uuid.uuid4().hex}")
        with open(file, "w") as out:
            for row in rows:
                out.write("\t".join(str(x) for x in row if x is not None) + "\n")
        return Written(file)

    def commit(self, messages: list) -> None:
        if self.overwrite and os.path.isdir(self.path):
            for name in os.listdir(self.path):
                if name.startswith("part-"):
                    os.remove(os.path.join(self.path, name))
        for message in messages:
            if message is not None:
                folder, name = os.path.split(message.file)
                os.replace(message.file, os.path.join(folder, name[1:] + ".txt"))

    def abort(self, messages: list) -> None:
        for message in messages:
            if message is not None and os.path.exists(message.file):
                os.remove(message.file)


class EdgeListSource(DataSource):
    """``format("edgelist")``: options ``path``, ``weighted`` (false), ``split_bytes`` (64 MB).

    The path must be readable as a file by the driver and all executors."""

    @classmethod
    def name(cls) -> str:
        return "edgelist"

    def schema(self) -> str:
        return "src long, dst long, w double" if self._weighted() else "src long, dst long"

    def _weighted(self) -> bool:
        return self.options.get("weighted", "false").lower() == "true"

    def reader(self, schema) -> DataSourceReader:
        return EdgeListReader(self.options["path"], self._weighted(), int(self.options.get("split_bytes", 64 << 20)))

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        return EdgeListWriter(self.options["path"], overwrite)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(EdgeListSource)
