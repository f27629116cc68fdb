"""Sharding by size-tiered compaction with a versioned manifest.

Arrivals are appended as small immutable shards. Shards of similar size form a tier
(``fanout`` times larger from tier to tier); when a tier has ``fanout`` shards or more,
runs of them are merged, each run into a shard of at most about ``target_bytes``. Every
append and every merge round writes new shards, then commits the list of live shards as
the next manifest version: a complete file that gets its final name in one step which fails if
the name is taken. Readers see whole versions only; a writer that dies leaves files that no
manifest names. Old versions stay readable until ``vacuum`` drops those before the last
``keep``. A merge task streams its run from the store and writes one file; rows are never shuffled.

Defined results: shards keep all columns and rows, nulls and repeated rows included; an
empty table commits a version without shards; a single row larger than the target is a
shard of its own. Arrivals may differ in columns: merged shards have all of them, and columns
that a row did not have are null; a column that changed its type is an error. Columns may
have any names; those that ``read`` adds give way by a longer name. Two writers that commit the same
version: one fails and can retry. On stores without a rename that respects existing
names, one writer at a time is required. The plan of a round sorts the list of shards of a tier in one
task, and a manifest is one file, which suits some 10^7 shards.
"""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator
from functools import reduce

import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.window import Window

from pathmeet.llm.warc_bundles import opened
from pathmeet.rows import free_name
from pathmeet.scratch import new_path, staged

ENTRY = "shard string, rows long, bytes long, plain_bytes long"
NAMES = [x.split()[0] for x in ENTRY.split(", ")]


def _entry(fs, folder: str, root: str, name: str, rows: int, plain: int) -> pa.RecordBatch:
    size = fs.get_file_info(f"{root}/{name}").size
    return pa.RecordBatch.from_pylist([{"shard": f"{folder}/{name}", "rows": rows, "bytes": size, "plain_bytes": plain}], schema=pa.schema([(NAMES[0], pa.string()), *((n, pa.int64()) for n in NAMES[1:])]))


def in_schema(table: pa.Table, kind: pa.Schema) -> pa.Table:
    """The table with the columns of ``kind`` in their order; those it lacks are null."""
    return pa.table([table.column(f.name) if f.name in table.column_names else pa.nulls(table.num_rows, f.type) for f in kind], schema=kind)


def dealt(names: DataFrame, count: int) -> DataFrame:
    """Rows of file names dealt evenly to tasks, about one each; a number of partitions of our own is
    kept by adaptive execution, which else would merge rows this small into one task."""
    cores = names.sparkSession.sparkContext.defaultParallelism
    return names.repartition(max(1, min(count, max(4 * cores, count // 64))))


class Store:
    """A folder of immutable shards and its manifest versions."""

    def __init__(self, spark: SparkSession, folder: str | None = None, fanout: int = 4, least_bytes: int = 1 << 20, target_bytes: int = 128 << 20, most: int = 32):
        self.spark, self.fanout, self.least, self.target, self.most = spark, fanout, least_bytes, target_bytes, most
        self.folder = folder or new_path(spark, "shards")
        self.jvm = spark.sparkContext._jvm
        self.path = self.jvm.org.apache.hadoop.fs.Path
        self.fs = self.path(self.folder).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        self.fs.mkdirs(self.path(f"{self.folder}/_versions"))

    def version(self) -> int:
        """The latest committed version, 0 before the first commit."""
        return max(self.versions(), default=0)

    def versions(self) -> list[int]:
        """The committed versions that can still be read."""
        names = [s.getPath().getName() for s in self.fs.listStatus(self.path(f"{self.folder}/_versions"))]
        return sorted(int(n) for n in names if n.isdigit())

    def manifest(self, version: int | None = None) -> DataFrame:
        """The live shards of a version with their tier."""
        version = self.version() if version is None else version
        if not version:
            return self.spark.createDataFrame([], f"{ENTRY}, tier int")
        stream = self.fs.open(self.path(f"{self.folder}/_versions/{version}"))
        try:
            listed = bytes(stream.readAllBytes()).decode()
        finally:
            stream.close()
        return self.spark.read.schema(f"{ENTRY}, tier int").parquet(listed)

    def tier(self, size):
        """0 below ``least_bytes``, then one more for each factor of ``fanout``."""
        return F.greatest(F.lit(0), F.floor(F.log(F.greatest(size, F.lit(1)) / self.least) / F.log(F.lit(float(self.fanout)))) + 1).cast("int")

    def commit(self, shards: DataFrame, base: int) -> int:
        """Makes ``shards`` version ``base + 1``; fails with FileExistsError if another writer was first."""
        listed = f"{self.folder}/_manifests/{uuid.uuid4().hex}"
        shards.select(*NAMES).withColumn("tier", self.tier(F.col("bytes"))).coalesce(1).write.parquet(listed)
        draft = f"{self.folder}/_drafts/{uuid.uuid4().hex}"
        out = self.fs.create(self.path(draft), False)
        out.write(listed.encode())
        out.close()
        self._publish(draft, f"{self.folder}/_versions/{base + 1}")
        return base + 1

    def _publish(self, draft: str, final: str) -> None:
        """Gives a complete file its final name, unless that is taken: a hard link on a local folder, a
        rename without overwriting elsewhere."""
        if self.path(self.folder).toUri().getScheme() in (None, "file"):
            plain = lambda name: self.path(name).toUri().getPath()
            os.link(plain(draft), plain(final))
            os.unlink(plain(draft))
            return
        rename = getattr(self.jvm.org.apache.hadoop.fs, "Options$Rename")
        never = self.spark.sparkContext._gateway.new_array(rename, 0)
        context = self.jvm.org.apache.hadoop.fs.FileContext.getFileContext(self.path(self.folder).toUri(), self.spark.sparkContext._jsc.hadoopConfiguration())
        try:
            context.rename(self.path(draft), self.path(final), never)
        except Exception as error:
            if self.fs.exists(self.path(final)):
                raise FileExistsError(final) from error
            raise

    def append(self, rows: DataFrame, arrival_bytes: int = 8 << 20) -> int:
        """Writes ``rows`` as shards of about ``arrival_bytes`` in memory and commits them."""
        folder = f"{self.folder}/data"

        def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            fs, root = opened(folder)
            fs.create_dir(root, recursive=True)

            def shard(held: list[pa.RecordBatch]) -> pa.RecordBatch:
                name = f"{uuid.uuid4().hex}.parquet"
                table = pa.Table.from_batches(held)
                with fs.open_output_stream(f"{root}/{name}", compression=None) as sink:
                    pq.write_table(table, sink, compression="zstd")
                return _entry(fs, folder, root, name, table.num_rows, table.nbytes)

            held: list[pa.RecordBatch] = []
            size = 0
            for batch in batches:
                step = max(1, int(batch.num_rows * arrival_bytes / max(1, batch.nbytes)))
                for at in range(0, batch.num_rows, step):
                    some = batch.slice(at, step)
                    held.append(some)
                    size += some.nbytes
                    if size >= arrival_bytes:
                        yield shard(held)
                        held, size = [], 0
            if held:
                yield shard(held)

        new = staged(rows.mapInArrow(write, ENTRY), "shards-new")
        base = self.version()
        return self.commit(self.manifest(base).select(*NAMES).unionByName(new), base)

    def plan(self, shards: DataFrame) -> DataFrame:
        """Runs to merge: (shard, tier, run) of tiers with ``fanout`` shards or more.

        In a tier, shards go by size and name into runs of at most about ``target_bytes`` and
        ``most`` shards; shards of half the target and more, and runs of one shard, stay."""
        small = shards.where(F.col("bytes") * 2 < self.target).withColumn("tier", self.tier(F.col("bytes")))
        ordered = Window.partitionBy("tier").orderBy("bytes", "shard")
        run = F.coalesce(F.floor(F.sum("bytes").over(ordered.rowsBetween(Window.unboundedPreceding, -1)) / self.target), F.lit(0))
        place = F.floor((F.row_number().over(ordered) - 1) / self.most)
        runs = small.withColumn("run", F.struct(run.cast("long").alias("by_bytes"), place.cast("long").alias("by_count"))).withColumn("in_tier", F.count("*").over(Window.partitionBy("tier")))
        runs = runs.withColumn("in_run", F.count("*").over(Window.partitionBy("tier", "run")))
        return runs.where((F.col("in_tier") >= self.fanout) & (F.col("in_run") > 1)).select("shard", "tier", "run")

    def compact(self) -> bool:
        """One round of merges, committed as one version; False if no tier was full."""
        base = self.version()
        live = self.manifest(base).select(*NAMES)
        planned = staged(self.plan(live), "shards-plan")
        if planned.isEmpty():
            return False
        runs = planned.groupBy("tier", "run").agg(F.sort_array(F.collect_list("shard")).alias("shards")).select("shards")
        folder = f"{self.folder}/data"

        def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            fs, root = opened(folder)
            for batch in batches:
                for shards in batch.column(0).to_pylist():
                    name = f"{uuid.uuid4().hex}.parquet"
                    rows = plain = 0
                    paths = [f"{root}/{shard.rpartition('/')[2]}" for shard in shards]
                    kinds = []
                    for path in paths:
                        with fs.open_input_file(path) as file:
                            kinds.append(pq.read_schema(file).remove_metadata())
                    kind = pa.unify_schemas(kinds)
                    with fs.open_output_stream(f"{root}/{name}", compression=None) as sink, pq.ParquetWriter(sink, kind, compression="zstd") as writer:
                        for path in paths:
                            with fs.open_input_file(path) as file:
                                source = pq.ParquetFile(file)
                                for group in range(source.num_row_groups):
                                    table = in_schema(source.read_row_group(group), kind)
                                    writer.write_table(table)
                                    rows, plain = rows + table.num_rows, plain + table.nbytes
                    yield _entry(fs, folder, root, name, rows, plain)

        # a number of partitions of our own: rows of file names look too small to be kept apart
        merged = staged(dealt(runs, planned.select("tier", "run").distinct().count()).mapInArrow(merge, ENTRY), "shards-merged")
        self.commit(live.join(planned.select("shard"), "shard", "left_anti").unionByName(merged), base)
        return True

    def compact_fully(self, keep: int = 2) -> int:
        """Rounds until no tier is full, with the last ``keep`` versions readable. Returns the version."""
        while self.compact():
            self.vacuum(keep)
        return self.version()

    def vacuum(self, keep: int = 2) -> None:
        """Drops the versions before the last ``keep`` (one at least) and the shards that only they name."""
        versions = self.versions()
        old, kept = versions[: -max(1, keep)], versions[-max(1, keep) :]
        if not old:
            return
        named = lambda some: reduce(DataFrame.unionByName, (self.manifest(v).select("shard") for v in some)).distinct()
        gone = staged(named(old).join(named(kept), "shard", "left_anti"), "shards-gone")
        for version in old:  # first the versions, so that no reader finds one whose shards are going
            self.fs.delete(self.path(f"{self.folder}/_versions/{version}"), False)

        def delete(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for shard in batch.column(0).to_pylist():
                    fs, path = opened(shard)
                    if fs.get_file_info(path).is_file:
                        fs.delete_file(path)
                yield batch

        dealt(gone, gone.count()).mapInArrow(delete, "shard string").write.format("noop").mode("overwrite").save()

    def read(self, schema: T.StructType, version: int | None = None) -> DataFrame:
        """The rows of a version with the columns ``_shard``, ``_position``, ``_tier`` and ``_version`` (longer if taken)."""
        version = self.version() if version is None else version
        listed = self.manifest(version).select("shard", "tier")
        added = [free_name(schema.fieldNames(), x) for x in ("_shard", "_position", "_tier", "_version")]
        kinds = (T.StringType(), T.LongType(), T.IntegerType(), T.IntegerType())
        out = T.StructType([*schema.fields, *(T.StructField(n, k) for n, k in zip(added, kinds, strict=True))])
        wanted, names = schema.fieldNames(), [f.name for f in out.fields]
        arrow = to_arrow_schema(schema)

        def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for shard, tier in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    fs, path = opened(shard)
                    with fs.open_input_file(path) as file:
                        at = 0
                        source = pq.ParquetFile(file)
                        there = [c for c in wanted if c in source.schema_arrow.names]
                        for part in source.iter_batches(batch_size=2048, columns=there):
                            n = part.num_rows
                            extra = [pa.array([shard.rpartition("/")[2]] * n, pa.string()), pa.array(range(at, at + n), pa.int64()), pa.array([tier] * n, pa.int32()), pa.array([version] * n, pa.int32())]
                            at += n
                            own = [part.column(part.schema.get_field_index(c)) if c in there else pa.nulls(n, arrow.field(c).type) for c in wanted]
                            yield pa.RecordBatch.from_arrays([*own, *extra], names=names)

        return dealt(listed, listed.count()).mapInArrow(read, out)


def op8_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Appends all documents, compacts until no tier is full, and reads every row of the last version back."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    store = Store(spark)
    store.append(docs)
    store.compact_fully()
    rows = store.read(docs.schema)
    return rows.select("doc_id", F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"), "lang", "source", "n_chars")


OP8_SQL = """
SELECT doc_id, sha256(coalesce(text, '')) AS text_sha256, lang, source, n_chars FROM documents
"""

QUERIES = {"op8_sharding": op8_sharding}
SQL = {"op8_sharding": OP8_SQL}
