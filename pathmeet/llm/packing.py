"""Packing by concatenate and cut: documents end to end, cut into fixed windows.

Pass one turns each document into token ids once, with its offset inside its task's
partition, and writes them with the partition number. Prefix sums over the partition
totals give every document its global offset; pass two cuts at multiples of the window and
writes the windows: token ids and the list of pieces that they are made of. Windows inside
one task's rows are written whole; what a task holds of a window that goes on elsewhere is a
boundary record, and boundary records of one window are stitched. Rows per piece are read
off the windows.

Only the last window can be short, so padding is less than one window in all; it is
filled to the window size unless its length is a power of two.

Defined results: null and empty texts are the end token alone; repeated rows are packed
as often as they occur; ids may be null. Very long texts, and runs of white space of any
length, are encoded whole. The text of a special token counts as that token, which is how
``tokenizers`` reads it. Empty tables give no windows and no pieces. Other columns are not read.
"""

from __future__ import annotations

import sys
import types
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pathmeet.joins import bounded_join
from pathmeet.scratch import staged

#: Bytes of ids in one output batch.
BATCH_BYTES = 4 << 20
WINDOW = 2048


def _held_by_process() -> types.ModuleType:
    """A module of this process alone, so that a loaded vocabulary outlives a task."""
    return sys.modules.setdefault("_packing_tables", types.ModuleType("_packing_tables"))


#: Fixed value: the split pattern of byte-level BPE vocabularies of this kind.
SPLIT = r"""'(?:[sdmt]|ll|ve|re)| ?\p{L}++| ?\p{N}++| ?[^\s\p{L}\p{N}]++|\s++$|\s+(?!\S)|\s"""


def byte_alphabet() -> dict[str, int]:
    """The characters that stand for bytes in a byte-level vocabulary: printable ones for
    themselves, the others for U+0100 onwards in the order of the bytes."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    other = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(other)}


def fast_model(vocabulary: str):
    """An encoder of the tokenizers file whose merges run in ``tiktoken``, about five times as fast.

    The ids of ordinary text are those of ``tokenizers``: ranks are the ids in the file, which number tokens
    in the order of the merges; this is checked on the file. Texts with the strings of special tokens, and with runs of
    white space at which the split pattern would recurse too deeply, go to ``tokenizers`` (``encoder``)."""
    import json

    import tiktoken

    with open(vocabulary, encoding="utf-8") as file:
        held = json.load(file)
    letters, model = byte_alphabet(), held["model"]
    merged = [model["vocab"]["".join(x.split(" ") if isinstance(x, str) else x)] for x in model["merges"]]
    if held["pre_tokenizer"]["type"] != "ByteLevel" or held["pre_tokenizer"].get("add_prefix_space") or held["normalizer"] or merged != sorted(merged):
        raise ValueError("not a byte-level vocabulary numbered by its merges")
    special = {x["content"] for x in held["added_tokens"] if x.get("special")}
    ranks = {bytes(letters[c] for c in token): i for token, i in model["vocab"].items() if token not in special}
    return tiktoken.Encoding("byte-level", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={})


def raw_ids(ids: list[int]) -> bytes:
    held = array("I", ids)
    if sys.byteorder == "big":
        held.byteswap()
    return held.tobytes()


#: White space characters in a row from which on ``tokenizers`` encodes the text.
LONG_RUN = 4096


def encoder(vocabulary: str):
    """text -> little-endian unsigned 32-bit ids, as ``Tokenizer.encode(text, add_special_tokens=False)`` gives."""
    import re

    tables = _held_by_process().__dict__
    if vocabulary not in tables:
        from tokenizers import Tokenizer

        plain, exact = fast_model(vocabulary), Tokenizer.from_file(vocabulary)
        special = [t.content for t in exact.get_added_tokens_decoder().values()]
        run = re.compile(rf"\s{{{LONG_RUN}}}")

        def encode(text: str) -> bytes:
            if any(x in text for x in special) or run.search(text):
                return raw_ids(exact.encode(text, add_special_tokens=False).ids)
            return raw_ids(plain.encode_ordinary(text))

        tables[vocabulary] = encode
    return tables[vocabulary]


def tokenised(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text", end_id: int = 1) -> DataFrame:
    """Pass one: (id, part, start, n, ids), written once; ``start`` counts inside the part."""
    slim = docs.select(F.col(id_col), F.coalesce(F.col(text_col), F.lit("")))
    kind = docs.schema[id_col].dataType.simpleString()
    names = [id_col, "part", "start", "n", "ids"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, end = encoder(vocabulary), int(end_id).to_bytes(4, "little")
        part, at = TaskContext.get().partitionId(), 0

        def batch_of(ids, starts, held):
            n = [len(x) // 4 for x in held]
            return pa.RecordBatch.from_arrays([ids, pa.array([part] * len(held), pa.int32()), pa.array(starts, pa.int64()), pa.array(n, pa.int64()), pa.array(held, pa.binary())], names=names)

        for batch in batches:
            held, starts, size, begun = [], [], 0, 0
            for i in range(batch.num_rows):
                ids = encode(batch.column(1)[i].as_py()) + end
                held.append(ids)
                starts.append(at)
                at += len(ids) // 4
                size += len(ids)
                if size >= BATCH_BYTES or i + 1 == batch.num_rows:
                    yield batch_of(batch.column(0).slice(begun, len(held)), starts, held)
                    held, starts, size, begun = [], [], 0, i + 1

    return staged(slim.mapInArrow(run, f"{id_col} {kind}, part int, start long, n long, ids binary"), "packing-tokens")


def with_offsets(tokens: DataFrame) -> DataFrame:
    """Adds ``at``, the global offset: prefix sums over the totals of the parts."""
    totals = tokens.groupBy("part").agg(F.sum("n").alias("total"))
    ahead = F.sum("total").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    ahead = staged(totals.select("part", F.coalesce(ahead, F.lit(0)).cast("long").alias("ahead")), "packing-offsets")
    return bounded_join(tokens, ahead, "part").withColumn("at", F.col("start") + F.col("ahead"))


def windows(placed: DataFrame, id_col: str = "doc_id", window: int = WINDOW, pad_id: int = 0, most_open: int = 64) -> DataFrame:
    """The packed windows: (sequence_id, tokens, ids, docs, starts, lengths, totals, offsets).

    ``ids`` are little-endian unsigned 32-bit token ids, padded to the window size (a short window whose length is
    a power of two stays short); ``tokens`` counts those before padding. The lists describe the pieces: document,
    its ids before the piece, ids in the piece, ids of the whole document, place in the window."""
    total = placed.agg(F.coalesce(F.max(F.col("at") + F.col("n")), F.lit(0))).first()[0]
    last, rest = divmod(total, window)
    id_kind = placed.schema[id_col].dataType.simpleString()
    lists = ["docs", "starts", "lengths", "totals", "offsets"]
    names = ["sequence_id", "tokens", "ids", *lists]
    kind = f"sequence_id long, tokens long, ids binary, docs array<{id_kind}>, " + ", ".join(f"{x} array<bigint>" for x in lists[1:])

    def size_of(sequence: int) -> int:
        return rest if sequence == last else window

    def record(sequence: int, parts: list[tuple]) -> tuple:
        """(sequence, tokens, ids, lists) of pieces (offset, ids, doc, start, total), in order; padded if whole."""
        parts = sorted(parts, key=lambda p: p[0])
        ids = b"".join(p[1] for p in parts)
        n = len(ids) // 4
        if n == size_of(sequence) and n & (n - 1):
            ids += int(pad_id).to_bytes(4, "little") * (window - n)
        return sequence, n, ids, [p[2] for p in parts], [p[3] for p in parts], [len(p[1]) // 4 for p in parts], [p[4] for p in parts], [p[0] for p in parts]

    def batch_of(records: list[tuple], id_type: pa.DataType) -> pa.RecordBatch:
        types = [pa.int64(), pa.int64(), pa.binary(), pa.list_(id_type), *[pa.list_(pa.int64())] * 4]
        columns = list(zip(*records, strict=True)) or [()] * len(types)
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=names)

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_windows: dict[int, list] = {}
        held: dict[int, int] = {}
        out: list[tuple] = []
        for batch in batches:
            id_type = batch.column(0).type
            for doc, at, n, ids in zip(*(batch.column(c).to_pylist() for c in range(4)), strict=True):
                done, view = 0, memoryview(ids)
                while done < n:
                    sequence, offset = divmod(at + done, window)
                    take = min(n - done, window - offset)
                    open_windows.setdefault(sequence, []).append((offset, bytes(view[4 * done : 4 * (done + take)]), doc, done, n))
                    held[sequence] = held.get(sequence, 0) + take
                    if held[sequence] == size_of(sequence):
                        out.append(record(sequence, open_windows.pop(sequence)))
                        held.pop(sequence)
                    done += take
                    if len(out) >= 512:
                        yield batch_of(out, id_type)
                        out = []
                while len(open_windows) > most_open:
                    sequence = min(open_windows)
                    out.append(record(sequence, open_windows.pop(sequence)))
                    held.pop(sequence)
            yield batch_of(out, id_type)
            out = []
        if open_windows:
            yield batch_of([record(s, parts) for s, parts in open_windows.items()], id_type)

    def stitch(table: pa.Table) -> pa.Table:
        sequence, parts = table.column("sequence_id")[0].as_py(), []
        for ids, *pieces in zip(*(table.column(c).to_pylist() for c in ("ids", *lists)), strict=True):
            at = 0
            for doc, start, length, whole, offset in zip(*pieces, strict=True):
                parts.append((offset, ids[4 * at : 4 * (at + length)], doc, start, whole))
                at += length
        return pa.Table.from_batches([batch_of([record(sequence, parts)], table.schema.field("docs").type.value_type)])

    found = staged(placed.select(id_col, "at", "n", "ids").mapInArrow(gather, kind), "packing-windows")
    whole = (F.col("tokens") == window) | ((F.col("sequence_id") == last) & (F.col("tokens") == rest))
    return found.where(whole).unionByName(found.where(~whole).groupBy("sequence_id").applyInArrow(stitch, kind))


def pieces(packed: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """One row per piece of a document, read off the windows; the checksum is that of the window's own ids."""
    listed = F.expr(
        "transform(arrays_zip(docs, starts, lengths, totals, offsets), p -> named_struct('d', p.docs, 'start', p.starts, 'length', p.lengths, "
        "'ids_crc32', crc32(substring(ids, cast(4 * p.offsets + 1 as int), cast(4 * p.lengths as int))), 'doc_tokens', p.totals, 'sequence_id', sequence_id, 'offset', p.offsets))"
    )
    one = packed.select(F.explode(listed).alias("p"))
    return one.select(F.col("p.d").alias(id_col), *(f"p.{x}" for x in ("start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")))


def sequences(packed: DataFrame) -> DataFrame:
    """(sequence_id, tokens, ids): the windows with their ids as lists, as a trainer reads them."""

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = [np.frombuffer(x, "<u4").astype(np.int64) for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(values, pa.list_(pa.int64()))], names=["sequence_id", "tokens", "ids"])

    return packed.select("sequence_id", "tokens", "ids").mapInArrow(listed, "sequence_id long, tokens long, ids array<bigint>")


def packed_windows(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, end_id: int = 1) -> DataFrame:
    return windows(with_offsets(tokenised(docs, vocabulary, id_col, text_col, end_id)), id_col, window)


def packed_pieces(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, end_id: int = 1) -> DataFrame:
    return pieces(packed_windows(docs, vocabulary, id_col, text_col, window, end_id), id_col)


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed_pieces(spark.read.parquet(f"{sf_dir}/documents.parquet"), default_vocabulary())


QUERIES = {"op7_packing": op7_packing}
SQL: dict[str, str] = {}
