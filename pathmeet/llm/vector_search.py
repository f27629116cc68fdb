"""Exact top-k by integer inner product with multi-resolution segment statistics.

A vector is cut into segments; with segment means m and deviations s, and w components in
a segment, the inner product of two vectors is at most the sum of w * (m m' + s s').
Levels go from few wide to many narrow segments; a pair is dropped as soon as its bound is
below the query's k-th score so far, and scores of what is left are computed exactly. Coarse
bounds say little about vectors without structure, so the levels go on to segments of one
or two components, where few pairs are left. The first k-th scores come from a bounded
sample of candidates, which only sets a starting bound: every candidate is bounded or scored.

Queries are rows: executors draw their starting bounds and write them in blocks of bounded
size to the shared folder. A task gathers candidates up to a bounded size and reads one block after
the other, so neither the driver nor a task ever holds all queries or all candidates. Bounds are
computed for tiles of pairs and rows are gathered for slices of them, so what a task holds besides
does not depend on how many pairs the bounds leave.

Defined results: vectors that are null or hold null or non-finite components take no part,
nor do rows with a null id; any finite component does, however large, and scores are exact
integers (those beyond a long are ranked exactly and stated as its ends). Vectors of
different lengths are not compared; rows with the query's id are its own; a query id with
several vectors counts once, with the least vector. Ties go to the smaller id. Repeated
candidates stay repeated. Fewer than k candidates give fewer rows; an empty table gives
none. Other columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pathmeet.scratch import new_path, staged

#: Segments of each level, coarse to fine.
LEVELS = (8, 16, 32, 48)
#: Share of the pairs below which they are followed one by one.
SPARSE = 0.3
#: Whole numbers below this are exact as doubles.
EXACT = 2.0**53
#: Pairs that are bounded at once.
TILE = 1 << 18
#: Components that are gathered at once, of either side of the pairs.
VALUES = 1 << 20
#: Bytes of candidates that a task holds.
HELD = 1 << 26


def usable(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(vec_id, x) of the vectors that take part; ``x`` as doubles."""
    finite = F.forall(vector_col, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < F.lit(float("inf"))))
    rows = vectors.where(F.col(id_col).isNotNull() & F.col(vector_col).isNotNull()).where(finite)
    return rows.select(F.col(id_col).cast("long").alias("vec_id"), F.transform(vector_col, lambda x: x.cast("double")).alias("x"))


def whole(x: np.ndarray, scale: int) -> np.ndarray:
    """floor(scale * x): doubles where all of it is exact in them, Python integers elsewhere."""
    with np.errstate(over="ignore"):
        v = np.floor(scale * x)
    if not v.size or np.abs(v).max() < EXACT:
        return v
    wide = [[math.floor(scale * c) if abs(c) < EXACT else int(c) * scale for c in row] for row in x.tolist()]
    return np.array(wide, dtype=object).reshape(x.shape)


def statistics(v: np.ndarray, segments: int) -> np.ndarray:
    """Means and deviations of the segments, weighted so that a dot product is the bound."""
    if not v.shape[1]:
        return np.zeros((len(v), 1))
    parts = np.array_split(np.arange(v.shape[1]), min(segments, v.shape[1]))
    return np.stack([np.sqrt(len(p)) * f(v[:, p], axis=1) for p in parts for f in (np.mean, np.std)], axis=1)


def dots(a: np.ndarray, i: np.ndarray, b: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Inner products of the rows a[i] and b[j], gathered in slices of bounded size."""
    out = np.empty(len(i))
    step = max(1, VALUES // max(1, a.shape[1]))
    for at in range(0, len(i), step):
        some = slice(at, at + step)
        np.einsum("ij,ij->i", a[i[some]], b[j[some]], out=out[some])
    return out


def narrow(v: np.ndarray) -> np.ndarray:
    """The same whole numbers in the smallest type that holds them."""
    most = np.abs(v).max(initial=0) if v.dtype != object else EXACT
    return v.astype(np.int16) if most < 1 << 15 else v.astype(np.int32) if most < 1 << 31 else v


def best(query: np.ndarray, ids: np.ndarray, score: np.ndarray, k: int) -> np.ndarray:
    """Indexes of the k best of each query: higher score first, then smaller id."""
    if score.dtype == object:
        order = np.array(sorted(range(len(query)), key=lambda i: (query[i], -score[i], ids[i])), np.int64)
    else:
        order = np.lexsort((ids, -score, query))
    place = np.arange(len(order))
    first = np.flatnonzero(np.diff(query[order], prepend=-1))
    rank = place - np.repeat(first, np.diff(np.append(first, len(order))))
    return order[rank < k]


class Search:
    """Running top-k of one block of queries over batches of candidates.

    ``shares`` counts the pairs that came to each level and to the exact scores."""

    def __init__(self, ids: np.ndarray, queries: np.ndarray, k: int, floor: np.ndarray | None = None):
        self.ids, self.q, self.k = ids, queries, k
        self.floor = np.full(len(ids), -np.inf) if floor is None else floor.copy()
        self.wide = queries.dtype == object
        self.stats = [] if self.wide else [statistics(queries, s) for s in LEVELS]
        self.weight = np.zeros(len(ids)) if self.wide else np.abs(queries).sum(axis=1)
        self.most = 0.0 if self.wide else float(np.abs(queries).max(initial=1))
        self.found: tuple = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, object if self.wide else np.int64))
        self.shares = np.zeros(len(LEVELS) + 1, np.int64)

    def add(self, ids: np.ndarray, v: np.ndarray) -> None:
        if not len(ids) or not len(self.ids):
            return
        if self.wide or v.dtype == object or self.most * float(np.abs(v).max(initial=1)) * max(1, v.shape[1]) >= EXACT:
            return self._add_wide(ids, v)
        most = float(np.abs(v).max(initial=1))
        theirs = [statistics(v, segments) for segments in LEVELS]
        step = max(1, TILE // len(ids))
        for at in range(0, len(self.ids), step):
            self._add_tile(slice(at, at + step), ids, v, theirs, most)

    def _add_tile(self, rows: slice, ids: np.ndarray, v: np.ndarray, theirs: list[np.ndarray], most: float) -> None:
        floor = self.floor[rows]
        limit = floor - 1e-9 * (1 + self.weight[rows]) * (1 + most)
        keep = np.ones((len(floor), len(ids)), bool)
        pairs = None
        for level, (own, other) in enumerate(zip(self.stats, theirs, strict=True)):
            if pairs is None:
                self.shares[level] += keep.sum()
                keep &= own[rows] @ other.T >= limit[:, None]
                if keep.mean() <= SPARSE:
                    pairs = np.nonzero(keep)
            else:
                i, j = pairs
                self.shares[level] += len(i)
                near = dots(own[rows], i, other, j) >= limit[i]
                pairs = i[near], j[near]
        # scores: whole numbers below 2^53 are exact
        if pairs is None:
            self.shares[-1] += keep.sum()
            dense = self.q[rows] @ v.T
            i, j = np.nonzero(keep & (dense >= floor[:, None]))
            score = dense[i, j]
        else:
            i, j = pairs
            self.shares[-1] += len(i)
            score = dots(self.q[rows], i, v, j)
            near = score >= floor[i]
            i, j, score = i[near], j[near], score[near]
        self._take(i + rows.start, ids, j, score.astype(np.int64))

    def _add_wide(self, ids: np.ndarray, v: np.ndarray) -> None:
        as_integers = lambda m: m if m.dtype == object else np.array([[int(c) for c in row] for row in m.tolist()], dtype=object).reshape(m.shape)
        q, c = as_integers(self.q), as_integers(v)
        for i in range(len(q)):
            score = np.array([sum(a * b for a, b in zip(q[i], row, strict=True)) for row in c], dtype=object)
            least = float(self.floor[i])  # Python compares large integers with floats exactly
            near = np.flatnonzero([s >= least for s in score.tolist()])
            self._take(np.full(len(near), i), ids, near, score[near])

    def _take(self, i: np.ndarray, ids: np.ndarray, j: np.ndarray, score: np.ndarray) -> None:
        other = self.ids[i] != ids[j]
        held = self.found[2]
        if score.dtype == object and held.dtype != object:
            held = held.astype(object)
        self.found = (np.concatenate([self.found[0], i[other]]), np.concatenate([self.found[1], ids[j][other]]), np.concatenate([held, score[other]]))
        if len(self.found[0]) > 8 * self.k * len(self.ids):
            self.reduce()

    def reduce(self) -> None:
        top = best(*self.found, self.k)
        self.found = tuple(x[top] for x in self.found)
        query, _, score = self.found
        full = np.bincount(query, minlength=len(self.ids)) >= self.k
        least: dict[int, int] = {}
        for i, s in zip(query.tolist(), score.tolist(), strict=True):
            least[i] = min(s, least.get(i, s))
        for i in np.flatnonzero(full).tolist():
            exact = least[i]
            self.floor[i] = max(self.floor[i], exact if abs(exact) < EXACT else np.nextafter(_as_double(exact), -np.inf))


def _as_double(value: int) -> float:
    try:
        return float(value)
    except OverflowError:
        return float(np.finfo(float).max) if value > 0 else -math.inf


#: Ends of a long.
LEAST, MOST = -(1 << 63), (1 << 63) - 1


def beyond(score: int) -> bytes | None:
    """A binary that sorts like the scores that a long cannot hold; null for the others."""
    if LEAST < score < MOST:
        return None
    raw = abs(score).to_bytes((abs(score).bit_length() + 7) // 8, "big")
    raw = len(raw).to_bytes(2, "big") + raw
    return b"\x01" + raw if score > 0 else b"\x00" + bytes(255 - b for b in raw)


def _rows(search: Search, kind: pa.Schema) -> pa.RecordBatch:
    search.reduce()
    query, vec, score = search.found
    if score.dtype != object:
        columns = [pa.array(search.ids[query], pa.int64()), pa.array(vec, pa.int64()), pa.array(score, pa.int64()), pa.nulls(len(vec), pa.binary())]
    else:
        exact = [int(s) for s in score.tolist()]
        columns = [pa.array(search.ids[query], pa.int64()), pa.array(vec, pa.int64()), pa.array([min(MOST, max(LEAST, s)) for s in exact], pa.int64()), pa.array([beyond(s) for s in exact], pa.binary())]
    return pa.RecordBatch.from_arrays(columns, schema=kind)


def _matrices(batch: pa.RecordBatch, scale: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, whole numbers) of the rows of a batch, by length of vector and apart where doubles are not exact."""
    ids = batch.column(0).to_numpy(zero_copy_only=False)
    lists = batch.column(1)
    values = lists.flatten().to_numpy(zero_copy_only=False)
    lengths = np.diff(lists.offsets.to_numpy())
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    for width in np.unique(lengths).tolist():
        rows = np.flatnonzero(lengths == width)
        x = values[(starts[rows][:, None] + np.arange(width)).ravel()].reshape(len(rows), width) if width else np.zeros((len(rows), 0))
        large = (np.abs(x) >= 2.0**23 / scale).any(axis=1) if width else np.zeros(len(rows), bool)
        for some in (~large, large):
            if some.any():
                yield ids[rows[some]], whole(x[some], scale)


def gathered(batches: Iterator[pa.RecordBatch], scale: int, held_rows: int, held_bytes: int = HELD) -> Iterator[list[tuple[np.ndarray, np.ndarray]]]:
    """Lists of (ids, whole numbers), each ended by the slice that brings it to ``held_rows`` rows or ``held_bytes``."""
    waiting: list[tuple[np.ndarray, np.ndarray]] = []
    count = size = 0
    for some in batches:
        step = max(1, VALUES * some.num_rows // max(1, len(some.column(1).flatten())))
        for at in range(0, some.num_rows, step):
            for ids, v in _matrices(some.slice(at, step), scale):
                v = narrow(v)
                waiting.append((ids, v))
                count += len(ids)
                size += v.nbytes if v.dtype != object else 48 * v.size
            if count >= held_rows or size >= held_bytes:
                yield waiting
                waiting, count, size = [], 0, 0
    if waiting:
        yield waiting


def top_k(
    spark: SparkSession, vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", k: int = 5, every: int = 50,
    scale: int = 256, block: int = 4096, sample: int = 2048, batch: int = 2048, held_rows: int = 1 << 18,
) -> DataFrame:
    """(query_id, rank, vec_id, score) of the rows whose id is divisible by ``every``.

    ``block`` bounds the queries that are read at once, ``held_rows`` the candidates that a task holds
    (``HELD`` their bytes), ``sample`` the candidates of the starting bound."""
    held = staged(usable(vectors, id_col, vector_col), "vectors")
    seeds = held.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).toArrow()
    seed_parts = [part for b in seeds.combine_chunks().to_batches() for part in _matrices(b, scale)]

    mine = held.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min("x").alias("x"))
    folder = new_path(spark, "query-blocks")
    listed = "file string, width int, queries int"

    def bound(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Writes blocks of queries with their starting bounds."""
        import uuid

        fs, root = opened(folder)
        fs.create_dir(root, recursive=True)
        names, widths, counts = [], [], []
        for some in batches:
            for at in range(0, some.num_rows, block):
                part = some.slice(at, block)
                for width, rows in _by_width(part):
                    floors = np.full(rows.num_rows, -np.inf)
                    place = {i: n for n, i in enumerate(rows.column(0).to_pylist())}
                    for ids, q in _matrices(rows, scale):
                        start = Search(ids, q, k)
                        for seed_ids, seed in seed_parts:
                            if seed.shape[1] == width:
                                start.add(seed_ids, seed)
                        start.reduce()
                        floors[[place[i] for i in ids.tolist()]] = start.floor
                    name = f"{uuid.uuid4().hex}.parquet"
                    with fs.open_output_stream(f"{root}/{name}", compression=None) as sink:
                        pq.write_table(pa.Table.from_batches([rows]).append_column("floor", pa.array(floors, pa.float64())), sink)
                    names.append(name)
                    widths.append(width)
                    counts.append(rows.num_rows)
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(widths, pa.int32()), pa.array(counts, pa.int32())], names=["file", "width", "queries"])

    blocks = staged(mine.mapInArrow(bound, listed), "query-list")
    names_at = blocks._jdf.inputFiles()  # the names of the list's own files; its rows are read by executors
    lists = [str(x) for x in names_at]
    kind = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64()), ("beyond", pa.binary())])

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = opened(folder)

        def blocks_of() -> Iterator[tuple[int, str]]:
            for one in lists:
                list_fs, path = opened(one)
                with list_fs.open_input_file(path) as file:
                    table = pq.read_table(file)
                yield from zip(table.column("width").to_pylist(), table.column("file").to_pylist(), strict=True)

        def against(candidates: list[tuple[np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
            widths = {v.shape[1] for _, v in candidates}
            for width, name in blocks_of():
                if width not in widths:
                    continue
                with fs.open_input_file(f"{root}/{name}") as file:
                    table = pq.read_table(file).combine_chunks()
                rows = table.to_batches()[0]
                floors = dict(zip(rows.column(0).to_pylist(), rows.column(2).to_pylist(), strict=True))
                for ids, q in _matrices(rows, scale):
                    running = Search(ids, q, k, np.array([floors[i] for i in ids.tolist()]))
                    for own, v in candidates:
                        if v.shape[1] == width:
                            step = max(1, min(batch, VALUES // max(1, width)))
                            for at in range(0, len(own), step):
                                some = v[at : at + step]
                                running.add(own[at : at + step], some if some.dtype == object else some.astype(np.float64))
                    yield _rows(running, kind)

        for candidates in gathered(batches, scale, held_rows):
            yield from against(candidates)

    found = held.mapInArrow(search, "query_id long, vec_id long, score long, beyond binary")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.col("score").desc(), F.col("beyond").desc(), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int"), "vec_id", "score")


def opened(uri: str):
    """File system and path of a URI; local paths too."""
    return pafs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (pafs.LocalFileSystem(), uri)


def _by_width(rows: pa.RecordBatch) -> Iterator[tuple[int, pa.RecordBatch]]:
    lengths = np.diff(rows.column(1).offsets.to_numpy())
    for width in np.unique(lengths).tolist():
        own = np.flatnonzero(lengths == width)
        step = max(1, VALUES // max(1, width))
        for at in range(0, len(own), step):
            yield width, rows.take(pa.array(own[at : at + step]))


def op10_vector_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(spark, spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


OP10_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::DOUBLE) AS v
  FROM embeddings
  WHERE embedding IS NOT NULL AND list_bool_and(list_transform(embedding, lambda x: x IS NOT NULL AND isfinite(x)))),
s AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.v, c.v)::BIGINT AS score
  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""

QUERIES = {"op10_vector_search": op10_vector_search}
SQL = {"op10_vector_search": OP10_SQL}
