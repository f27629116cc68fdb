"""Triangles by colours of nodes: no wedge is sent anywhere.

Nodes are dealt to ``p`` colours by a hash. A task holds the links between three colours (with repeats)
and finds the triangles of just these, so a link is needed by ``p`` tasks and a task holds some 6 m / p^2
links. Rounds take the triples by their least colour; each sends three times the links at most."""

from __future__ import annotations

import math
from collections.abc import Iterator
from contextlib import contextmanager
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathmeet.scratch import discard, staged

#: Links that a task is meant to hold, links sorted at once where they are packed, and wedges tested at once.
TASK_LINKS, PACK_LINKS, WEDGES = 4_000_000, 1_000_000, 1_000_000
_MIX = np.uint64(0x9E3779B97F4A7C15)


@contextmanager
def _cleaned(spark: SparkSession) -> Iterator[None]:
    """The shuffle files of a table written inside are deleted as soon as it is written."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, "false")
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def triangle_counts(edges: DataFrame, task_links: int = TASK_LINKS) -> DataFrame:
    """(id, triangles) of the nodes in triangles; ``edges`` (src, dst) may repeat links, in either direction, and hold loops and nulls."""
    a, b = F.least("src", "dst").cast("long"), F.greatest("src", "dst").cast("long")
    with _cleaned(edges.sparkSession):
        links = staged(edges.where("src is not null and dst is not null and src <> dst").select(a.alias("a"), b.alias("b")), "triangle-links")
        p = max(1, math.ceil(math.sqrt(6 * links.count() / task_links)))
        rounds = []
        for least in range(p):
            packs = links.mapInArrow(_packer(p, least), "triple long, pack binary")
            tasks = 3 * (p - least) * (p - least + 1) // 2  # a number that is given is kept, however few bytes the packs have
            found = packs.repartition(tasks, "triple").groupBy("triple").applyInArrow(_counter(p), "id long, triangles long")
            rounds.append(staged(found.groupBy("id").agg(F.sum("triangles").alias("triangles")), "triangle-round"))
        out = staged(reduce(DataFrame.unionByName, rounds).groupBy("id").agg(F.sum("triangles").alias("triangles")), "triangles")
    for done in (links, *rounds):
        discard(done)
    return out


def _colours(ids: np.ndarray, p: int) -> np.ndarray:
    return (((ids.astype(np.uint64) * _MIX) >> np.uint64(33)) % np.uint64(p)).astype(np.int64)


def _packed(a: np.ndarray, b: np.ndarray) -> bytes:
    """Links sorted by a: steps of a, then b, as planes of bytes, most of which are constant."""
    return np.concatenate([np.diff(a, prepend=0), b]).view(np.uint8).reshape(-1, 8).T.tobytes()


def _unpacked(pack: bytes) -> tuple[np.ndarray, np.ndarray]:
    both = np.ascontiguousarray(np.frombuffer(pack, np.uint8).reshape(8, -1).T).view(np.int64).ravel()
    half = len(both) // 2
    return np.cumsum(both[:half]), both[half:]


def _packer(p: int, least: int):
    """Links to packs by pair of colours, each sent to the triples of this round that need it."""

    def packs(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
        ca, cb = _colours(a, p), _colours(b, p)
        low, high = np.minimum(ca, cb), np.maximum(ca, cb)
        pair = low * p + high
        order = np.lexsort((b, a, pair))
        order = order[low[order] >= least]
        a, b, pair = a[order], b[order], pair[order]
        triples, held = [], []
        starts = np.flatnonzero(np.diff(pair, prepend=-1))
        for at, end in zip(starts, np.append(starts, len(pair))[1:], strict=True):
            i, j = divmod(int(pair[at]), p)
            pack = _packed(a[at:end], b[at:end])
            for k in range(least, p) if i == least else (least,):
                x, y, z = sorted((i, j, k))
                triples.append((x * p + y) * p + z)
                held.append(pack)
        return pa.RecordBatch.from_arrays([pa.array(triples, pa.int64()), pa.array(held, pa.binary())], ["triple", "pack"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting, rows = [], 0
        for batch in batches:
            waiting.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
            rows += batch.num_rows
            if rows >= PACK_LINKS:
                yield packs(*(np.concatenate(x) for x in zip(*waiting, strict=True)))
                waiting, rows = [], 0
        if rows:
            yield packs(*(np.concatenate(x) for x in zip(*waiting, strict=True)))

    return run


def _counter(p: int):
    def run(table: pa.Table) -> pa.Table:
        triple = table.column("triple")[0].as_py()
        colours = np.array([triple // (p * p), triple // p % p, triple % p])
        a, b = (np.concatenate(x) for x in zip(*(_unpacked(x.as_py()) for x in table.column("pack")), strict=True))
        ids, counts = counted(a, b, colours, p)
        return pa.table({"id": ids, "triangles": counts})

    return run


def counted(a: np.ndarray, b: np.ndarray, colours: np.ndarray, p: int) -> tuple[np.ndarray, np.ndarray]:
    """Nodes and their triangles whose three colours are ``colours`` (sorted). Links go from the lower to the higher (degree, id) here."""
    ids = np.unique(np.concatenate([np.unique(a), np.unique(b)]))
    n = len(ids)
    links = np.unique(np.searchsorted(ids, a) * n + np.searchsorted(ids, b))
    one, two = np.divmod(links, n)
    by_rank = np.argsort(np.bincount(one, minlength=n) + np.bincount(two, minlength=n), kind="stable")
    rank = np.empty(n, np.int64)
    rank[by_rank] = np.arange(n)
    one, two = rank[one], rank[two]
    links = np.sort(np.minimum(one, two) * n + np.maximum(one, two))
    del one, two, rank
    tail, head = (x.astype(np.int32) for x in np.divmod(links, n))
    colour = _colours(ids[by_rank], p).astype(np.int32)
    after = np.cumsum(np.bincount(tail, minlength=n))[tail] - np.arange(len(tail)) - 1  # wedges: a link with the later ones of its tail
    upto = np.concatenate([[0], np.cumsum(after)])
    bits = np.uint64(64 - max(10, min(25, int(len(links)).bit_length() + 3)))
    spots = np.zeros(1 << (64 - int(bits)), bool)  # most wedges are told open by their spot
    spots[(links.astype(np.uint64) * _MIX) >> bits] = True
    apart = len(set(colours.tolist())) == 3
    total, at = np.zeros(n, np.int64), 0
    while at < len(links):
        end = max(at + 1, int(np.searchsorted(upto, upto[at] + WEDGES, "right")) - 1)
        first = np.repeat(np.arange(at, end), after[at:end])
        second = np.arange(len(first)) - (upto[first] - upto[at]) + first + 1
        at = end
        if apart:
            other = colour[head[first]] != colour[head[second]]
            first, second = first[other], second[other]
        closing = head[first].astype(np.int64) * n + head[second]
        maybe = np.flatnonzero(spots[(closing.astype(np.uint64) * _MIX) >> bits])
        closing = closing[maybe]
        place = np.minimum(np.searchsorted(links, closing), len(links) - 1)
        maybe = maybe[links[place] == closing]
        corners = np.stack([tail[first[maybe]], head[first[maybe]], head[second[maybe]]])
        ours = (np.sort(colour[corners], axis=0) == colours[:, None]).all(0)
        total += np.bincount(corners[:, ours].ravel(), minlength=n)
    seen = np.flatnonzero(total)
    return ids[by_rank[seen]], total[seen]
