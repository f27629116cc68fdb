"""Components that drew no anchor, and searches shared by many sources."""

import duckdb
import pytest
from pyspark.sql import functions as F

from pathmeet.operators import baselines, shared
from pathmeet.operators.graph import build_graph
from pathmeet.plans import extensions as catalog
from pathmeet.sources.tables import TABLES


@pytest.fixture(scope="module")
def with_islands(spark, sf, tmp_path_factory):
    """The given tables with 40 more customers that bought one part each, which nobody else bought."""
    out = str(tmp_path_factory.mktemp("islands"))
    db = duckdb.connect()
    for t in TABLES:
        more = ""
        if t == "orders":
            more = f" UNION ALL SELECT t.* REPLACE (o_orderkey + 10000000 + i AS o_orderkey, 10000000 + i AS o_custkey) FROM (SELECT * FROM '{sf}/orders.parquet' LIMIT 1) t, range(40) r(i)"
        if t == "lineitem":
            first = f"(SELECT o_orderkey FROM (SELECT * FROM '{sf}/orders.parquet' LIMIT 1))"
            more = f" UNION ALL SELECT t.* REPLACE ({first} + 10000000 + i AS l_orderkey, 10000000 + i AS l_partkey, 'R' AS l_returnflag) FROM (SELECT * FROM '{sf}/lineitem.parquet' LIMIT 1) t, range(40) r(i)"
        db.execute(f"COPY (SELECT * FROM '{sf}/{t}.parquet'{more}) TO '{out}/{t}.parquet' (FORMAT parquet)")
    return out


@pytest.mark.parametrize("name", ["anchors_literal", "anchors_calibrated", "anchors_uniform", "anchor_size_profile", "radii", "radius_profile", "repaired_radii", "weighted_radii"])
def test_components_without_an_anchor(spark, with_islands, name):
    db = duckdb.connect()
    for t in TABLES:
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{with_islands}/{t}.parquet'")
    cursor = db.execute(catalog.SQL[name])
    columns = [c[0] for c in cursor.description]
    expected = sorted(map(tuple, cursor.fetchall()))
    assert sorted(map(tuple, catalog.QUERIES[name](spark, with_islands).select(*columns).collect())) == expected


def _true_distances(pairs):
    near: dict = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    out = {}
    for s in near:
        level, seen, d = {s}, {s: 0}, 0
        while level:
            d += 1
            level = {x for v in level for x in near[v]} - seen.keys()
            seen |= dict.fromkeys(level, d)
        out |= {(s, v): d for v, d in seen.items()}
    return out


@pytest.fixture(scope="module")
def two_parts(spark):
    """A ring with chords of more nodes than a block has sources, and a line apart from it."""
    ring = [(i, (i + 1) % 1300) for i in range(1300)] + [(i, (i * k + 400) % 1300) for i in range(1300) for k in (7, 11, 19)]
    pairs = [p for p in ring if p[0] != p[1]] + [(2000 + i, 2001 + i) for i in range(5)]
    return build_graph(spark.createDataFrame(pairs, "src long, dst long")), _true_distances(pairs)


def test_counts_of_all_pairs(two_parts):
    g, truth = two_parts
    counts: dict = {}
    for d in truth.values():
        counts[d] = counts.get(d, 0) + 1
    assert dict(map(tuple, shared.distance_counts(g, blocks=1).collect())) == counts


def test_shared_two_sided_search(spark, two_parts):
    g, truth = two_parts
    asked = [(i * 1000 + j, s, t) for i, s in enumerate([*range(1300), 2000, 2005]) for j, t in enumerate([0, 3, 651, 2003, 2005, 99999]) if (i + j) % 3 == 0 or s > 1999]
    found = shared.bidirectional_distance(g, spark.createDataFrame(asked, "qid long, s long, t long")).collect()
    assert {r["qid"]: r["dist"] for r in found} == {q: truth.get((s, t)) for q, s, t in asked}
    assert len(found) == len(asked)


def test_shared_search_goes_on_from_seeds(spark, two_parts):
    g, truth = two_parts
    asked = [(s * 10_000 + t, s, t) for s in range(0, 300, 9) for t in range(600, 900, 7) if truth[s, t] > 4]
    depth = {u: u % 3 for _, s, t in asked for u in (s, t)}
    seeds = [(u, v, truth[u, v], r) for u, r in depth.items() for v in range(1300) if truth[u, v] <= r]
    found = shared.bidirectional_distance(g, spark.createDataFrame(asked, "qid long, s long, t long"), spark.createDataFrame(seeds, "u long, v long, d long, depth long"))
    assert {r["qid"]: r["dist"] for r in found.collect()} == {q: truth[s, t] for q, s, t in asked}
