"""Entries for the operators around the engine: subgraphs, joins, windows, sets, arrays, streams."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pathmeet.functions.kernels import meet_packed, register_table_functions
from pathmeet.operators import graph, vicinity
from pathmeet.operators.triangles import triangle_counts
from pathmeet.plans import workloads as w
from pathmeet.plans.catalog import MAIN, QUERIES, SQL, entry
from pathmeet.plans.oracle import oracle
from pathmeet.sources import tables
from pathmeet.streaming import requests as rq


@entry(oracle("g_trade_all").query("SELECT src, dst FROM arcs WHERE src % 16 IN (0, 1, 4) AND dst % 16 IN (0, 1, 4)"))
def ops_induced_subgraph(spark, sf_dir):
    g = w.graph_of(spark, sf_dir, "g_trade_all")
    return graph.induced(g, g.nodes.where((F.col("id") % 16).isin(0, 1, 4)).select("id")).arcs.select("src", "dst")


@entry(oracle(MAIN, "sample").add("near", "SELECT id AS u, id AS v, 0 AS d FROM sample UNION SELECT u, dst, d + 1 FROM near JOIN arcs ON src = v WHERE d < 2").query("SELECT u, v, min(d) AS d FROM near GROUP BY 1, 2"))
def ops_within_hops(spark, sf_dir):
    return graph.within_hops(w.graph_of(spark, sf_dir, MAIN), w.sample_of(spark, sf_dir, MAIN), 2)


@entry(oracle(MAIN, "pairs").query("SELECT p.s, p.t, count(*) AS common FROM pairs p JOIN arcs a ON a.src = p.s JOIN arcs b ON b.src = p.t AND b.dst = a.dst GROUP BY 1, 2"))
def ops_common_neighbours(spark, sf_dir):
    return graph.common_neighbours(w.graph_of(spark, sf_dir, MAIN), w.sample_pairs(w.sample_of(spark, sf_dir, MAIN)))


@entry(oracle("g_copurchase").query("SELECT x.src AS id, count(*) // 2 AS triangles FROM arcs x JOIN arcs y ON x.dst = y.src JOIN arcs z ON z.src = y.dst AND z.dst = x.src GROUP BY 1"))
def ops_triangles(spark, sf_dir):
    return triangle_counts(tables.edges(spark, sf_dir, "g_copurchase"))


def _core_sql(k: int, rounds: int = 16) -> str:
    """Peels often enough for the tested scales; each round keeps the nodes with ``k`` neighbours among those left."""
    o = oracle(MAIN).add("core0", f"SELECT id FROM nodes WHERE deg >= {k}")
    for i in range(rounds):
        o.add(f"core{i + 1}", f"SELECT src AS id FROM arcs WHERE src IN (SELECT id FROM core{i}) AND dst IN (SELECT id FROM core{i}) GROUP BY src HAVING count(*) >= {k}")
    return o.query(f"SELECT id FROM core{rounds}")


@entry(_core_sql(7))
def ops_k_core(spark, sf_dir):
    return graph.k_core(w.graph_of(spark, sf_dir, MAIN), 7)


@entry(oracle(MAIN).query("SELECT id, deg, CASE WHEN row_number() OVER (ORDER BY deg DESC, id) <= 10 THEN row_number() OVER (ORDER BY deg DESC, id) END AS place FROM nodes ORDER BY deg DESC, id LIMIT 10"))
def ops_top_hubs(spark, sf_dir):
    top = w.graph_of(spark, sf_dir, MAIN).nodes.orderBy(F.desc("deg"), "id").limit(10)
    return top.withColumn("place", F.row_number().over(Window.orderBy(F.desc("deg"), "id")).cast("long"))


@entry(oracle(MAIN, "vicinity").query("SELECT u, v, d FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY d, v) AS k FROM vicinity WHERE d > 0 AND v % 16 = 0) WHERE k <= 3"))
def ops_nearest_customers(spark, sf_dir):
    """The three customers nearest to each sample node, among its vicinity."""
    rows = w.index_of(spark, sf_dir, MAIN).vicinity.where("d > 0 and v % 16 = 0")
    return rows.withColumn("k", F.row_number().over(Window.partitionBy("u").orderBy("d", "v"))).where("k <= 3").select("u", "v", "d")


@entry(oracle(MAIN, "cases").query("SELECT s, t FROM cases WHERE d <= rs + rt AND rs > 0 AND rt > 0 AND s < t"))
def ops_meet_by_bound(spark, sf_dir):
    """Pairs that meet by the inequality on radii: a theta condition over joined facts."""
    truth = w.pair_truth_of(spark, sf_dir, MAIN)
    r = w.drawn_radii(spark, sf_dir, MAIN).where("r > 0").select("u", "r")
    pairs = w.sample_pairs(w.sample_of(spark, sf_dir, MAIN)).join(r.toDF("s", "rs"), "s").join(r.toDF("t", "rt"), "t")
    return pairs.join(truth.toDF("s", "t", "d"), ["s", "t"]).where("d <= rs + rt").select("s", "t")


@entry(oracle(MAIN, "vicinity", "pairs").query("SELECT DISTINCT p.s, p.t FROM pairs p JOIN vicinity a ON a.u = p.s JOIN vicinity b ON b.u = p.t AND b.v = a.v"))
def ops_intersecting_sets(spark, sf_dir):
    """The definition itself: pairs whose member sets intersect, by arrays."""
    sets = w.staged(w.index_of(spark, sf_dir, MAIN).vicinity.groupBy("u").agg(F.sort_array(F.collect_set("v")).alias("members")), "sets")
    pairs = w.sample_pairs(w.sample_of(spark, sf_dir, MAIN)).join(sets.toDF("s", "a"), "s").join(sets.toDF("t", "b"), "t")
    return pairs.where(F.arrays_overlap("a", "b")).select("s", "t")


@entry(oracle(MAIN, "cases", "boundary").query("SELECT p.s, p.t, min(x.d + y.d) AS dist FROM cases p JOIN boundary x ON x.u = p.s JOIN vicinity y ON y.u = p.t AND y.v = x.v WHERE case_ = 'meet' GROUP BY 1, 2"))
def ops_meet_packed(spark, sf_dir):
    """The serving form: packed sorted arrays met in an Arrow function."""
    ix = w.index_of(spark, sf_dir, MAIN)
    packed = w.staged(vicinity.pack(ix.vicinity, ix.boundary, ix.radius, "distance"), "packed")
    met = w.answers_of(spark, sf_dir, MAIN, probe="boundary").where("case = 'meet'").select("s", "t")
    rows = met.join(packed.select(F.col("u").alias("s"), F.col("boundary").alias("own")), "s").join(packed.select(F.col("u").alias("t"), F.col("members").alias("other")), "t")
    return rows.withColumn("m", meet_packed("own", "other")).select("s", "t", "m.dist")


@entry(oracle(MAIN, "vicinity").query("SELECT u, count(*) AS size, list_sort(list(v))[1] AS least, max(d) AS depth FROM vicinity GROUP BY u"))
def ops_packed_rows(spark, sf_dir):
    ix = w.index_of(spark, sf_dir, MAIN)
    packed = vicinity.pack(ix.vicinity, ix.boundary, ix.radius)
    return packed.select("u", F.col("size").cast("long"), F.element_at("members", 1)["v"].alias("least"), F.array_max(F.transform("members", lambda m: m["d"])).alias("depth"))


@entry("""SELECT p.event_id AS purchase, max_by(c.event_id, (c.ts, c.event_id)) AS click FROM events p JOIN events c
 ON c.user_id = p.user_id AND c.event_type = 'click' AND c.ts <= p.ts WHERE p.event_type = 'purchase' GROUP BY 1""")
def ops_as_of_join(spark, sf_dir):
    """The latest click of a user before each purchase, by one sort per user: union, then last value."""
    events = tables.load(spark, sf_dir, "events")["events"]
    rows = events.where("event_type in ('click', 'purchase')").withColumn("bought", F.col("event_type") == "purchase")
    before = Window.partitionBy("user_id").orderBy("ts", "bought", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    both = rows.withColumn("last", F.last(F.when(~F.col("bought"), F.col("event_id")), True).over(before))
    return both.where("bought and last is not null").select(F.col("event_id").alias("purchase"), F.col("last").alias("click"))


@entry("SELECT a.event_id AS request, count(*) AS near FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 600 MINUTE GROUP BY 1")
def ops_interval_join(spark, sf_dir):
    """Events of the same user within ten hours after an event, by hour buckets: an equality join that reads two buckets a side."""
    e = tables.load(spark, sf_dir, "events")["events"].select("user_id", "event_id", F.col("ts").cast("timestamp").alias("ts"))
    span = 600 * 60
    cell = F.floor(F.unix_micros("ts") / (span * 1_000_000))
    one = e.select("user_id", F.col("event_id").alias("request"), F.col("ts").alias("at"), F.explode(F.array(cell, cell + 1)).alias("cell"))
    two = e.select("user_id", "ts", cell.alias("cell"))
    found = one.join(two, ["user_id", "cell"]).where((F.col("ts") > F.col("at")) & (F.unix_micros("ts") <= F.unix_micros("at") + span * 1_000_000))
    return found.groupBy("request").agg(F.count("*").alias("near"))


@entry("""SELECT event_type, count(*) AS n, sum((props->>'k')::BIGINT) AS k FROM events GROUP BY 1""")
def ops_json_props(spark, sf_dir):
    e = tables.load(spark, sf_dir, "events")["events"]
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k"))


@entry(r"SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, count(*) AS pages FROM pages GROUP BY 1")
def ops_page_hosts(spark, sf_dir):
    return tables.load(spark, sf_dir, "pages")["pages"].groupBy(F.expr("parse_url(url, 'HOST')").alias("host")).agg(F.count("*").alias("pages"))


@entry("SELECT c_mktsegment, o_orderstatus, count(*) AS orders, grouping(c_mktsegment) + grouping(o_orderstatus) AS level FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY CUBE (c_mktsegment, o_orderstatus)")
def ops_cube(spark, sf_dir):
    t = tables.load(spark, sf_dir, "orders", "customer")
    joined = t["orders"].join(t["customer"], F.col("o_custkey") == F.col("c_custkey"))
    return joined.cube("c_mktsegment", "o_orderstatus").agg(F.count("*").alias("orders"), (F.grouping("c_mktsegment") + F.grouping("o_orderstatus")).cast("long").alias("level"))


@entry(oracle(MAIN, "cases").query("SELECT s, count(*) FILTER (case_ = 'meet') AS meet, count(*) FILTER (case_ = 'unanswered') AS unanswered FROM cases GROUP BY s"))
def ops_pivot_cases(spark, sf_dir):
    by = w.answers_of(spark, sf_dir, MAIN, probe="boundary").groupBy("s").pivot("case", ["meet", "unanswered"]).agg(F.count(F.lit(1)))
    return by.fillna(0)


@entry("SELECT conv_id, turn, length(text) - lag(length(text), 1, 0) OVER (PARTITION BY conv_id ORDER BY turn) AS grown FROM conversations")
def ops_lag(spark, sf_dir):
    c = tables.load(spark, sf_dir, "conversations")["conversations"]
    before = F.lag(F.length("text"), 1, 0).over(Window.partitionBy("conv_id").orderBy("turn"))
    return c.select("conv_id", "turn", (F.length("text") - before).cast("long").alias("grown"))


@entry(oracle("g_turn_chain").query("SELECT src, count(*) AS hops FROM (WITH RECURSIVE f AS (SELECT src, dst, 1 AS d FROM arcs WHERE src < dst UNION SELECT f.src, a.dst, d + 1 FROM f JOIN arcs a ON a.src = f.dst AND a.dst > a.src WHERE d < 8) SELECT * FROM f) GROUP BY src"))
def ops_recursive_sql(spark, sf_dir):
    """Forward hops of conversation turns by a recursive SQL query with a depth bound."""
    arcs = w.graph_of(spark, sf_dir, "g_turn_chain").arcs
    return spark.sql(
        """WITH RECURSIVE f(src, dst, d) AS (SELECT src, dst, 1 FROM {arcs} WHERE src < dst
           UNION ALL SELECT f.src, a.dst, d + 1 FROM f JOIN {arcs} a ON a.src = f.dst AND a.dst > a.src WHERE d < 8)
           SELECT src, count(DISTINCT dst) AS hops FROM f GROUP BY src""",
        arcs=arcs,
    )


@entry()
def ops_path_table_function(spark, sf_dir):
    register_table_functions(spark)
    found = QUERIES["path_steps"](spark, sf_dir).groupBy("qid").agg(F.sort_array(F.collect_list(F.struct("pos", "node"))).alias("p")).select("qid", F.transform("p", lambda x: x["node"]).alias("path"))
    return spark.sql("SELECT qid, f.pos, f.node FROM {p}, LATERAL path_nodes(path) f", p=found)


@entry("SELECT date_trunc('day', ts) AS start, event_type, count(*) AS requests, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    out = rq.run_once(spark, rq.windowed_counts(rq.event_stream(spark, sf_dir), "1 day"))
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@entry("""SELECT time_bucket(INTERVAL 6 HOUR, ts) - to_hours((6 * k)::BIGINT) AS start, event_type, count(*) AS requests, round(sum(value), 4) AS total
 FROM events, (SELECT unnest(range(4)) AS k) GROUP BY 1, 2""")
def stream_sliding(spark, sf_dir):
    out = rq.run_once(spark, rq.windowed_counts(rq.event_stream(spark, sf_dir), "1 day", "6 hours"))
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@entry("""SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS stop, count(*) AS requests FROM (
  SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS session FROM (
    SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, session""")
def stream_sessions(spark, sf_dir):
    out = rq.run_once(spark, rq.session_counts(rq.event_stream(spark, sf_dir)))
    return out.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "stop")})


@entry("SELECT id, count(*) AS arrivals FROM (SELECT user_id * 16 + 6 AS id FROM events UNION ALL SELECT (user_id // 2) * 16 + 6 FROM events) GROUP BY 1")
def stream_degrees(spark, sf_dir):
    asked = rq.requests(rq.event_stream(spark, sf_dir))
    return rq.run_once(spark, rq.degree_stream(asked.select(F.col("s").alias("src"), F.col("t").alias("dst"))))


@entry(oracle("g_user_flow").add("asked", "SELECT event_id AS qid, user_id * 16 + 6 AS s, (user_id // 2) * 16 + 6 AS t FROM events").add(
    "walk", "SELECT id AS s, id AS v, 0 AS d FROM nodes UNION SELECT s, dst, d + 1 FROM walk JOIN arcs ON src = v WHERE d < 4").add(
    "least", "SELECT s, v, min(d) AS d FROM walk GROUP BY 1, 2").query("SELECT qid, asked.s, t, d AS dist FROM asked LEFT JOIN least ON least.s = asked.s AND least.v = t"))
def stream_answers(spark, sf_dir):
    """Requests of the event stream answered batch by batch against the index of the user graph."""
    ix = w.index_of(spark, sf_dir, "g_user_flow", 4.0, False)
    return rq.answered_requests(spark, ix, rq.requests(rq.event_stream(spark, sf_dir)), fallback="exact").select("qid", "s", "t", "dist")


__all__ = ["QUERIES", "SQL"]
