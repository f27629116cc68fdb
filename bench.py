"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
GRAPH, ALPHA, NODES, SEARCHED = "g_cust_part_r", 4.0, 200, 500


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from pathmeet.operators import baselines, meet
    from pathmeet.operators.index import build_index, save_index
    from pathmeet.functions.searches import in_process_searches
    from pathmeet.operators.serve import LocalOracle
    from pathmeet.plans import workloads as w
    from pathmeet.scratch import staged

    took: dict[str, float] = {}
    more: dict[str, float] = {}

    def timed(name: str, run):
        began = time.perf_counter()
        out = run()
        took[name] = round(time.perf_counter() - began, 3)
        return out

    def written(df):
        return staged(df, "bench")

    g = timed("build_graph", lambda: w.graph_of(spark, SF_DIR, GRAPH))
    sample = written(w.sample_nodes(g, size=NODES))
    index = timed("build_index", lambda: build_index(g, ALPHA, sources=sample))
    pairs = written(w.sample_pairs(sample))
    asked = pairs.count()
    answers = timed("distance_boundary", lambda: written(meet.distance(index, pairs)))
    timed("distance_full", lambda: written(meet.distance(index, pairs, probe="full")))
    # one batch for all three methods: met pairs in the order of a hash
    met = written(answers.where("case = 'meet'").orderBy(F.xxhash64("qid"), "qid").limit(SEARCHED).select("qid", "s", "t"))
    timed("distance_same_batch", lambda: written(meet.distance(index, met)))
    bfs = timed("bfs_distance", lambda: written(baselines.bfs_distance(g, met)))
    bidi = timed("bidirectional_bfs", lambda: written(baselines.bidirectional_bfs(g, met)))
    probes = answers.where("case in ('meet', 'unanswered')").agg(F.avg("probes"), F.max("probes")).first()
    answered = answers.where("dist is not null").count()
    more |= {
        "pairs": asked, "answered_share": round(answered / asked, 4), "mean_probes": round(probes[0] or 0, 2), "worst_probes": probes[1],
        "bfs_arcs": round(bfs.agg(F.avg("scanned")).first()[0] or 0, 1), "bidirectional_arcs": round(bidi.agg(F.avg("scanned")).first()[0] or 0, 1),
        "same_batch": met.count(), "same_batch_ms_per_query": round(1000 * took["distance_same_batch"] / max(1, met.count()), 3), "ms_per_query": round(1000 * took["distance_boundary"] / asked, 4), "bfs_ms_per_query": round(1000 * took["bfs_distance"] / max(1, met.count()), 3),
        "bidirectional_ms_per_query": round(1000 * took["bidirectional_bfs"] / max(1, met.count()), 3),
    }
    folder = f"file://{tempfile.mkdtemp()}/index"
    timed("save_index", lambda: save_index(index, folder, 8))
    local = LocalOracle(spark, folder)
    ends = [(r.s, r.t) for r in met.collect()]
    local.prepare(spark, sorted({u for p in ends for u in p}))
    for s, t in ends:  # the rows of the endpoints are read once
        local.distance(s, t)
    began = time.perf_counter()
    for s, t in ends:
        local.distance(s, t)
    more["single_query_ms"] = round(1000 * (time.perf_counter() - began) / max(1, len(ends)), 4)
    more |= in_process_searches(g, ends)
    for name, run in {"op1": "exact_dedup", "op3": "source_mixing", "op4": "simhash_links", "op7": "packing"}.items():
        try:
            from pathmeet import llm

            query = llm.queries()[f"{name}_{run}"]
        except ImportError:
            break
        timed(f"{name}_{run}", lambda query=query: query(spark, SF_DIR).write.format("noop").mode("overwrite").save())
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": SF_DIR.rpartition("sf")[2], "measures": more}))


if __name__ == "__main__":
    main()
    sys.stdout.flush()
