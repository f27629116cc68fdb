"""Graphs derived from the given tables: one edge rule each, in SQL that Spark and DuckDB share.

A rule names its tables in braces and returns (src, dst) or (src, dst, w). Rules whose
functions differ between the engines carry a text for each."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

RULES: dict[str, str] = {
    "g_cust_part_r": "SELECT o_custkey * 16 AS src, l_partkey * 16 + 2 AS dst FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey WHERE l_returnflag = 'R'",
    "g_cust_part": "SELECT o_custkey * 16 AS src, l_partkey * 16 + 2 AS dst FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey",
    "g_cust_supp": "SELECT o_custkey * 16 AS src, l_suppkey * 16 + 1 AS dst FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey",
    "g_order_part": "SELECT l_orderkey * 16 + 3 AS src, l_partkey * 16 + 2 AS dst FROM {lineitem}",
    "g_order_part_r": "SELECT l_orderkey * 16 + 3 AS src, l_partkey * 16 + 2 AS dst FROM {lineitem} WHERE l_returnflag = 'R'",
    "g_copurchase": "SELECT a.l_partkey * 16 + 2 AS src, b.l_partkey * 16 + 2 AS dst FROM {lineitem} a JOIN {lineitem} b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey",
    "g_trade_all": """
        SELECT l_orderkey * 16 + 3 AS src, l_partkey * 16 + 2 AS dst FROM {lineitem}
        UNION ALL SELECT o_orderkey * 16 + 3, o_custkey * 16 FROM {orders}
        UNION ALL SELECT l_partkey * 16 + 2, l_suppkey * 16 + 1 FROM {lineitem} WHERE l_linenumber = 1
        UNION ALL SELECT c_custkey * 16, CAST(c_nationkey AS BIGINT) * 16 + 4 FROM {customer}
        UNION ALL SELECT s_suppkey * 16 + 1, CAST(s_nationkey AS BIGINT) * 16 + 4 FROM {supplier}
        UNION ALL SELECT CAST(n_nationkey AS BIGINT) * 16 + 4, CAST(n_regionkey AS BIGINT) * 16 + 5 FROM {nation}""",
    # directed: each customer who bought a part passes it on to the next one
    "g_handed_on": """
        SELECT src, dst FROM (
          SELECT o_custkey * 16 AS src, lead(o_custkey * 16) OVER (PARTITION BY l_partkey ORDER BY o_orderdate, o_orderkey) AS dst
          FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND l_linenumber = 1) AS h
        WHERE dst IS NOT NULL""",
    "g_turn_chain": """
        SELECT (a.conv_id * 1024 + a.turn) * 16 + 12 AS src, (b.conv_id * 1024 + b.turn) * 16 + 12 AS dst
        FROM {conversations} a JOIN {conversations} b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1""",
    "g_trade_weighted": """
        SELECT o_custkey * 16 AS src, l_partkey * 16 + 2 AS dst, CAST(1 + floor(100 * min(l_discount) + 0.5) AS BIGINT) AS w
        FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' GROUP BY o_custkey, l_partkey""",
}

#: (Spark, DuckDB) texts of rules whose functions differ.
SPLIT_RULES: dict[str, tuple[str, str]] = {
    # the next event is sought inside its hour; the last of an hour meets the first of the next hour with events
    "g_user_flow": (
        """WITH e AS (SELECT user_id, ts, event_id, unix_micros(CAST(ts AS TIMESTAMP)) div 3600000000 AS h FROM {events}),
        inner_pairs AS (SELECT user_id, lead(user_id) OVER (PARTITION BY h ORDER BY ts, event_id) AS next_user FROM e),
        ends AS (SELECT h, min_by(user_id, struct(ts, event_id)) AS first_user, max_by(user_id, struct(ts, event_id)) AS last_user FROM e GROUP BY h),
        seams AS (SELECT last_user AS user_id, lead(first_user) OVER (ORDER BY h) AS next_user FROM ends)
        SELECT user_id * 16 + 6 AS src, next_user * 16 + 6 AS dst FROM (SELECT * FROM inner_pairs UNION ALL SELECT * FROM seams) AS f WHERE next_user IS NOT NULL""",
        """SELECT user_id * 16 + 6 AS src, next_user * 16 + 6 AS dst
        FROM (SELECT user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS next_user FROM events) WHERE next_user IS NOT NULL""",
    ),
    # documents meet at shared lines: bipartite, so a line of very many documents adds an edge each, not all pairs
    "g_doc_line": (
        """SELECT doc_id * 16 + 8 AS src, CAST(conv(substring(md5(line), 1, 12), 16, 10) AS BIGINT) * 16 + 11 AS dst
        FROM (SELECT doc_id, explode(split(text, '\\n')) AS line FROM {documents}) AS x WHERE length(line) > 10""",
        """SELECT doc_id * 16 + 8 AS src, ('0x' || substr(md5(line), 1, 12))::BIGINT * 16 + 11 AS dst
        FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) > 10""",
    ),
    "g_page_link": (
        r"""SELECT page_id * 16 + 10 AS src, CAST(conv(substring(md5(href), 1, 12), 16, 10) AS BIGINT) * 16 + 11 AS dst
        FROM (SELECT page_id, explode(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM {pages}) AS h""",
        r"""SELECT page_id * 16 + 10 AS src, ('0x' || substr(md5(href), 1, 12))::BIGINT * 16 + 11 AS dst
        FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)""",
    ),
    "g_user_type_window": (
        """SELECT user_id * 16 + 6 AS src, CAST(conv(substring(md5(concat(event_type, ':', CAST(unix_micros(CAST(ts AS TIMESTAMP)) div 3600000000 AS STRING))), 1, 12), 16, 10) AS BIGINT) * 16 + 7 AS dst FROM {events}""",
        """SELECT user_id * 16 + 6 AS src, ('0x' || substr(md5(event_type || ':' || (epoch_us(ts) // 3600000000)::VARCHAR), 1, 12))::BIGINT * 16 + 7 AS dst FROM events""",
    ),
    "g_doc_source": (
        """SELECT d.doc_id * 16 + 8 AS src, CAST(conv(substring(md5(concat(source, ':', lang)), 1, 12), 16, 10) AS BIGINT) * 16 + 7 AS dst
        FROM {documents} d LEFT SEMI JOIN {labels} l ON d.doc_id = l.doc_id""",
        """SELECT doc_id * 16 + 8 AS src, ('0x' || substr(md5(source || ':' || lang), 1, 12))::BIGINT * 16 + 7 AS dst
        FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)""",
    ),
    "g_bench_doc": (
        r"""WITH d AS (SELECT DISTINCT doc_id, g FROM (SELECT doc_id, explode(transform(sequence(0, size(w) - 8), i -> concat_ws(' ', slice(w, i + 1, 8)))) AS g
              FROM (SELECT doc_id, split(trim(regexp_replace(text, '[ \t\n]+', ' ')), ' ') AS w FROM {documents}) AS t WHERE size(w) >= 8) AS x),
        b AS (SELECT DISTINCT item_id, g FROM (SELECT item_id, explode(transform(sequence(0, size(w) - 8), i -> concat_ws(' ', slice(w, i + 1, 8)))) AS g
              FROM (SELECT item_id, split(trim(regexp_replace(text, '[ \t\n]+', ' ')), ' ') AS w FROM {benchmark}) AS t WHERE size(w) >= 8) AS x)
        SELECT doc_id * 16 + 8 AS src, item_id * 16 + 13 AS dst FROM d JOIN b ON d.g = b.g""",
        r"""SELECT d.doc_id * 16 + 8 AS src, b.item_id * 16 + 13 AS dst FROM
        (SELECT DISTINCT doc_id, array_to_string(w[i:i+7], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT doc_id, string_split(trim(regexp_replace(text, '[ \t\n]+', ' ', 'g')), ' ') AS w FROM documents))) d
        JOIN (SELECT DISTINCT item_id, array_to_string(w[i:i+7], ' ') AS g FROM (SELECT item_id, w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT item_id, string_split(trim(regexp_replace(text, '[ \t\n]+', ' ', 'g')), ' ') AS w FROM benchmark))) b
        ON d.g = b.g""",
    ),
}


def _social(step: int, degree: int) -> tuple[str, str]:
    """A power-law graph of ``2 * step`` nodes per customer and about ``degree`` links per node.

    Ends are drawn by rank, with the weight of a rank falling as its power; draws are of md5, which both engines have."""
    shape = 1 / (1 - 1 / (2.3 - 1))
    drawn = lambda number: " , ".join(f"CAST(least(n - 1, floor(pow({number(end)} / 281474976710656.0, {shape!r}) * n)) AS BIGINT) * 16 + 14 AS {end}" for end in ("src", "dst"))
    of_spark = drawn(lambda end: f"CAST(conv(substring(md5(concat(k, ':{end}')), 1, 12), 16, 10) AS DOUBLE)")
    of_duck = drawn(lambda end: f"('0x' || substr(md5(k::VARCHAR || ':{end}'), 1, 12))::BIGINT::DOUBLE")
    return (
        f"SELECT {of_spark} FROM (SELECT c_custkey * 1000 + i AS k FROM (SELECT c_custkey, explode(sequence(1, {step * degree})) AS i FROM {{customer}})) AS e CROSS JOIN (SELECT {2 * step} * count(*) AS n FROM {{customer}}) AS c",
        f"SELECT {of_duck} FROM (SELECT c_custkey * 1000 + unnest(range(1, {step * degree} + 1)) AS k FROM customer) e, (SELECT {2 * step} * count(*) AS n FROM customer) c",
    )


#: Synthetic graphs of a social shape: three sizes, two densities.
SOCIAL = {f"g_social_{step}_{degree}": (step, degree) for step in (1, 2, 4) for degree in (8, 16)}
SPLIT_RULES |= {name: _social(*shape) for name, shape in SOCIAL.items()}
WEIGHTED = {"g_trade_weighted", "g_vec_knn"}

KNN_SQL = """SELECT a AS src, b AS dst, 1 + d2 // 10000 AS w FROM (
  SELECT a, b, d2, row_number() OVER (PARTITION BY a ORDER BY d2, b) AS k FROM (
    SELECT p.vec_id * 16 + 9 AS a, q.vec_id * 16 + 9 AS b,
           list_sum(list_transform(range(1, 65), lambda i: (p.v[i] - q.v[i]) * (p.v[i] - q.v[i])))::BIGINT AS d2
    FROM (SELECT vec_id, list_transform(embedding, lambda x: round(x::DOUBLE * 1000)::BIGINT) AS v FROM embeddings) p
    JOIN (SELECT vec_id, list_transform(embedding, lambda x: round(x::DOUBLE * 1000)::BIGINT) AS v FROM embeddings) q ON p.vec_id <> q.vec_id)) WHERE k <= 6"""


def load(spark: SparkSession, sf_dir: str, *names: str) -> dict[str, DataFrame]:
    return {n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in names}


def edges(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    """Raw edges of a derived graph."""
    if graph == "g_vec_knn":
        return knn_edges(load(spark, sf_dir, "embeddings")["embeddings"])
    text = RULES.get(graph) or SPLIT_RULES[graph][0]
    used = [t for t in TABLES if "{" + t + "}" in text]
    return spark.sql(text, **load(spark, sf_dir, *used))


def edges_sql(graph: str) -> str:
    """The same edges for DuckDB."""
    if graph == "g_vec_knn":
        return KNN_SQL
    text = RULES.get(graph) or SPLIT_RULES[graph][1]
    for t in TABLES:
        text = text.replace("{" + t + "}", t)
    return text


def knn_edges(vectors: DataFrame, k: int = 6, block: int = 2048) -> DataFrame:
    """Edges to the ``k`` nearest vectors by integer squared distance; weight 1 + distance div 10000.

    Vectors are dealt to blocks by id hash, and a task gets one pair of blocks: it looks for the neighbours of the
    first block's vectors in the second block. So a task holds ``2 * block`` vectors however many there are, while
    rows sent and work grow with the square of the number of blocks, as an exact search must."""
    import numpy as np
    import pyarrow as pa
    from pyspark.sql import functions as F
    from pyspark.sql.window import Window

    whole = vectors.select((F.col("vec_id") * 16 + 9).alias("id"), F.transform("embedding", lambda x: F.round(x.cast("double") * 1000).cast("long")).alias("v"))
    blocks = max(1, -(-vectors.count() // block))
    dealt = whole.withColumn("b", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    asking = dealt.withColumn("to", other).select("id", "v", F.col("b").alias("own"), "to", F.lit(False).alias("at_home"))
    answering = dealt.withColumn("own", other).select("id", "v", "own", F.col("b").alias("to"), F.lit(True).alias("at_home"))

    def nearest(table: pa.Table) -> pa.Table:
        ids = table.column("id").to_numpy()
        v = np.array(table.column("v").to_pylist(), np.int64).reshape(len(ids), -1)
        home = table.column("at_home").to_numpy(zero_copy_only=False)
        theirs, their_ids = v[home], ids[home]
        v, ids = v[~home], ids[~home]
        norm = (theirs * theirs).sum(1)
        out: list[tuple[np.ndarray, ...]] = []
        for at in range(0, len(ids), 512):
            q = v[at : at + 512]
            d2 = (q * q).sum(1)[:, None] + norm[None, :] - 2 * (q @ theirs.T)
            i, j = np.nonzero(ids[at : at + 512][:, None] != their_ids[None, :])
            order = np.lexsort((their_ids[j], d2[i, j], i))
            i, j = i[order], j[order]
            first = np.flatnonzero(np.diff(i, prepend=-1))
            rank = np.arange(len(i)) - np.repeat(first, np.diff(np.append(first, len(i))))
            i, j = i[rank < k], j[rank < k]
            out.append((ids[at + i], their_ids[j], d2[i, j]))
        a, b, d = (np.concatenate(x) if out else np.zeros(0, np.int64) for x in (zip(*out, strict=True) if out else ((), (), ())))
        return pa.table({"a": a, "b": b, "d2": d})

    near = asking.unionByName(answering).groupBy("own", "to").applyInArrow(nearest, "a long, b long, d2 long")
    rank = F.row_number().over(Window.partitionBy("a").orderBy("d2", "b"))
    return near.withColumn("k", rank).where(F.col("k") <= k).select(F.col("a").alias("src"), F.col("b").alias("dst"), F.expr("1 + d2 div 10000").alias("w"))
