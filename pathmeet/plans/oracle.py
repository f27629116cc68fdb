"""DuckDB SQL for the engine's relations, composed from common table expressions.

Recursion with UNION gives (source, node, level) rows; the least level is the distance."""

from __future__ import annotations

from pathmeet.sources.tables import edges_sql

MOST_HOPS = 16


class Oracle:
    """A chain of CTEs for one graph, alpha and seed; ``query`` closes it."""

    def __init__(self, graph: str, alpha: float = 4.0, seed: int = 7, calibration: str = "literal", uniform: bool = False, weighted: bool = False):
        self.parts: list[tuple[str, str]] = []
        w = "min(w)" if weighted else "1"
        self.add("raw", edges_sql(graph))
        self.add("edges", f"SELECT least(src, dst) AS a, greatest(src, dst) AS b, {w}::BIGINT AS w FROM raw WHERE src <> dst GROUP BY ALL" if not weighted else "SELECT least(src, dst) AS a, greatest(src, dst) AS b, min(w)::BIGINT AS w FROM raw WHERE src <> dst GROUP BY 1, 2")
        self.add("arcs", "SELECT a AS src, b AS dst, w FROM edges UNION ALL SELECT b, a, w FROM edges")
        self.add("nodes", "SELECT src AS id, count(*) AS deg FROM arcs GROUP BY 1")
        self.add("nm", "SELECT (SELECT count(*) FROM nodes) AS n, (SELECT count(*) FROM edges) AS m")
        self.add("stepped", "SELECT id, deg, (2 * n * deg + m - 1) // m AS steps, n, m FROM nodes, nm")
        factor = f"(m / ({float(alpha)} * n * sqrt(n::DOUBLE)))"
        if calibration == "anchor_count":
            factor = f"((m / ({float(alpha)} * sqrt(n::DOUBLE))) / (SELECT sum(steps) FROM stepped)::DOUBLE)"
        self.add("plain_p", f"SELECT id, deg, least(1.0::DOUBLE, {factor} * steps) AS p FROM stepped")
        self.add("prob", "SELECT id, deg, (SELECT round(avg(round(p, 12)), 9) FROM plain_p) AS p FROM plain_p" if uniform else "SELECT * FROM plain_p")
        self.add("anchors", f"SELECT id, p, ('0x' || substr(md5(id::VARCHAR || ':{seed}'), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS draw FROM prob WHERE ('0x' || substr(md5(id::VARCHAR || ':{seed}'), 1, 8))::BIGINT / 4294967296.0::DOUBLE < p")

    def add(self, name: str, sql: str) -> Oracle:
        self.parts.append((name, sql))
        return self

    def has(self, name: str) -> bool:
        return any(n == name for n, _ in self.parts)

    def need(self, *names: str) -> Oracle:
        for name in names:
            if not self.has(name):
                getattr(self, f"_{name}")()
        return self

    def _reach(self) -> None:
        self.add("reach", f"SELECT id AS v, 0 AS d FROM anchors UNION SELECT dst, d + 1 FROM reach JOIN arcs ON src = v WHERE d < {MOST_HOPS}")

    def _radius(self) -> None:
        self.need("reach")
        self.add("radius", "SELECT v AS u, min(d) AS r FROM reach GROUP BY 1")

    def _sample(self) -> None:
        self.add("sample", "SELECT id FROM (SELECT id, n, row_number() OVER (ORDER BY md5('0:' || id::VARCHAR), id) AS k FROM nodes, nm) WHERE k <= CASE WHEN n >= 20000 THEN 1000 WHEN n >= 2000 THEN 200 ELSE 50 END")

    def _vicinity(self) -> None:
        """Vicinities of the sample nodes."""
        self.need("radius", "sample")
        self.add("grow", "SELECT id AS u, id AS v, 0 AS d FROM sample UNION SELECT g.u, dst, d + 1 FROM grow g JOIN radius x ON g.u = x.u AND g.d < x.r JOIN arcs ON src = v")
        self.add("vicinity", "SELECT g.u, v, min(d) AS d, min(d) < any_value(r) AS inside FROM grow g JOIN radius x ON g.u = x.u GROUP BY g.u, v")

    def _boundary(self) -> None:
        self.need("vicinity")
        self.add("boundary", """SELECT DISTINCT c.u, c.v, c.d FROM vicinity c JOIN radius x ON c.u = x.u AND x.r > 0 AND NOT c.inside
            JOIN arcs ON src = c.v WHERE NOT EXISTS (SELECT 1 FROM vicinity o WHERE o.u = c.u AND o.v = dst)""")

    def _exact(self) -> None:
        """Distances from the sample nodes to all nodes."""
        self.need("sample")
        self.add("walk", f"SELECT id AS s, id AS v, 0 AS d FROM sample UNION SELECT s, dst, d + 1 FROM walk JOIN arcs ON src = v WHERE d < {MOST_HOPS}")
        self.add("exact", "SELECT s, v, min(d) AS d FROM walk GROUP BY 1, 2")

    def _pairs(self) -> None:
        self.need("sample")
        self.add("pairs", pairs_sql("sample"))

    def _cases(self) -> None:
        """The answer of each pair by what the definitions say, from exact distances and radii."""
        self.need("exact", "pairs", "vicinity")
        self.add("facts", """SELECT p.qid, p.s, p.t, e.d, rs.r AS rs, rt.r AS rt, s.id IS NOT NULL AS as_, t.id IS NOT NULL AS at_,
              ms.v IS NOT NULL AS in_s, mt.v IS NOT NULL AS in_t
            FROM pairs p LEFT JOIN exact e ON e.s = p.s AND e.v = p.t JOIN radius rs ON rs.u = p.s JOIN radius rt ON rt.u = p.t
            LEFT JOIN anchors s ON s.id = p.s LEFT JOIN anchors t ON t.id = p.t
            LEFT JOIN vicinity ms ON ms.u = p.s AND ms.v = p.t LEFT JOIN vicinity mt ON mt.u = p.t AND mt.v = p.s""")
        self.add("cases", """SELECT qid, s, t, d, rs, rt, CASE WHEN d IS NULL THEN 'unreachable' WHEN as_ THEN 'source_anchor' WHEN at_ THEN 'target_anchor'
              WHEN in_s THEN 'target_in_source' WHEN in_t THEN 'source_in_target' WHEN d <= rs + rt THEN 'meet' ELSE 'unanswered' END AS case_ FROM facts""")

    def query(self, sql: str) -> str:
        return "WITH RECURSIVE " + ",\n".join(f"{n} AS ({s})" for n, s in self.parts) + "\n" + sql


def pairs_sql(sample: str, on: str = "a.id < b.id") -> str:
    """Pairs of a sample, numbered by the places of their ends in it."""
    placed = f"(SELECT id, row_number() OVER (ORDER BY id) AS k FROM {sample})"
    return f"SELECT a.k * 1000000 + b.k AS qid, a.id AS s, b.id AS t FROM {placed} a JOIN {placed} b ON {on}"


def oracle(graph: str, *needs: str, **options) -> Oracle:
    return Oracle(graph, **options).need(*needs)
