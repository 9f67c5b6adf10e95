"""An independent form of the method in DuckDB SQL: all labels scored, everything recounted each iteration, the loop unrolled."""

from __future__ import annotations

from graphpart.functions.draws import draw_sql


class Loop:
    """Common table expressions of T iterations; ``names[t]`` is the labelling (v, label) after t. ``active`` (v) restricts who may move."""

    def __init__(self, edges: str, k: int, t: int, c: float = 1.05, seed: int = 42, directed: bool = True, unit: str = "degree", throttle: bool = True, start: str | None = None, labels: list[int] | None = None, active: str | None = None) -> None:
        self.k, self.labels = k, labels or list(range(k))
        w = "CAST(count(*) AS BIGINT)" if directed else "CAST(1 AS BIGINT)"
        load = {"degree": "deg", "vertices": "1"}[unit]
        self.ctes = [
            ("e", f"SELECT DISTINCT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM ({edges}) WHERE src IS NOT NULL AND dst IS NOT NULL AND src <> dst"),
            ("arcs", f"SELECT src, dst, {w} AS w FROM (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e) GROUP BY src, dst"),
            ("verts", "SELECT src AS v, count(*) AS deg, CAST(sum(w) AS BIGINT) AS wdeg FROM arcs GROUP BY src"),
            ("ids", "SELECT unnest([" + ", ".join(map(str, self.labels)) + "]) AS label"),
            ("cap", f"SELECT CAST({c} AS DOUBLE) * CAST(sum({load}) AS DOUBLE) / CAST({len(self.labels)} AS DOUBLE) AS c, CAST(sum({load}) AS BIGINT) AS total, sum(deg) AS arcs, count(*) AS n FROM verts"),
            *([("act0", active)] if active else []),
            ("lab0", start or f"SELECT v, CAST({draw_sql(seed, 0, 'init', 'v')} % {k} AS INTEGER) AS label FROM verts"),
        ]
        for i in range(1, t + 1):
            p = f"lab{i - 1}"
            self.ctes += [
                (f"loads{i}", f"SELECT ids.label, CAST(coalesce(sum({'deg' if unit == 'degree' else 'CASE WHEN v.v IS NULL THEN 0 ELSE 1 END'}), 0) AS BIGINT) AS b FROM ids LEFT JOIN {p} l ON l.label = ids.label LEFT JOIN verts v ON v.v = l.v GROUP BY ids.label"),
                (f"h{i}", f"SELECT a.dst AS v, l.label, CAST(sum(a.w) AS BIGINT) AS h FROM arcs a JOIN {p} l ON l.v = a.src GROUP BY a.dst, l.label"),
                (f"s{i}", f"""SELECT x.v, d.label, p.label AS cur, x.deg, CAST(coalesce(h.h, 0) AS DOUBLE) / CAST(x.wdeg AS DOUBLE) - CAST(d.b AS DOUBLE) / cap.c AS s
FROM verts x JOIN {p} p ON p.v = x.v CROSS JOIN loads{i} d CROSS JOIN cap LEFT JOIN h{i} h ON h.v = x.v AND h.label = d.label"""),
                (f"best{i}", f"SELECT v, cur, {f'CASE WHEN v IN (SELECT v FROM act{i - 1}) THEN label ELSE cur END' if active else 'label'} AS best, deg FROM (SELECT *, row_number() OVER (PARTITION BY v ORDER BY s DESC, (label = cur) DESC, {draw_sql(seed, i, 'tie', 'v', 'label')} DESC, label DESC) AS r FROM s{i}) WHERE r = 1"),
                (f"m{i}", f"SELECT best AS label, CAST(sum({load}) AS BIGINT) AS m FROM best{i} WHERE best <> cur GROUP BY best"),
                (f"p{i}", f"SELECT m.label, cap.c - CAST(d.b AS DOUBLE) AS r, m.m, " + (f"least(1.0, greatest(0.0, (cap.c - CAST(d.b AS DOUBLE)) / CAST(m.m AS DOUBLE)))" if throttle else "1.0") + f" AS p FROM m{i} m JOIN loads{i} d USING (label) CROSS JOIN cap"),
                (f"lab{i}", f"SELECT b.v, CAST(CASE WHEN b.best <> b.cur AND {draw_sql(seed, i, 'mig', 'b.v')} / 4294967296.0 < p.p THEN b.best ELSE b.cur END AS INTEGER) AS label FROM best{i} b LEFT JOIN p{i} p ON p.label = b.best"),
            ]
            if active:  # neighbours of movers join who may move
                self.ctes.append((f"act{i}", f"SELECT v FROM act{i - 1} UNION SELECT a.dst FROM arcs a JOIN {p} x ON x.v = a.src JOIN lab{i} y ON y.v = a.src WHERE x.label <> y.label"))
        self.t = t

    def sql(self, query: str) -> str:
        return "WITH " + ",\n".join(f"{n} AS MATERIALIZED ({q})" for n, q in self.ctes) + "\n" + query

    def labels_sql(self) -> str:
        return self.sql(f"SELECT v, label FROM lab{self.t}")

    def history_sql(self) -> str:
        """t, phi, rho, migrated, messages of each iteration."""
        parts = []
        for i in range(self.t + 1):
            phi = f"(SELECT round(avg(CASE WHEN x.label = y.label THEN 1.0 ELSE 0.0 END), 6) FROM arcs a JOIN lab{i} x ON x.v = a.src JOIN lab{i} y ON y.v = a.dst)"
            rho = f"(SELECT round(max(b) * {len(self.labels)}.0 / sum(b), 6) FROM (SELECT sum(deg) AS b FROM verts JOIN lab{i} USING (v) GROUP BY label))"
            moved = f"(SELECT count(*) FROM lab{i} a JOIN lab{i - 1} b USING (v) WHERE a.label <> b.label)" if i else "0"
            told = f"(SELECT coalesce(sum(deg), 0) FROM lab{i} a JOIN lab{i - 1} b USING (v) JOIN verts USING (v) WHERE a.label <> b.label)" if i else "0"
            first = "(SELECT arcs FROM cap)" if i == 1 else "0"
            parts.append(f"SELECT {i} AS t, {phi} AS phi, {rho} AS rho, CAST({moved} AS BIGINT) AS migrated, CAST({told} + {first} AS BIGINT) AS messages")
        return self.sql(" UNION ALL ".join(parts))


def smallworld_sql(keys: str, d: int, beta: float, seed: int = 42) -> str:
    """The small world over a table's keys (key), by rank."""
    return f"""WITH k AS MATERIALIZED (SELECT key, row_number() OVER (ORDER BY key) - 1 AS v, count(*) OVER () AS n FROM (SELECT DISTINCT key FROM ({keys}) WHERE key IS NOT NULL)),
e AS (SELECT k.key AS a, CASE WHEN {draw_sql(seed, 0, 'rewire', 'k.v', 'i')} / 4294967296.0 < {beta} THEN {draw_sql(seed, 0, 'target', 'k.v', 'i')} % k.n ELSE (k.v + i) % k.n END AS at FROM k CROSS JOIN (SELECT unnest(range(1, {d + 1})) AS i))
SELECT e.a * 8 AS src, k.key * 8 AS dst FROM e JOIN k ON k.v = e.at WHERE e.a <> k.key"""
