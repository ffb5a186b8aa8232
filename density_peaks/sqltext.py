"""SQL of the methods: brute-force statements for an oracle, and statements over Spark views.

Each statement is put together from named parts; distances are written with the same
operations in the same order as in the library, so both engines give the same bits.
"""

from __future__ import annotations

from density_peaks import points

_GAP = {
    "euclidean": "sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y))",
    "manhattan": "abs(a.x - b.x) + abs(a.y - b.y)",
    "chebyshev": "greatest(abs(a.x - b.x), abs(a.y - b.y))",
}


def pairs(view: str, metric: str = "euclidean") -> str:
    """CTEs p (points) and d (id, nbr, dist of all ordered pairs)."""
    return f"p AS ({points.sql(view)}), d AS (SELECT a.id, b.id AS nbr, {_GAP[metric]} AS dist FROM p a JOIN p b ON a.id <> b.id)"


def rho_part(d_c: float, count_self: bool = False, table: str = "d", name: str = "r", cap: float | None = None) -> str:
    """CTE of id, rho for one cutoff over pairs; cap counts listed neighbours only."""
    near = f"dist < {d_c!r}" + (f" AND dist < {cap!r}" if cap is not None else "")
    return f"{name} AS (SELECT p.id, coalesce(n, 0)::BIGINT + {int(count_self)} AS rho FROM p LEFT JOIN (SELECT id, count(*) AS n FROM {table} WHERE {near} GROUP BY id) USING (id))"


def dep_part(tie: str = "strict", tau: float | None = None, cap: str | None = None, r: str = "r", name: str = "dep") -> str:
    """CTE of the dependent table from r and d; with tau only nearer neighbours are seen and tops get cap."""
    up = "o.rho > s.rho" + (" OR (o.rho = s.rho AND o.id < s.id)" if tie == "by_id" else "")
    seen = f"AND d.dist < {tau!r}" if tau is not None else ""
    far = cap or "coalesce(f.far, 0e0)"
    return (
        f"{name}_m AS (SELECT d.id, min(d.dist) AS delta, arg_min(d.nbr, {{'a': d.dist, 'b': d.nbr}}) AS mu FROM d JOIN {r} s ON d.id = s.id JOIN {r} o ON d.nbr = o.id WHERE ({up}) {seen} GROUP BY d.id), "
        f"{name}_f AS (SELECT id, max(dist) AS far FROM d GROUP BY id), "
        f"{name} AS (SELECT s.id, s.rho, CASE WHEN m.mu IS NULL THEN {far} ELSE m.delta END AS delta, m.mu, m.mu IS NULL AS is_top, (m.mu IS NULL AND {'true' if cap else 'false'}) AS is_capped "
        f"FROM {r} s LEFT JOIN {name}_m m ON s.id = m.id LEFT JOIN {name}_f f ON s.id = f.id)"
    )


def diagonal() -> str:
    """The diagonal of the bounding box of p, as a scalar subquery."""
    return "(SELECT sqrt((max(x) - min(x)) * (max(x) - min(x)) + (max(y) - min(y)) * (max(y) - min(y))) FROM p)"


def top_part(k: int, dep: str = "dep", name: str = "c") -> str:
    """CTE of the k ids of greatest rho * delta."""
    return f"{name} AS (SELECT id FROM {dep} ORDER BY rho * delta DESC, id LIMIT {k})"


def box_part(dep_from: str, k: int, dep: str, name: str) -> str:
    """CTE of ids of dep within the thresholds that the top k of dep_from span."""
    return f"{name}_b AS (SELECT min(rho) AS r, min(delta) AS l FROM (SELECT * FROM {dep_from} ORDER BY rho * delta DESC, id LIMIT {k})), {name} AS (SELECT id FROM {dep}, {name}_b WHERE rho >= r AND delta >= l)"


def label_part(dep: str = "dep", c: str = "c", name: str = "l") -> str:
    """Recursive CTE of id, cluster, depth, is_center by following parents down from centers and roots."""
    return (
        f"{name} AS (SELECT id, id AS cluster, 0 AS depth, id IN (SELECT id FROM {c}) AS is_center FROM {dep} WHERE mu IS NULL OR id IN (SELECT id FROM {c}) "
        f"UNION ALL SELECT e.id, u.cluster, u.depth + 1, false FROM {dep} e JOIN {name} u ON e.mu = u.id WHERE e.id NOT IN (SELECT id FROM {c}))"
    )


def score_select(g: str, c: str) -> str:
    """Pair scores of clusterings g and c (id, cluster)."""
    return (
        f"SELECT tp::DECIMAL(38,0) AS tp, (cp - tp)::DECIMAL(38,0) AS fp, (gp - tp)::DECIMAL(38,0) AS fn, CASE WHEN cp > 0 THEN tp::DOUBLE / cp END AS precision, CASE WHEN gp > 0 THEN tp::DOUBLE / gp END AS recall, "
        f"CASE WHEN cp > 0 AND gp > 0 AND tp > 0 THEN 2 * (tp::DOUBLE / cp) * (tp::DOUBLE / gp) / ((tp::DOUBLE / cp) + (tp::DOUBLE / gp)) END AS f1 FROM "
        f"(SELECT coalesce(sum(n * (n - 1) / 2), 0)::HUGEINT AS tp FROM (SELECT count(*) AS n FROM {g} g JOIN {c} c USING (id) GROUP BY g.cluster, c.cluster)), "
        f"(SELECT coalesce(sum(n * (n - 1) / 2), 0)::HUGEINT AS gp FROM (SELECT count(*) AS n FROM {g} GROUP BY cluster)), (SELECT coalesce(sum(n * (n - 1) / 2), 0)::HUGEINT AS cp FROM (SELECT count(*) AS n FROM {c} GROUP BY cluster))"
    )


def spark_rho(view: str, d_c: float, count_self: bool = False) -> str:
    """Spark SQL for density over a registered view of points, by an equality join on grid cells; equal points are joined once, with their number."""
    side = d_c * (1 + 1e-6)
    return f"""
    WITH a AS (SELECT x, y, count(*) AS w, floor(x / {side!r}D) AS cx, floor(y / {side!r}D) AS cy FROM {view} GROUP BY x, y),
    b AS (SELECT x, y, w, cx + ox AS cx, cy + oy AS cy FROM a LATERAL VIEW explode(array(-1, 0, 1)) o1 AS ox LATERAL VIEW explode(array(-1, 0, 1)) o2 AS oy),
    n AS (SELECT a.x, a.y, sum(b.w) AS n FROM a JOIN b ON a.cx = b.cx AND a.cy = b.cy WHERE sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)) < {d_c!r}D GROUP BY a.x, a.y)
    SELECT v.id, CAST(coalesce(n, 1) - 1 + {int(count_self)} AS BIGINT) AS rho FROM {view} v LEFT JOIN n ON v.x = n.x AND v.y = n.y
    """


def spark_cluster(dep: str, k: int) -> str:
    """Spark SQL for clusters from a registered dependent table, with its k points of greatest gamma as centers."""
    return f"""
    WITH RECURSIVE c AS (SELECT id FROM {dep} ORDER BY rho * delta DESC, id LIMIT {k}),
    e AS (SELECT d.id, CASE WHEN c.id IS NULL THEN d.mu END AS mu FROM {dep} d LEFT JOIN c ON d.id = c.id),
    l(id, cluster) AS (SELECT id, id FROM e WHERE mu IS NULL UNION ALL SELECT e.id, l.cluster FROM e JOIN l ON e.mu = l.id)
    SELECT id, cluster FROM l
    """
