"""DuckDB SQL for small dense algebra, so that oracles go another way than the engine."""

from __future__ import annotations


def proximity_sql(view: str, similarity: str, d: float, stats: str = "") -> str:
    """CTEs up to a(i, j, v), the scaled proximity of the ratings view."""
    head = f"r AS ({view}), n AS (SELECT count(DISTINCT user_id) AS n FROM r), it AS (SELECT item_id, sqrt(sum(rating * rating)) AS norm, count(*) AS k, sum(rating) AS s1, sum(rating * rating) AS s2 FROM r GROUP BY 1), "
    head += "co AS (SELECT x.item_id AS i, y.item_id AS j, sum(x.rating * y.rating) AS dot, count(*) AS both FROM r x JOIN r y ON x.user_id = y.user_id GROUP BY 1, 2), ".replace(" AS both", " AS b2")
    value = {
        "cosine": "coalesce(dot, 0) / (p.norm * q.norm)",
        "pearson": "(coalesce(dot, 0) / n.n - p.s1 * q.s1 / n.n / n.n) / sqrt((p.s2 / n.n - p.s1 * p.s1 / n.n / n.n) * (q.s2 / n.n - q.s1 * q.s1 / n.n / n.n))",
        "jaccard": "coalesce(b2 * 1.0 / (p.k + q.k - b2), 0)",
    }[similarity]
    return head + f"a AS (SELECT p.item_id AS i, q.item_id AS j, pow(p.norm, {d}) * ({value}) * pow(q.norm, {d}) AS v FROM it p CROSS JOIN it q CROSS JOIN n LEFT JOIN co ON co.i = p.item_id AND co.j = q.item_id)"


def power_sql(rounds: int = 60) -> str:
    """CTE w(i, x): the leading unit vector of a, by power iteration from all ones."""
    return (
        f"pw(k, i, x) AS (SELECT 0, i, CAST(1 AS DOUBLE) FROM (SELECT DISTINCT i FROM a) UNION ALL "
        f"SELECT k + 1, i, y / sqrt(sum(y * y) OVER ()) FROM (SELECT pw.k AS k, a.i AS i, sum(a.v * pw.x) AS y FROM pw JOIN a ON a.j = pw.i WHERE pw.k < {rounds} GROUP BY 1, 2)), "
        f"w AS (SELECT i, x FROM pw WHERE k = {rounds})"
    )


def sign_sql(cut: str, rounds: int = 45) -> str:
    """CTE phi(i, j, v): the projector on the eigenvalues of a above ``cut``, by the matrix-sign iteration."""
    product = "SELECT s.i AS i, y.j AS j, sum(s.v * y.v) AS v FROM (SELECT x.i AS i, y.j AS j, sum(x.v * y.v) AS v FROM sg x JOIN sg y ON x.j = y.i GROUP BY 1, 2) s JOIN sg y ON s.j = y.i GROUP BY 1, 2"
    return (
        f"sh AS (SELECT i, j, v - CASE WHEN i = j THEN ({cut}) ELSE 0 END AS v FROM a), "
        f"sg(k, i, j, v) AS (SELECT 0, i, j, v / (SELECT sqrt(sum(v * v)) FROM sh) FROM sh UNION ALL "
        f"SELECT z.k + 1, z.i, z.j, 1.5 * z.v - 0.5 * c.v FROM sg z JOIN ({product}) c ON c.i = z.i AND c.j = z.j WHERE z.k < {rounds}), "
        f"phi AS (SELECT i, j, (CASE WHEN i = j THEN 1 ELSE 0 END + v) / 2 AS v FROM sg WHERE k = {rounds})"
    )


def inverse_sql(matrix: str, name: str, rounds: int = 40) -> str:
    """CTE ``name``(i, j, v): the inverse of the matrix CTE (i, j, v), by Newton's iteration from the scaled transpose."""
    inner = f"SELECT m.i AS i, x.j AS j, sum(m.v * x.v) AS v FROM {matrix} m JOIN nz x ON m.j = x.i GROUP BY 1, 2"
    return (
        f"nz(k, i, j, v) AS (SELECT 0, j, i, v / ((SELECT max(s) FROM (SELECT sum(abs(v)) AS s FROM {matrix} GROUP BY i)) * (SELECT max(s) FROM (SELECT sum(abs(v)) AS s FROM {matrix} GROUP BY j))) FROM {matrix} UNION ALL "
        f"SELECT x.k + 1, x.i, x.j, 2 * x.v - c.v FROM nz x JOIN (SELECT x.i AS i, b.j AS j, sum(x.v * b.v) AS v FROM nz x JOIN ({inner}) b ON x.j = b.i GROUP BY 1, 2) c ON c.i = x.i AND c.j = x.j WHERE x.k < {rounds}), "
        f"{name} AS (SELECT i, j, v FROM nz WHERE k = {rounds})"
    )


def graph_sql(view: str) -> str:
    """CTEs of the small graph: nodes(i), ad(i, j, v) dense, dg(i, d), lp (Laplacian)."""
    return (
        f"r AS ({view}), e AS (SELECT 'u' || user_id AS a, 'i' || item_id AS b FROM r), ed AS (SELECT a AS i, b AS j FROM e UNION ALL SELECT b, a FROM e), nodes AS (SELECT DISTINCT i FROM ed), "
        "ad AS (SELECT p.i AS i, q.i AS j, CASE WHEN ed.i IS NULL THEN 0.0 ELSE 1.0 END AS v FROM nodes p CROSS JOIN nodes q LEFT JOIN ed ON ed.i = p.i AND ed.j = q.i), "
        "dg AS (SELECT i, sum(v) AS d FROM ad GROUP BY 1), lp AS (SELECT ad.i, ad.j, CASE WHEN ad.i = ad.j THEN d ELSE 0 END - v AS v FROM ad JOIN dg ON dg.i = ad.i), "
        "pm AS (SELECT ad.i, ad.j, v / d AS v FROM ad JOIN dg ON dg.i = ad.i)"
    )


def averaged_sql(t: int) -> str:
    """CTE zt(i, j, v): the mean of the first t powers of pm."""
    return (
        f"pp(k, i, j, v) AS (SELECT 1, i, j, v FROM pm UNION ALL SELECT x.k + 1, x.i, y.j, sum(x.v * y.v) FROM pp x JOIN pm y ON x.j = y.i WHERE x.k < {t} GROUP BY 1, 2, 3), "
        f"zt AS (SELECT i, j, sum(v) / {t} AS v FROM pp GROUP BY 1, 2)"
    )


KERNEL_OUT = "SELECT CAST(substr(k.i, 2) AS INT) AS user_id, substr(k.j, 2) AS item_id, round(k.v, 6) + 0.0 AS score FROM ker k WHERE k.i LIKE 'u%' AND k.j LIKE 'i%'"
