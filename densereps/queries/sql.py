"""Pieces of DuckDB SQL: point sets, density states, components, samples; independent of the DataFrame operators."""

from __future__ import annotations

from densereps.sources.points import recipe


def points(name: str, into: str = "p") -> str:
    return f"{into} AS ({recipe(name, 'duck')})"


def sample(source: str, seed: int, first: int, last: int, into: str) -> str:
    """The places first to last - 1 of the permutation."""
    return (
        f"{into} AS (SELECT id, x, y, rank FROM (SELECT *, row_number() OVER (ORDER BY md5('{seed}:' || id), id) - 1 AS rank FROM {source}) "
        f"WHERE rank >= {first} AND rank < {last})"
    )


def pairs(a: str, b: str, eps: float, into: str) -> str:
    d2 = "(a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)"
    return f"{into} AS (SELECT a.id AS src, b.id AS dst, {d2} AS d2 FROM {a} a, {b} b WHERE {d2} <= {eps} * {eps})"


def density(source: str, eps: float, threshold: int, s: str = "") -> str:
    """CTEs pr, c, st, cc, lab (each with suffix s): pairs, counts, states, components of cores, all labels."""
    return f"""
{pairs(source, source, eps, "pr" + s)},
c{s} AS (SELECT src AS id, count(*) AS n_eps FROM pr{s} GROUP BY src),
st{s} AS (SELECT id, n_eps, CASE WHEN n_eps >= {threshold} THEN 'core' WHEN EXISTS (SELECT 1 FROM pr{s} JOIN c{s} k ON k.id = pr{s}.dst
          WHERE pr{s}.src = c{s}.id AND k.n_eps >= {threshold}) THEN 'border' ELSE 'noise' END AS state FROM c{s}),
e{s} AS (SELECT src, dst FROM pr{s} JOIN st{s} u ON u.id = src JOIN st{s} v ON v.id = dst WHERE u.state = 'core' AND v.state = 'core'),
cc{s}(id, cluster) USING KEY (id) AS (SELECT id, id FROM st{s} WHERE state = 'core' UNION
     SELECT e{s}.dst, min(cc{s}.cluster) FROM cc{s} JOIN e{s} ON cc{s}.id = e{s}.src JOIN recurring.cc{s} AS r ON r.id = e{s}.dst
     WHERE cc{s}.cluster < r.cluster GROUP BY e{s}.dst),
bd{s} AS (SELECT src AS id, min(cluster) AS cluster FROM pr{s} JOIN st{s} ON st{s}.id = src AND state = 'border' JOIN cc{s} ON cc{s}.id = dst GROUP BY src),
lab{s} AS (SELECT id, n_eps, state, coalesce(cc{s}.cluster, bd{s}.cluster, -1) AS cluster FROM st{s} LEFT JOIN cc{s} USING (id) LEFT JOIN bd{s} USING (id))"""


def recursive(*ctes: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(ctes)


def reps(lab: str, tau: float, into: str = "rep") -> str:
    return (
        f"{into} AS (SELECT id, cluster, n_eps FROM (SELECT *, max(n_eps) OVER (PARTITION BY cluster) AS top FROM {lab} WHERE state = 'core') "
        f"WHERE n_eps = top OR n_eps * 1.0 / top <= {tau})"
    )


def nearest(points_: str, rep: str, into: str) -> str:
    """Labels by the nearest representative, ties to the smaller id; rep has id, cluster, x, y."""
    return (
        f"{into} AS (SELECT id, cluster FROM (SELECT t.id, r.cluster, row_number() OVER (PARTITION BY t.id ORDER BY "
        f"(t.x - r.x) * (t.x - r.x) + (t.y - r.y) * (t.y - r.y), r.id) AS k FROM {points_} t, {rep} r) WHERE k = 1)"
    )


def entropy_nmi(rows: str, a: str, b: str) -> str:
    """SELECT n, nmi over rows with labels a and b; geometric mean."""
    return f"""
SELECT n, CASE WHEN ha * hb > 1e-24 THEN round((ha + hb - hab) / sqrt(ha * hb), 6) WHEN ha < 1e-12 AND hb < 1e-12 THEN 1.0 ELSE 0.0 END AS nmi FROM
(SELECT (SELECT count(*) FROM {rows}) AS n,
  (SELECT -sum(k * 1.0 / t * ln(k * 1.0 / t)) FROM (SELECT count(*) AS k, sum(count(*)) OVER () AS t FROM {rows} GROUP BY {a})) AS ha,
  (SELECT -sum(k * 1.0 / t * ln(k * 1.0 / t)) FROM (SELECT count(*) AS k, sum(count(*)) OVER () AS t FROM {rows} GROUP BY {b})) AS hb,
  (SELECT -sum(k * 1.0 / t * ln(k * 1.0 / t)) FROM (SELECT count(*) AS k, sum(count(*)) OVER () AS t FROM {rows} GROUP BY {a}, {b})) AS hab)"""
