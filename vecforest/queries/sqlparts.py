"""Common table expressions for the DuckDB side; they compute from the base tables with the same coefficients."""

from __future__ import annotations

import numpy as np


def number(x: float) -> str:
    return f"CAST({float(x)!r} AS DOUBLE)"


def numbers(xs) -> str:
    return "CAST([" + ",".join(repr(float(x)) for x in xs) + "] AS DOUBLE[])"


VECTORS = "v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e, label FROM embeddings)"
QUERIES = "q AS (SELECT vec_id AS query_id, e AS qe FROM v WHERE vec_id % 100 = 0)"
#: Pairs of each query with all other vectors; d is the true distance.
PAIRS = "d AS (SELECT query_id, vec_id, round(list_distance(e, qe), 9) AS dist FROM v, q WHERE vec_id <> query_id)"


def coefficients(matrix: np.ndarray, K: int, name: str = "a") -> str:
    rows = ",".join(f"({i // K + 1},{i % K + 1},{numbers(r)})" for i, r in enumerate(matrix))
    return f"{name}(space, dim, c) AS (VALUES {rows})"


#: Vectors that a tree can hold: finite, and of the greatest length.
FIT_VECTORS = "v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e, label FROM embeddings WHERE len(embedding) = (SELECT max(len(embedding)) FROM embeddings) AND len(list_filter(embedding, lambda z: isfinite(z))) = len(embedding))"


def projected(name: str = "pr", coef: str = "a", used: str = "c") -> str:
    return f"{name} AS (SELECT vec_id, space, dim, round(list_dot_product(e, {used}), 9) AS x FROM v, {coef})"


def proximity(kind: str, w: float = 1.0, order: int = 1) -> str:
    """pq(query_id, vec_id, space, p)."""
    agg = {
        "l2": "round(sqrt(sum((o.x - s.x) * (o.x - s.x))), 9)",
        "linf": f"round(2 * max(abs(o.x - s.x)) / {number(w)}, 9)",
        "kth": f"round(list_sort(list(abs(o.x - s.x)))[{order}], 9)",
    }[kind]
    return f"pq AS (SELECT s.vec_id AS query_id, o.vec_id, o.space, {agg} AS p FROM pr o JOIN pr s ON o.space = s.space AND o.dim = s.dim AND s.vec_id % 100 = 0 AND o.vec_id <> s.vec_id GROUP BY ALL)"


def need(beta: float, k: int) -> str:
    return f"CAST(ceil(round({number(beta)} * n + {k}, 9)) AS BIGINT)"


def radii_by_budget(beta: float, k: int) -> str:
    """rt(query_id, t, rp): one round at the least radius that fills the budget."""
    return f"""m AS (SELECT query_id, vec_id, min(p) AS p FROM pq GROUP BY ALL),
nn AS (SELECT query_id, count(*) AS n FROM m GROUP BY ALL),
rt AS (SELECT query_id, 0 AS t, p AS rp FROM (SELECT m.query_id, p, row_number() OVER (PARTITION BY m.query_id ORDER BY p) AS r, n FROM m JOIN nn USING (query_id)) WHERE r = least({need(beta, k)}, n))"""


def radii_fixed(first: float, c: float, rounds: int) -> str:
    rows = ",".join(f"({t},{number(r)})" for t, r in enumerate(first * np.power(c, np.arange(rounds))))
    return f"""nn AS (SELECT query_id, count(DISTINCT vec_id) AS n FROM pq GROUP BY ALL),
g(t, rp) AS (VALUES {rows}), rt AS (SELECT query_id, t, rp FROM q, g)"""


def stopped(L: int, k: int, c: float, eps: float, beta: float, rounds: int) -> str:
    """en(query_id, vec_id, e) entry steps; st(query_id, s) stops; po: the pool with distances."""
    return f"""ent AS (SELECT pq.query_id, vec_id, space, min(t) AS t FROM pq JOIN rt ON pq.query_id = rt.query_id AND p <= rp GROUP BY ALL),
en AS (SELECT query_id, vec_id, min(t * {L} + space) AS e FROM ent GROUP BY ALL),
cu AS (SELECT query_id, e, sum(count(*)) OVER (PARTITION BY query_id ORDER BY e) AS upto FROM en GROUP BY query_id, e),
sb AS (SELECT cu.query_id, min(e) AS s FROM cu JOIN nn USING (query_id) WHERE upto >= least({need(beta, k)}, n) GROUP BY ALL),
nr AS (SELECT en.query_id, vec_id, greatest((e - 1) // {L}, min(t)) AS t FROM en JOIN d USING (query_id, vec_id) JOIN rt ON rt.query_id = en.query_id AND dist <= {number(c)} * (rp / {number(eps)}) GROUP BY en.query_id, vec_id, e),
cn AS (SELECT query_id, t, sum(count(*)) OVER (PARTITION BY query_id ORDER BY t) AS upto FROM nr GROUP BY query_id, t),
sn AS (SELECT query_id, (min(t) + 1) * {L} AS s FROM cn WHERE upto >= {k} GROUP BY ALL),
st AS (SELECT q.query_id, least(coalesce(sb.s, {rounds * L}), coalesce(sn.s, {rounds * L})) AS s FROM q LEFT JOIN sb USING (query_id) LEFT JOIN sn USING (query_id)),
po AS (SELECT en.query_id, en.vec_id, e, dist FROM en JOIN st ON st.query_id = en.query_id AND e <= s JOIN d ON d.query_id = en.query_id AND d.vec_id = en.vec_id)"""


def best(k: int, source: str = "po", name: str = "res") -> str:
    return f"{name} AS (SELECT query_id, rank, vec_id, dist FROM (SELECT query_id, vec_id, dist, row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id) AS rank FROM {source}) WHERE rank <= {k})"


def truth(k: int) -> str:
    return best(k, "d", "truth")


def edges(regions: int, source: str = "pr", name: str = "ed") -> str:
    """ed(space, dim, z, edge) for z = 0..regions: outer edges from all rows, inner ones by rank."""
    return f"""rk AS (SELECT space, dim, x, row_number() OVER (PARTITION BY space, dim ORDER BY x) AS r, count(*) OVER (PARTITION BY space, dim) AS m FROM {source}),
{name} AS (SELECT space, dim, z, x AS edge FROM rk, (SELECT unnest(range(1, {regions})) AS z) WHERE r = least(m, z * m // {regions} + 1)
UNION ALL SELECT space, dim, 0, min(x) FROM pr GROUP BY space, dim UNION ALL SELECT space, dim, {regions}, max(x) FROM pr GROUP BY space, dim)"""


def symbols(regions: int, source: str = "ed", name: str = "sy") -> str:
    return f"""il AS (SELECT space, dim, list(edge) AS es FROM {source} WHERE z BETWEEN 1 AND {regions - 1} GROUP BY ALL),
{name} AS (SELECT vec_id, space, dim, x, len(list_filter(es, lambda z: z <= x)) AS s FROM pr JOIN il USING (space, dim))"""


def trees(K: int, max_size: int, bits: int = 8) -> str:
    """tr(space, path, c, b): each point in each node that holds it, by codes c; b is how many bits a dimension has used there."""
    each = lambda x: "[" + ",".join(x.format(j=j) for j in range(1, K + 1)) + "]"
    even = ",".join(f"CASE WHEN b[{j}] < {bits} THEN (abs(2 * o[{j}] - n) * {bits} + b[{j}]) * {K} + {j - 1} END" for j in range(1, K + 1))
    same = f"{bits} - CASE WHEN xor(lo[j], hi[j]) = 0 THEN 0 ELSE length(bin(xor(lo[j], hi[j]))) END"
    return f"""co AS (SELECT vec_id, space, list(CAST(s AS INTEGER) ORDER BY dim) AS c FROM sy GROUP BY vec_id, space),
tr AS (SELECT space, array_to_string(list_transform(c, lambda s: s >> {bits - 1}), '') AS path, c, list_transform(c, lambda s: 1) AS b FROM co
UNION ALL SELECT space, CASE WHEN split THEN path || '|' || (h - 1) || ':' || ((c[h] >> ({bits - 1} - b[h])) & 1) ELSE path END, c,
list_transform(range(1, {K + 1}), lambda j: CASE WHEN NOT split THEN greatest(b[j], {same}) WHEN j = h THEN b[j] + 1 ELSE b[j] END)
FROM (SELECT *, o[h] NOT IN (0, n) AS split FROM (SELECT *, CAST(best % {K} AS INTEGER) + 1 AS h FROM (SELECT *, least({even}) AS best FROM
(SELECT *, count(*) OVER w AS n, {each(f"CAST(sum((c[{{j}}] >> greatest({bits - 1} - b[{{j}}], 0)) & 1) OVER w AS BIGINT)")} AS o, {each("min(c[{j}]) OVER w")} AS lo, {each("max(c[{j}]) OVER w")} AS hi FROM tr WINDOW w AS (PARTITION BY space, path))
WHERE n > {max_size}) WHERE best IS NOT NULL)))"""


def with_(*parts: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n"
