"""DuckDB statements for the core queries, from the raw tables."""

from __future__ import annotations

K = 8

#: All ordered pairs with their distance; 500 vectors at the scale that is checked.
PAIRS = """
v AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings),
p AS (SELECT a.vec_id AS src, b.vec_id AS dst, list_distance(a.x, b.x) AS dist FROM v a JOIN v b ON a.vec_id <> b.vec_id)
"""


def top(source: str, k: int, where: str = "true", keep: str = "src, dst, dist") -> str:
    return f"SELECT {keep}, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS rank FROM {source} WHERE {where} QUALIFY rank <= {k}"


def graph(k: int, h: int | None = None) -> str:
    return top("p", k, f"src % {h} = dst % {h}" if h else "true")


def exact_graph(k: int, name: str = "g") -> str:
    return f"WITH {PAIRS}, {name} AS ({graph(k)})"


EXACT_KNN10 = """
WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings),
d AS (SELECT q.vec_id AS q_id, b.vec_id, {dist} AS d FROM v q JOIN v b ON q.vec_id % 11 = 7 AND b.vec_id % 11 <> 7),
r AS (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY d, vec_id)::INTEGER AS rank FROM d)
SELECT q_id, rank, vec_id, round({out}, 6) AS {name} FROM r WHERE rank <= 10
"""


def knn10(dist: str, name: str = "dist", out: str = "d") -> str:
    return EXACT_KNN10.format(dist=dist, name=name, out=out)


def lifted(h: int, k: int = K, fresh: str = "") -> str:
    """Tables ``own`` and ``lifted`` on exact inputs with the exact nearest of each foreign part."""
    pool = -(-k // (h - 1))
    return f"""WITH {PAIRS},
own AS (SELECT src, dst, dist FROM ({graph(k, h)})),
far AS (SELECT src, dst, dist, row_number() OVER (PARTITION BY src, dst % {h} ORDER BY dist, dst) AS r FROM p WHERE src % {h} <> dst % {h} QUALIFY r <= {pool}),
lifted AS ({top("(SELECT src, dst, dist FROM own UNION ALL SELECT src, dst, dist FROM far)", k)}){fresh}"""


def lift_result(h: int) -> str:
    return lifted(h) + " SELECT src, dst, round(dist, 6) AS dist, rank::INTEGER AS rank FROM lifted"


#: The arithmetic start: the nearest half of the own list, and foreign ids by a formula that flips parity.
START = f"""
own AS (SELECT src, dst, dist FROM ({top("p", K // 2, "src % 2 = dst % 2")})),
start AS (
  SELECT src, dst, dist, true AS is_new FROM own
  UNION ALL
  SELECT p.src, p.dst, p.dist, true FROM range({K - K // 2}) AS j(j) JOIN p ON p.dst = (p.src * 17 + 62 * j.j + 1) % (SELECT count(*) FROM v)
)"""


def round_of(before: str, after: str, scope: str = "cross") -> str:
    """CTEs for one refinement round."""
    cross = "AND a.member % 2 <> b.member % 2" if scope == "cross" else ""
    b = before
    return f"""
pool_{after} AS (
  SELECT "pivot", member, bool_or(is_new) AS is_new FROM (
    SELECT src AS "pivot", dst AS member, is_new FROM {b} UNION ALL SELECT dst, src, is_new FROM {b}) GROUP BY "pivot", member),
pair_{after} AS (
  SELECT DISTINCT a.member AS x, b.member AS y FROM pool_{after} a JOIN pool_{after} b ON a."pivot" = b."pivot" AND a.member < b.member AND (a.is_new OR b.is_new) {cross}),
offer_{after} AS (
  SELECT p.src, p.dst, p.dist FROM pair_{after} JOIN p ON (p.src = x AND p.dst = y) OR (p.src = y AND p.dst = x)),
{after} AS (
  SELECT src, dst, dist, is_new FROM (
    SELECT src, dst, dist, bool_and(is_new) AS is_new FROM (
      SELECT src, dst, dist, false AS is_new FROM {b} UNION ALL SELECT src, dst, dist, true FROM offer_{after}) GROUP BY src, dst, dist)
  QUALIFY row_number() OVER (PARTITION BY src ORDER BY dist, dst) <= {K})"""


def refined(rounds: int, scope: str = "cross") -> str:
    out, before = f"WITH {PAIRS}, {START}", "start"
    for i in range(1, rounds + 1):
        out += "," + round_of(before, f"r{i}", scope)
        before = f"r{i}"
    return out


def thinned(source: str, rule: str, alpha: float = 1.2, tau: float = 0.02, name: str = "t") -> str:
    """Recursive CTE ``{name}``: neighbours one by one, near to far, against those kept. ``source`` has src, dst, dist, rank."""
    hides = {
        "kept": "d.dist <= n.dist",
        "alpha": f"{alpha} * d.dist <= n.dist",
        "tau": f"w.dist < n.dist AND d.dist < n.dist - 3 * {tau}",
    }
    if rule == "lune":
        return f"""
deg AS (SELECT dst AS id, count(*) AS indeg FROM {source} GROUP BY dst),
{name} AS (
  SELECT n.src, n.dst, n.dist FROM {source} n JOIN deg ON deg.id = n.dst
  WHERE deg.indeg = 1 OR NOT EXISTS (
    SELECT 1 FROM {source} w JOIN p d ON d.src = w.dst AND d.dst = n.dst WHERE w.src = n.src AND w.rank < n.rank AND w.dist < n.dist AND d.dist < n.dist))"""
    return f"""
deg AS (SELECT dst AS id, count(*) AS indeg FROM {source} GROUP BY dst),
clash AS (
  SELECT n.src, n.rank AS v, list(w.rank) AS by FROM {source} n JOIN {source} w ON w.src = n.src AND w.rank < n.rank
  JOIN p d ON d.src = w.dst AND d.dst = n.dst WHERE {hides[rule]} GROUP BY n.src, n.rank),
walk AS (
  SELECT src, 0::BIGINT AS pos, []::BIGINT[] AS kept FROM (SELECT DISTINCT src FROM {source})
  UNION ALL
  SELECT w.src, n.rank, CASE WHEN deg.indeg = 1 OR c.by IS NULL OR NOT list_has_any(w.kept, c.by) THEN list_append(w.kept, n.rank) ELSE w.kept END
  FROM walk w JOIN {source} n ON n.src = w.src AND n.rank = w.pos + 1 JOIN deg ON deg.id = n.dst LEFT JOIN clash c ON c.src = n.src AND c.v = n.rank),
{name} AS (
  SELECT n.src, n.dst, n.dist FROM (SELECT src, arg_max(kept, pos) AS kept FROM walk GROUP BY src) f JOIN {source} n ON n.src = f.src AND list_contains(f.kept, n.rank))"""


def recursive(sql: str) -> str:
    return sql.replace("WITH ", "WITH RECURSIVE ", 1)


def back(source: str, k: int, name: str = "b") -> str:
    return f"""
{name} AS ({top(f"(SELECT DISTINCT src, dst, dist FROM (SELECT src, dst, dist FROM {source} UNION ALL SELECT dst, src, dist FROM {source}))", k)})"""


EDGE_OUT = " SELECT src, dst, round(dist, 6) AS dist FROM {}"
RANK_OUT = " SELECT src, dst, round(dist, 6) AS dist, rank::INTEGER AS rank FROM {}"


def composition(h: int, k: int = 16) -> str:
    return f"""WITH {PAIRS}, f AS ({graph(k)}), s AS ({graph(k, h)})
SELECT {h} AS h, avg((s.src IS NOT NULL)::INT)::DOUBLE AS kept, avg((s.src IS NULL AND f.src % {h} = f.dst % {h})::INT)::DOUBLE AS new_same,
  avg((s.src IS NULL AND f.src % {h} <> f.dst % {h})::INT)::DOUBLE AS new_cross
FROM f LEFT JOIN s ON f.src = s.src AND f.dst = s.dst"""


REACH = """,
start AS (SELECT vec_id FROM (
  SELECT vec_id, list_distance(x, (SELECT list(m ORDER BY i) FROM (SELECT i, avg(x[i]) AS m FROM v, range(1, 65) AS t(i) GROUP BY i))) AS d FROM v) ORDER BY d, vec_id LIMIT 1),
reach AS (SELECT vec_id AS id FROM start UNION SELECT g.dst FROM reach JOIN g ON g.src = reach.id)
"""

SCC = """,
far AS (SELECT src AS a, dst AS b FROM g UNION SELECT far.a, g.dst FROM far JOIN g ON g.src = far.b)
SELECT count(DISTINCT least(id, coalesce(low, id)))::BIGINT AS n_scc FROM (
  SELECT v.vec_id AS id, (SELECT min(x.b) FROM far x WHERE x.a = v.vec_id AND EXISTS (SELECT 1 FROM far y WHERE y.a = x.b AND y.b = v.vec_id)) AS low FROM v)
"""


def changed(r: int, form: str) -> str:
    """Exact lift of all vectors (part 0) and the multiples of r (part 1): ``delete`` drops those, ``overlap`` keeps one copy of each."""
    if form == "delete":
        return f"""WITH {PAIRS}, g AS ({top("p", K, f"src % {r} <> 0 AND dst % {r} <> 0")}) SELECT src, dst, round(dist, 6) AS dist FROM g"""
    return f"""WITH {PAIRS}, g AS ({graph(K)}) SELECT src, dst, round(dist, 6) AS dist FROM g"""
