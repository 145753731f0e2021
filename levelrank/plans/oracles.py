"""SQL texts that state the same results for an independent engine.

``partition_sql`` says components and levels by reachability and recursive fixpoints,
``rank_sql`` the ranks as a power series. Both take any edge query.
"""

from __future__ import annotations

from levelrank.sources import generate as G
from levelrank.sources.tables import ORACLE

C = 0.85
TERMS = 260


def figure_sql() -> str:
    """The worked example of eight vertices over every eight parts with keys in a row; text of both engines."""
    rows = ((1, 2), (1, 3), (2, 4), (3, 5), (3, 6), (2, 6), (5, 6), (7, 8), (4, 2), (8, 7), (2, 7))
    return "SELECT a.p_partkey AS src, b.p_partkey AS dst FROM (VALUES " + ", ".join(f"({a}, {b})" for a, b in rows) + ") t(x, y) JOIN part a ON a.p_partkey % 8 = x - 1 JOIN part b ON b.p_partkey = a.p_partkey + y - x"


def generated_sql(dense: bool, factor: int = 1) -> str:
    """The generator as a recursive pointer chase over the size of ``part``."""
    div = lambda s: s.replace(" div ", " // ")
    h = lambda x, s: div(G.mixed(x, s))
    first = lambda e: div(G._first_of(e))
    seeds = ", ".join(f"({i}, {v})" for i, v in enumerate(v for p in G.seed_pairs() for v in p))
    kept = "(CASE WHEN d <= 1 THEN 0 ELSE length(bin(d - 1)) END)" if dense else f"({h('src', G.COUNT_SALT)}) % 3"
    two = 2 * G.SEED_EDGES
    return f"""(WITH RECURSIVE size AS (SELECT count(*) * {factor} AS n FROM part),
    seeds(i, v) AS (VALUES {seeds}),
    started AS (SELECT unnest(range({G.SEED_EDGES}, {G.SEED_EDGES} + greatest(0, (n - {G.SEED_VERTICES})) * {G.LINKS})) AS e FROM size),
    chase AS (SELECT e, ({h('e', G.LINK_SALT)}) % {first('e')} AS t FROM started
      UNION ALL SELECT e, ({h('t // 2', G.LINK_SALT)}) % {first('t // 2')} FROM chase WHERE t >= {two} AND t % 2 = 1),
    ended AS (SELECT e, t FROM chase WHERE t < {two} OR t % 2 = 0),
    half AS (SELECT {G.SEED_VERTICES} + (e - {G.SEED_EDGES}) // {G.LINKS} AS a, CASE WHEN t < {two} THEN s.v ELSE {G.SEED_VERTICES} + (t // 2 - {G.SEED_EDGES}) // {G.LINKS} END AS b FROM ended LEFT JOIN seeds s ON s.i = t
      UNION ALL SELECT x.v, y.v FROM seeds x JOIN seeds y ON y.i = x.i + 1 AND x.i % 2 = 0),
    und AS (SELECT DISTINCT least(a, b) AS a, greatest(a, b) AS b FROM half WHERE a <> b),
    near AS (SELECT a AS src, b AS dst FROM und UNION ALL SELECT b, a FROM und),
    ranked AS (SELECT src, dst, count(*) OVER (PARTITION BY src) AS d, row_number() OVER (PARTITION BY src ORDER BY {h('src * 1000003 + dst', G.KEEP_SALT)}, dst) AS r FROM near)
    SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM ranked WHERE r <= {kept})"""


def copies_sql(one: str, copies: int = 10) -> str:
    return f"SELECT src + k * {G.COPY_STRIDE} AS src, dst + k * {G.COPY_STRIDE} AS dst FROM ({one}) o, range({copies}) t(k)"


def bridged_sql(one: str, extra: int = 20) -> str:
    return f"""SELECT src, dst FROM ({copies_sql(one)}) c UNION ALL
    (WITH one AS ({one}), ids AS (SELECT id, row_number() OVER (ORDER BY id) - 1 AS p, count(*) OVER () AS n FROM (SELECT src AS id FROM one UNION SELECT dst FROM one) t)
    SELECT a.id + (i % 10) * {G.COPY_STRIDE} AS src, b.id + ((i * 3 + 1) % 10) * {G.COPY_STRIDE} AS dst
    FROM range({extra}) w(i) JOIN ids a ON a.p = (i * 7919) % a.n JOIN ids b ON b.p = (i * 104729 + 1) % b.n)"""


def edge_sql(graph: str) -> str:
    if graph == "figure_example":
        return figure_sql()
    if graph in ("pa_sparse", "pa_dense"):
        return f"SELECT * FROM {generated_sql(graph == 'pa_dense')} g"
    if graph.endswith("_x10"):
        return copies_sql(edge_sql(graph[:-4]))
    if graph.endswith("_x10_bridged"):
        return bridged_sql(edge_sql(graph[: -len("_x10_bridged")]))
    return ORACLE[graph]


def vertex_sql(graph: str) -> str | None:
    return "SELECT CAST(unnest(range(count(*))) AS BIGINT) AS id FROM part" if graph.startswith("pa_") else None


def base(edges: str, vertices: str | None = None) -> str:
    more = f" UNION {vertices}" if vertices else ""
    return f"""WITH RECURSIVE e0 AS MATERIALIZED (SELECT DISTINCT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM ({edges}) q),
    v AS MATERIALIZED (SELECT src AS id FROM e0 UNION SELECT dst FROM e0{more}),
    e AS MATERIALIZED (SELECT src, dst FROM e0 WHERE src <> dst)"""


def partition_sql(edges: str, select: str, vertices: str | None = None) -> str:
    """``select`` over part(id, component, kind, size, level, scc, scc_level), e, dag(a, b, cost)."""
    return base(edges, vertices) + f""",
    reach(a, b) AS (SELECT id, id FROM v UNION SELECT r.a, e.dst FROM reach r JOIN e ON r.b = e.src),
    sets AS MATERIALIZED (SELECT x.a AS id, min(x.b) AS scc FROM reach x JOIN reach y ON x.a = y.b AND x.b = y.a GROUP BY x.a),
    nodes AS MATERIALIZED (SELECT scc, count(*) > 1 AS multi FROM sets GROUP BY scc),
    dag AS MATERIALIZED (SELECT DISTINCT x.scc AS a, y.scc AS b, CASE WHEN p.multi OR q.multi THEN 1 ELSE 0 END AS cost
      FROM e JOIN sets x ON e.src = x.id JOIN sets y ON e.dst = y.id JOIN nodes p ON p.scc = x.scc JOIN nodes q ON q.scc = y.scc WHERE x.scc <> y.scc),
    lv(scc, level) AS (SELECT scc, 0 FROM nodes UNION SELECT dag.a, lv.level + dag.cost FROM lv JOIN dag ON dag.b = lv.scc),
    level AS MATERIALIZED (SELECT scc, max(level) AS level FROM lv GROUP BY scc),
    pl(scc, level) AS (SELECT scc, 0 FROM nodes UNION SELECT dag.a, pl.level + 1 FROM pl JOIN dag ON dag.b = pl.scc),
    plain AS MATERIALIZED (SELECT scc, max(level) AS level FROM pl GROUP BY scc),
    tie AS MATERIALIZED (SELECT a, b FROM dag JOIN level x ON x.scc = a JOIN level y ON y.scc = b WHERE cost = 0 AND x.level = y.level),
    both_ AS MATERIALIZED (SELECT a, b FROM tie UNION SELECT b, a FROM tie),
    lab(scc, l) AS (SELECT scc, scc FROM nodes UNION SELECT both_.b, lab.l FROM lab JOIN both_ ON lab.scc = both_.a WHERE lab.l < both_.b),
    comp AS MATERIALIZED (SELECT scc, min(l) AS component FROM lab GROUP BY scc),
    part AS MATERIALIZED (SELECT s.id, c.component, CASE WHEN n.multi THEN 'scc' ELSE 'cac' END AS kind, count(*) OVER (PARTITION BY c.component) AS size, CAST(l.level AS INTEGER) AS level, s.scc, CAST(p.level AS INTEGER) AS scc_level
      FROM sets s JOIN nodes n ON n.scc = s.scc JOIN level l ON l.scc = s.scc JOIN plain p ON p.scc = s.scc JOIN comp c ON c.scc = s.scc)
    {select}"""


def series_sql(edges: str, select: str, vertices: str | None = None, c: float = C, terms: int = TERMS, weight: str = "1.0", loops: bool = False, prob: str | None = None) -> str:
    """``select`` over r(k, id, term), ranks(id, rank), prob(src, dst, p); ``weight`` is an expression of id, or of a column w of ``wt``."""
    kept = "e0" if loops else "e"
    probs = prob or f"SELECT src, dst, 1.0::DOUBLE / count(*) OVER (PARTITION BY src) AS p FROM {kept}"
    return base(edges, vertices) + f""",
    prob AS MATERIALIZED ({probs}),
    r(k, id, term) AS (SELECT 0, id, ({weight})::DOUBLE FROM v UNION ALL SELECT r.k + 1, prob.dst, sum(r.term * prob.p * {c}) FROM r JOIN prob ON r.id = prob.src WHERE r.k < {terms} GROUP BY r.k, prob.dst),
    ranks AS (SELECT id, sum(term) AS rank FROM r GROUP BY id)
    {select}"""


RANK_OUT = "SELECT id, CAST(floor(rank * 1e6 + 0.2718281) AS BIGINT) AS rank_e6 FROM ranks"


def rank_sql(graph: str, **how) -> str:
    return series_sql(edge_sql(graph), RANK_OUT, vertex_sql(graph), **how)
