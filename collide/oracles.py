"""DuckDB SQL of the workloads, put together from a few common table expressions. Vectors are long: (id, dim, x)."""

from __future__ import annotations

from .plans.subspaces import SubspacePlan

VECTORS = {
    "emb": (64, "SELECT vec_id AS id, i - 1 AS dim, CAST(floor(CAST(x AS DOUBLE) * 10000 + 0.5) AS BIGINT) AS x FROM (SELECT vec_id, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS i FROM embeddings)"),
    "doc": (64, """SELECT d.doc_id AS id, g.dim, CAST(coalesce(c.c, 0) AS BIGINT) AS x FROM documents d CROSS JOIN (SELECT unnest(range(64)) AS dim) g LEFT JOIN
      (SELECT doc_id, CAST(('0x' || substr(md5(t), 1, 8)) AS BIGINT) % 64 AS dim, count(*) AS c FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(coalesce(text, '')), '[\\x20\\x09-\\x0D]+')) AS t FROM documents) WHERE t <> '' GROUP BY ALL) c
      ON c.doc_id = d.doc_id AND c.dim = g.dim"""),
    "demand": (84, """SELECT p.id, g.dim, CAST(coalesce(c.q, 0) AS BIGINT) AS x FROM (SELECT DISTINCT l_partkey AS id FROM lineitem WHERE (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 BETWEEN 0 AND 83) p CROSS JOIN (SELECT unnest(range(84)) AS dim) g LEFT JOIN
      (SELECT l_partkey AS id, (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS dim, sum(l_quantity) AS q FROM lineitem GROUP BY ALL) c USING (id, dim)"""),
}
_LINE = ["l_quantity * 100", "floor(l_extendedprice / 10 + 0.5)", "floor(l_discount * 10000 + 0.5)", "floor(l_tax * 10000 + 0.5)", "l_linenumber * 500", "date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE))", "ascii(l_returnflag) * 50", "ascii(l_linestatus) * 50"]
VECTORS["line"] = (8, f"SELECT id, dim - 1 AS dim, x FROM (SELECT id, unnest(xs) AS x, generate_subscripts(xs, 1) AS dim FROM (SELECT row_number() OVER (ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS id, [{', '.join(f'CAST({x} AS BIGINT)' for x in _LINE)}] AS xs FROM lineitem))")


def plan_values(plan: SubspacePlan) -> str:
    return ", ".join(f"({i}, {s})" for s, dims in enumerate(plan.dims) for i in dims)


def ceil_share(ratio: float | str) -> str:
    return f"CAST(ceil(CAST({ratio} AS DECIMAL(9, 6)) * (SELECT n FROM n)) AS BIGINT)"


def pool_size(beta: float | str, k: int) -> str:
    return f"greatest({k}, {ceil_share(beta)})"


def base(kind: str, mod: int, rest: int, plan: SubspacePlan | None = None, metric: str = "l2", where: str = "true") -> str:
    """v, p, q, n and, with a plan, parts(qid, id, sub, dist)."""
    d, sql = VECTORS[kind]
    if where != "true":
        sql = f"SELECT * FROM ({sql}) WHERE {where}"
    out = f"WITH v AS ({sql}), p AS (SELECT * FROM v WHERE id % {mod} <> {rest}), q AS (SELECT id AS qid, dim, x FROM v WHERE id % {mod} = {rest}), n AS (SELECT count(DISTINCT id) AS n FROM p)"
    if plan is None:
        plan = SubspacePlan(d, (tuple(range(d)),))
    diff = "abs(p.x - q.x)" if metric == "l1" else "(p.x - q.x) * (p.x - q.x)"
    return out + f", pl(dim, sub) AS (VALUES {plan_values(plan)}), parts AS (SELECT q.qid, p.id, pl.sub, CAST(sum({diff}) AS BIGINT) AS dist FROM p JOIN q USING (dim) JOIN pl USING (dim) GROUP BY ALL), whole AS (SELECT qid, id, sum(dist) AS dist FROM parts GROUP BY ALL)"


def length(metric: str, unit: float, value: str = "dist") -> str:
    return f"round({'sqrt(CAST(' + value + ' AS DOUBLE))' if metric == 'l2' else 'CAST(' + value + ' AS DOUBLE)'}{f' / {unit}' if unit != 1 else ''}, 6)"


def truth(k: int, metric: str = "l2", unit: float = 1.0) -> str:
    return f", truth AS (SELECT qid, CAST(rank AS INTEGER) AS rank, id, {length(metric, unit)} AS distance FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rank FROM whole) WHERE rank <= {k})"


def scores(m: str) -> str:
    return f""", ranked AS (SELECT *, row_number() OVER (PARTITION BY qid, sub ORDER BY dist, id) AS r FROM parts), hits AS (SELECT qid, sub, id FROM ranked WHERE r <= {m}),
      scores AS (SELECT w.qid, w.id, CAST(coalesce(h.c, 0) AS INTEGER) AS score FROM whole w LEFT JOIN (SELECT qid, id, count(*) AS c FROM hits GROUP BY ALL) h USING (qid, id))"""


def result(pool: str, k: int, metric: str, unit: float) -> str:
    return f""", pool AS (SELECT qid, id, score FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS r FROM scores) WHERE r <= {pool}),
      result AS (SELECT qid, CAST(rank AS INTEGER) AS rank, id, {length(metric, unit)} AS distance, score FROM (SELECT qid, id, score, dist, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rank FROM pool JOIN whole USING (qid, id)) WHERE rank <= {k})"""


def scan(kind: str, mod: int, rest: int, plan: SubspacePlan, alpha: float, beta: float, k: int, metric: str = "l2", unit: float = 1.0, where: str = "true") -> str:
    return base(kind, mod, rest, plan, metric, where) + scores(ceil_share(alpha)) + result(pool_size(beta, k), k, metric, unit)


def sweep(kind: str, mod: int, rest: int, plan: SubspacePlan, settings: list[tuple[float, float]], k: int, metric: str, unit: float, first: bool = True) -> str:
    """WITH ... that ends in `measured` (alpha, beta, recall, mre) over all settings."""
    values = ", ".join(f"(CAST({a} AS DOUBLE), CAST({b} AS DOUBLE), {ceil_share(a)}, {pool_size(b, k)})" for a, b in settings)
    return base(kind, mod, rest, plan, metric) + truth(k, metric, unit) + f""", s(alpha, beta, m, pool) AS (SELECT * FROM (VALUES {values})),
      ranked AS (SELECT *, row_number() OVER (PARTITION BY qid, sub ORDER BY dist, id) AS r FROM parts),
      sc AS (SELECT s.alpha, s.beta, s.pool, x.qid, x.id, count(*) FILTER (WHERE x.r <= s.m) AS score, sum(x.dist) AS dist FROM ranked x CROSS JOIN s GROUP BY ALL),
      po AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY alpha, beta, qid ORDER BY score DESC, id) AS pr FROM sc) WHERE pr <= pool),
      res AS (SELECT alpha, beta, qid, rank, id, {length(metric, unit)} AS distance FROM (SELECT *, row_number() OVER (PARTITION BY alpha, beta, qid ORDER BY dist, id) AS rank FROM po) WHERE rank <= {k}),
      nq AS (SELECT count(DISTINCT qid) AS nq FROM q),
      measured AS (SELECT s.alpha, s.beta, (SELECT count(*) FROM res JOIN truth USING (qid, id) WHERE res.alpha = s.alpha AND res.beta = s.beta) / CAST((SELECT nq FROM nq) * {k} AS DOUBLE) AS recall,
        (SELECT round(avg(CASE WHEN t.distance > 0 THEN (r.distance - t.distance) / t.distance WHEN r.distance = 0 THEN 0.0 END), 6) FROM res r JOIN truth t ON r.qid = t.qid AND r.rank = t.rank WHERE r.alpha = s.alpha AND r.beta = s.beta) AS mre FROM s)"""


def cell_index(kind: str, mod: int, rest: int, plan: SubspacePlan, sqrt_k: int, rounds: int, seed: int = 0, metric: str = "l2", parts: int = 2) -> str:
    """Adds c<rounds>(half, cid, dim, x), code(id, half, cid), sizes(sub, c1, c2, n_points). Rounds are written out, and each is
    materialised; means are rounded half up to the grid."""
    halves = ", ".join(f"({i}, {h})" for h, dims in enumerate(plan.parts(parts)) for i in dims)
    far = "abs(ph.x - c.x)" if metric == "l1" else "(ph.x - c.x) * (ph.x - c.x)"
    out = base(kind, mod, rest, plan, metric) + f""", hv(dim, half) AS (VALUES {halves}), ph AS MATERIALIZED (SELECT p.id, hv.half, p.dim, p.x FROM p JOIN hv USING (dim)),
      seeds AS (SELECT id, row_number() OVER (ORDER BY md5('{seed}:' || CAST(id AS VARCHAR)), id) - 1 AS cid FROM (SELECT DISTINCT id FROM p) QUALIFY cid < {sqrt_k}),
      c0 AS MATERIALIZED (SELECT ph.half, s.cid, ph.dim, CAST(ph.x AS DOUBLE) AS x FROM ph JOIN seeds s USING (id))"""
    for t in range(rounds + 1):
        out += f""", a{t} AS MATERIALIZED (SELECT id, half, cid FROM (SELECT ph.id, ph.half, c.cid, sum({far}) AS dist FROM ph JOIN c{t} c ON c.half = ph.half AND c.dim = ph.dim GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY id, half ORDER BY dist, cid) = 1)"""
        if t < rounds:
            out += f""", c{t + 1} AS MATERIALIZED (SELECT c.half, c.cid, c.dim, coalesce(m.x, c.x) AS x FROM c{t} c LEFT JOIN (SELECT a.half, a.cid, ph.dim, floor(CAST(sum(ph.x) AS DOUBLE) / count(*) + 0.5) AS x FROM a{t} a JOIN ph ON ph.id = a.id AND ph.half = a.half GROUP BY ALL) m ON m.half = c.half AND m.cid = c.cid AND m.dim = c.dim)"""
    if parts == 1:
        return out + f""", cells AS (SELECT id, half AS sub, cid AS c1, 0 AS c2 FROM a{rounds}), sizes AS (SELECT sub, c1, c2, count(*) AS n_points FROM cells GROUP BY ALL)"""
    return out + f""", code AS (SELECT * FROM a{rounds}), cells AS (SELECT x.id, x.half // 2 AS sub, x.cid AS c1, y.cid AS c2 FROM code x JOIN code y ON x.id = y.id AND y.half = x.half + 1 WHERE x.half % 2 = 0),
      sizes AS (SELECT sub, c1, c2, count(*) AS n_points FROM cells GROUP BY ALL)"""


def walked(plan: SubspacePlan, rounds: int, m: str, metric: str = "l2", parts: int = 2) -> str:
    """Adds taken(qid, sub, c1, c2, sum_dist, n_points, pop_order) by the sorted walk, and index scores."""
    far = "abs(q.x - c.x)" if metric == "l1" else "(q.x - c.x) * (q.x - c.x)"
    grid = "SELECT x.qid, x.half // 2 AS sub, x.cid AS c1, y.cid AS c2, x.pos AS p1, y.pos AS p2, x.dist + y.dist AS sum_dist FROM ql x JOIN ql y ON x.qid = y.qid AND y.half = x.half + 1 WHERE x.half % 2 = 0"
    if parts == 1:
        grid = "SELECT qid, half AS sub, cid AS c1, 0 AS c2, pos AS p1, 0 AS p2, dist AS sum_dist FROM ql"
    return f""", qd AS (SELECT q.qid, c.half, c.cid, sum({far}) AS dist FROM q JOIN c{rounds} c USING (dim) GROUP BY ALL),
      ql AS (SELECT *, row_number() OVER (PARTITION BY qid, half ORDER BY dist, cid) - 1 AS pos FROM qd),
      grid AS ({grid}),
      run AS (SELECT g.*, coalesce(s.n_points, 0) AS n_points, row_number() OVER w AS pop_order, coalesce(sum(coalesce(s.n_points, 0)) OVER (PARTITION BY g.qid, g.sub ORDER BY g.sum_dist, g.p1, g.p2 ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
        FROM grid g LEFT JOIN sizes s ON s.sub = g.sub AND s.c1 = g.c1 AND s.c2 = g.c2 WINDOW w AS (PARTITION BY g.qid, g.sub ORDER BY g.sum_dist, g.p1, g.p2)),
      taken AS (SELECT qid, CAST(sub AS INTEGER) AS sub, CAST(c1 AS INTEGER) AS c1, CAST(c2 AS INTEGER) AS c2, CAST(sum_dist AS DOUBLE) AS sum_dist, CAST(n_points AS BIGINT) AS n_points, CAST(pop_order AS INTEGER) AS pop_order FROM run WHERE before < {m}),
      ihits AS (SELECT t.qid, c.id, CAST(count(*) AS INTEGER) AS score FROM taken t JOIN cells c ON c.sub = t.sub AND c.c1 = t.c1 AND c.c2 = t.c2 GROUP BY ALL),
      scores AS (SELECT w.qid, w.id, CAST(coalesce(h.score, 0) AS INTEGER) AS score FROM whole w LEFT JOIN ihits h USING (qid, id))"""
