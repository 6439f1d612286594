"""Experiment workloads of the search engine on the given tables, each with the SQL that gives the same rows where there is one."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import evaluate, oracles, theory
from .costmodel import METHODS, predict
from .functions import vectors
from .functions.distances import order_distance, true_distance
from .functions.vectors import VectorSet, held_out
from .operators import blocks
from .operators.candidates import top_scored
from .operators.cellindex import CellIndex, IndexParams, build_cell_index
from .operators.collisions import RANKED_POINTS, collision_scores, exploded, part_distances, scan_scores, subspace_collisions, whole_space_collisions
from .operators.exact import blocks_of, exact_knn, first_k, paired, radius_search
from .operators.scan import SearchParams, collision_scan
from .operators.search import activated_cells, count_hits_postings, indexed_search, score_codes
from .plans.subspaces import SubspacePlan, plan_contiguous, plan_random
from .session import BROADCAST_QUERIES, materialise, share_of

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}

K = 10
GRID = 10000.0
#: kind: (maker, modulus and remainder of the held-out ids, dimension, grid unit)
SETS = {"emb": (vectors.emb_grid, 25, 7, 64, GRID), "doc": (vectors.doc_counts, 50, 3, 64, 1.0), "demand": (vectors.demand, 100, 1, 84, 1.0), "line": (vectors.line, 5000, 1, 8, 1.0)}


def data(spark: SparkSession, sf_dir: str, kind: str) -> VectorSet:
    """A vector set of the tables: derived once and written, so that passes over it do not derive it again."""
    make, mod, rest, d, unit = SETS[kind]
    found = make(spark, sf_dir)
    return held_out(found if kind == "line" else materialise(found, kind), mod, rest, d, unit)  # line is written as it is numbered


def plan_of(kind: str, n_sub: int | None = None) -> SubspacePlan:
    return plan_contiguous(SETS[kind][3], n_sub or (4 if kind == "line" else 8))


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


def _set(kind: str) -> tuple[int, int, float]:
    _, mod, rest, _, unit = SETS[kind]
    return mod, rest, unit


# --- exact search and definitions -------------------------------------------------------------------------------------

for _metric, _name in (("l2", "exact_knn"), ("l1", "exact_knn_l1")):
    query(_name, oracles.base("emb", 25, 7, None, _metric) + oracles.truth(K, _metric, GRID) + " SELECT * FROM truth")(
        lambda s, d, m=_metric: exact_knn(*(v := data(s, d, "emb"), (v.points, v.queries))[1], K, 64, m, GRID)
    )


@query("whole_space_collisions", oracles.base("emb", 25, 7) + f" SELECT qid, id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS r FROM whole) WHERE r <= {oracles.ceil_share(0.05)}")
def _whole(s, d):
    v = data(s, d, "emb")
    return whole_space_collisions(v.points, v.queries, 64, share_of(0.05, v.n))


@query("subspace_collisions", oracles.base("emb", 25, 7, plan_of("emb")) + oracles.scores(oracles.ceil_share(0.05)) + " SELECT qid, CAST(sub AS INTEGER) AS sub, id FROM hits")
def _collisions(s, d):
    v = data(s, d, "emb")
    return subspace_collisions(v.points, v.queries, plan_of("emb"), share_of(0.05, v.n))


@query("collision_scores", oracles.base("emb", 25, 7, plan_of("emb")) + oracles.scores(oracles.ceil_share(0.05)) + " SELECT * FROM scores WHERE score > 0")
def _scores(s, d):
    v = data(s, d, "emb")
    m = share_of(0.05, v.n)
    if blocks.fits(v.n, v.d):
        return blocks.scan(v.points, v.queries, list(plan_of("emb").dims), v.d, m, blocks.scored(1), blocks.SCORED)
    return collision_scores(subspace_collisions(v.points, v.queries, plan_of("emb"), m))


def _scan(kind: str, plan: SubspacePlan, alpha: float, beta: float, metric: str = "l2", select: str = "auto") -> Query:
    return lambda s, d: collision_scan(data(s, d, kind), plan, SearchParams(K, alpha, beta, metric), select)


for _name, _kind, _plan, _alpha, _beta, _metric in (
    ("collision_scan", "emb", plan_of("emb"), 0.1, 0.1, "l2"),
    ("collision_scan_doc", "doc", plan_of("doc"), 0.1, 0.05, "l2"),
    ("collision_scan_l1", "emb", plan_of("emb"), 0.1, 0.1, "l1"),
    ("scan_random_plan", "emb", plan_random(64, 8, 1), 0.1, 0.1, "l2"),
    ("scan_remainder_plan", "demand", plan_of("demand", 8), 0.1, 0.05, "l2"),
):
    query(_name, oracles.scan(_kind, *_set(_kind)[:2], _plan, _alpha, _beta, K, _metric, _set(_kind)[2]) + " SELECT * FROM result")(_scan(_kind, _plan, _alpha, _beta, _metric))
query("collision_scan_by_border", ORACLE_SQL["collision_scan"])(_scan("emb", plan_of("emb"), 0.1, 0.1, select="histogram"))


@query("scan_without_rerank", oracles.base("emb", 25, 7, plan_of("emb")) + oracles.scores(oracles.ceil_share(0.1)) + f" SELECT qid, CAST(r AS INTEGER) AS rank, id, score FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS r FROM scores) WHERE r <= {K}")
def _plain(s, d):
    return collision_scan(data(s, d, "emb"), plan_of("emb"), SearchParams(K, 0.1, 0.1), rank_again=False)


# --- sweeps -----------------------------------------------------------------------------------------------------------


def sweep(v: VectorSet, plan: SubspacePlan, settings: list[tuple[float, float]], k: int = K, metric: str = "l2") -> DataFrame:
    """alpha, beta, recall, mre for all settings from one pass over the distances. Ranks all points: for test-scale studies;
    single settings at scale go through collision_scan."""
    parts = exploded(part_distances(v.points, v.queries, list(plan.dims), metric))
    ranked = parts.withColumn("r", F.row_number().over(Window.partitionBy("qid", "sub").orderBy("dist", "id")))
    alphas = sorted({a for a, _ in settings})
    sums = ranked.groupBy("qid", "id").agg(F.sum("dist").alias("dist"), *[F.sum((F.col("r") <= share_of(a, v.n)).cast("int")).alias(f"s{i}") for i, a in enumerate(alphas)])
    rows = F.array(*[F.struct(F.lit(float(a)).alias("alpha"), F.lit(float(b)).alias("beta"), F.lit(max(k, share_of(b, v.n))).alias("pool"), F.col(f"s{alphas.index(a)}").alias("score")) for a, b in settings])
    each = sums.select("qid", "id", "dist", F.explode(rows).alias("x")).select("qid", "id", "dist", "x.*")
    w = Window.partitionBy("alpha", "beta", "qid")
    pool = each.withColumn("pr", F.row_number().over(w.orderBy(F.col("score").desc(), "id"))).where(F.col("pr") <= F.col("pool"))
    found = pool.withColumn("rank", F.row_number().over(w.orderBy("dist", "id"))).where(F.col("rank") <= k)
    result = found.select("alpha", "beta", "qid", F.col("rank").cast("int").alias("rank"), "id", F.round(true_distance(F.col("dist"), metric, v.unit), 6).alias("distance"))
    truth = exact_knn(v.points, v.queries, k, v.d, metric, v.unit)
    recall = evaluate.recall_at_k(result, truth, k, ("alpha", "beta"))
    return recall.join(evaluate.mean_relative_error(result, truth, ("alpha", "beta")).drop("excluded"), ["alpha", "beta"])


def _sweep_sql(kind: str, plan: SubspacePlan, settings: list, columns: str, metric: str = "l2") -> str:
    mod, rest, unit = _set(kind)
    return oracles.sweep(kind, mod, rest, plan, settings, K, metric, unit) + f" SELECT {columns} FROM measured"


BETAS = [0.001, 0.005, 0.01, 0.05, 0.1, 0.2]
ALPHAS = [0.01, 0.03, 0.05, 0.1, 0.2]
SUBSPACES = [2, 4, 6, 8, 10, 12, 16]

query("scan_recall_grid", _sweep_sql("emb", plan_of("emb"), [(0.05, b) for b in BETAS], "beta, recall"))(lambda s, d: sweep(data(s, d, "emb"), plan_of("emb"), [(0.05, b) for b in BETAS]).select("beta", "recall"))
query("sweep_alpha", _sweep_sql("emb", plan_of("emb"), [(a, 0.1) for a in ALPHAS], "alpha, recall, mre"))(lambda s, d: sweep(data(s, d, "emb"), plan_of("emb"), [(a, 0.1) for a in ALPHAS]).select("alpha", "recall", "mre"))
query("sweep_beta", _sweep_sql("doc", plan_of("doc"), [(0.1, b) for b in BETAS], "beta, recall, mre"))(lambda s, d: sweep(data(s, d, "doc"), plan_of("doc"), [(0.1, b) for b in BETAS]).select("beta", "recall", "mre"))
query("sweep_subspaces", " UNION ALL ".join(f"SELECT * FROM ({_sweep_sql('emb', plan_of('emb', n), [(0.1, 0.1)], f'CAST({n} AS INTEGER) AS n_sub, recall')})" for n in SUBSPACES))(
    lambda s, d: _union([sweep(v, plan_of("emb", n), [(0.1, 0.1)]).select(F.lit(n).alias("n_sub"), "recall") for v in [data(s, d, "emb")] for n in SUBSPACES])
)
query("metric_l1_l2", " UNION ALL ".join(f"SELECT * FROM ({_sweep_sql(kind, plan_of(kind), [(0.1, 0.1)], f'{chr(39)}{kind}{chr(39)} AS dataset, {chr(39)}{m}{chr(39)} AS metric, recall, mre', m)})" for kind in SETS for m in ("l1", "l2")))(
    lambda s, d: _union([sweep(v, plan_of(kind), [(0.1, 0.1)], metric=m).select(F.lit(kind).alias("dataset"), F.lit(m).alias("metric"), "recall", "mre") for kind in SETS for v in [data(s, d, kind)] for m in ("l1", "l2")])
)


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


# --- score curves, dimensionality, theory -----------------------------------------------------------------------------

CURVE = 20


def pareto_curve(v: VectorSet, plan: SubspacePlan, alpha: float = 0.1, buckets: int = CURVE) -> DataFrame:
    if blocks.fits(v.n, v.d):
        sums = blocks.scan(v.points, v.queries, list(plan.dims), v.d, share_of(alpha, v.n), blocks.curve(buckets), blocks.CURVE)
        return sums.groupBy("rank_bucket").agg(F.round(F.sum("total") / F.sum("n"), 6).alias("avg_score"))
    scores = scan_scores(v.points, v.queries, plan, share_of(alpha, v.n), select="rank" if v.n <= RANKED_POINTS else "histogram")
    whole = paired(v.points, v.queries).select("qid", "id", order_distance("vec", "qvec", v.d).alias("dist"))
    return evaluate.score_by_rank(scores, whole, buckets)


def _curve_sql(kind: str, n_sub: int) -> str:
    mod, rest, _ = _set(kind)
    return (
        oracles.base(kind, mod, rest, plan_of(kind, n_sub))
        + oracles.scores(oracles.ceil_share(0.1))
        + f", tr AS (SELECT qid, id, CAST(floor((row_number() OVER (PARTITION BY qid ORDER BY dist, id) - 1) * {CURVE} / CAST(count(*) OVER (PARTITION BY qid) AS DOUBLE)) AS INTEGER) AS rank_bucket FROM whole) SELECT rank_bucket, round(CAST(sum(score) AS DOUBLE) / count(*), 6) AS avg_score FROM tr JOIN scores USING (qid, id) GROUP BY ALL"
    )


for _kind, _n in (("emb", 8), ("doc", 8), ("demand", 10)):
    query(f"pareto_curve_{_kind}", _curve_sql(_kind, _n))(lambda s, d, k=_kind, n=_n: pareto_curve(data(s, d, k), plan_of(k, n)))

query("curve_slope", f"SELECT rank_bucket, round(avg_score - lag(avg_score) OVER (ORDER BY rank_bucket), 6) AS slope FROM ({_curve_sql('doc', 8)})")(
    lambda s, d: pareto_curve(data(s, d, "doc"), plan_of("doc")).select("rank_bucket", F.round(F.col("avg_score") - F.lag("avg_score").over(Window.orderBy("rank_bucket")), 6).alias("slope"))  # CURVE rows
)

LID_K = 50


@query("dataset_summary", " UNION ALL ".join(
    f"SELECT * FROM ({oracles.base(k, *_set(k)[:2]) + oracles.truth(LID_K, 'l2', _set(k)[2])}, far AS (SELECT *, max(distance) OVER (PARTITION BY qid) AS far FROM truth WHERE distance > 0), each AS (SELECT qid, -1 / avg(ln(distance / far)) AS lid FROM far WHERE distance < far GROUP BY qid) SELECT '{k}' AS name, (SELECT n FROM n) AS n, CAST({SETS[k][3]} AS INTEGER) AS d, (SELECT round(avg(lid), 4) FROM each) AS lid)"
    for k in SETS))
def _summary(s, d):
    out = []
    for k in SETS:
        v = data(s, d, k)
        out.append(evaluate.lid_mle(exact_knn(v.points, v.queries, LID_K, v.d, unit=v.unit), LID_K).select(F.lit(k).alias("name"), F.lit(v.n).cast("long").alias("n"), F.lit(v.d).alias("d"), "lid"))
    return _union(out)


query("subspace_moments", oracles.base("demand", 100, 1, plan_of("demand")) + " SELECT CAST(sub AS INTEGER) AS sub, round(avg(dist), 4) AS mean, round(var_pop(dist) / 1e6, 2) AS variance_m FROM parts GROUP BY sub")(
    lambda s, d: theory.subspace_moments((v := data(s, d, "demand")).points, v.queries, plan_of("demand")).select("sub", F.round("mean", 4).alias("mean"), F.round(F.col("variance") / 1e6, 2).alias("variance_m"))
)


@query("ordering_agreement", oracles.base("doc", 50, 3, plan_of("doc")) + oracles.scores(oracles.ceil_share(0.05)) + """, x AS (SELECT qid, id, score, dist FROM scores JOIN whole USING (qid, id))
    SELECT a.score AS high, b.score AS low, count(*) AS pairs, CAST(count(*) FILTER (WHERE a.dist < b.dist) AS DOUBLE) / count(*) AS agreement FROM x a JOIN x b ON a.qid = b.qid AND a.score > b.score GROUP BY ALL""")
def _agreement(s, d):
    v = data(s, d, "doc")
    scores = scan_scores(v.points, v.queries, plan_of("doc"), share_of(0.05, v.n), select="rank" if v.n <= RANKED_POINTS else "histogram")
    return theory.ordering_agreement(scores, paired(v.points, v.queries).select("qid", "id", order_distance("vec", "qvec", 64).alias("dist")), 8)


@query("order_moments")
def _moments(s, d):
    """Formula and data: mean k-th distance over the subspaces, and the bounds."""
    v = data(s, d, "demand")
    m = theory.subspace_moments(v.points, v.queries, plan_of("demand")).agg(F.avg("mean").alias("m"), F.avg("variance").alias("v")).first()
    rows, bound = [], theory.ordering_bound(m["m"], m["v"], 8, 0.05)
    for k in (1, 5, 10):
        mean, var = theory.kth_moments(k, v.n, 8, m["m"], m["v"])
        rows.append((k, mean, var, theory.answer_bound(k, v.n), bound["probability"], bound["side_condition_ok"], theory.alpha_floor(m["m"], m["v"])))
    return s.createDataFrame(rows, "k int, expected double, variance double, answer_bound double, ordering_bound double, side_condition_ok boolean, alpha_floor double")


#: Rows and dimension of each vector set.
_SIZES = """SELECT count(*) AS n, CAST(max(length(embedding)) AS INTEGER) AS d FROM embeddings
  UNION ALL SELECT count(doc_id), 64 FROM documents UNION ALL SELECT count(DISTINCT l_partkey), 84 FROM lineitem UNION ALL SELECT count(l_orderkey), 8 FROM lineitem"""


def _complexity_sql() -> str:
    """The formulas as SQL arithmetic, with the parameters' defaults; K 2500, 8 subspaces, 10 rounds, alpha .05, beta .005."""
    log = "ln({}) / ln(2)"
    pool = f"({log.format('greatest(2.0, 0.005 * n)')})"
    f = {
        ("exact_knn", "index"): "0", ("exact_knn", "space"): "0", ("exact_knn", "query"): "n * d",
        ("scan", "index"): "0", ("scan", "space"): "0", ("scan", "query"): f"n * d + 8 * n * {log.format('n')} + n * {pool} + 0.005 * n * d",
        ("indexed", "index"): "n * (50 * d * 10 + 8)", ("indexed", "space"): "50 * d + n * 8", ("indexed", "query"): f"n * (0.05 * 8 + 0.005 * d + {pool}) + 50 * (d + 0.05 * 50 * {log.format('50')})",
        ("encoded_projection_trees", "index"): "4 * 16 * n * (d + 8)", ("encoded_projection_trees", "space"): "4 * 16 * n", ("encoded_projection_trees", "query"): "n * (0.005 * d + 4 * 16 * 8)",
        ("rotated_product_quantiser", "index"): "n * (50 + 256) * d * 10", ("rotated_product_quantiser", "space"): f"n * (2 * 8 + {log.format('50')}) + (50 + 256) * d", ("rotated_product_quantiser", "query"): "n * (0.01 * 2 + 0.005 * d) + (50 + 256) * d",
        ("projection_forest", "index"): f"4 * n * d * {log.format('n')}", ("projection_forest", "space"): "4 * d * n", ("projection_forest", "query"): f"4 * d * {log.format('n')} + 0.005 * n * d",
        ("layered_graph", "index"): f"n * d * {log.format('n')}", ("layered_graph", "space"): "n * 25", ("layered_graph", "query"): f"d * {log.format('n')}",
        ("tree_graph_hybrid", "index"): f"n * d * {log.format('n')}", ("tree_graph_hybrid", "space"): "n * (d + 25)", ("tree_graph_hybrid", "query"): f"d * {log.format('n')}",
    }
    return " UNION ALL ".join(f"SELECT '{m}' AS method, n, CAST(d AS INTEGER) AS d, '{p}' AS phase, round(CAST({x} AS DOUBLE), 3) AS operations FROM (SELECT CAST(n AS DOUBLE) AS n_, n, CAST(d AS DOUBLE) AS d_, d FROM ({_SIZES}) AS s(n, d) WHERE n > 0)".replace("CAST(" + x, "CAST(" + _as_double(x)) for (m, p), x in f.items())


def _as_double(formula: str) -> str:
    import re

    return re.sub(r"\b([nd])\b", r"\1_", formula)


@query("complexity_table", _complexity_sql())
def _complexity(s, d):
    """The formulas at the sizes of the sets that the tables hold."""
    t = lambda name: vectors.table(s, d, name)
    sizes = [t("embeddings").agg(F.count(F.lit(1)), F.max(F.size("embedding"))), t("documents").agg(F.count("doc_id"), F.lit(64)), t("lineitem").agg(F.countDistinct("l_partkey"), F.lit(84)), t("lineitem").agg(F.count("l_orderkey"), F.lit(8))]
    rows = [(m, n, dim, phase, float(v)) for n, dim in (x.first() for x in sizes) if n for m in METHODS for phase, v in predict(m, n, dim).items()]
    return s.createDataFrame(rows, "method string, n long, d int, phase string, operations double").withColumn("operations", F.round("operations", 3))


# --- vector sets and relational work around the search ----------------------------------------------------------------

_LONG = {"doc": "doc_vectors", "demand": "demand_vectors"}
for _kind, _name in _LONG.items():
    query(_name, f"SELECT id, CAST(dim AS INTEGER) AS dim, CAST(x AS DOUBLE) AS x FROM ({oracles.VECTORS[_kind][1]}) WHERE x <> 0")(
        lambda s, d, k=_kind: SETS[k][0](s, d).select("id", F.posexplode("vec").alias("dim", "x")).where("x <> 0")
    )
query("user_vectors", "WITH t AS (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS r FROM (SELECT DISTINCT event_type FROM events)) SELECT user_id AS id, CAST(r * 24 + hour(ts) AS INTEGER) AS dim, CAST(count(*) AS DOUBLE) AS x FROM events JOIN t USING (event_type) GROUP BY ALL")(
    lambda s, d: vectors.user(s, d).select("id", F.posexplode("vec").alias("dim", "x")).where("x <> 0")
)
query("emb_norms", "SELECT vec_id AS id, round(sqrt(sum(CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS norm FROM (SELECT vec_id, unnest(embedding) AS x FROM embeddings) GROUP BY vec_id")(
    lambda s, d: vectors.emb(s, d).select("id", F.round(F.sqrt(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x * x)), 4).alias("norm"))
)
query("points_minus_queries", "SELECT vec_id AS id FROM embeddings WHERE vec_id % 25 <> 7")(lambda s, d: vectors.emb(s, d).select("id").join(data(s, d, "emb").queries.select(F.col("qid").alias("id")), "id", "left_anti"))
query("radius_search", oracles.base("emb", 25, 7) + f" SELECT qid, id, {oracles.length('l2', GRID)} AS distance FROM whole WHERE dist <= 1.2 * {GRID} * 1.2 * {GRID}")(
    lambda s, d: radius_search((v := data(s, d, "emb")).points, v.queries, 1.2, 64, unit=GRID)
)


def _passages(s, d):
    """Benchmark passages as queries on documents they were not drawn from the points of."""
    points = vectors.doc_counts(s, d)
    queries = vectors.bench_counts(s, d).select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
    return VectorSet(points, queries, 64, 1.0, points.count())


_BENCH = oracles.VECTORS["doc"][1].replace("documents", "benchmark").replace("doc_id", "item_id")
_PASSAGE = f"WITH p AS ({oracles.VECTORS['doc'][1]}), q AS (SELECT id AS qid, dim, x FROM ({_BENCH})), n AS (SELECT count(DISTINCT id) AS n FROM p), pl(dim, sub) AS (VALUES {oracles.plan_values(plan_of('doc'))}), parts AS (SELECT q.qid, p.id, pl.sub, CAST(sum((p.x - q.x) * (p.x - q.x)) AS BIGINT) AS dist FROM p JOIN q USING (dim) JOIN pl USING (dim) GROUP BY ALL), whole AS (SELECT qid, id, sum(dist) AS dist FROM parts GROUP BY ALL)"
query("passage_search", _PASSAGE + oracles.scores(oracles.ceil_share(0.1)) + oracles.result(oracles.pool_size(0.05, K), K, "l2", 1.0) + " SELECT * FROM result")(lambda s, d: collision_scan(_passages(s, d), plan_of("doc"), SearchParams(K, 0.1, 0.05)))


def _filtered(s, d, before: bool):
    """Search among English documents: filtered before the search, or after it."""
    v = data(s, d, "doc")
    english = vectors.table(s, d, "documents").where("lang = 'en'").select(F.col("doc_id").alias("id"))
    if before:
        points = v.points.join(english, "id", "left_semi")
        v = replace(v, points=points, n=points.count())
    found = collision_scan(v, plan_of("doc"), SearchParams(K, 0.1, 0.1))
    return found if before else found.join(english, "id", "left_semi").select("qid", "rank", "id", "distance", "score")


_EN = "id IN (SELECT doc_id FROM documents WHERE lang = 'en')"
query("filtered_search_post", oracles.scan("doc", 50, 3, plan_of("doc"), 0.1, 0.1, K) + f" SELECT * FROM result WHERE {_EN}")(lambda s, d: _filtered(s, d, False))
query("filtered_search_pre", oracles.scan("doc", 50, 3, plan_of("doc"), 0.1, 0.1, K).replace("p AS (SELECT * FROM v WHERE id % 50 <> 3)", f"p AS (SELECT * FROM v WHERE id % 50 <> 3 AND {_EN})") + " SELECT * FROM result")(lambda s, d: _filtered(s, d, True))


def knn_join(left: DataFrame, right: DataFrame, k: int, d: int, unit: float, rows: int = BROADCAST_QUERIES) -> DataFrame:
    """qid, rank, id, distance: k nearest rows of right for every row of left but itself, in blocks of left that stay small enough
    to broadcast. The exact form; the indexed search takes the same blocks."""
    out = []
    for b in blocks_of(left, "id", rows):
        q = b.select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
        dist = paired(right, q).where("id <> qid").select("qid", "id", order_distance("vec", "qvec", d).alias("dist"))
        out.append(first_k(dist, k))
    return _union(out).select("qid", F.col("rank").cast("int").alias("rank"), "id", F.round(true_distance(F.col("dist"), "l2", unit), 6).alias("distance"))


query("knn_join_emb", f"WITH v AS ({oracles.VECTORS['emb'][1]}), w AS (SELECT a.id AS qid, b.id, sum((a.x - b.x) * (a.x - b.x)) AS dist FROM v a JOIN v b ON a.dim = b.dim AND a.id <> b.id GROUP BY ALL) SELECT qid, CAST(rank AS INTEGER) AS rank, id, {oracles.length('l2', GRID)} AS distance FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rank FROM w) WHERE rank <= 5")(
    lambda s, d: knn_join(v := vectors.emb_grid(s, d), v, 5, 64, GRID, 500)
)


@query("candidate_overlap", oracles.base("emb", 25, 7, plan_of("emb")) + oracles.scores(oracles.ceil_share(0.1)) + f""", p1 AS (SELECT qid, id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS r FROM scores) WHERE r <= {oracles.pool_size(0.1, K)}),
    p2 AS (SELECT qid, id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS r FROM whole) WHERE r <= {oracles.pool_size(0.1, K)}) SELECT qid, count(*) AS shared FROM (SELECT * FROM p1 INTERSECT SELECT * FROM p2) GROUP BY qid""")
def _overlap(s, d):
    v = data(s, d, "emb")
    pool = SearchParams(K, 0.1, 0.1).pool(v.n)
    if blocks.fits(v.n, v.d):
        counts = blocks.scan(v.points, v.queries, list(plan_of("emb").dims), v.d, share_of(0.1, v.n), blocks.counted(pool), blocks.COUNTED)
        return counts.where("shared > 0").select("qid", "shared")
    a = top_scored(scan_scores(v.points, v.queries, plan_of("emb"), share_of(0.1, v.n)), pool).select("qid", "id")
    b = whole_space_collisions(v.points, v.queries, 64, pool)
    return a.intersect(b).groupBy("qid").agg(F.count(F.lit(1)).alias("shared"))


_DOC_HITS = oracles.scan("doc", 50, 3, plan_of("doc"), 0.1, 0.05, K) + oracles.truth(K) + ", h AS (SELECT t.qid, t.id, CASE WHEN r.id IS NULL THEN 0 ELSE 1 END AS hit FROM truth t LEFT JOIN result r USING (qid, id))"


def _doc_hits(s, d) -> DataFrame:
    v = data(s, d, "doc")
    truth = exact_knn(v.points, v.queries, K, 64)
    found = collision_scan(v, plan_of("doc"), SearchParams(K, 0.1, 0.05)).select("qid", "id", F.lit(1).alias("got"))
    return truth.select("qid", "id").join(found, ["qid", "id"], "left").select("qid", "id", F.coalesce("got", F.lit(0)).alias("hit"))


query("recall_diff", _DOC_HITS + " SELECT qid, id FROM h WHERE hit = 0")(lambda s, d: _doc_hits(s, d).where("hit = 0").select("qid", "id"))
query("recall_rollup", _DOC_HITS + " SELECT lang, source, CAST(sum(hit) AS DOUBLE) / count(*) AS recall, count(*) AS wanted FROM h JOIN documents d ON d.doc_id = h.qid GROUP BY ROLLUP (lang, source)")(
    lambda s, d: _doc_hits(s, d).join(vectors.table(s, d, "documents").select(F.col("doc_id").alias("qid"), "lang", "source"), "qid").rollup("lang", "source").agg((F.sum("hit") / F.count(F.lit(1))).alias("recall"), F.count(F.lit(1)).alias("wanted"))
)
_PIVOT = [(a, b) for a in (0.05, 0.1) for b in (0.05, 0.1)]
query("recall_pivot", _sweep_sql("emb", plan_of("emb"), _PIVOT, "alpha, max(CASE WHEN beta = 0.05 THEN recall END) AS beta_05, max(CASE WHEN beta = 0.1 THEN recall END) AS beta_10").replace(" FROM measured", " FROM measured GROUP BY alpha"))(
    lambda s, d: sweep(data(s, d, "emb"), plan_of("emb"), _PIVOT).groupBy("alpha").pivot("beta", [0.05, 0.1]).agg(F.max("recall")).withColumnsRenamed({"0.05": "beta_05", "0.1": "beta_10"})
)


@query("asof_user_vector", "SELECT event_id, user_id, count(*) OVER w AS seen, CAST(sum(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END) OVER w AS BIGINT) AS clicks FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)")
def _asof(s, d):
    """What was known of a user just before each event."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return vectors.table(s, d, "events").select("event_id", "user_id", F.count(F.lit(1)).over(w).alias("seen"), F.sum((F.col("event_type") == "click").cast("long")).over(w).alias("clicks"))


def _topk_sql(s, d, lateral: bool) -> DataFrame:
    v = data(s, d, "emb")
    v.points.createOrReplaceTempView("collide_points")
    v.queries.createOrReplaceTempView("collide_queries")
    dist = "aggregate(zip_with(p.vec, q.qvec, (x, y) -> (x - y) * (x - y)), 0D, (s, t) -> s + t)"
    if lateral:
        return s.sql(f"SELECT q.qid, t.id, round(sqrt(t.dist) / {GRID}D, 6) AS distance FROM collide_queries q, LATERAL (SELECT p.id, {dist} AS dist FROM collide_points p ORDER BY dist, p.id LIMIT 3) t")
    return s.sql(f"SELECT qid, CAST(rank AS INT) AS rank, id, round(sqrt(dist) / {GRID}D, 6) AS distance FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rank FROM (SELECT /*+ BROADCAST(q) */ q.qid, p.id, {dist} AS dist FROM collide_points p CROSS JOIN collide_queries q)) WHERE rank <= {K}")


query("sql_topk", ORACLE_SQL["exact_knn"])(lambda s, d: _topk_sql(s, d, False))
query("lateral_topk", oracles.base("emb", 25, 7) + oracles.truth(3, "l2", GRID) + " SELECT qid, id, distance FROM truth")(lambda s, d: _topk_sql(s, d, True))

# --- the index --------------------------------------------------------------------------------------------------------

ROOT, ROUNDS, A_INDEX, B_INDEX = 6, 2, 0.1, 0.1
_INDEX_PARAMS = IndexParams(sqrt_k=ROOT, iterations=ROUNDS, grid=True)


@lru_cache(maxsize=32)
def _cached_index(app: str, sf_dir: str, kind: str, root: int, n_sub: int | None, metric: str, parts: int) -> CellIndex:
    s = SparkSession.getActiveSession()
    return build_cell_index(data(s, sf_dir, kind).points, plan_of(kind, n_sub), replace(_INDEX_PARAMS, sqrt_k=root, metric=metric, parts=parts))


def index_of(s: SparkSession, sf_dir: str, kind: str = "emb", root: int = ROOT, n_sub: int | None = None, metric: str = "l2", parts: int = 2) -> CellIndex:
    return _cached_index(s.sparkContext.applicationId, sf_dir, kind, root, n_sub, metric, parts)


def _index_sql(rest: str, root: int = ROOT, walk: bool = False, kind: str = "emb", n_sub: int | None = None, metric: str = "l2", alpha: float = A_INDEX, parts: int = 2) -> str:
    plan = plan_of(kind, n_sub)
    out = oracles.cell_index(kind, *_set(kind)[:2], plan, root, ROUNDS, 0, metric, parts)
    if walk:
        out += oracles.walked(plan, ROUNDS, oracles.ceil_share(alpha), metric, parts)
    return out + rest


def _indexed_sql(columns: str, root: int = ROOT, kind: str = "emb", n_sub: int | None = None, metric: str = "l2", alpha: float = A_INDEX, beta: float = B_INDEX, parts: int = 2) -> str:
    """columns, with `recall` as $recall and the mean relative error as $mre."""
    unit = SETS[kind][4]
    recall = f"(SELECT count(*) FROM result JOIN truth USING (qid, id)) / CAST((SELECT count(DISTINCT qid) FROM q) * {K} AS DOUBLE)"
    mre = "(SELECT round(avg(CASE WHEN t.distance > 0 THEN (r.distance - t.distance) / t.distance WHEN r.distance = 0 THEN 0.0 END), 6) FROM result r JOIN truth t USING (qid, rank))"
    rest = oracles.result(oracles.pool_size(beta, K), K, metric, unit) + oracles.truth(K, metric, unit)
    return _index_sql(rest, root, True, kind, n_sub, metric, alpha, parts) + " SELECT " + columns.replace("$recall", recall + " AS recall").replace("$mre", mre + " AS mre")


def _indexed(s, d, root: int = ROOT, kind: str = "emb", n_sub: int | None = None, metric: str = "l2", alpha: float = A_INDEX, beta: float = B_INDEX, parts: int = 2) -> DataFrame:
    """recall, mre of the indexed search."""
    return _measured(s, d, root, kind, n_sub, metric, alpha, beta, parts, *_with_truth(s, d, kind, metric))


def _with_truth(s, d, kind: str, metric: str) -> tuple[VectorSet, DataFrame]:
    """A set and its true neighbours, written once for all settings of a study."""
    v = data(s, d, kind)
    return v, materialise(exact_knn(v.points, v.queries, K, v.d, metric, v.unit), "truth")


def _measured(s, d, root, kind, n_sub, metric, alpha, beta, parts, v: VectorSet, truth: DataFrame) -> DataFrame:
    found = materialise(indexed_search(index_of(s, d, kind, root, n_sub, metric, parts), v, SearchParams(K, alpha, beta, metric)), "found")
    return evaluate.recall_at_k(found, truth, K).crossJoin(F.broadcast(evaluate.mean_relative_error(found, truth).drop("excluded")))  # two single rows


def _indexed_each(s, d, settings: list[dict]) -> list[DataFrame]:
    """`_indexed` of each setting; sets and truths are formed once."""
    sets: dict = {}
    out = []
    for x in settings:
        x = {"root": ROOT, "kind": "emb", "n_sub": None, "metric": "l2", "alpha": A_INDEX, "beta": B_INDEX, "parts": 2} | x
        key = x["kind"], x["metric"]
        sets[key] = sets.get(key) or _with_truth(s, d, *key)
        out.append(_measured(s, d, *x.values(), *sets[key]))
    return out


query("cell_index_centroids", _index_sql(f" SELECT CAST(half AS INTEGER) AS half, CAST(cid AS INTEGER) AS cid, CAST(row_number() OVER (PARTITION BY half, cid ORDER BY dim) - 1 AS INTEGER) AS dim, x FROM c{ROUNDS}"))(
    lambda s, d: _cached_index.__wrapped__(s.sparkContext.applicationId, d, "emb", ROOT, None, "l2", 2).centroid_rows(s).select("half", "cid", F.posexplode("centroid").alias("dim", "x"))  # trained here, not taken from another query
)
query("cell_codes", _index_sql(f" SELECT id, CAST(sub AS INTEGER) AS sub, CAST(c1 * {ROOT} + c2 AS INTEGER) AS cell FROM cells"))(lambda s, d: index_of(s, d).codes.select("id", F.posexplode("cells").alias("sub", "cell")))
query("cell_sizes", _index_sql(f" SELECT CAST(sub AS INTEGER) AS sub, CAST(c1 * {ROOT} + c2 AS INTEGER) AS cell, n_points FROM sizes"))(lambda s, d: index_of(s, d).cell_sizes())


def _cells(s, d, walk: str) -> DataFrame:
    i, v = index_of(s, d), data(s, d, "emb")
    return activated_cells(i, v.queries, share_of(A_INDEX, i.n), walk)


for _walk in ("prefix", "activation", "heap"):
    query(f"walk_cells_{_walk}", _index_sql(" SELECT * FROM taken", walk=True))(lambda s, d, w=_walk: _cells(s, d, w).select("qid", "sub", "c1", "c2", "sum_dist", "n_points", "pop_order"))
query("count_hits_inverted", _index_sql(" SELECT * FROM ihits", walk=True))(lambda s, d: count_hits_postings(index_of(s, d).postings(), _cells(s, d, "prefix")))
query("count_hits_forward", _index_sql(" SELECT * FROM ihits", walk=True))(lambda s, d: score_codes(index_of(s, d).codes, _cells(s, d, "activation"), 8).where("score > 0"))
_INDEXED = _index_sql(oracles.result(oracles.pool_size(B_INDEX, K), K, "l2", GRID), walk=True)
for _layout in ("forward", "inverted", "arrow"):
    query("indexed_search" if _layout == "forward" else f"indexed_search_{_layout}", _INDEXED + " SELECT * FROM result")(
        lambda s, d, x=_layout: indexed_search(index_of(s, d).with_postings() if x == "inverted" else index_of(s, d), data(s, d, "emb"), SearchParams(K, A_INDEX, B_INDEX), layout=x)
    )


_VERSUS = [(kind, a, b) for kind in ("emb", "doc", "line") for a, b in ((A_INDEX, B_INDEX), (0.03, 0.003))]


def _scan_recall_sql(kind: str, alpha: float, beta: float) -> str:
    unit = SETS[kind][4]
    return oracles.scan(kind, *_set(kind)[:2], plan_of(kind), alpha, beta, K, "l2", unit) + oracles.truth(K, "l2", unit) + f" SELECT 'scan' AS method, (SELECT count(*) FROM result JOIN truth USING (qid, id)) / CAST((SELECT count(DISTINCT qid) FROM q) * {K} AS DOUBLE) AS recall"


def _set_columns(kind: str, a: float, b: float) -> str:
    return f"'{kind}' AS dataset, CAST({a} AS DOUBLE) AS alpha, CAST({b} AS DOUBLE) AS beta"


def _versus_sql(settings) -> str:
    return " UNION ALL ".join(f"SELECT {_set_columns(*x)}, * FROM ({sql})" for x in settings for sql in (_indexed_sql("'indexed' AS method, $recall", kind=x[0], alpha=x[1], beta=x[2]), _scan_recall_sql(*x)))


def _versus(s, d, settings) -> DataFrame:
    out = []
    for kind, a, b in settings:
        v, p = data(s, d, kind), SearchParams(K, a, b)
        truth = exact_knn(v.points, v.queries, K, v.d, unit=v.unit)
        both = {"indexed": indexed_search(index_of(s, d, kind), v, p), "scan": collision_scan(v, plan_of(kind), p)}
        out += [evaluate.recall_at_k(r, truth, K).select(F.lit(kind).alias("dataset"), F.lit(a).alias("alpha"), F.lit(b).alias("beta"), F.lit(m).alias("method"), "recall") for m, r in both.items()]
    return _union(out)


query("indexed_vs_scan", _versus_sql(_VERSUS[:1]))(lambda s, d: _versus(s, d, _VERSUS[:1]))
#: At the settings of the small sets and at the printed ones, on three sets.
query("indexed_vs_scan_sets", _versus_sql(_VERSUS))(lambda s, d: _versus(s, d, _VERSUS))


ROOTS = (2, 4, 8, 16, 32, 64)


@query("sweep_k", " UNION ALL ".join(f"SELECT * FROM ({_indexed_sql(f'CAST({r} AS INTEGER) AS sqrt_k, $recall, CAST({8 * 64 * r} + (SELECT n FROM n) * 24 AS BIGINT) AS index_bytes', r)})" for r in ROOTS))
def _sweep_k(s, d):
    return _union([f.select(F.lit(r).alias("sqrt_k"), "recall", F.lit(index_of(s, d, root=r).footprint()).cast("long").alias("index_bytes")) for r, f in zip(ROOTS, _indexed_each(s, d, [{"root": r} for r in ROOTS]), strict=True)])


#: The index in the parameter studies: name of the column, values, and how a value enters.
INDEX_SWEEPS = {
    "sweep_alpha_indexed": ("alpha", "DOUBLE", [0.01, 0.03, 0.05, 0.1, 0.2], lambda x: {"alpha": x}),
    "sweep_beta_indexed": ("beta", "DOUBLE", [0.001, 0.005, 0.01, 0.05, 0.1, 0.2], lambda x: {"beta": x, "kind": "doc"}),
    "sweep_subspaces_indexed": ("n_sub", "INTEGER", [2, 4, 6, 8, 10, 12, 16], lambda x: {"n_sub": x}),
}
for _name, (_column, _type, _values, _into) in INDEX_SWEEPS.items():
    query(_name, " UNION ALL ".join(f"SELECT * FROM ({_indexed_sql(f'CAST({x} AS {_type}) AS {_column}, $recall, $mre', **_into(x))})" for x in _values))(
        lambda s, d, c=_column, xs=_values, into=_into: _union([f.select(F.lit(x).alias(c), "recall", "mre") for x, f in zip(xs, _indexed_each(s, d, [into(x) for x in xs]), strict=True)])
    )
query("metric_l1_l2_indexed", " UNION ALL ".join(f"SELECT * FROM ({_indexed_sql(f'{chr(39)}{kind}{chr(39)} AS dataset, {chr(39)}{m}{chr(39)} AS metric, $recall, $mre', kind=kind, metric=m)})" for kind in SETS for m in ("l1", "l2")))(
    lambda s, d: _union([_indexed(s, d, kind=kind, metric=m).select(F.lit(kind).alias("dataset"), F.lit(m).alias("metric"), "recall", "mre") for kind in SETS for m in ("l1", "l2")])
)


@query("flat_vs_multi", " UNION ALL ".join(f"SELECT * FROM ({_indexed_sql(f'{chr(39)}{m}{chr(39)} AS method, $recall, CAST({c} AS INTEGER) AS distances', r, parts=p)})" for m, r, c, p in (("multi", ROOT, 2 * ROOT, 2), ("flat", ROOT * ROOT, ROOT * ROOT, 1))))
def _flat_vs_multi(s, d):
    """The multi-index and a flat index of as many cells: recall and distances computed per query and subspace."""
    return _union([_indexed(s, d, r, parts=p).select(F.lit(m).alias("method"), "recall", F.lit(c).alias("distances")) for m, r, c, p in (("multi", ROOT, 2 * ROOT, 2), ("flat", ROOT * ROOT, ROOT * ROOT, 1))])


# --- growth, walks by hand, streams ------------------------------------------------------------------------------------


GROWTH = (16, 4, 1)


def _growth_sql(share: int) -> str:
    where = f"id % {share} = {1 % share}"
    return oracles.scan("line", 5000, 1, plan_of("line"), 0.05, 0.005, K, "l2", 1.0, where) + oracles.truth(K) + f" SELECT (SELECT n FROM n) AS n, (SELECT count(*) FROM result JOIN truth USING (qid, id)) / CAST((SELECT count(DISTINCT qid) FROM q) * {K} AS DOUBLE) AS recall"


@query("scaling", " UNION ALL ".join(f"SELECT * FROM ({_growth_sql(x)})" for x in GROWTH))
def _scaling(s, d):
    """Recall of the scan on growing parts of the line items; the points are 8-dimensional."""
    out = []
    lines = vectors.line(s, d).persist()
    for share in GROWTH:
        v = held_out(lines.where(F.pmod(F.col("id"), F.lit(share)) == 1 % share), 5000, 1, 8)
        found = collision_scan(v, plan_of("line"), SearchParams(K, 0.05, 0.005))
        out.append(evaluate.recall_at_k(found, exact_knn(v.points, v.queries, K, 8), K).select(F.lit(v.n).cast("long").alias("n"), "recall"))
    return _union(out)


_TRACE = f"""WITH v AS ({oracles.VECTORS["emb"][1]}), x AS (SELECT id, dim // 4 AS half, abs(x) AS x, row_number() OVER (PARTITION BY id, dim // 4 ORDER BY abs(x)) - 1 AS pos FROM v WHERE dim < 8 AND id % 25 = 7),
  c AS (SELECT a.id AS qid, a.pos AS i, b.pos AS j, a.x + b.x AS total, row_number() OVER (PARTITION BY a.id ORDER BY a.x + b.x, a.pos, b.pos) AS round FROM x a JOIN x b ON a.id = b.id AND a.half = 0 AND b.half = 1)
  SELECT qid, CAST(round AS INTEGER) AS round, CAST(i AS INTEGER) AS pos1, CAST(j AS INTEGER) AS pos2, CAST(total AS DOUBLE) AS total, CAST(least(4, 1 + (SELECT count(*) FROM c e WHERE e.qid = c.qid AND e.round < c.round AND e.j = 0)) - (SELECT count(*) FROM c e WHERE e.qid = c.qid AND e.round < c.round AND e.j = 3) AS INTEGER) AS active FROM c WHERE round <= 6"""


@query("walk_trace", _TRACE)
def _walk_trace(s, d):
    """The activation walk round by round, for each held-out embedding: two lists of four values each, one point a cell, six rounds."""
    from . import sqlapi

    sqlapi.register(s)
    side = lambda at: F.array_sort(F.transform(F.slice("qvec", at, 4), F.abs))
    data(s, d, "emb").queries.select("qid", side(1).alias("one"), side(5).alias("two")).createOrReplaceTempView("collide_lists")
    return s.sql("SELECT l.qid, t.* FROM collide_lists l, LATERAL walk_trace(l.one, l.two, array_repeat(1, 16), 6) t")


@query("user_windows", "SELECT date_trunc('day', ts) AS start, user_id, event_type, count(*) AS n FROM events GROUP BY ALL")
def _user_windows(s, d):
    from .streaming.online import user_windows

    return user_windows(vectors.table(s, d, "events"))


@query("synthetic_search")
def _synthetic(s, d):
    """The rehearsal at scale: vectors made in place, the border form of the scan, forward search."""
    from .sources.vectors_io import synthetic_vectors

    v = held_out(synthetic_vectors(s, 20_000, 32, 1, 50), 2000, 3, 32)
    return collision_scan(v, plan_contiguous(32, 4), SearchParams(K, 0.05, 0.01), select="histogram")


# --- relational operators around the search ---------------------------------------------------------------------------

query("mean_relative_error", oracles.scan("emb", 25, 7, plan_of("emb"), 0.1, 0.05, K, "l2", GRID) + oracles.truth(K, "l2", GRID) + " SELECT round(avg(CASE WHEN t.distance > 0 THEN (r.distance - t.distance) / t.distance WHEN r.distance = 0 THEN 0.0 END), 6) AS mre, CAST(count(*) FILTER (WHERE t.distance = 0 AND r.distance > 0) AS BIGINT) AS excluded FROM result r JOIN truth t USING (qid, rank)")(
    lambda s, d: evaluate.mean_relative_error(collision_scan(v := data(s, d, "emb"), plan_of("emb"), SearchParams(K, 0.1, 0.05)), exact_knn(v.points, v.queries, K, 64, unit=GRID))
)
query("recall_by_distance", oracles.scan("doc", 50, 3, plan_of("doc"), 0.1, 0.05, K) + oracles.truth(K) + f", lim AS (SELECT qid, max(distance) AS far FROM truth GROUP BY qid) SELECT CAST(count(*) FILTER (WHERE distance <= far) AS DOUBLE) / ((SELECT count(DISTINCT qid) FROM q) * {K}) AS recall FROM result JOIN lim USING (qid)")(
    lambda s, d: evaluate.recall_by_distance(collision_scan(v := data(s, d, "doc"), plan_of("doc"), SearchParams(K, 0.1, 0.05)), exact_knn(v.points, v.queries, K, 64), K)
)
query("train_sample", "SELECT vec_id AS id FROM embeddings WHERE CAST(('0x' || substr(md5('0:' || CAST(vec_id AS VARCHAR)), 1, 8)) AS BIGINT) < CAST(floor(least(1.0, 100.0 / (SELECT count(*) FROM embeddings)) * 4294967296) AS BIGINT)")(
    lambda s, d: _train_sample(vectors.emb(s, d))
)
query("score_rank", oracles.base("emb", 25, 7, plan_of("emb")) + oracles.scores(oracles.ceil_share(0.1)) + " SELECT qid, id, score, dense_rank() OVER (PARTITION BY qid ORDER BY score DESC) AS class, CAST(ntile(4) OVER (PARTITION BY qid ORDER BY score DESC, id) AS INTEGER) AS quarter FROM scores")(
    lambda s, d: scan_scores((v := data(s, d, "emb")).points, v.queries, plan_of("emb"), share_of(0.1, v.n), select="rank")
    .withColumn("class", F.dense_rank().over(Window.partitionBy("qid").orderBy(F.col("score").desc())).cast("long"))
    .withColumn("quarter", F.ntile(4).over(Window.partitionBy("qid").orderBy(F.col("score").desc(), "id")))
)
query("distinct_candidates", oracles.base("emb", 25, 7, plan_of("emb")) + oracles.scores(oracles.ceil_share(0.05)) + " SELECT qid, count(DISTINCT id) AS candidates, count(*) AS collisions FROM hits GROUP BY qid")(
    lambda s, d: _distinct(data(s, d, "emb"))
)
query("volume_by_nation", "SELECT r_name, n_name, count(*) AS orders, round(sum(o_totalprice), 2) AS volume FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY GROUPING SETS ((r_name, n_name), (r_name), ())")(
    lambda s, d: _volume(s, d)
)
query("centroid_mean", f"WITH v AS ({oracles.VECTORS['emb'][1]}) SELECT label, CAST(dim AS INTEGER) AS dim, CAST(sum(x) AS DOUBLE) / count(*) AS mean FROM v JOIN embeddings e ON e.vec_id = v.id GROUP BY ALL")(
    lambda s, d: vectors.emb_grid(s, d).join(vectors.table(s, d, "embeddings").select(F.col("vec_id").alias("id"), "label"), "id").select("label", F.posexplode("vec").alias("dim", "x")).groupBy("label", "dim").agg((F.sum("x") / F.count(F.lit(1))).alias("mean"))
)


def _distinct(v: VectorSet) -> DataFrame:
    m = share_of(0.05, v.n)
    if blocks.fits(v.n, v.d):
        return blocks.scan(v.points, v.queries, list(plan_of("emb").dims), v.d, m, blocks.counted(), blocks.COUNTED).select("qid", "candidates", "collisions")
    return subspace_collisions(v.points, v.queries, plan_of("emb"), m).groupBy("qid").agg(F.countDistinct("id").alias("candidates"), F.count(F.lit(1)).alias("collisions"))


def _train_sample(points: DataFrame) -> DataFrame:
    from .operators.clustering import train_sample

    return train_sample(points, 100).select("id")


def _volume(s, d) -> DataFrame:
    t = lambda n: vectors.table(s, d, n)
    j = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("orders"), F.round(F.sum(F.col("o_totalprice").cast("decimal(18,2)")), 2).cast("double").alias("volume"))


query("events_props", "SELECT event_type, CAST(props ->> '$.k' AS BIGINT) // 10 AS decile, count(*) AS n FROM events GROUP BY ALL")(
    lambda s, d: vectors.table(s, d, "events").select("event_type", F.floor(F.from_json("props", "k long")["k"] / 10).alias("decile")).groupBy("event_type", "decile").agg(F.count(F.lit(1)).alias("n"))
)
