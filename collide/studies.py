"""Studies of cost and of the guarantees: build time, bytes, queries a second, break-even, walks, front ends, knees of curves.

Times are measured on the session at hand, so they have no SQL; builds and searches are timed apart, each with its result
computed whole. What does not depend on time has SQL.
"""

from __future__ import annotations

from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import evaluate, oracles, theory
from .costmodel import break_even, clusterings, cumulative_cost
from .functions import vectors
from .operators import baselines, blocks
from .operators.candidates import rerank, top_scored
from .operators.cellindex import build_cell_index
from .operators.collisions import RANKED_POINTS, scan_scores
from .operators.exact import exact_knn, paired
from .operators.fronts import front_end, gaussian
from .operators.scan import SearchParams, collision_scan
from .operators.search import centroid_distances, indexed_search
from .operators.walks import WALKS
from .plans.subspaces import plan_contiguous
from .session import materialise, share_of
from .workloads import _INDEX_PARAMS, A_INDEX, B_INDEX, BETAS, CURVE, K, _curve_sql, _doc_hits, _set, _sweep_sql, _union, data, index_of, pareto_curve, plan_of, query, sweep

METHODS = baselines.GUARANTEED | baselines.UNGUARANTEED
#: Sets of the cost studies: the hard one and the easy one.
COST_SETS = ("emb", "doc")
#: How each method is built, and its settings from narrow to wide.
BUILD = {"layered_graph": {"ef_build": 60}}
SETTINGS = {
    "indexed": [{"alpha": 0.05, "beta": 0.05}, {"alpha": A_INDEX, "beta": B_INDEX}, {"alpha": 0.2, "beta": 0.2}],
    "encoded_projection_trees": [{"beta": 0.05}, {"beta": 0.2}],
    "query_centred_windows": [{"beta": 0.05}, {"beta": 0.2}],
    "projected_metric_ball": [{"beta": 0.05}, {"beta": 0.2}],
    "circular_match": [{"check_k": 64}, {"check_k": 256}],
    "rotated_product_quantiser": [{"beta": 0.05, "gamma": 0.2}, {"beta": 0.2, "gamma": 0.5}],
    "projection_forest": [{"search_k": 500}, {"search_k": 2000}],
    "layered_graph": [{"ef": 20}, {"ef": 100}],
    "tree_graph_hybrid": [{"probes": 1, "hops": 1}, {"probes": 4, "hops": 3}],
}


@lru_cache(maxsize=1)
def _prepared(app: str, sf_dir: str, kind: str) -> tuple[vectors.VectorSet, int, DataFrame]:
    """A set, its number of queries and its true neighbours: derived once for all methods."""
    s = SparkSession.getActiveSession()
    found = data(s, sf_dir, kind)
    v = vectors.VectorSet(materialise(found.points, "points"), materialise(found.queries, "queries"), found.d, found.unit, found.n)
    return v, v.queries.count(), materialise(exact_knn(v.points, v.queries, K, v.d, unit=v.unit), "truth")


@lru_cache(maxsize=64)
def _measured(app: str, sf_dir: str, kind: str, name: str) -> tuple[float, int, tuple]:
    """(seconds to build, bytes of the state, per setting (setting, recall, mean relative error, seconds a query))."""
    v, nq, truth = _prepared(app, sf_dir, kind)
    if name == "indexed":
        index, build = evaluate.timed(lambda: build_cell_index(v.points, plan_of(kind), _INDEX_PARAMS))
        size, run = index.footprint(), lambda x: indexed_search(index, v, SearchParams(K, x["alpha"], x["beta"]))
    else:
        method = METHODS[name]
        state, build = evaluate.timed(lambda: method.build(v, **BUILD.get(name, {})))
        size, run = state.bytes(), lambda x: method.search(state, v, K, **x)
    rows = []
    for x in SETTINGS[name]:
        result, seconds = evaluate.timed(lambda x=x: materialise(run(x), "found"))
        quality = evaluate.recall_at_k(result, truth, K).crossJoin(evaluate.mean_relative_error(result, truth)).first()  # a row each, in one go
        rows.append((", ".join(f"{a}={b}" for a, b in x.items()), quality["recall"], quality["mre"], seconds / nq))
    return build, size, tuple(rows)


def measured(s: SparkSession, sf_dir: str, kind: str, name: str):
    return _measured(s.sparkContext.applicationId, sf_dir, kind, name)


def _cost(names):
    rows = "dataset string, method string, seconds double, bytes long, parallel_in_print boolean"
    return lambda s, d: s.createDataFrame([(k, n, m[0], m[1], METHODS[n].parallel if n in METHODS else True) for k in COST_SETS for n in ("indexed", *names) for m in [measured(s, d, k, n)]], rows)


def _tradeoff(names):
    rows = "dataset string, method string, setting string, recall double, mre double, qps double"
    return lambda s, d: s.createDataFrame([(k, n, x, r, e, evaluate.qps(t)) for k in COST_SETS for n in ("indexed", *names) for x, r, e, t in measured(s, d, k, n)[2]], rows)


for _part, _names in (("guaranteed", baselines.GUARANTEED), ("unguaranteed", baselines.UNGUARANTEED)):
    query(f"index_cost_{_part}")(_cost(_names))
    query(f"tradeoff_{_part}")(_tradeoff(_names))

#: The methods whose cumulative cost is compared.
CUMULATIVE = ("indexed", "encoded_projection_trees", *baselines.UNGUARANTEED)


def _at_best(s, d, kind: str, name: str) -> tuple[float, float]:
    """(build, seconds a query) at the setting of the best recall."""
    build, _, rows = measured(s, d, kind, name)
    return build, max(rows, key=lambda r: (r[1], -r[3]))[3]


@query("cumulative_cost")
def _cumulative(s, d):
    rows = [(k, n, q, cumulative_cost(*_at_best(s, d, k, n), q)) for k in COST_SETS for n in CUMULATIVE for q in (0, 100, 10_000, 1_000_000)]
    return s.createDataFrame(rows, "dataset string, method string, queries long, seconds double")


@query("break_even")
def _break_even(s, d):
    """Queries that the index answers before a method answers its first, and after how many the method overtakes (null: never)."""
    rows = []
    for k in COST_SETS:
        ours = _at_best(s, d, k, "indexed")
        for n in CUMULATIVE[1:]:
            theirs = _at_best(s, d, k, n)
            even = break_even(ours, theirs)
            rows.append((k, n, max(0.0, (sum(theirs) - ours[0]) / ours[1]), None if even is None else float(even)))
    return s.createDataFrame(rows, "dataset string, method string, before_first double, overtaken_after double")


@query("easy_hard")
def _easy_hard(s, d):
    """Each method's best recall and queries a second on the hard and on the easy set."""
    rows = [(k, n, max(x[1] for x in m[2]), max(evaluate.qps(x[3]) for x in m[2])) for k in COST_SETS for n in SETTINGS for m in [measured(s, d, k, n)]]
    return s.createDataFrame(rows, "dataset string, method string, recall double, qps double")


#: Clusterings and clusters of the published settings: two of 50 a subspace, against two of 2**10 and more.
PUBLISHED = (("indexed", clusterings(8), 50), ("rotated_product_quantiser", 2, 1024))


@query("clustering_work", "SELECT method, CAST(c AS INTEGER) AS clusterings, CAST(r AS INTEGER) AS clusters, n, d, c * r * n AS work FROM (SELECT count(*) AS n, CAST(max(len(embedding)) AS INTEGER) AS d FROM embeddings WHERE vec_id % 25 <> 7) AS e, (VALUES " + ", ".join(f"('{m}', {c}, {r})" for m, c, r in PUBLISHED) + ") AS p(method, c, r)")
def _clustering_work(s, d):
    """Points compared with centroids in a round over the embeddings: clusterings times clusters times points, at the published settings."""
    e = data(s, d, "emb").points.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("vec")).alias("d"))
    p = s.createDataFrame(list(PUBLISHED), "method string, clusterings int, clusters int")
    return p.crossJoin(F.broadcast(e)).select("method", "clusterings", "clusters", "n", "d", (F.col("clusterings") * F.col("clusters") * F.col("n")).alias("work"))  # a single row


# --- walks ------------------------------------------------------------------------------------------------------------


@query("walk_timing")
def _walk_timing(s, d):
    """Seconds of the walks alone, over the sorted lists of all queries and subspaces, with what they take; by clusters and share."""
    import time

    rows = []
    for root in (4, 8, 16, 32):
        index, v = index_of(s, d, "emb", root), data(s, d, "emb")
        lists: dict = {}
        for r in centroid_distances(index, v.queries).collect():  # a block of queries
            lists.setdefault((r["qid"], r["sub"]), {})[r["half"]] = ([x["dist"] for x in r["ranked"]], [x["cid"] for x in r["ranked"]])
        table = {(r["sub"], r["cell"]): r["n_points"] for r in index.cell_sizes().collect()}  # a row per cell
        each = [(a[0], b[0], [[table.get((sub, i * root + j), 0) for j in b[1]] for i in a[1]]) for (_, sub), x in lists.items() for a, b in [(x[0], x[1])]]
        for alpha in (0.01, 0.05, 0.1, 0.2):
            target = share_of(alpha, index.n)
            for name, walk in WALKS.items():
                start = time.perf_counter()
                taken = [walk(a, b, sizes, target) for a, b, sizes in each]
                seconds = time.perf_counter() - start
                held = sum(sizes[i][j] for (_, _, sizes), t in zip(each, taken, strict=True) for i, j in t)
                rows.append((root, alpha, name, seconds, sum(map(len, taken)), held / (target * len(each))))
    return s.createDataFrame(rows, "sqrt_k int, alpha double, walk string, seconds double, pops long, overshoot double")


# --- front ends -------------------------------------------------------------------------------------------------------

FRONTS = [("emb", 8, 0.1, 0.1), ("emb", 4, 0.1, 0.1), ("doc", 4, 0.1, 0.05), ("doc", 8, 0.05, 0.1), ("doc", 8, 0.1, 0.1)]
FRONT_DIMS = 32
LSH_GRID = 1000


def _front_recall(s, d, fronts) -> DataFrame:
    out = []
    for kind, n_sub, alpha, beta in FRONTS:
        v = data(s, d, kind)
        truth = exact_knn(v.points, v.queries, K, v.d, unit=v.unit)
        p = SearchParams(K, alpha, beta)
        for front in fronts:
            f = front_end(v, front, FRONT_DIMS)
            if front == "lsh":  # on a grid, so that no engine's sums of equal points differ
                f = vectors.VectorSet(*[x.select(i, F.transform(c, lambda y: F.floor(y * LSH_GRID + 0.5).cast("double")).alias(c)) for x, i, c in ((f.points, "id", "vec"), (f.queries, "qid", "qvec"))], f.d, 1.0, f.n)
            pool = top_scored(scan_scores(f.points, f.queries, plan_contiguous(f.d, n_sub), p.collide(v.n), select="rank"), p.pool(v.n), n=v.n)
            found = rerank(pool, v.points, v.queries, K, v.d, unit=v.unit)
            out.append(evaluate.recall_at_k(found, truth, K).select(F.lit(kind).alias("dataset"), F.lit(front).alias("front"), F.lit(n_sub).alias("n_sub"), F.lit(alpha).alias("alpha"), F.lit(beta).alias("beta"), "recall"))
    return _union(out)


def _front_sql(kind: str, n_sub: int, alpha: float, beta: float, front: str) -> str:
    mod, rest, unit = _set(kind)
    whole = oracles.base(kind, mod, rest)
    if front == "divide":
        sql = oracles.base(kind, mod, rest, plan_of(kind, n_sub))
    else:
        w = gaussian(oracles.VECTORS[kind][0], FRONT_DIMS)
        values = ", ".join(f"({i}, {j}, CAST({float(x)!r} AS DOUBLE))" for i, r in enumerate(w) for j, x in enumerate(r))
        plan = plan_contiguous(FRONT_DIMS, n_sub)
        sql = whole + f""", w(dim, j, w) AS (VALUES {values}), pv AS (SELECT id, j, CAST(floor(sum(x * w) * {LSH_GRID} + 0.5) AS BIGINT) AS x FROM v JOIN w USING (dim) GROUP BY ALL), pl2(j, sub2) AS (VALUES {oracles.plan_values(plan)}),
          lsh AS (SELECT q.id AS qid, p.id, sub2 AS sub, sum((p.x - q.x) * (p.x - q.x)) AS dist FROM pv p JOIN pv q ON p.j = q.j AND p.id % {mod} <> {rest} AND q.id % {mod} = {rest} JOIN pl2 ON pl2.j = p.j GROUP BY ALL)"""
    scored = oracles.scores(oracles.ceil_share(alpha))
    if front != "divide":
        scored = scored.replace("FROM parts)", "FROM lsh)")
    recall = f"(SELECT count(*) FROM result JOIN truth USING (qid, id)) / CAST((SELECT count(DISTINCT qid) FROM q) * {K} AS DOUBLE)"
    return sql + scored + oracles.result(oracles.pool_size(beta, K), K, "l2", unit) + oracles.truth(K, "l2", unit) + f" SELECT '{kind}' AS dataset, '{front}' AS front, CAST({n_sub} AS INTEGER) AS n_sub, CAST({alpha} AS DOUBLE) AS alpha, CAST({beta} AS DOUBLE) AS beta, {recall} AS recall"


query("front_ends_divide_lsh", " UNION ALL ".join(f"SELECT * FROM ({_front_sql(*x, front)})" for x in FRONTS for front in ("divide", "lsh")))(lambda s, d: _front_recall(s, d, ("divide", "lsh")))
query("front_end_ablation")(lambda s, d: _front_recall(s, d, ("divide", "lsh", "pca")))


@query("front_end_speed")
def _front_speed(s, d):
    """Seconds to prepare points for division: nothing but the division, a Gaussian projection, principal components; the best of
    three, each written whole."""
    out = []
    for kind in ("emb", "doc", "line"):
        v = data(s, d, kind)
        v = vectors.VectorSet(materialise(v.points, "points"), materialise(v.queries, "queries"), v.d, v.unit, v.n)
        plan, took = plan_of(kind), {}
        for front in ("divide", "lsh", "pca"):

            def run(front=front):
                f = front_end(v, front, v.d)
                f.points.select("id", *[F.array(*[F.col("vec")[i] for i in dims]) for dims in plan.dims]).write.format("noop").mode("overwrite").save()

            took[front] = min(evaluate.timed(run)[1] for _ in range(3))
        out += [(kind, front, t, t / took["divide"]) for front, t in took.items()]
    return s.createDataFrame(out, "dataset string, front string, seconds double, times_division double")


# --- knees, least shares, scope of the guarantees ---------------------------------------------------------------------


def _knee_sql(kind: str, n_sub: int) -> str:
    return f"""SELECT '{kind}' AS dataset, rank_bucket / CAST({CURVE} AS DOUBLE) AS turning_point FROM (SELECT *, abs((y1 - y0) * rank_bucket - (x1 - x0) * avg_score + x1 * y0 - y1 * x0) AS apart FROM
      (SELECT *, first_value(rank_bucket) OVER w AS x0, last_value(rank_bucket) OVER w AS x1, first_value(avg_score) OVER w AS y0, last_value(avg_score) OVER w AS y1 FROM ({_curve_sql(kind, n_sub)}) WINDOW w AS (ORDER BY rank_bucket ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING))) ORDER BY apart DESC, rank_bucket LIMIT 1"""


@query("turning_points", " UNION ALL ".join(f"SELECT * FROM ({_knee_sql(k, n)})" for k, n in (("emb", 8), ("doc", 8), ("demand", 10))))
def _turning_points(s, d):
    """Where the score curve bends, as a share of the points: large scores lie before it."""
    out = []
    for kind, n in (("emb", 8), ("doc", 8), ("demand", 10)):
        curve = [(float(r["rank_bucket"]), r["avg_score"]) for r in pareto_curve(data(s, d, kind), plan_of(kind, n)).orderBy("rank_bucket").collect()]  # CURVE rows
        out.append((kind, evaluate.turning_point(curve) * (curve[-1][0] - curve[0][0]) / CURVE + curve[0][0] / CURVE))
    return s.createDataFrame(out, "dataset string, turning_point double")


TARGETS = (0.5, 0.7, 0.9)


@query("least_beta", f"WITH m AS ({_sweep_sql('doc', plan_of('doc'), [(0.1, b) for b in BETAS], 'beta, recall')}) SELECT CAST(target AS DOUBLE) AS target, (SELECT min(beta) FROM m WHERE recall >= target) AS beta FROM (VALUES {', '.join(f'({t})' for t in TARGETS)}) AS t(target)")
def _least_beta(s, d):
    """The least share of points re-ranked whose recall reaches a target (null: none of those tried)."""
    curve = [(r["beta"], r["recall"]) for r in sweep(data(s, d, "doc"), plan_of("doc"), [(0.1, b) for b in BETAS]).collect()]  # a row per setting
    return s.createDataFrame([(t, evaluate.min_beta_for_recall(curve, t)) for t in TARGETS], "target double, beta double")


@query("guarantee_scope", oracles.base("doc", 50, 3, plan_of("doc")) + oracles.scores(oracles.ceil_share(0.1)) + oracles.truth(K) + " SELECT CAST(count(*) FILTER (WHERE score = 8) AS DOUBLE) / count(*) AS full_score, CAST(count(*) FILTER (WHERE score >= 4) AS DOUBLE) / count(*) AS half_score FROM truth JOIN scores USING (qid, id)")
def _scope(s, d):
    """The share of true neighbours that collide in all subspaces, for which alone the bound is argued, and in half of them."""
    v = data(s, d, "doc")
    scores = scan_scores(v.points, v.queries, plan_of("doc"), share_of(0.1, v.n), select="rank" if v.n <= RANKED_POINTS else "histogram")
    true = exact_knn(v.points, v.queries, K, 64).select("qid", "id").join(scores, ["qid", "id"])
    share = lambda c: (F.sum(c.cast("long")) / F.count(F.lit(1)))
    return true.agg(share(F.col("score") == 8).alias("full_score"), share(F.col("score") >= 4).alias("half_score"))


_ANSWERED = oracles.scan("doc", 50, 3, plan_of("doc"), 0.1, 0.1, K) + oracles.truth(K) + f", h AS (SELECT t.qid, count(r.id) AS hits FROM truth t LEFT JOIN result r USING (qid, id) GROUP BY t.qid) SELECT avg(CASE WHEN hits = {K} THEN 1.0 ELSE 0.0 END) AS answered FROM h"


@query("answered_share", _ANSWERED)
def _answered(s, d):
    """The share of queries all of whose neighbours were found, beside which the bound of one half stands."""
    v = data(s, d, "doc")
    return theory.answered_share(collision_scan(v, plan_of("doc"), SearchParams(K, 0.1, 0.1)), exact_knn(v.points, v.queries, K, 64), K)


@query("moments_identity", oracles.base("demand", 100, 1, plan_of("demand")) + ", s AS (SELECT sub, avg(dist) AS m, var_pop(dist) AS v FROM parts GROUP BY sub) SELECT round((SELECT avg(dist) FROM whole), 4) AS mean, round((SELECT sum(m) FROM s), 4) AS sum_of_means, round((SELECT var_pop(dist) FROM whole) / 1e6, 2) AS variance_m, round((SELECT sum(v) FROM s) / 1e6, 2) AS sum_of_variances_m")
def _identity(s, d):
    """Mean and variance of whole distances against the sums over subspaces; the second pair differs as far as subspaces depend on
    each other."""
    v = data(s, d, "demand")
    dims = [list(x) for x in plan_of("demand").dims]
    (mean, var), *each = theory.pair_moments(v.points, v.queries, [list(range(v.d)), *dims])
    total = lambda i: None if mean is None else float(sum(x[i] for x in each))
    both = s.createDataFrame([(mean, total(0), var, total(1))], "mean double, sm double, var double, sv double")
    return both.select(F.round("mean", 4).alias("mean"), F.round("sm", 4).alias("sum_of_means"), F.round(F.col("var") / 1e6, 2).alias("variance_m"), F.round(F.col("sv") / 1e6, 2).alias("sum_of_variances_m"))


@query("answer_condition")
def _condition(s, d):
    """For each k: the t that the bound takes, the least t that its condition asks for, and whether that holds on the data."""
    v = data(s, d, "demand")
    m = theory.subspace_moments(v.points, v.queries, plan_of("demand")).agg(F.avg("mean").alias("m"), F.avg("variance").alias("v")).first()
    rows = [(k, a, *theory.answer_condition(k, v.n, 8, m["m"], m["v"], a)) for k in (1, 10, 50) for a in (0.01, 0.05, 0.1)]
    return s.createDataFrame(rows, "k int, alpha double, t double, least_t double, holds boolean")


@query("engine_counts")
def _engine_counts(s, d):
    """Rows that pass each step of the scan, counted by the engine while it runs."""
    from pyspark.sql import Observation

    v, p = data(s, d, "emb"), SearchParams(K, 0.1, 0.1)
    seen = {n: Observation(n) for n in ("pairs", "scored", "pool")}
    rows = None
    if blocks.fits(v.n, v.d):
        rows = blocks.scan(v.points, v.queries, list(plan_of("emb").dims), v.d, p.collide(v.n), blocks.steps(p.pool(v.n)), blocks.STEPS)
        for n, o in seen.items():
            rows = rows.observe(o, F.coalesce(F.sum(n), F.lit(0)).alias("rows"))
    else:
        count = F.count(F.lit(1)).alias("rows")
        paired(v.points, v.queries).observe(seen["pairs"], count).write.format("noop").mode("overwrite").save()
        scores = scan_scores(v.points, v.queries, plan_of("emb"), p.collide(v.n)).observe(seen["scored"], F.sum((F.col("score") > 0).cast("long")).alias("rows"))
        rows = top_scored(scores, p.pool(v.n), n=v.n).observe(seen["pool"], count)
    rows.write.format("noop").mode("overwrite").save()
    return s.createDataFrame([(n, int(o.get["rows"])) for n, o in seen.items()], "step string, rows long")


# --- more relational work around the search ---------------------------------------------------------------------------

_EN_HITS = "FROM h JOIN documents d ON d.doc_id = h.qid"


def _hits_sql(select: str) -> str:
    from .workloads import _DOC_HITS

    return _DOC_HITS + select


query("recall_cube", _hits_sql(f" SELECT lang, source, CAST(sum(hit) AS DOUBLE) / count(*) AS recall, count(*) AS wanted {_EN_HITS} GROUP BY CUBE (lang, source)"))(
    lambda s, d: _doc_hits(s, d).join(vectors.table(s, d, "documents").select(F.col("doc_id").alias("qid"), "lang", "source"), "qid").cube("lang", "source").agg((F.sum("hit") / F.count(F.lit(1))).alias("recall"), F.count(F.lit(1)).alias("wanted"))
)


def _found_and_true(s, d) -> tuple[DataFrame, DataFrame]:
    v = data(s, d, "doc")
    found = collision_scan(v, plan_of("doc"), SearchParams(K, 0.1, 0.05)).select("qid", "id", F.col("rank").alias("found_rank"))
    return found, exact_knn(v.points, v.queries, K, 64).select("qid", "id", F.col("rank").alias("true_rank"))


_BOTH = oracles.scan("doc", 50, 3, plan_of("doc"), 0.1, 0.05, K) + oracles.truth(K)
query("ranks_full_outer", _BOTH + " SELECT coalesce(r.qid, t.qid) AS qid, coalesce(r.id, t.id) AS id, r.rank AS found_rank, t.rank AS true_rank FROM result r FULL JOIN truth t ON r.qid = t.qid AND r.id = t.id")(
    lambda s, d: (x := _found_and_true(s, d))[0].join(x[1], ["qid", "id"], "full")
)
query("neighbours_union_except", _BOTH + " SELECT 'either' AS part, count(*) AS n FROM (SELECT qid, id FROM result UNION SELECT qid, id FROM truth) UNION ALL SELECT 'found_only', count(*) FROM (SELECT qid, id FROM result EXCEPT SELECT qid, id FROM truth)")(
    lambda s, d: _set_counts(*_found_and_true(s, d))
)
query("nearest_pairs", _BOTH + " SELECT qid, id, distance FROM truth ORDER BY distance, qid, id LIMIT 25")(
    lambda s, d: exact_knn((v := data(s, d, "doc")).points, v.queries, K, 64).select("qid", "id", "distance").orderBy("distance", "qid", "id").limit(25)
)
query("filtered_by_quality", oracles.scan("doc", 50, 3, plan_of("doc"), 0.1, 0.1, K).replace("p AS (SELECT * FROM v WHERE id % 50 <> 3)", "p AS (SELECT * FROM v WHERE id % 50 <> 3 AND id IN (SELECT doc_id FROM labels WHERE quality = 1))") + " SELECT * FROM result")(
    lambda s, d: _good_only(s, d)
)
query("revenue_sets", "SELECT event_type, CAST(date_part('hour', ts) AS INTEGER) AS hour, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY GROUPING SETS ((event_type, hour), (hour))")(
    lambda s, d: _event_sets(s, d)
)


def _set_counts(found: DataFrame, true: DataFrame) -> DataFrame:
    a, b = found.select("qid", "id"), true.select("qid", "id")
    n = F.count(F.lit(1)).alias("n")
    return a.union(b).distinct().agg(n).select(F.lit("either").alias("part"), "n").unionByName(a.exceptAll(b).distinct().agg(n).select(F.lit("found_only").alias("part"), "n"))


def _good_only(s, d) -> DataFrame:
    v = data(s, d, "doc")
    good = vectors.table(s, d, "labels").where("quality = 1").select(F.col("doc_id").alias("id")).distinct()
    points = materialise(v.points.join(good, "id", "left_semi"), "good")
    return collision_scan(vectors.VectorSet(points, v.queries, v.d, v.unit, points.count()), plan_of("doc"), SearchParams(K, 0.1, 0.1))


def _event_sets(s, d) -> DataFrame:
    vectors.table(s, d, "events").createOrReplaceTempView("collide_events")
    return s.sql("SELECT event_type, hour, count(*) AS n, round(sum(value), 2) AS total FROM (SELECT event_type, hour(ts) AS hour, value FROM collide_events) GROUP BY GROUPING SETS ((event_type, hour), (hour))")


@query("query_rank_window", oracles.base("emb", 25, 7) + oracles.truth(K, "l2", 10000.0) + " SELECT qid, id, distance, round(distance - lag(distance) OVER (PARTITION BY qid ORDER BY rank), 6) AS gap FROM truth")
def _gaps(s, d):
    """How far apart neighbouring neighbours lie: what separates the k-th from the next."""
    v = data(s, d, "emb")
    near = exact_knn(v.points, v.queries, K, 64, unit=v.unit)
    return near.select("qid", "id", "distance", F.round(F.col("distance") - F.lag("distance").over(Window.partitionBy("qid").orderBy("rank")), 6).alias("gap"))
