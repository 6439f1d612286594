import hashlib
import math
import random
import struct

import duckdb
import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from collide import costmodel, evaluate, session, sqlapi, studies, theory, workloads
from collide.functions import vectors
from collide.functions.vectors import VectorSet, held_out, numbered, validate_vectors
from collide.operators import baselines, blocks, clustering, collisions, walks
from collide.operators.candidates import top_scored
from collide.operators.cellindex import CellIndex, IndexParams, build_cell_index, build_flat_index, suggest_index
from collide.operators.collisions import hit_scores, scan_scores
from collide.operators.exact import exact_knn, in_blocks
from collide.operators.fronts import front_end
from collide.operators.scan import SearchParams, collision_scan, suggest_params
from collide.operators.search import activated_cells, count_hits_postings, indexed_search, score_codes, score_codes_arrow
from collide.plans.subspaces import plan_contiguous, plan_random, single_subspace
from collide.session import share_of
from collide.sources import vectors_io
from collide.streaming import online

SF = "/root/testdata/sf0.001"
PLAN = plan_contiguous(64, 8)
R = random.Random(3)


@pytest.fixture(scope="module")
def emb(spark):
    v = workloads.data(spark, SF, "emb")
    return VectorSet(v.points.persist(), v.queries.persist(), v.d, v.unit, v.n)


@pytest.fixture(scope="module")
def truth(emb):
    return exact_knn(emb.points, emb.queries, 10, 64, unit=emb.unit).persist()


@pytest.fixture(scope="module")
def index(emb):
    return build_cell_index(emb.points, PLAN, IndexParams(sqrt_k=6, iterations=3, grid=True))


@given(st.integers(1, 130), st.integers(1, 20), st.integers(0, 5))
def test_plans_cover_every_dimension_once(d, n_sub, seed):
    if n_sub > d:
        with pytest.raises(ValueError):
            plan_random(d, n_sub, seed)
        return
    for p in (plan_contiguous(d, n_sub), plan_random(d, n_sub, seed)):
        assert sorted(i for x in p.dims for i in x) == list(range(d))
        assert all(len(x) == d // n_sub for x in p.dims[:-1])


def test_odd_dimensions_and_halves():
    p = plan_contiguous(7, 3)
    assert [len(x) for x in p.dims] == [2, 2, 3]
    assert [len(h) for h in p.halves()] == [1, 1, 1, 1, 2, 1]
    assert plan_random(64, 8, 3) == plan_random(64, 8, 3) != plan_random(64, 8, 4)
    assert len(single_subspace(64, 5)) == 5


def test_shares_are_exact_decimals():
    assert share_of(0.07, 100) == 7 and share_of(0.05, 480) == 24 and share_of(0.003, 1000) == 3 and share_of(1e-3, 1) == 1
    assert SearchParams(50, 0.05, 0.005).pool(500) == 50 and SearchParams(5, 0.05, 0.1, max_pool=20).pool(1000) == 20
    assert suggest_params(10**6, 128).beta == 0.005


def test_uneven_axes_are_repaired_by_the_score(spark):
    """Each axis alone ranks a far point first; colliding on both axes marks the near ones."""
    pts = [(1, [0.1, 9.0]), (2, [9.0, 0.1]), (3, [0.5, 0.5]), (4, [0.6, 0.4]), (5, [8.0, 8.0]), (6, [7.0, 9.5])]
    points = spark.createDataFrame(pts, "id long, vec array<double>")
    queries = spark.createDataFrame([(0, [0.0, 0.0])], "qid long, qvec array<double>")
    scores = {r["id"]: r["score"] for r in scan_scores(points, queries, plan_contiguous(2, 2), 3).collect()}
    assert scores == {1: 1, 2: 1, 3: 2, 4: 2, 5: 0, 6: 0}


@pytest.mark.parametrize("metric", ["l2", "l1"])
def test_borders_equal_ranking(emb, metric):
    m = share_of(0.1, emb.n)
    a = scan_scores(emb.points, emb.queries, PLAN, m, metric, "histogram")
    b = scan_scores(emb.points, emb.queries, PLAN, m, metric, "rank")
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))
    total = a.groupBy("qid").agg(F.sum("score").alias("s"), F.max("score").alias("hi"), F.min("score").alias("lo")).collect()
    assert all(r["s"] == 8 * m and 0 <= r["lo"] <= r["hi"] <= 8 for r in total)


@pytest.mark.parametrize("metric,m", [("l2", 24), ("l1", 100), ("l2", 1), ("l2", 480)])
def test_scores_by_distance_classes(emb, metric, m):
    """Two passes give the ranked scores; copies and equal distances included."""
    points = emb.points.unionByName(emb.points.select((F.col("id") + 10_000).alias("id"), "vec").where("id % 3 = 0"))
    plain = {tuple(r) for r in scan_scores(points, emb.queries, PLAN, m, metric, select="rank").collect()}
    assert {tuple(r) for r in scan_scores(points, emb.queries, PLAN, m, metric).collect()} == plain
    assert {tuple(r) for r in hit_scores(points, emb.queries, PLAN, m, metric).collect()} == {r for r in plain if r[2]}


def test_scan_forms_each_distance_twice(spark, emb, monkeypatch):
    """The executed passes over all pairs: one to count, one to write; the pool comes from what was written."""
    from collide.operators import collisions

    passes = []
    real = collisions.part_distances
    monkeypatch.setattr(collisions, "part_distances", lambda *a, **k: passes.append(1) or real(*a, **k))
    result = collision_scan(emb, PLAN, SearchParams(10, 0.1, 0.1), select="histogram")
    assert len(passes) == 1 and "BroadcastNestedLoopJoin" not in result._jdf.queryExecution().executedPlan().toString()


def test_blocks_of_queries_change_nothing(emb, index):
    p = SearchParams(10, 0.1, 0.1)
    for run in (lambda b: collision_scan(b, PLAN, p), lambda b: indexed_search(index, b, p), lambda b: exact_knn(b.points, b.queries, 10, 64)):
        assert {tuple(r) for r in in_blocks(emb, run, rows=6).collect()} == {tuple(r) for r in run(emb).collect()}


def test_numbers_are_those_of_one_sorted_window(spark):
    lines = spark.read.parquet(f"{SF}/lineitem.parquet")
    from pyspark.sql import Window

    plain = lines.select(F.row_number().over(Window.orderBy(*lines.columns)).cast("long").alias("id"), "l_orderkey", "l_linenumber", "l_extendedprice", "l_shipdate")
    mine = numbered(lines.repartition(7)).select(*plain.columns)
    assert plain.exceptAll(mine).isEmpty() and mine.count() == lines.count()


def test_scores_know_ranks_only_by_their_side_of_the_border(spark):
    """Any change of distances that keeps who is inside keeps the scores."""
    rows = [(i, [float(R.randrange(1, 60)), float(R.randrange(1, 60))]) for i in range(80)]
    q = spark.createDataFrame([(0, [0.0, 0.0])], "qid long, qvec array<double>")
    a = spark.createDataFrame(rows, "id long, vec array<double>")
    b = a.select("id", F.transform("vec", lambda x: x * x * x + 5).alias("vec"))
    plan = plan_contiguous(2, 2)
    got = [{tuple(r) for r in scan_scores(p, q, plan, 9, select="rank").collect()} for p in (a, b)]
    assert got[0] == got[1]


@pytest.mark.parametrize("policy", ["hash", "all"])
def test_tie_policies(emb, policy):
    scores = scan_scores(emb.points, emb.queries, PLAN, 48, select="rank").persist()
    plain = top_scored(scores, 40).groupBy("qid").agg(F.min("score").alias("cut"))
    got = top_scored(scores, 40, policy).join(plain, "qid")
    assert got.where("score < cut").isEmpty()
    n = got.groupBy("qid").count()
    assert n.where("count < 40").isEmpty() and (policy == "all" or n.where("count > 40").isEmpty())


def test_pools_by_histogram_and_ranking(emb):
    s = scan_scores(emb.points, emb.queries, PLAN, share_of(0.1, emb.n), select="rank").persist()
    for policy in ("id", "hash"):
        a, b = top_scored(s, 30, policy), top_scored(s, 30, policy, emb.n)
        assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))
    assert top_scored(s, 30, "all").count() >= top_scored(s, 30).count() == 30 * emb.queries.count()
    small = {tuple(r) for r in top_scored(s, 10).collect()}
    assert small <= {tuple(r) for r in top_scored(s, 60).collect()}


def test_full_shares_give_the_truth(emb, truth):
    for found in (collision_scan(emb, PLAN, SearchParams(10, 0.1, 1.0)), collision_scan(emb, PLAN, SearchParams(10, 1.0, 1.0))):
        assert sorted((r["qid"], r["rank"], r["id"]) for r in found.collect()) == sorted((r["qid"], r["rank"], r["id"]) for r in truth.collect())


def test_recall_grows_with_beta(emb, truth):
    r = [evaluate.recall_at_k(collision_scan(emb, PLAN, SearchParams(10, 0.1, b)), truth, 10).first()["recall"] for b in (0.02, 0.1, 0.3, 1.0)]
    assert r == sorted(r) and r[-1] == 1.0 and r[1] > 0.4


def test_a_query_that_is_a_point_ranks_first(emb, index):
    twin = VectorSet(emb.points, emb.points.limit(3).select(F.col("id").alias("qid"), F.col("vec").alias("qvec")), 64, emb.unit, emb.n)
    for found in (collision_scan(twin, PLAN, SearchParams(3, 0.05, 0.1)), indexed_search(index, twin, SearchParams(3, 0.05, 0.1))):
        first = found.where("rank = 1").collect()
        assert all(r["qid"] == r["id"] and r["distance"] == 0 and r["score"] == 8 for r in first)


# --- walks ------------------------------------------------------------------------------------------------------------

D1, D2 = [0.2, 0.4, 0.6, 0.9], [0.5, 0.8, 1.2, 1.4]


def test_walk_example():
    trace: list = []
    got = walks.activation_walk(D1, D2, [[1] * 4] * 4, 6, trace)
    assert got == [(0, 0), (1, 0), (0, 1), (2, 0), (1, 1), (0, 2)]
    assert [round(t[3], 6) for t in trace[:3]] == [0.7, 0.9, 1.0]
    assert trace[3][4] == trace[2][4]  # nothing new opens in the third round


@settings(max_examples=300, deadline=None)
@given(st.data())
def test_walks_agree(data):
    k1, k2 = data.draw(st.integers(1, 6)), data.draw(st.integers(1, 6))
    d1 = sorted(data.draw(st.lists(st.integers(0, 5), min_size=k1, max_size=k1)))
    d2 = sorted(data.draw(st.lists(st.integers(0, 5), min_size=k2, max_size=k2)))
    sizes = [[data.draw(st.integers(0, 3)) for _ in range(k2)] for _ in range(k1)]
    target = data.draw(st.integers(0, sum(map(sum, sizes)) + 2))
    a = walks.activation_walk(d1, d2, sizes, target)
    assert a == walks.heap_walk(d1, d2, sizes, target) == walks.sorted_walk(d1, d2, sizes, target)
    assert len(set(a)) == len(a)


def test_engine_walks_agree(emb, index):
    target = share_of(0.1, index.n)
    got = [sorted(map(tuple, activated_cells(index, emb.queries, target, w).select("qid", "sub", "c1", "c2", "pop_order").collect())) for w in ("prefix", "activation", "heap")]
    assert got[0] == got[1] == got[2]
    stats = evaluate.walk_stats(activated_cells(index, emb.queries, target), target).collect()
    assert all(r["overshoot"] >= 1 for r in stats)


# --- index ------------------------------------------------------------------------------------------------------------


def test_index_invariants(emb, index):
    assert index.codes.count() == emb.n and index.codes.select("id").distinct().count() == emb.n
    assert {r["n"] for r in index.cell_sizes().groupBy("sub").agg(F.sum("n_points").alias("n")).collect()} == {emb.n}
    assert all(b <= a for a, b in zip(index.costs, index.costs[1:]))
    x = {r["id"]: np.array(r["vec"]) for r in emb.points.limit(20).collect()}
    for r in index.codes.where(F.col("id").isin(*x)).collect():
        for h, dims in enumerate(index.parts()):
            cid = r["cells"][h // 2] // 6 if h % 2 == 0 else r["cells"][h // 2] % 6
            far = ((index.centroids[h] - x[r["id"]][list(dims)]) ** 2).sum(axis=1)
            assert far[cid] == far.min()


def test_layouts_agree(emb, index):
    cells = activated_cells(index, emb.queries, share_of(0.1, index.n)).persist()
    a = {tuple(r) for r in count_hits_postings(index.postings(), cells).collect()}
    b = {tuple(r) for r in score_codes(index.codes, cells, 8).where("score > 0").collect()}
    c = {tuple(r) for r in score_codes_arrow(index.codes, cells, 8, 36).where("score > 0").collect()}
    assert a == b == c
    p = SearchParams(10, 0.02, 0.9)  # few hits, so the pool is filled up with points of score 0
    got = [sorted(map(tuple, indexed_search(index, emb, p, layout=x).collect())) for x in ("forward", "inverted", "arrow")]
    assert got[0] == got[1] == got[2]


def test_forward_layout_shuffles_no_hits(emb, index):
    cells = activated_cells(index, emb.queries, share_of(0.1, index.n)).persist()
    cells.count()
    plan = score_codes(index.codes, cells, 8)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastNestedLoopJoin" in plan and "SortMergeJoin" not in plan and "hashpartitioning(id" not in plan and "hashpartitioning(qid, id" not in plan


def test_index_round_trip_and_updates(spark, emb, index, tmp_path):
    index.write(str(tmp_path / "ix"))
    again = CellIndex.load(spark, str(tmp_path / "ix"))
    p = SearchParams(10, 0.1, 0.1)
    assert sorted(map(tuple, indexed_search(again, emb, p).collect())) == sorted(map(tuple, indexed_search(index, emb, p).collect()))
    fewer = index.remove(emb.points.where("id < 50").select("id"))
    assert fewer.n < index.n and fewer.append(emb.points.where("id < 50")).n == index.n
    assert sorted(map(tuple, fewer.append(emb.points.where("id < 50")).codes.collect())) == sorted(map(tuple, index.codes.collect()))


@pytest.mark.parametrize("parts,k", [(1, 16), (3, 3)])
def test_other_numbers_of_parts(emb, truth, parts, k):
    ix = build_flat_index(emb.points, PLAN, k, IndexParams(iterations=2)) if parts == 1 else build_cell_index(emb.points, plan_contiguous(64, 8), IndexParams(sqrt_k=k, iterations=2, parts=parts))
    r = evaluate.recall_at_k(indexed_search(ix, emb, SearchParams(10, 0.2, 0.3)), truth, 10).first()["recall"]
    assert r > 0.5


def test_l1_index_and_other_options(emb):
    true = exact_knn(emb.points, emb.queries, 10, 64, "l1", emb.unit)
    ix = build_cell_index(emb.points, PLAN, IndexParams(sqrt_k=6, iterations=3, metric="l1", how="farthest"))
    assert evaluate.recall_at_k(indexed_search(ix, emb, SearchParams(10, 0.2, 0.3, "l1")), true, 10).first()["recall"] > 0.5
    with pytest.raises(ValueError):
        indexed_search(ix, emb, SearchParams(10, 0.2, 0.3))
    plain = build_cell_index(emb.points, PLAN, IndexParams(sqrt_k=6, iterations=2))
    cells = [activated_cells(plain, emb.queries, 48, half_distance=h).select("qid", "sub", "cell") for h in ("squared", "plain")]
    assert 0.5 < cells[0].intersect(cells[1]).count() / cells[0].count() < 1
    assert suggest_index(10**6).sqrt_k == 50 and suggest_index(800).sqrt_k == 10


def test_stored_postings_are_read_by_cell(spark, emb, index, tmp_path):
    index.write(str(tmp_path / "stored"))
    kept = CellIndex.load(spark, str(tmp_path / "stored"))
    one = VectorSet(emb.points, emb.queries.limit(1).persist(), emb.d, emb.unit, emb.n)
    cells = activated_cells(kept, one.queries, 10).persist()
    hits = count_hits_postings(kept.postings(), cells)
    plan = hits._jdf.queryExecution().executedPlan().toString()
    pushed = plan[plan.index("PushedFilters") :]
    assert "PartitionFilters: [(((" in plan or "sub#" in plan[plan.index("PartitionFilters") : plan.index("PushedFilters")]
    assert "cell" in pushed[: pushed.index("ReadSchema")]
    want = count_hits_postings(index.postings(), cells)
    assert {tuple(r) for r in hits.collect()} == {tuple(r) for r in want.collect()}
    assert {tuple(r) for r in indexed_search(kept, emb, SearchParams(10, 0.1, 0.1), layout="inverted").collect()} == {tuple(r) for r in indexed_search(index, emb, SearchParams(10, 0.1, 0.1)).collect()}


def test_closest_centroids_equal_plain_differences():
    rng = np.random.default_rng(0)
    x, c = rng.standard_normal((5_000, 7)), rng.standard_normal((300, 7))
    c[17] = c[5]
    for metric in ("l1", "l2"):
        diff = x[:, None, :] - c[None]
        far = np.abs(diff).sum(axis=2) if metric == "l1" else (diff * diff).sum(axis=2)
        assert (clustering.assign(x, c, metric) == far.argmin(axis=1)).all()


def test_library_trainer(emb, truth):
    ix = build_cell_index(emb.points, PLAN, IndexParams(sqrt_k=4, iterations=3, trainer="mllib", seed=1))
    assert evaluate.recall_at_k(indexed_search(ix, emb, SearchParams(10, 0.2, 0.3)), truth, 10).first()["recall"] > 0.5


# --- baselines and fronts ---------------------------------------------------------------------------------------------

FULL = {
    "encoded_projection_trees": {"beta": 1.0}, "query_centred_windows": {"beta": 1.0}, "projected_metric_ball": {"beta": 1.0}, "circular_match": {"check_k": 500},
    "rotated_product_quantiser": {"beta": 1.0, "gamma": 1.0}, "projection_forest": {"search_k": 20_000, "trees": 4}, "layered_graph": {"ef": 500}, "tree_graph_hybrid": {"beam": 500, "probes": 500, "hops": 1},
}


@pytest.mark.parametrize("name", FULL)
def test_full_probing_is_exact(emb, truth, name):
    search = (baselines.GUARANTEED | baselines.UNGUARANTEED)[name]
    assert evaluate.recall_at_k(search(emb, 10, **FULL[name]), truth, 10).first()["recall"] == 1.0


@pytest.mark.parametrize("name", FULL)
def test_builds_are_kept_and_searched_again(emb, truth, name):
    """One build answers narrow and wide probes, in any blocks of queries; a wider probe is at least as good, and bytes are those
    of what is stored."""
    method = (baselines.GUARANTEED | baselines.UNGUARANTEED)[name]
    state = method.build(emb, **studies.BUILD.get(name, {}))
    assert state.bytes() > 480 * 8 and all(t.inputFiles() for t in state.tables.values())
    narrow, wide = (method.search(state, emb, 10, **x).persist() for x in studies.SETTINGS[name])
    recall = [evaluate.recall_at_k(r, truth, 10).first()["recall"] for r in (narrow, wide)]
    assert 0.1 < recall[0] <= recall[1] + 0.02
    blocks = in_blocks(emb, lambda b: method.find(state, b, 10, **studies.SETTINGS[name][0]), rows=7)
    assert {tuple(r) for r in blocks.collect()} == {tuple(r) for r in narrow.collect()}


BLOCK_SETTINGS = {"encoded_projection_trees": {"beta": 0.1}, "query_centred_windows": {"beta": 0.1}, "projected_metric_ball": {"beta": 0.1}, "circular_match": {"check_k": 30}, "rotated_product_quantiser": {"beta": 0.05, "gamma": 0.2}, "projection_forest": {"search_k": 40}, "layered_graph": {"ef": 10}, "tree_graph_hybrid": {"probes": 1, "hops": 2, "beam": 12}}


@pytest.mark.parametrize("name", sorted(BLOCK_SETTINGS))
def test_baselines_search_by_blocks(emb, monkeypatch, name):
    """no pool is made a row per query and point and re-ranked by a join; the rows are those of the joins."""
    v, method = emb, (baselines.GUARANTEED | baselines.UNGUARANTEED)[name]
    state = method.build(v)
    rows = lambda df: sorted((r["qid"], r["rank"], r["id"], r["distance"]) for r in df.collect())
    with monkeypatch.context() as m:
        m.setattr(baselines, "rerank", None)
        found = rows(method.search(state, v, 10, **BLOCK_SETTINGS[name]))
    with monkeypatch.context() as m:
        m.setattr(blocks, "NUMBERS", 0)
        assert found == rows(method.search(state, v, 10, **BLOCK_SETTINGS[name]))
    assert len({r[0] for r in found}) == v.queries.count()


def test_leaves_stay_bounded(spark):
    """Four times the points give more leaves, not larger ones."""
    most = []
    for n in (1_000, 4_000):
        v = held_out(vectors_io.synthetic_vectors(spark, n, 16, 3, 20).persist(), 100, 3, 16)
        boxes = baselines.build_encoded_trees(v, leaf_rows=64)["boxes"]
        tree = baselines.build_tree_graph(v, leaf_rows=100)
        most.append((boxes.agg(F.avg("n")).first()[0], max(tree["sizes"].values())))
    assert all(a <= 130 and b <= 200 for a, b in most), most


def test_front_ends(emb, truth):
    for front in ("divide", "lsh", "pca"):
        f = front_end(emb, front, 32)
        assert f.d == (64 if front == "divide" else 32) and f.points.count() == emb.n


# --- measures, theory, costs ------------------------------------------------------------------------------------------


def test_measures(spark):
    truth = spark.createDataFrame([(0, 1, 10, 0.0), (0, 2, 11, 2.0)], "qid long, rank int, id long, distance double")
    found = spark.createDataFrame([(0, 1, 10, 0.0), (0, 2, 12, 3.0)], "qid long, rank int, id long, distance double")
    assert evaluate.recall_at_k(found, truth, 2).first()["recall"] == 0.5
    m = evaluate.mean_relative_error(found, truth).first()
    assert m["mre"] == 0.25 and m["excluded"] == 0
    assert evaluate.recall_by_distance(found, truth, 2).first()["recall"] == 0.5
    assert 0.15 < evaluate.turning_point([(x / 20, math.exp(-x / 2)) for x in range(21)]) < 0.3
    assert evaluate.min_beta_for_recall([(0.1, 0.5), (0.2, 0.9), (0.3, 0.95)], 0.9) == 0.2
    assert costmodel.break_even((0, 10), (100, 5)) == 20 and costmodel.break_even((0, 1), (5, 2)) is None
    assert costmodel.cumulative_cost(5, 0.5, 10) == 10


def test_copies(spark):
    points = spark.createDataFrame([(i, [1.0, 1.0]) for i in range(5)] + [(9, [3.0, 3.0])], "id long, vec array<double>")
    v = VectorSet(points, spark.createDataFrame([(0, [1.0, 1.0])], "qid long, qvec array<double>"), 2, 1.0, 6)
    got = collision_scan(v, plan_contiguous(2, 2), SearchParams(3, 0.5, 0.5)).collect()
    assert [r["id"] for r in sorted(got, key=lambda r: r["rank"])] == [0, 1, 2] and all(r["distance"] == 0 for r in got)


def test_theory():
    for m, var, ns, alpha in ((10.0, 4.0, 8, 0.05), (1.0, 2.0, 10, 0.1)):
        b = theory.ordering_bound(m, var, ns, alpha)
        assert math.isclose(b["probability"], 0.75 - math.exp(-2)) and b["probability"] > b["claimed"]
        assert 0 < theory.alpha_floor(m, var) <= 1
        assert math.isclose(theory.collision_threshold(m, var, alpha) ** 2, (1 - alpha) * (var + m * m))
    assert all(theory.answer_bound(k, n) >= 0.5 for n in (100, 10_000) for k in (1, 10, 50))
    means = [theory.kth_moments(k, 1000, 8, 10.0, 4.0)[0] for k in (1, 10, 100)]
    assert means == sorted(means)


def test_costs_order_the_methods():
    c = {m: costmodel.predict(m, 10_000_000, 128) for m in costmodel.METHODS}
    assert c["indexed"]["query"] < c["scan"]["query"] and c["indexed"]["space"] < c["encoded_projection_trees"]["space"] * 0.2
    assert costmodel.choose_layout(1, 0.03, 10**9, 8) == "inverted" and costmodel.choose_layout(8, 0.1, 10**9, 8) == "forward"
    assert costmodel.choose_layout(100, 0.03, 10**9, 8) == "arrow" and costmodel.clusterings(8) == 16


# --- sources, SQL, streams --------------------------------------------------------------------------------------------


def test_validation(spark):
    ok = spark.createDataFrame([(1, [1.0, 2.0])], "id long, vec array<double>")
    assert validate_vectors(ok) == (1, 2)
    for bad in ([(1, None)], [(1, [1.0]), (2, [1.0, 2.0])], [(1, [float("nan")])], [(1, [float("inf")])]):
        with pytest.raises(ValueError):
            validate_vectors(spark.createDataFrame(bad, "id long, vec array<double>"))


def test_sources(spark, tmp_path):
    rows = [[random.random() for _ in range(4)] for _ in range(25)]
    vectors_io.write_fixed_vectors(str(tmp_path / "x.fvecs"), rows)
    got = vectors_io.load_vectors(spark, str(tmp_path / "x.fvecs"), format="binary").orderBy("id").collect()
    assert [r["vec"] for r in got] == [list(struct.unpack("4f", struct.pack("4f", *x))) for x in rows]
    df = spark.createDataFrame([(i, x) for i, x in enumerate(rows)], "id long, vec array<double>")
    df.write.json(str(tmp_path / "j"))
    assert vectors_io.load_vectors(spark, str(tmp_path / "j"), format="json").count() == 25
    df.selectExpr("concat_ws(',', cast(id as string), vec[0], vec[1], vec[2], vec[3])").write.text(str(tmp_path / "t"))
    assert vectors_io.load_vectors(spark, str(tmp_path / "t"), format="csv").where("size(vec) = 4").count() == 25
    assert validate_vectors(vectors_io.synthetic_vectors(spark, 100, 8, 1, 5)) == (100, 8)


def test_orc_and_sessions(spark, tmp_path):
    df = vectors_io.synthetic_vectors(spark, 40, 4, 1)
    df.write.orc(str(tmp_path / "o"))
    assert vectors_io.load_vectors(spark, str(tmp_path / "o"), format="orc").count() == 40
    e = spark.createDataFrame([(1, "2024-01-01 00:00:00"), (1, "2024-01-01 00:20:00"), (1, "2024-01-01 02:00:00"), (2, "2024-01-01 00:00:00")], "user_id long, ts string")
    assert sorted((r["user_id"], r["n"]) for r in online.user_sessions(e).collect()) == [(1, 1), (1, 2), (2, 1)]


def test_late_rows_are_counted(spark, tmp_path):
    """Rows behind the watermark are dropped, and how many is told."""
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    for i, days in enumerate(([10, 11], [12], [1, 2, 13])):
        spark.createDataFrame([(d, None, 1, "click", 1.0, "{}") for d in days], schema).withColumn("ts", F.timestamp_seconds(F.col("event_id") * 86_400)).coalesce(1).write.mode("append").parquet(str(tmp_path / "in" / str(i)))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in" / "*"))
    q = online.user_windows(stream).writeStream.format("noop").outputMode("append").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert online.late_rows(q) == 2


def test_sql_surface(spark, emb):
    sqlapi.register(spark)
    assert spark.sql("SELECT l2_squared(array(0D, 3D), array(4D, 0D)) AS a, l1_distance(array(0D, 3D), array(4D, 0D)) AS b, subspace_l2(array(0D, 3D), array(4D, 0D), 2, 1) AS c").first()[:] == (25.0, 7.0, 9.0)
    assert spark.sql("SELECT count(*) FROM walk_trace(array(0.2D, 0.4D), array(0.5D, 0.8D), array(1, 1, 1, 1), 4)").first()[0] == 4


def test_streams_equal_batches(spark, index, emb, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    path = str(tmp_path / "events")
    events.write.parquet(path)
    stream = spark.readStream.schema(events.schema).parquet(path)
    q = online.running_counts(stream).writeStream.format("memory").queryName("running").outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination()
    got = {r["user_id"]: r["seen"] for r in spark.sql("SELECT user_id, max(seen) AS seen FROM running GROUP BY user_id").collect()}
    assert got == {r["user_id"]: r["n"] for r in events.groupBy("user_id").agg(F.count("*").alias("n")).collect()}
    q = online.user_windows(stream).writeStream.format("memory").queryName("windows").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    assert sorted(map(tuple, spark.table("windows").collect())) == sorted(map(tuple, online.user_windows(events).collect()))
    points = str(tmp_path / "points")
    emb.points.where("id < 40").write.parquet(points)
    q = online.ingest(index, spark.readStream.schema(emb.points.schema).parquet(points), str(tmp_path / "codes"), str(tmp_path / "cp1"))
    q.awaitTermination()
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "codes")).collect())) == sorted(map(tuple, index.codes.where("id < 40").collect()))
    asked = str(tmp_path / "asked")
    emb.queries.limit(4).write.parquet(asked)
    out = []
    q = online.answer(index, emb.points, spark.readStream.schema(emb.queries.schema).parquet(asked), SearchParams(5, 0.1, 0.1), lambda df, n: out.extend(df.collect()), str(tmp_path / "cp2"))
    q.awaitTermination()
    assert len(out) == 20


# --- oracles ----------------------------------------------------------------------------------------------------------

FAST = ["walk_trace", "clustering_work", "complexity_table", "exact_knn", "collision_scan", "collision_scan_l1", "scan_random_plan", "subspace_collisions", "sweep_beta", "pareto_curve_doc", "cell_codes", "walk_cells_heap", "indexed_search", "user_windows", "asof_user_vector", "walk_trace", "complexity_table", "scaling", "flat_vs_multi", "guarantee_scope", "moments_identity", "front_ends_divide_lsh", "ranks_full_outer", "recall_cube"]


@pytest.mark.parametrize("name", FAST)
def test_oracle(spark, name):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    a, b = workloads.QUERIES[name](spark, SF), con.sql(workloads.ORACLE_SQL[name])
    columns = sorted(a.columns)
    assert columns == sorted(b.columns)
    mine = sorted(repr(tuple(None if r[c] is None else float(r[c]) if isinstance(r[c], (int, float)) else str(r[c]) for c in columns)) for r in a.collect())
    order = [b.columns.index(c) for c in columns]
    theirs = sorted(repr(tuple(None if r[i] is None else float(r[i]) if isinstance(r[i], (int, float)) else str(r[i]) for i in order)) for r in b.fetchall())
    assert mine == theirs


def test_held_out_queries_leave_the_points(spark):
    v = held_out(spark.createDataFrame([(i, [float(i)]) for i in range(50)], "id long, vec array<double>"), 10, 3, 1)
    assert v.n == 45 and v.queries.count() == 5 and v.points.where("id % 10 = 3").count() == 0


@pytest.mark.parametrize("metric", ["l2", "l1"])
def test_nearest_by_blocks_equals_rows_per_pair(spark, metric):
    """off the grid and on it, with ties, copies and a null id; no row is made per pair."""
    rng = np.random.default_rng(3)
    x = np.vstack([rng.integers(-3, 4, (150, 6)), rng.integers(-3, 4, (30, 6)).repeat(3, axis=0)]).astype(float)
    for scale in (1.0, 0.37):
        points = spark.createDataFrame([(None if i == 7 else i, (r * scale).tolist()) for i, r in enumerate(x)], "id long, vec array<double>")
        queries = points.where("id % 9 = 1").select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
        got = exact_knn(points, queries, 12, 6, metric)
        assert "BroadcastNestedLoopJoin" not in got._jdf.queryExecution().toString()
        assert [tuple(r) for r in got.orderBy("qid", "rank").collect()] == [tuple(r) for r in exact_knn(points, queries, 12, 6, metric, kernel="unrolled").orderBy("qid", "rank").collect()]
    assert exact_knn(points, queries.limit(0), 3, 6, metric).count() == 0 == exact_knn(points.limit(0), queries, 3, 6, metric).count()


@pytest.mark.parametrize("metric", ["l2", "l1"])
def test_scan_by_blocks_equals_ranking(spark, metric):
    """scores, pools and ranks of the block form, with many ties and copies; on the grid and off it; no shuffle of pairs."""
    rng = np.random.default_rng(5)
    x = np.vstack([rng.integers(-2, 3, (120, 8)), rng.integers(-2, 3, (20, 8)).repeat(4, axis=0)]).astype(float)
    plan = plan_contiguous(8, 4)
    for scale in (1.0, 0.37):
        v = held_out(spark.createDataFrame([(i, (r * scale).tolist()) for i, r in enumerate(x)], "id long, vec array<double>"), 10, 3, 8)
        for p in (SearchParams(5, 0.1, 0.1, metric), SearchParams(7, 0.3, 0.02, metric), SearchParams(400, 1.0, 1.0, metric)):
            for again in (True, False):
                got = collision_scan(v, plan, p, rank_again=again)
                assert "BroadcastNestedLoopJoin" not in got._jdf.queryExecution().toString()
                assert {tuple(r) for r in got.collect()} == {tuple(r) for r in collision_scan(v, plan, p, "rank", again).collect()}


def test_scores_by_blocks(spark, emb):
    """Scores, counts and the curve without a row for every pair."""
    m = share_of(0.05, emb.n)
    plain = scan_scores(emb.points, emb.queries, PLAN, m, select="rank").where("score > 0")
    got = blocks.scan(emb.points, emb.queries, list(PLAN.dims), 64, m, blocks.scored(1), blocks.SCORED)
    assert {tuple(r) for r in got.collect()} == {tuple(r) for r in plain.collect()}
    counts = blocks.scan(emb.points, emb.queries, list(PLAN.dims), 64, m, blocks.counted(), blocks.COUNTED)
    assert {(r["qid"], r["candidates"], r["collisions"]) for r in counts.collect()} == {tuple(r) for r in plain.groupBy("qid").agg(F.count("id"), F.sum("score")).collect()}


def test_token_counts_where_texts_are_read(spark):
    """null, empty and very long texts, rows of one id, odd white space; no token is shuffled."""
    rows = [(1, "a b c\tA\x0bb"), (1, "a"), (2, None), (3, ""), (4, "İx \U0001f600 " * 30_000), (None, "a\x1fb a")]
    got = vectors.token_counts(spark.createDataFrame(rows, "i long, text string"), "i")
    want = {}
    for i, t in rows:
        for w in spark.createDataFrame([(t,)], "text string").select(F.explode(vectors.tokens())).collect():
            want.setdefault(i, [0.0] * 64)[int(hashlib.md5(w[0].encode()).hexdigest()[:8], 16) % 64] += 1
        want.setdefault(i, [0.0] * 64)
    assert {r["id"]: r["vec"] for r in got.collect()} == want
    assert "Generate" not in got._jdf.queryExecution().executedPlan().toString()


def test_words_of_many_texts_at_once(spark, monkeypatch):
    """texts are cut into words together, as many as the bound allows; a longer one goes by itself."""
    rows = [(i, t) for i, t in enumerate(["", " a\x0bb ", "\u00a0 A\x1fb", "c " * 500, "\n", None, "b a\x85"] * 3)]
    texts = spark.createDataFrame(rows, "i long, text string").coalesce(1)
    seen = []
    for bound in (1, 20, 1 << 23):
        monkeypatch.setattr(vectors, "TEXTS", bound)
        seen.append({r["id"]: r["vec"] for r in vectors.token_counts(texts, "i").collect()})
    want = {i: [0.0] * 64 for i, _ in rows}
    for i, t in rows:
        for w in (t or "").lower().encode().split():
            want[i][int(hashlib.md5(w).hexdigest()[:8], 16) % 64] += 1
    assert seen == [want] * 3


def test_values_summed_by_place(spark):
    """null ids and values, an id of very many rows and one without rows in a batch; dealt out once, and only by id."""
    rng = np.random.default_rng(5)
    rows = [(None if i % 11 == 0 else 7 if i % 2 else int(i % 40), int(rng.integers(0, 12)), None if i % 13 == 0 else float(rng.integers(1, 50))) for i in range(25_000)]
    got = vectors.summed(spark.createDataFrame(rows, "id long, m int, q double"), 12)
    assert got._jdf.queryExecution().executedPlan().toString().count("Exchange") == 1
    want = {}
    for i, m, q in rows:
        want.setdefault(i, [0.0] * 12)[m] += q or 0.0
    found = got.collect()
    assert {r["id"]: r["vec"] for r in found} == want and len(found) == len(want)
    assert vectors.summed(spark.createDataFrame([], "id long, m int, q double"), 12).count() == 0


def test_line_is_written_once(spark):
    """the numbered rows are files already, and hold the vectors alone."""
    from collide import session

    before = len(session._tables)
    v = workloads.data(spark, SF, "line")
    assert len(session._tables) == before + 1 and v.points.columns == ["id", "vec"]
    assert spark.read.parquet(session._tables[-1]).columns == ["at", "vec"]


def test_points_are_collected_into_one_copy(spark):
    """unsorted and null ids, vectors and cells stay together, and beside what was fetched there is one copy at a time."""
    import tracemalloc

    rng = np.random.default_rng(9)
    n, d = 20_000, 32
    x = rng.integers(0, 99, (n, d)).astype(float)
    ids = rng.permutation(n)
    points = spark.createDataFrame([(int(i), r.tolist()) for i, r in zip(ids, x, strict=True)] + [(-1, None)], "id long, vec array<double>").persist()
    codes = points.where("vec IS NOT NULL").select("id", F.array((F.col("id") % 7).cast("int"), (F.col("id") % 3).cast("int")).alias("cells"))
    for cells in (None, codes):
        blocks.collected(points, d, cells)
        tracemalloc.start()
        got = blocks.collected(points, d, cells)
        most = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        assert got.x.dtype == np.float32 and np.array_equal(got.x.T, x[np.argsort(ids)]) and np.array_equal(got.ids, np.arange(n)) and got.top == x.max()
        assert most < 1.9 * got.x.nbytes + 40 * n
    assert np.array_equal(got.codes, [np.arange(n) % 7, np.arange(n) % 3])
    halves = blocks.collected(spark.createDataFrame([(None, [0.1, 2.0]), (5, [3.0, 4.0]), (2, [1.0, 0.0])], "id long, vec array<double>"), 2)
    assert halves.x.dtype == np.float64 and halves.x.T.tolist() == [[0.1, 2.0], [1.0, 0.0], [3.0, 4.0]] and halves.top == np.inf
    assert blocks.collected(points.limit(0), d).x.shape == (d, 0)


def test_distances_by_one_product():
    """lengths as two more dimensions, for values that four bytes hold too."""
    rng = np.random.default_rng(3)
    q, p = rng.integers(-9000, 9000, (5, 8)), rng.integers(-9000, 9000, (8, 70))
    want = ((q[:, :, None] - p[None]) ** 2).sum(axis=1)
    for kind in (np.float32, np.float64):
        got = blocks.distances(q.astype(kind), p.astype(kind), "l2", True)
        assert got.dtype == np.float64 and np.array_equal(got, want)
    best = blocks.Best(5, 4)
    for j in range(0, 70, 9):
        best.offer(want[:, j : j + 9].astype(float), np.arange(70)[j : j + 9])
    best.settle()
    assert [list(best.id[best.q == i]) for i in range(5)] == [list(np.lexsort((np.arange(70), w))[:4]) for w in want]


def test_moments_without_pairs(spark):
    """Mean and variance over all pairs from moments of either side."""
    rng = np.random.default_rng(11)
    x = rng.integers(0, 90, (300, 10)).astype(float)
    v = held_out(spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "id long, vec array<double>"), 10, 3, 10)
    plan = plan_contiguous(10, 3)
    got = {r["sub"]: (r["mean"], r["variance"]) for r in theory.subspace_moments(v.points, v.queries, plan).collect()}
    p, q = x[np.arange(300) % 10 != 3], x[np.arange(300) % 10 == 3]
    for s, dims in enumerate(plan.dims):
        dist = ((p[:, None, list(dims)] - q[None, :, list(dims)]) ** 2).sum(axis=2)
        assert got[s] == pytest.approx((dist.mean(), dist.var()), rel=1e-12)
    assert theory.subspace_moments(v.points, v.queries.limit(0), plan).count() == 0


@pytest.mark.parametrize("parts,half", [(1, "squared"), (2, "squared"), (2, "plain")])
def test_indexed_search_by_blocks_equals_codes(emb, parts, half):
    """the walk, the pool and the neighbours, without a row for every pair or cell."""
    index = build_cell_index(emb.points, PLAN, IndexParams(sqrt_k=5, iterations=1, grid=True, parts=parts))
    for alpha, beta in ((0.05, 0.05), (0.3, 0.02), (1.0, 1.0)):
        p = SearchParams(10, alpha, beta, half_distance=half)
        got = indexed_search(index, emb, p)
        assert "BroadcastNestedLoopJoin" not in got._jdf.queryExecution().toString()
        assert {tuple(r) for r in got.collect()} == {tuple(r) for r in indexed_search(index, emb, p, layout="forward").collect()}
    more = indexed_search(index.remove(emb.points.where("id < 40")), emb, p)  # other points than the index has
    assert {tuple(r) for r in more.collect()} == {tuple(r) for r in indexed_search(index.remove(emb.points.where("id < 40")), emb, p, layout="forward").collect()}


def test_engine_counts_without_pairs(spark):
    """the same counts as from rows per pair."""
    v, p = workloads.data(spark, SF, "emb"), SearchParams(10, 0.1, 0.1)
    scores = scan_scores(v.points, v.queries, PLAN, p.collide(v.n), select="rank")
    got = {r["step"]: r["rows"] for r in workloads.QUERIES["engine_counts"](spark, SF).collect()}
    assert got == {"pairs": v.n * v.queries.count(), "scored": scores.where("score > 0").count(), "pool": top_scored(scores, p.pool(v.n)).count()}
    rows = blocks.scan(v.points, v.queries, list(PLAN.dims), 64, p.collide(v.n), blocks.steps(p.pool(v.n)), blocks.STEPS)
    assert rows.count() == v.queries.count()


def test_queries_without_data_of_their_own(spark, tmp_path):
    """What they give follows from the tables."""
    for t in ("embeddings", "documents", "lineitem"):
        x = spark.read.parquet(f"{SF}/{t}.parquet")
        (x.where("vec_id % 50 <> 7") if t == "embeddings" else x.limit(77)).write.parquet(f"{tmp_path}/{t}.parquet")
    n = spark.read.parquet(f"{tmp_path}/embeddings.parquet").count()
    run = lambda name: workloads.QUERIES[name](spark, str(tmp_path)).collect()
    assert {r["n"] for r in run("complexity_table")} >= {n, 77}
    assert {(r["work"], r["d"]) for r in run("clustering_work")} == {(800 * 480, 64), (2048 * 480, 64)}
    trace = run("walk_trace")
    assert {r["qid"] for r in trace} == {i for i in range(500) if i % 25 == 7 and i % 50 != 7} and len(trace) == 60
    before = len(session._tables)
    workloads.index_of(spark, str(tmp_path))
    between = len(session._tables)
    assert len(run("cell_index_centroids")) == 16 * workloads.ROOT * 4 and len(session._tables) - between == between - before  # built anew


def test_borders_are_found_by_blocks(emb, monkeypatch):
    """No row is made per pair; class counts that are handed on early are added up."""
    want = collision_scan(emb, PLAN, SearchParams(10, 0.1, 0.1), select="rank").collect()
    monkeypatch.setattr(collisions, "paired", lambda *a, **b: pytest.fail("a row per pair"))
    for held in (blocks.HELD, 0):
        monkeypatch.setattr(blocks, "HELD", held)
        got = collision_scan(emb, PLAN, SearchParams(10, 0.1, 0.1), select="histogram").collect()
        assert {tuple(r) for r in got} == {tuple(r) for r in want}


def test_few_picked_need_few_distances(monkeypatch):
    """a pool of a few leaves forms distances to its own points alone, and books are looked up, not decoded for each point."""
    from collide.operators import baseline_blocks

    rng = np.random.default_rng(3)
    x = rng.integers(0, 50, (8, 5_000)).astype(np.float32)
    p = blocks.Points(np.arange(5_000), x, 49.0)
    q = rng.integers(0, 50, (6, 8)).astype(np.float64)
    formed, plain = [], blocks.distances
    monkeypatch.setattr(blocks, "distances", lambda a, b, *rest: formed.append(len(a) * b.shape[1]) or plain(a, b, *rest))
    own = baseline_blocks.members(np.arange(5_000) % 100)
    pick = baseline_blocks.forest(lambda trees, sizes, one: iter([(0, 3), (0, 7)]))
    at, rank, place, dist = baseline_blocks.picked(([], {}, [own]), pick, p, q, True, np.float64, 5)
    assert sum(formed) == 6 * 100
    whole = ((q[:, :, None] - x) ** 2).sum(axis=1)
    pool = np.flatnonzero(np.isin(np.arange(5_000) % 100, (3, 7)))
    for i in range(6):
        want = pool[np.argsort(whole[i, pool], kind="stable")[:5]]
        assert place[at == i].tolist() == want.tolist() and dist[at == i].tolist() == whole[i, want].tolist() and rank[at == i].tolist() == [1, 2, 3, 4, 5]

    c, words = [rng.random((4, 4)) * 50, rng.random((4, 4)) * 50], [rng.random((4, 2)) for _ in range(4)]
    cell, codes = rng.integers(0, 16, 5_000).astype(np.int32), rng.integers(0, 4, (5_000, 4)).astype(np.int32)
    formed.clear()
    marked = baseline_blocks.quantised(2_000, 300)((np.zeros(8), np.eye(8), c, words, cell, baseline_blocks.keys(cell, codes, words)), p, q, np.zeros(6))
    assert sum(formed) <= 6 * 16 * 4 * 4
    decoded = np.hstack([c[0][cell // 4], c[1][cell % 4]]) + np.hstack([w[codes[:, s]] for s, w in enumerate(words)])
    centre = np.array([np.concatenate([c[0][j // 4], c[1][j % 4]]) for j in range(16)])
    for i in range(6):
        order = np.argsort(((q[i] - centre) ** 2).sum(axis=1), kind="stable")
        n = np.bincount(cell, minlength=16)[order]
        inside = np.flatnonzero(np.isin(cell, order[n.cumsum() - n < 2_000]))
        estimate = np.round(((q[i] - decoded[inside]) ** 2).sum(axis=1), 9)
        assert np.flatnonzero(marked[i]).tolist() == sorted(inside[np.argsort(estimate, kind="stable")[:300]].tolist())
