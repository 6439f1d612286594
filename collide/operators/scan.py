"""Index-free search by collision scores."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..functions.vectors import VectorSet
from ..plans.subspaces import SubspacePlan
from ..session import share_of
from . import blocks
from .candidates import rerank, top_scored, without_rerank
from .collisions import hit_scores, scan_scores, with_zeros
from .exact import in_blocks, reported


@dataclass(frozen=True)
class SearchParams:
    """k neighbours; alpha, the share of points that collide in a subspace; beta, the share re-ranked (k rows at least)."""

    k: int = 50
    alpha: float = 0.05
    beta: float = 0.005
    metric: str = "l2"
    tie_policy: str = "id"
    half_distance: str = "squared"
    max_pool: int | None = None

    def __post_init__(self):
        if self.k < 1 or not 0 < self.alpha <= 1 or not 0 < self.beta <= 1:
            raise ValueError("k >= 1 and alpha, beta in (0, 1]")
        if self.half_distance not in ("squared", "plain"):
            raise ValueError("half_distance is squared or plain")

    def collide(self, n: int) -> int:
        return share_of(self.alpha, n)

    def pool(self, n: int) -> int:
        """Rows re-ranked. A cap (max_pool) gives up the stated guarantee; it is for pools that no cluster could re-rank."""
        p = max(self.k, share_of(self.beta, n))
        return min(p, max(self.k, self.max_pool)) if self.max_pool else p


def suggest_params(n: int, d: int, hard: bool = False, k: int = 50) -> SearchParams:
    """Defaults by size: smaller shares for more points, a larger pool for hard data, and few enough full scores at small beta."""
    alpha = 0.05 if n < 50_000_000 else 0.03
    beta = (0.005 if n < 50_000_000 else 0.003) * (2 if hard else 1)
    if beta * n < 4 * k:
        beta = min(1.0, 4 * k / max(n, 1))
    return SearchParams(k, alpha, beta)


def collision_scan(data: VectorSet, plan: SubspacePlan, params: SearchParams, select: str = "auto", rank_again: bool = True) -> DataFrame:
    """qid, rank, id, distance, score. select: blocks (all points broadcast, queries dealt out), histogram (no ranking of all points),
    rank (plain), or auto: blocks where the points fit, else histogram. All give the same rows. Without rank_again the scores alone
    decide, and there is no distance."""
    if select == "auto":
        select = "blocks" if blocks.fits(data.n, data.d) and params.tie_policy == "id" and plan.n_sub < 256 else "histogram"
    if select == "blocks":
        points, scores = blocks.collected(data.points, data.d), blocks.collisions(list(plan.dims), params.collide(data.n), params.metric)
        if not rank_again:
            return blocks.by_query(points, data.queries, data.d, scores, blocks.best(params.k), blocks.BEST)
        return reported(blocks.by_query(points, data.queries, data.d, scores, blocks.found(params.k, params.pool(data.n)), blocks.FOUND), params.metric, data.unit)
    return in_blocks(data, lambda block: _scan_block(block, plan, params, select, rank_again))


def _scan_block(data: VectorSet, plan: SubspacePlan, params: SearchParams, select: str, rank_again: bool) -> DataFrame:
    if select == "rank":
        scores = scan_scores(data.points, data.queries, plan, params.collide(data.n), params.metric, select)
    else:
        hits = hit_scores(data.points, data.queries, plan, params.collide(data.n), params.metric)
        scores = with_zeros(hits, data.points, data.queries, min(data.n, params.pool(data.n) if rank_again else params.k))
    if not rank_again:
        return without_rerank(scores, params.k)
    pool = top_scored(scores, params.pool(data.n), params.tie_policy, data.n if select == "rank" else None)
    return rerank(pool, data.points, data.queries, params.k, data.d, params.metric, data.unit)
