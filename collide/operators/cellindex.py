"""The cell index: two clusterings per subspace, a cell number per point and subspace."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.subspaces import SubspacePlan
from ..session import materialise, ship
from .clustering import Centroids, assign, lloyd, matrix, mllib_centroids

FORMAT = 1


@dataclass(frozen=True)
class IndexParams:
    """sqrt_k clusters per part; cells of a subspace are all combinations of its parts' clusters."""

    sqrt_k: int = 50
    iterations: int = 10
    parts: int = 2
    seed: int = 0
    trainer: str = "lloyd"
    sample_rows: int | None = None
    metric: str = "l2"
    grid: bool = False
    how: str = "hash"

    def __post_init__(self):
        if self.sqrt_k < 1 or self.iterations < 0 or self.parts < 1 or self.trainer not in ("lloyd", "mllib"):
            raise ValueError(f"bad index parameters: {self}")


def suggest_index(n: int) -> IndexParams:
    """50 clusters per part, fewer where a cell would hold under an eighth of a point on average."""
    return IndexParams(sqrt_k=50 if n >= 20_000 else max(2, int((n / 8) ** 0.5)))


@dataclass(frozen=True)
class CellIndex:
    plan: SubspacePlan
    params: IndexParams
    centroids: Centroids
    codes: DataFrame  # id, cells array<int>
    n: int
    costs: list[float] = field(default_factory=list)
    stored: DataFrame | None = None  # postings on disk, by subspace and sorted by cell

    @property
    def d(self) -> int:
        return self.plan.d

    def parts(self) -> list:
        return self.plan.parts(self.params.parts)

    def centroid_rows(self, spark: SparkSession) -> DataFrame:
        rows = [(h, i, [float(v) for v in c]) for h, x in enumerate(self.centroids) for i, c in enumerate(x)]
        return spark.createDataFrame(rows, "half int, cid int, centroid array<double>")

    def cell_sizes(self) -> DataFrame:
        """sub, cell, n_points of all cells that hold points."""
        return self.codes.select(F.posexplode("cells").alias("sub", "cell")).groupBy("sub", "cell").agg(F.count(F.lit(1)).alias("n_points"))

    def postings(self) -> DataFrame:
        """sub, cell, id: the inverted form, as stored or (not kept after appends) from the codes."""
        if self.stored is not None:
            return self.stored
        return self.codes.select(F.posexplode("cells").alias("sub", "cell"), "id").select("sub", "cell", "id")

    def with_postings(self) -> CellIndex:
        """The inverted form written: sorted by subspace and cell, so that a query's cells are few row groups."""
        sorted_ = self.codes.select(F.posexplode("cells").alias("sub", "cell"), "id").select("sub", "cell", "id").repartitionByRange("sub", "cell").sortWithinPartitions("sub", "cell")
        return replace(self, stored=materialise(sorted_, "postings"))

    def append(self, points: DataFrame) -> CellIndex:
        """New points under the frozen centroids: one map over them, no retraining, the codes there are stay as they are."""
        more = materialise(assign_codes(points, self.centroids, self.parts(), self.d, self.params.metric, self.params.parts), "codes")
        return replace(self, codes=self.codes.unionByName(more), n=self.n + more.count(), stored=None)

    def remove(self, ids: DataFrame) -> CellIndex:
        codes = materialise(self.codes.join(ids.select("id"), "id", "left_anti"), "codes")
        return replace(self, codes=codes, n=codes.count(), stored=None)

    def footprint(self) -> int:
        """Bytes of centroids and cell numbers, without vectors: two bytes per cell number, eight per id and value."""
        return 8 * sum(c.size for c in self.centroids) + self.n * (8 + 2 * self.plan.n_sub)

    def write(self, path: str) -> None:
        """Codes, postings (by subspace, sorted by cell, so a query reads only its cells) and all that is needed to use them."""
        spark = self.codes.sparkSession
        self.codes.write.mode("overwrite").parquet(f"{path}/codes")
        self.postings().repartitionByRange("sub", "cell").sortWithinPartitions("sub", "cell").write.mode("overwrite").partitionBy("sub").parquet(f"{path}/postings")
        self.centroid_rows(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/centroids")
        meta = {"format": FORMAT, "d": self.d, "dims": self.plan.dims, "kind": self.plan.kind, "plan_seed": self.plan.seed, "n": self.n, "params": self.params.__dict__}
        spark.createDataFrame([(json.dumps(meta),)], "meta string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")

    @staticmethod
    def load(spark: SparkSession, path: str) -> CellIndex:
        meta = json.loads(spark.read.text(f"{path}/meta").first()[0])
        if meta["format"] != FORMAT:
            raise ValueError(f"index format {meta['format']}, expected {FORMAT}")
        plan = SubspacePlan(meta["d"], tuple(tuple(x) for x in meta["dims"]), meta["kind"], meta["plan_seed"])
        rows = spark.read.parquet(f"{path}/centroids").orderBy("half", "cid").collect()  # sqrt_k x d numbers
        halves: dict[int, list] = {}
        for r in rows:
            halves.setdefault(r["half"], []).append(r["centroid"])
        return CellIndex(plan, IndexParams(**meta["params"]), [np.array(halves[h]) for h in sorted(halves)], spark.read.parquet(f"{path}/codes"), meta["n"], stored=spark.read.parquet(f"{path}/postings").select(F.col("sub").cast("int").alias("sub"), "cell", "id"))


def assign_codes(points: DataFrame, centroids: Centroids, parts: list, d: int, metric: str = "l2", per_sub: int = 2) -> DataFrame:
    """id, cells: one map over the points. A cell's number counts its parts' clusters like digits."""
    ship(points.sparkSession)
    shared = points.sparkSession.sparkContext.broadcast(centroids)

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = shared.value
        for b in batches:
            x = matrix(b.column("vec"), d)
            cells = np.zeros((len(x), len(parts) // per_sub), dtype=np.int32)
            for h, dims in enumerate(parts):
                s = h // per_sub
                cells[:, s] = cells[:, s] * len(c[h]) + assign(x[:, list(dims)], c[h], metric)
            offsets = pa.array(np.arange(0, cells.size + 1, cells.shape[1], dtype=np.int32))
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.ListArray.from_arrays(offsets, pa.array(cells.reshape(-1), pa.int32()))], ["id", "cells"])

    return points.select("id", "vec").mapInArrow(code, "id long, cells array<int>")


def build_cell_index(points: DataFrame, plan: SubspacePlan, params: IndexParams = IndexParams()) -> CellIndex:
    """Train, encode, keep. One scan per round for all clusterings and one to encode."""
    parts = plan.parts(params.parts)
    if params.trainer == "mllib":
        centroids, costs = mllib_centroids(points, parts, params.sqrt_k, params.iterations, params.seed), []
    else:
        centroids, costs = lloyd(points, parts, params.sqrt_k, plan.d, params.iterations, params.seed, params.grid, params.metric, params.sample_rows, params.how)
    codes = materialise(assign_codes(points, centroids, parts, plan.d, params.metric, params.parts), "codes")
    return CellIndex(plan, params, centroids, codes, codes.count(), costs)


def build_flat_index(points: DataFrame, plan: SubspacePlan, k: int, params: IndexParams = IndexParams()) -> CellIndex:
    """The contrast: k clusters over whole subspaces."""
    return build_cell_index(points, plan, replace(params, parts=1, sqrt_k=k))
