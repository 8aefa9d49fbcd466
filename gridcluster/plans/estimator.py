"""The method as an estimator and model of Spark's ML pipelines."""

from __future__ import annotations

import numpy as np
from pyspark.ml import Estimator, Model
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.sql import DataFrame

from ..operators import kmeans
from ..operators.align import fused_transform
from ..operators.grid import GridSpec
from .pipeline import GridResult, grid_cluster


class _GridParams(Params):
    k = Param(Params._dummy(), "k", "clusters", TypeConverters.toInt)
    seed = Param(Params._dummy(), "seed", "seed", TypeConverters.toInt)
    restarts = Param(Params._dummy(), "restarts", "restarts of k-means", TypeConverters.toInt)
    passes = Param(Params._dummy(), "passes", "Lloyd passes", TypeConverters.toInt)
    aligner = Param(Params._dummy(), "aligner", "affine or linear", TypeConverters.toString)
    fuse = Param(Params._dummy(), "fuse", "map and align in one step", TypeConverters.toBoolean)


class GridClusterer(Estimator, _GridParams):
    """fit: points with row_id, row_grp and feats. The model labels rows of the same row groups."""

    def __init__(self, spec: GridSpec, k: int, seed: int = 0, restarts: int = 5, passes: int = 300, aligner: str = "affine", fuse: bool = True):
        super().__init__()
        self.spec = spec
        self._set(k=k, seed=seed, restarts=restarts, passes=passes, aligner=aligner, fuse=fuse)

    def _fit(self, dataset: DataFrame) -> GridModel:
        get = lambda p: self.getOrDefault(p)
        found = grid_cluster(dataset, self.spec, get(self.k), seed=get(self.seed), restarts=get(self.restarts), passes=get(self.passes), aligner=get(self.aligner), fuse=get(self.fuse))
        return GridModel(self.spec, found)


class GridModel(Model, _GridParams):
    def __init__(self, spec: GridSpec, result: GridResult):
        super().__init__()
        self.spec, self.result = spec, result

    @property
    def centers(self) -> np.ndarray:
        return self.result.centers

    def _transform(self, dataset: DataFrame) -> DataFrame:
        others = tuple(c for c in dataset.columns if c not in ("row_id", "row_grp", "feats"))
        z = fused_transform(dataset, self.spec, self.result.maps, self.result.aligner, keep=others)
        return kmeans.assign(z, self.result.centers)
