"""How well raw rows could be rebuilt if a party's map leaked."""

from __future__ import annotations

import warnings
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .grid import GridSpec
from .numeric import matrix


def leak_probe(points: DataFrame, spec: GridSpec, maps: dict, thin: float = 0.01) -> dict[tuple[int, int], float]:
    """For each party the share of (scaled) variance that the best linear inverse of its map can't recover.

    0 means that rows can be rebuilt from codes by whoever holds the map; below `thin` there is a warning,
    since a code one narrower than the data may leave out very little.
    """
    cols = spec.col_groups
    inverse = {key: np.linalg.pinv(m.proj) for key, m in maps.items()}

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lost: dict[tuple[int, int], np.ndarray] = {}
        for b in it:
            if not b.num_rows:
                continue
            x, grp = matrix(b.column("feats")), b.column("row_grp").to_numpy()
            for i in np.unique(grp):
                for j, c in enumerate(cols):
                    m = maps[int(i), j]
                    s = (x[grp == i][:, list(c)] - m.mean) / m.scale
                    back = s @ m.proj @ inverse[int(i), j]
                    lost[int(i), j] = lost.get((int(i), j), 0) + np.array([((s - back) ** 2).sum(), (s**2).sum()])
        yield pa.RecordBatch.from_pylist([{"i": i, "j": j, "lost": float(v[0]), "all": float(v[1])} for (i, j), v in lost.items()], schema=pa.schema([("i", pa.int32()), ("j", pa.int32()), ("lost", pa.float64()), ("all", pa.float64())]))

    found = points.select("row_grp", "feats").mapInArrow(run, "i int, j int, lost double, all double").groupBy("i", "j").agg(F.sum("lost").alias("lost"), F.sum("all").alias("all")).collect()
    out = {(r["i"], r["j"]): r["lost"] / r["all"] if r["all"] else 0.0 for r in found}
    if any(v < thin for v in out.values()):
        warnings.warn("some party's map keeps nearly all variance: the second privacy layer is thin", stacklevel=2)
    return out
