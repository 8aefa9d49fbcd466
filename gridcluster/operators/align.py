"""Aligners: per row group a linear or affine map from its codes into one common space."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .numeric import gram, list_column, matrix, tsqr

#: Relative cut-off of eigenvalues that count as zero in a pseudo-inverse.
CUTOFF = 1e-12


@dataclass
class Aligner:
    """For each row group the weights of its concatenated code and a shift (zeros when linear)."""

    weights: dict[int, np.ndarray]
    shift: dict[int, np.ndarray]
    kind: str
    cross: np.ndarray
    spans: dict[int, slice]

    @property
    def width(self) -> int:
        return next(iter(self.weights.values())).shape[1]

    def full(self, i: int) -> np.ndarray:
        return np.vstack([self.weights[i], self.shift[i]]) if self.kind == "affine" else self.weights[i]

    def residual(self, a: int, b: int) -> float:
        """Relative difference of two row groups' aligned anchors, from the cross products alone.

        Cancellation leaves a floor near 1e-7; `anchor_difference` compares the rows themselves.
        """
        ga, gb, k = self.full(a), self.full(b), self.cross
        sa, sb = self.spans[a], self.spans[b]
        own = np.trace(ga.T @ k[sa, sa] @ ga)
        other = np.trace(gb.T @ k[sb, sb] @ gb)
        both = np.trace(ga.T @ k[sa, sb] @ gb)
        return float(np.sqrt(max(0.0, own - 2 * both + other) / max(own, 1e-300)))


def anchor_rows(codes: DataFrame) -> tuple[DataFrame, list[tuple[int, int, int]]]:
    """Anchor codes side by side, one row an anchor, and the order of blocks as (row_grp, col_grp, width)."""
    sizes = codes.groupBy("row_grp", "col_grp").agg(F.max(F.size("code")).alias("w")).orderBy("row_grp", "col_grp").collect()
    ordered = F.sort_array(F.collect_list(F.struct("row_grp", "col_grp", "code")))
    wide = codes.groupBy("anchor_id").agg(ordered.alias("blocks")).select("anchor_id", F.flatten("blocks.code").alias("codes"))
    return wide, [(r["row_grp"], r["col_grp"], r["w"]) for r in sizes]


def fit_aligner(codes: DataFrame, kind: str = "affine", width: int | str | float = "min_code", target: str = "U", solver: str = "gram") -> Aligner:
    """Aligners from the parties' anchor codes.

    With all groups' codes A = [A_1 ... A_c] (a column of ones in each when affine) only A'A is needed:
    the left singular vectors are A V / s, so G_i = pinv(A_i'A_i) A_i'A V / s, one small eigenproblem
    for any number of anchors. target US leaves out the division: wide directions stay wide.
    width: a number, a share of the squared singular values (0..1), or `min_code`: the least code width
    of a row group, one more when affine. solver `tsqr` works on the triangular factor of A instead.
    """
    if kind not in ("affine", "linear") or target not in ("U", "US"):
        raise ValueError((kind, target))
    wide, blocks = anchor_rows(codes)
    one = kind == "affine"
    order, spans = block_order(blocks, one)
    if solver == "tsqr":
        ready = wide.select(F.concat("codes", F.array(F.lit(1.0))).alias("codes")) if one else wide
        r = tsqr(ready, "codes")[:, order]
        return solve_aligner(r.T @ r, spans, kind, width, target, r)
    return solve_aligner(gram(wide, "codes", with_one=one)[np.ix_(order, order)], spans, kind, width, target)


def block_order(blocks: list[tuple[int, int, int]], one: bool) -> tuple[list[int], dict[int, slice]]:
    """Columns of the anchors' codes side by side, brought to row groups in a row, each with the trailing constant if `one`; and each group's span."""
    order, spans, at = [], {}, 0
    total = sum(w for *_, w in blocks)
    for i in sorted({b[0] for b in blocks}):
        mine = [k for k, b in enumerate(blocks) if b[0] == i]
        begin = at
        for k in mine:
            offset = sum(b[2] for b in blocks[:k])
            order.extend(range(offset, offset + blocks[k][2]))
            at += blocks[k][2]
        if one:
            order.append(total)
            at += 1
        spans[i] = slice(begin, at)
    return order, spans


def solve_aligner(cross: np.ndarray, spans: dict[int, slice], kind: str, width: int | str | float, target: str, r: np.ndarray | None = None) -> Aligner:
    """The aligners from the cross products of all groups' anchor codes, or better from their triangular factor r."""
    one = kind == "affine"
    if r is not None:
        _, left, vt = np.linalg.svd(r, full_matrices=False)
        v = vt.T
    else:
        values, vectors = np.linalg.eigh(cross)
        left, v = np.sqrt(np.maximum(values[::-1], 0)), vectors[:, ::-1]
    if width == "min_code":
        m = min(s.stop - s.start for s in spans.values())
    elif isinstance(width, float) and 0 < width < 1:
        share = np.cumsum(left**2) / (left**2).sum()
        m = int(np.searchsorted(share, width) + 1)
    else:
        m = int(width)
    m = min(m, int((left > np.sqrt(CUTOFF) * left[0]).sum()))
    lead = v[:, :m] * np.where(np.abs(v[:, :m]).max(axis=0) == v[:, :m].max(axis=0), 1.0, -1.0)
    divide = left[:m] if target == "U" else np.ones(m)
    weights, shift = {}, {}
    for i, s in spans.items():
        if r is not None:
            g = np.linalg.pinv(r[:, s], rcond=np.sqrt(CUTOFF)) @ (r @ lead) / divide
        else:
            g = np.linalg.pinv(cross[s, s], rcond=CUTOFF, hermitian=True) @ (cross[s] @ lead) / divide
        weights[i], shift[i] = (g[:-1], g[-1]) if one else (g, np.zeros(m))
    return Aligner(weights, shift, kind, cross, spans)


def concat_codes(codes: DataFrame, key: str = "row_id") -> DataFrame:
    """Codes of a row's column parties side by side: key, row_grp, code. Fails on a repeated row id."""
    ordered = F.sort_array(F.collect_list(F.struct("col_grp", "code")))
    parts = codes.groupBy(key, "row_grp").agg(ordered.alias("parts"), F.size(F.collect_set("col_grp")).alias("parties"))
    return parts.select(key, "row_grp", _checked(F.flatten("parts.code"), F.size("parts") == F.col("parties"), key).alias("code"))


def _checked(value, ok, key: str):
    """value, or an error: parts of two rows of one id would be added up to a point that neither is."""
    return F.when(ok, value).otherwise(F.raise_error(F.concat(F.lit(f"{key} "), F.coalesce(F.col(key).cast("string"), F.lit("null")), F.lit(" has more or fewer parts than there are column parties: ids must be unique and every party must hold the row"))).cast("array<double>"))


def apply_aligner(codes: DataFrame, aligner: Aligner, widths: dict[tuple[int, int], int], key: str = "row_id") -> DataFrame:
    """Common coordinates of every row: key, row_grp, z.

    The aligner is linear in the concatenated code, so each column party's part is mapped where it
    lies, and one sum by row takes the place of a join of all parts: z = sum of parts + shift.
    Row ids must be unique, and each column party must hold the row: anything else is an error.
    """
    parts: dict[tuple[int, int], np.ndarray] = {}
    for i, w in aligner.weights.items():
        at = 0
        for j in sorted(j for a, j in widths if a == i):
            parts[i, j] = w[at : at + widths[i, j]]
            at += widths[i, j]
    first = {i: min(j for a, j in widths if a == i) for i in aligner.weights}
    m, shift = aligner.width, aligner.shift

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            grp, col = b.column("row_grp").to_numpy(), b.column("col_grp").to_numpy()
            for i, j in sorted(set(zip(grp.tolist(), col.tolist()))):
                mine = pa.array((grp == i) & (col == j))
                part = b.filter(mine)
                z = matrix(part.column("code")) @ parts[i, j] + (shift[i] if j == first[i] else 0)
                yield pa.RecordBatch.from_arrays([part.column(key), part.column("row_grp"), *(pa.array(z[:, k].copy()) for k in range(m))], names=[key, "row_grp", *(f"z{k}" for k in range(m))])

    kind = dict(codes.dtypes)[key]
    mapped = codes.select(key, "row_grp", "col_grp", "code").mapInArrow(run, f"{key} {kind}, row_grp int, " + ", ".join(f"z{k} double" for k in range(m)))
    parties = F.element_at(F.create_map(*(F.lit(x) for i in first for x in (i, sum(a == i for a, _ in widths)))), F.col("row_grp"))
    summed = mapped.groupBy(key, "row_grp").agg(*(F.sum(f"z{k}").alias(f"z{k}") for k in range(m)), F.count(F.lit(1)).alias("parts"))
    return summed.select(key, "row_grp", _checked(F.array(*(f"z{k}" for k in range(m))), F.col("parts") == parties, key).alias("z"))


def fused_transform(points: DataFrame, spec, maps: dict, aligner: Aligner, key: str = "row_id", keep: tuple[str, ...] = ()) -> DataFrame:
    """Trusted single-cluster mode: party map and aligner folded into one affine map a row group; no shuffle.

    Not for parties that must not meet: the hub doesn't hold the maps, the parties don't hold the aligner.
    """
    folded = {}
    for i, w in aligner.weights.items():
        a = np.zeros((spec.width, aligner.width))
        b = aligner.shift[i].copy()
        at = 0
        for j, cols in enumerate(spec.col_groups):
            p = maps[i, j]
            g = p.matrix @ w[at : at + p.width]
            a[list(cols)] = g
            b = b - p.mean @ g
            at += p.width
        folded[i] = (a, b)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            x, grp = matrix(batch.column("feats")), batch.column("row_grp").to_numpy()
            z = np.zeros((len(x), aligner.width))
            for i in np.unique(grp):
                a, b = folded[int(i)]
                z[grp == i] = x[grp == i] @ a + b
            yield pa.RecordBatch.from_arrays([batch.column(key), batch.column("row_grp"), list_column(z), *(batch.column(c) for c in keep)], names=[key, "row_grp", "z", *keep])

    types = dict(points.dtypes)
    extra = "".join(f", {c} {types[c]}" for c in keep)
    return points.select(key, "row_grp", "feats", *keep).mapInArrow(run, f"{key} {types[key]}, row_grp int, z array<double>{extra}")


def anchor_difference(codes: DataFrame, aligner: Aligner, a: int, b: int) -> float:
    """Root mean square difference of the aligned anchors of two row groups over that of the first."""
    widths = {(r["row_grp"], r["col_grp"]): r["w"] for r in codes.groupBy("row_grp", "col_grp").agg(F.max(F.size("code")).alias("w")).collect()}
    z = apply_aligner(codes, aligner, widths, key="anchor_id")
    left = z.where(F.col("row_grp") == a).select("anchor_id", F.col("z").alias("x"))
    right = z.where(F.col("row_grp") == b).select("anchor_id", F.col("z").alias("y"))
    from ..functions.vectors import dot, sqdist

    r = left.join(right, "anchor_id").agg(F.sum(sqdist(F.col("x"), F.col("y"))).alias("d"), F.sum(dot(F.col("x"), F.col("x"))).alias("n")).first()
    return float(np.sqrt(r["d"] / max(r["n"], 1e-300)))
