"""When affine aligners can make all row groups' codes equal, and aligners that do."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .grid import GridSpec


def block_projection(spec: GridSpec, maps: dict, i: int) -> tuple[np.ndarray, np.ndarray]:
    """Row group i's whole map as (features x code, mean): its parties' maps on the diagonal."""
    total = sum(maps[i, j].width for j in range(len(spec.col_groups)))
    f, mean, at = np.zeros((spec.width, total)), np.zeros(spec.width), 0
    for j, cols in enumerate(spec.col_groups):
        m = maps[i, j]
        f[np.ix_(list(cols), range(at, at + m.width))] = m.matrix
        mean[list(cols)] = m.mean
        at += m.width
    return f, mean


@dataclass
class ExactnessReport:
    """equal_ranges: all maps span the same directions; full_rank: the anchors' codes have full rank with ones.

    Both together: affine aligners exist under which all groups' anchors coincide. The recipe by singular
    vectors need not be those, and rows beside the anchors' span are not covered.
    """

    equal_ranges: bool
    full_rank: bool
    angle: float

    @property
    def affine_exact(self) -> bool:
        return self.equal_ranges and self.full_rank


def exactness_report(projections: dict[int, np.ndarray], anchor_codes: dict[int, np.ndarray], tol: float = 1e-8) -> ExactnessReport:
    """angle: the largest sine between the ranges of two maps. Unequal widths have unequal ranges."""
    bases = {i: np.linalg.qr(f)[0] for i, f in projections.items()}
    first = next(iter(bases.values()))
    angle = 0.0
    for b in bases.values():
        if b.shape != first.shape:
            angle = 1.0
            break
        angle = max(angle, float(np.linalg.norm(b - first @ (first.T @ b), 2)))
    ranks = all(np.linalg.matrix_rank(np.hstack([a, np.ones((len(a), 1))])) == a.shape[1] + 1 for a in anchor_codes.values())
    return ExactnessReport(angle <= tol, ranks, angle)


def exact_affine(projections: dict[int, np.ndarray], means: dict[int, np.ndarray]) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """For maps of one range: weights and shift of each group under which every row has common coordinates.

    With B a basis of the range, F_i = B T_i; weights T_i^-1 bring codes to B, and the shift puts the
    group's own mean back, so x maps to x B whatever the group.
    """
    basis = np.linalg.qr(next(iter(projections.values())))[0]
    out = {}
    for i, f in projections.items():
        inner = basis.T @ f
        out[i] = (np.linalg.inv(inner), means[i] @ basis)
    return out
