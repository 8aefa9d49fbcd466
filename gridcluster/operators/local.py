"""Neighbours, components and embeddings of one table that a task can hold: exact, without a matrix of rows x rows."""

from __future__ import annotations

import warnings
from collections.abc import Iterable

import numpy as np
import pyarrow as pa

from .numeric import fix_signs

#: Rows of a leaf, about; leaves beyond the least number that a row's first radius comes from.
LEAF_ROWS, LOOK_LEAVES = 256, 7
#: Rows that are sifted at once for a leaf.
SIFT_ROWS = 2048
#: Eight rows that are all too far, as bytes, and the part of a radius that rounding may be.
ALL_FAR, SLACK_PART = np.uint64(0x0101010101010101), 0.05
#: Products with the edges in one filter, at most.
MOST_DEGREE = 300
#: Nodes whose sums of edges are made at once, and edges and rows of vectors that other steps take at once.
NODES, SOME_EDGES, SOME_ROWS = 4096, 1 << 20, 1 << 16
#: Places of nodes in one process, of which there are some twenty for each node.
PLACE = np.int32


class LeafTree:
    """Rows in the leaves of a tree of median cuts, each with its box: only leaves whose box may hold a neighbour are searched.

    Of rows in one place the q + 1 of least id are searched; any other has the q of least id for neighbours. The
    bounds are sums of the same differences, in the same order, as the distances, so rounding leaves no neighbour out.
    """

    def __init__(self, ids: np.ndarray, z: np.ndarray, q: int, leaf: int = LEAF_ROWS):
        order = np.lexsort((ids, *z.T[::-1]))
        same = np.concatenate([[False], (z[order[1:]] == z[order[:-1]]).all(axis=1)]) if len(ids) else np.zeros(0, dtype=bool)
        begin = np.maximum.accumulate(np.where(same, 0, np.arange(len(ids)))) if len(ids) else order
        more = np.arange(len(ids)) - begin > q
        self.q, self.more = q, ids[order[more]]
        self.first = ids[order[begin[more, None] + np.arange(q)]] if more.any() else np.zeros((0, q), dtype=np.int64)
        cut = [np.sort(order[~more])]
        done = []
        while cut:
            rows = cut.pop()
            if len(rows) <= leaf:
                done.append(rows)
                continue
            x = z[rows]
            widest = int((x.max(axis=0) - x.min(axis=0)).argmax())
            half = np.argpartition(x[:, widest], len(rows) // 2)
            cut += [rows[half[: len(rows) // 2]], rows[half[len(rows) // 2 :]]]
        done = [d for d in done if len(d)]
        rows = np.concatenate([*done, np.zeros(0, dtype=np.int64)])
        self.begin = np.concatenate([[0], np.cumsum([len(d) for d in done])]).astype(np.int64)
        self.ids, self.z = ids[rows], z[rows]
        self.middle = self.z.mean(axis=0) if len(rows) else np.zeros(z.shape[1])
        self.sift, self.held = _sifter(self.z, self.middle), None
        self.low = np.array([z[d].min(axis=0) for d in done]).reshape(len(done), z.shape[1])
        self.high = np.array([z[d].max(axis=0) for d in done]).reshape(len(done), z.shape[1])

    def __len__(self) -> int:
        return len(self.low)

    def nearest(self, leaves: Iterable[int], include_self: bool = False) -> pa.Table:
        """src, dst, dist of the rows of some leaves, and of their share of the rows in crowded places."""
        from .graph import _EDGES

        out = [_EDGES.empty_table()]
        for i in leaves:
            own = slice(self.begin[i], self.begin[i + 1])
            x = self.z[own]
            near = np.zeros(len(self))
            for c in range(x.shape[1]):
                near += np.maximum(np.maximum(self.low[:, c] - self.high[i, c], self.low[i, c] - self.high[:, c]), 0) ** 2
            radius = self._radius(x, near)
            some = np.nonzero(near <= radius.max())[0]
            # a few of the rows meet most of the boxes that any row does
            met = self._met(x[::8], radius[::8], some)
            rest = some[~met]
            rows = self._rows(np.sort(np.concatenate([some[met], rest[self._met(x, radius, rest)]])))
            out.append(pa.table(self._closest(i, rows, radius, include_self), schema=_EDGES))
            a, b = len(self.more) * i // len(self), len(self.more) * (i + 1) // len(self)
            if a < b:
                out.append(pa.table({"src": np.repeat(self.more[a:b], self.q), "dst": self.first[a:b].reshape(-1), "dist": np.zeros((b - a) * self.q)}, schema=_EDGES))
        return pa.concat_tables(out)

    def _met(self, x: np.ndarray, radius: np.ndarray, leaves: np.ndarray) -> np.ndarray:
        """Whether the box of each leaf lies within a row's radius."""
        gap, over, under = (np.zeros((len(x), len(leaves))) for _ in range(3))
        for c in range(x.shape[1]):
            np.subtract(self.low[leaves, c], x[:, c : c + 1], out=over)
            np.subtract(x[:, c : c + 1], self.high[leaves, c], out=under)
            np.maximum(over, under, out=over)
            np.maximum(over, 0, out=over)
            gap += np.multiply(over, over, out=over)
        return (gap <= radius[:, None]).any(axis=0)

    def _radius(self, x: np.ndarray, near: np.ndarray) -> np.ndarray:
        """For each row of a leaf a distance within which it has q others, from the leaves that are nearest to its own."""
        by = np.argsort(near, kind="stable")
        enough = int(np.searchsorted(np.cumsum(np.diff(self.begin)[by]), 2 * self.q + 1)) + LOOK_LEAVES
        known = self._rows(by[:enough])
        if len(known) <= self.q:
            return np.full(len(x), np.inf)
        middle = x.mean(axis=0)
        with np.errstate(over="ignore", invalid="ignore", under="ignore"):
            square, left = _left(x, middle)
            # the q-th beside the row itself, and more than the products' rounding
            d = np.partition(left @ _sifter(self.z[known], middle).T, self.q, axis=1)[:, self.q] + square
            d += _rounding(square, np.maximum(d, 0), x.shape[1])
        return np.where(np.isfinite(d), d, np.inf)

    def _closest(self, leaf: int, rows: np.ndarray, radius: np.ndarray, include_self: bool) -> dict[str, np.ndarray]:
        """The q of some rows that are nearest to each row of a leaf, ties to the lower id; none lies beyond radius.

        Single-precision products sift the rows; their limit lies above the radius by more than their rounding, and
        what is left is compared by differences. They are taken around the middle of all rows, or, where their rounding
        would be much of a radius, around the leaf's.
        """
        x, ids = self.z[self.begin[leaf] : self.begin[leaf + 1]], self.ids[self.begin[leaf] : self.begin[leaf + 1]]
        width = x.shape[1]
        with np.errstate(over="ignore", invalid="ignore", under="ignore"):
            middle = self.middle
            square, left = _left(x, middle)
            more = _rounding(square, radius, width)
            shared = bool((more <= SLACK_PART * radius).all())
            if not shared:
                middle = x.mean(axis=0)
                square, left = _left(x, middle)
                more = _rounding(square, radius, width)
            limit = (radius - square + more).astype(np.float32)[:, None]
            held = []
            for at in range(0, len(rows), SIFT_ROWS):
                some = rows[at : at + SIFT_ROWS]
                b = self.sift.take(some, axis=0) if shared else _sifter(self.z[some], middle)
                size = len(x), -(-len(b) // 8) * 8
                far, product = self._buffers(len(x) * SIFT_ROWS)
                far, product = far[: size[0] * size[1]].reshape(size), product[: len(x) * len(b)].reshape(len(x), len(b))
                far[:, len(b) :] = True
                np.greater(np.matmul(left, b.T, out=product), limit, out=far[:, : len(b)])
                eights = np.flatnonzero(far.reshape(-1).view(np.uint64) != ALL_FAR)  # few hold a near row
                eight, one = np.nonzero(~far.reshape(-1, 8)[eights])
                row, col = np.divmod(eights[eight] * 8 + one, size[1])
                held.append((row, col + at))
        row, col = (np.concatenate(c) for c in zip(*held))
        a, b, d = x.take(row, axis=0), self.z.take(rows[col], axis=0), np.zeros(len(row))
        for c in range(width):  # differences, not products: equal points are at distance 0
            d += (a[:, c] - b[:, c]) ** 2
        to = self.ids[rows[col]]
        ok = np.isfinite(d) if include_self else np.isfinite(d) & (to != ids[row])
        row, to, d = row[ok], to[ok], d[ok]
        if len(held) > 1:
            order = np.argsort(row.astype(np.int16) if len(x) < 1 << 15 else row, kind="stable")
            row, to, d = row[order], to[order], d[order]
        place = np.arange(len(row)) - np.searchsorted(row, row)
        if 0 < self.q < place.max(initial=-1):
            table = np.full((len(x), int(place.max()) + 1), np.inf)
            table[row, place] = d
            few = d <= np.partition(table, self.q - 1, axis=1)[row, self.q - 1]
            row, to, d = row[few], to[few], d[few]
        order = np.lexsort((to, d, row))
        row, to, d = row[order], to[order], d[order]
        first = np.arange(len(row)) - np.searchsorted(row, row) < self.q
        return {"src": ids[row[first]], "dst": to[first], "dist": d[first]}

    def _buffers(self, cells: int) -> tuple[np.ndarray, np.ndarray]:
        """Memory of a block's comparisons, which all leaves share."""
        if self.held is None or len(self.held[0]) < cells:
            self.held = np.empty(cells, dtype=bool), np.empty(cells, dtype=np.float32)
        return self.held

    def __getstate__(self) -> dict:
        return self.__dict__ | {"held": None}

    def _rows(self, leaves: np.ndarray) -> np.ndarray:
        count = self.begin[leaves + 1] - self.begin[leaves]
        return np.arange(int(count.sum())) + np.repeat(self.begin[leaves] - np.cumsum(count) + count, count)


def _sifter(z: np.ndarray, middle: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore", invalid="ignore", under="ignore"):
        b = (z - middle).astype(np.float32)
        return np.hstack([b, np.einsum("ij,ij->i", b, b)[:, None]])


def _left(x: np.ndarray, middle: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Squared lengths, and rows whose products with those of `_sifter` are squared distances less these."""
    a = x - middle
    return (a**2).sum(axis=1), np.hstack([-2 * a, np.ones((len(a), 1))]).astype(np.float32)


def _rounding(square: np.ndarray, radius: np.ndarray, width: int) -> np.ndarray:
    """More than what single precision may be off for points within radius."""
    reach = (2 * np.sqrt(square) + np.sqrt(radius)) ** 2
    return np.where(reach < 1e36, 4 * (width + 4) * np.finfo(np.float32).eps * reach + 1e-36, np.inf)


def least_roots(n: int, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """For each of n nodes the least node that the links left, right tie it to."""
    root = np.arange(n, dtype=PLACE)
    while True:
        a, b = root[left], root[right]
        low, new = np.minimum(a, b), root.copy()
        np.minimum.at(new, a, low)  # roots are hooked, so whole trees move
        np.minimum.at(new, b, low)
        while not np.array_equal(new, new[new]):
            new = new[new]
        if np.array_equal(new, root):
            return root
        root = new


#: Patches of a graph whose eigenvectors the search for the graph's own begins with: the matrix of more patches than a
#: graph is worth takes longer than the products that it saves.
PATCHES, LEAST_PATCHES, PATCH_NODES = 1000, 128, 40


#: Residual of a vector in parts of the gap to the first that isn't wanted, and a residual that is always small enough.
GAP_PART, LEAST_LEFT = 0.1, 1e-7


def patches(n: int, at_s: np.ndarray, at_d: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """The patch of each node of a graph, grown along edges from a drawn node each; -1 in components without one."""
    patch = np.full(n, -1, dtype=PLACE)
    drawn = rng.choice(n, min(PATCHES, max(LEAST_PATCHES, n // PATCH_NODES), -(-n // 4)), replace=False)
    patch[drawn] = np.arange(len(drawn))
    open_ = patch[at_s] < 0
    s, d = at_s[open_], at_d[open_]
    while True:
        met = patch[d] >= 0
        if not met.any():
            return patch
        patch[s[met]] = patch[d[met]]
        open_ = patch[s] < 0
        s, d = s[open_], d[open_]


def coarse_vectors(patch: np.ndarray, at_s: np.ndarray, at_d: np.ndarray, w: np.ndarray, root: np.ndarray, count: int) -> np.ndarray:
    """Rough eigenvectors, at most count: those of the graph of patches.

    They vary over the graph as the wanted ones do, which a filter needs hundreds of products to make from noise.
    """
    m, inside = int(patch.max()) + 1, patch >= 0
    weights, links = np.zeros(m * m), []
    for e in range(0, len(w), SOME_EDGES):
        a, b = patch[at_s[e : e + SOME_EDGES]], patch[at_d[e : e + SOME_EDGES]]
        known = (a >= 0) & (b >= 0)
        pairs = a[known].astype(np.int64) * m + b[known]
        weights += np.bincount(pairs, weights=w[e : e + SOME_EDGES][known], minlength=m * m)
        links.append(np.unique(pairs))
    weights, (a, b) = weights.reshape(m, m), np.divmod(np.unique(np.concatenate(links)), m)
    size = np.sqrt(np.bincount(patch[inside], weights=root[inside] ** 2, minlength=m))
    flat = len(np.unique(least_roots(m, a, b)))  # as many vectors of components, which are known
    vectors = np.linalg.eigh(weights / np.outer(size, size))[1][:, ::-1][:, flat : flat + count]
    out = (vectors / size[:, None])[patch]
    out *= root[:, None]
    out[~inside] = 0.0
    return out


def sparse_embedding(ids: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray, k: int, tol: float, degree: int, rounds: int = 60, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """The eigenvalues and vectors of `spectral.dense_embedding`, of symmetric edges, without the matrix.

    Each component of the graph has one vector of eigenvalue 0, which is written down; of more than k components
    those of most rows count. The others come from subspace iteration with a Chebyshev filter, as in
    `spectral.subspace_embedding`, to a residual of at most tol.
    """
    n = len(ids)
    # edges that come twice, as those of mutual neighbours, are put together
    at = links_between(ids, src, dst)
    by = np.argsort(at, kind="stable")
    at, w = at[by], np.asarray(w, dtype=np.float64)[by]
    first = np.nonzero(np.concatenate([[True], at[1:] != at[:-1]]))[0]
    at, w = at[first], np.add.reduceat(w, first)
    return _embedding(n, *_ends(at, n), w, k, tol, degree, rounds, seed)


def neighbour_links(ids: np.ndarray, z: np.ndarray, q: int) -> list[np.ndarray]:
    """The q nearest of each row, ties by id, for `neighbour_embedding`. ids are sorted."""
    tree, out = LeafTree(ids, z, q), []
    for a in range(0, len(tree), 64):
        t = tree.nearest(range(a, min(a + 64, len(tree))))
        out.append(links_between(ids, t["src"].to_numpy(), t["dst"].to_numpy()))
    return out


def links_between(ids: np.ndarray, src: np.ndarray, dst: np.ndarray) -> np.ndarray:
    """Pairs of ids as one number each: place of src * n + place of dst."""
    return _positions(ids, src) * len(ids) + _positions(ids, dst)


def neighbour_embedding(n: int, links: list[np.ndarray], k: int, tol: float, degree: int, rounds: int = 60, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """The same of the neighbour graph of n rows, made symmetric by the mean. links: arrays of place of a row * n + place of
    a neighbour, each pair once; the list is emptied, as some 16 bytes an edge are held besides it."""
    count = sum(map(len, links))
    both, at = np.empty(2 * count, dtype=np.int64), 0
    while links:
        one = links.pop()
        both[at : at + len(one)] = one
        s, d = _ends(one, n)
        np.add(np.multiply(d, n, dtype=np.int64), s, out=both[at + len(one) : at + 2 * len(one)])
        at += 2 * len(one)
    both.sort()
    first = np.concatenate([[True], both[1:] != both[:-1]])
    mutual = np.concatenate([~first[1:], [False]])[first]
    both = both[first]
    s, d = _ends(both, n)
    del both, first
    return _embedding(n, s, d, mutual, k, tol, degree, rounds, seed)


def _ends(at: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Both nodes of links that are written as one number, in four bytes each."""
    s, d = np.empty(len(at), dtype=PLACE), np.empty(len(at), dtype=PLACE)
    for e in range(0, len(at), SOME_EDGES):
        s[e : e + SOME_EDGES], d[e : e + SOME_EDGES] = np.divmod(at[e : e + SOME_EDGES], n)
    return s, d


def _embedding(n: int, at_s: np.ndarray, at_d: np.ndarray, w: np.ndarray, k: int, tol: float, degree: int, rounds: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """w: weights of the edges, or whether an edge is of weight 1, not a half."""
    rng = np.random.default_rng(seed)
    patch = patches(n, at_s, at_d, rng)
    order = np.argsort(patch, kind="stable")  # what is near in the graph is near in memory
    place = np.empty(n, dtype=PLACE)
    place[order] = np.arange(n)
    patch = patch[order]
    del order
    at = np.multiply(place[at_s], 2 * n if w.dtype == bool else n, dtype=np.int64)
    if w.dtype == bool:
        at += 2 * place[at_d] + w  # the weight travels in the last bit
        del at_s, at_d
        at.sort()
        w = np.where(at & 1, np.float32(1), np.float32(0.5))
        at >>= 1
    else:
        at += place[at_d]
        by = np.argsort(at, kind="stable")
        at, w = at[by], w[by]
        del at_s, at_d, by
    at_s, at_d = _ends(at, n)
    del at
    begin = np.searchsorted(at_s, np.arange(n + 1, dtype=PLACE))
    root = np.sqrt(np.where(np.diff(begin) > 0, np.add.reduceat(w, np.minimum(begin[:-1], len(w) - 1), dtype=np.float64), 0.0))
    one_way = at_s < at_d
    _, part, rows = np.unique(least_roots(n, at_s[one_way], at_d[one_way]), return_inverse=True, return_counts=True)
    unit = root / np.sqrt(np.bincount(part, weights=root**2))[part]
    flat = np.argsort(-rows, kind="stable")[:k]
    still = np.where(part[:, None] == flat, unit[:, None], 0.0)
    rest = k - len(flat)
    if not rest:
        return np.zeros(k), fix_signs(still[place])
    size = min(max(8, rest + max(4, k)), n - len(rows))
    x = coarse_vectors(patch, at_s, at_d, w, root, size)
    times = Products(n, at_s, at_d, w, 1 / root)
    del at_s, at_d, w, one_way, begin, patch

    def moving(x: np.ndarray) -> np.ndarray:
        """x without what lies in the components' own vectors, orthonormal; x is written over."""
        for c in range(x.shape[1]):
            x[:, c] -= unit * np.bincount(part, weights=unit * x[:, c])[part]
        return orthonormal(x)

    if x.shape[1] < size:
        x = np.hstack([x, rng.standard_normal((n, size - x.shape[1]))])
    x = moving(x)
    low = 0.5
    for _ in range(rounds):
        # a narrow gap below 1 needs a filter of high degree: begun anew too early it hardly tells vectors apart
        wanted = max(degree, min(MOST_DEGREE, int(4 / np.arccosh(1 + 2 * (1 - low) / (1 + low)))))
        if wanted > degree:  # its rounding in single precision is noise, most of which the short filter takes away
            x = x.astype(np.float32)
            x = filtered(times, x, low, wanted)
            x = x.astype(np.float64)
            x = filtered(times, moving(x), 0.5, degree)
        else:
            x = filtered(times, x, low, wanted)
        x = moving(x)
        image = times(x)
        ritz, turn = np.linalg.eigh(x.T @ image)
        ritz, turn = ritz[::-1], turn[:, ::-1]
        turned(x, turn)
        turned(image, turn)
        for c in range(rest):
            image[:, c] -= x[:, c] * ritz[c]
        left = float(np.linalg.norm(image[:, :rest], axis=0).max())
        del image
        low = float(np.clip(ritz[-1], -0.5, 1 - 1e-6))
        # what is left mixes a vector with the next ones by left / gap
        if left <= min(tol, max(GAP_PART * float(ritz[rest - 1] - ritz[min(rest, size - 1)]), LEAST_LEFT)):
            break
    else:
        warnings.warn(f"the embedding was left with residuals of {left:.1e} after {rounds} rounds", stacklevel=3)
    return np.concatenate([np.zeros(len(flat)), 1 - ritz[:rest]]), fix_signs(np.hstack([still, x[:, :rest]])[place])


def _blocks(n: int) -> list[slice]:
    """About SOME_ROWS rows each, and never few."""
    ends = np.linspace(0, n, max(1, n // SOME_ROWS) + 1).astype(int).tolist()
    return [slice(a, b) for a, b in zip(ends, ends[1:])]


def orthonormal(x: np.ndarray) -> np.ndarray:
    """An orthonormal base of x's columns, written over x: blocks of rows first, then what is left of each."""
    blocks = _blocks(len(x))
    if len(blocks) == 1:
        return np.linalg.qr(x)[0]
    tops = []
    for b in blocks:
        x[b], r = np.linalg.qr(x[b])
        tops.append(r)
    last = np.linalg.qr(np.vstack(tops))[0].reshape(len(blocks), -1, x.shape[1])
    for b, t in zip(blocks, last):
        x[b] = x[b] @ t
    return x


def turned(x: np.ndarray, turn: np.ndarray) -> None:
    """x @ turn, written over x."""
    for b in _blocks(len(x)):
        x[b] = x[b] @ turn


def _positions(ids: np.ndarray, some: np.ndarray) -> np.ndarray:
    """Places of some of ids, which are sorted."""
    if len(ids) and ids[-1] - ids[0] == len(ids) - 1:
        return some - ids[0]
    return np.searchsorted(ids, some)


def filtered(times: Products, x: np.ndarray, low: float, degree: int) -> np.ndarray:
    """A Chebyshev polynomial of the normalised weights times x: damps what lies between -1 and low."""
    half, mid = x.dtype.type((low + 1) / 2), x.dtype.type((low - 1) / 2)
    new = times(x)
    new -= mid * x
    new /= half
    old, x = x, None
    twice = 2 / half
    for _ in range(degree - 1):
        y = times(new)
        for b in _blocks(len(y)):
            part = y[b]
            part *= twice
            part -= (mid * twice) * new[b]
            part -= old[b]
        old, new = new, y
        del y  # three blocks at most
    return new


class Products:
    """Normalised weights times rows of vectors, in the vectors' precision.

    Edges of one weight are summed without it: the j-th edges of all nodes that have one are one gather of rows. Nodes
    lie so that those of many edges come first, and what a few nodes have beyond the others is summed one by one.
    """

    def __init__(self, n: int, at_s: np.ndarray, at_d: np.ndarray, w: np.ndarray, scale: np.ndarray):
        self.scale = {np.dtype(t): scale[:, None].astype(t) for t in (np.float32, np.float64)}
        values = np.unique(w)
        kinds = [(float(v), w == v) for v in values] if len(values) <= 4 else [(1.0, np.ones(len(w), dtype=bool))]
        self.parts = []
        for value, mine in kinds:
            s, d = at_s[mine], at_d[mine]
            begin = np.searchsorted(s, np.arange(n + 1))
            have = np.diff(begin)
            order = np.concatenate([np.argsort(-have[a : a + NODES], kind="stable") + a for a in range(0, n, NODES)])
            blocks = []
            for a in range(0, n, NODES):
                nodes = order[a : a + NODES]
                count, at = have[nodes], begin[nodes]
                layers = []
                j = 0
                while (m := int(np.searchsorted(-count, -j, side="left"))) > len(nodes) // 64:
                    layers.append((d[at[:m] + j], None if len(values) <= 4 else w[at[:m] + j, None]))
                    j += 1
                tail = None
                if m:
                    rest = np.concatenate([np.arange(at[i] + j, at[i] + count[i]) for i in range(m)])
                    tail = d[rest], None if len(values) <= 4 else w[rest, None], np.concatenate([[0], np.cumsum(count[:m] - j)[:-1]])
                blocks.append((np.argsort(nodes), layers, tail))
            self.parts.append((value, blocks))

    def __call__(self, x: np.ndarray) -> np.ndarray:
        width, scale = x.shape[1], self.scale[x.dtype]
        row = max(4, 1 << (width - 1).bit_length()) if width <= 8 else -(-width // 4) * 4  # rows that are copied as a whole
        y = np.zeros((len(x), row), dtype=x.dtype)
        np.multiply(x, scale, out=y[:, :width])
        out = np.zeros_like(y)
        held, sums = np.empty((NODES, row), dtype=x.dtype), np.empty((NODES, row), dtype=x.dtype)
        for value, blocks in self.parts:
            for b, (back, layers, tail) in enumerate(blocks):
                own = sums[: len(back)]
                own[:] = 0
                for to, v in layers:
                    z = y.take(to, axis=0, out=held[: len(to)], mode="clip")
                    if v is not None:
                        z *= v
                    own[: len(to)] += z
                if tail:
                    to, v, begin = tail
                    z = y.take(to, axis=0)
                    own[: len(begin)] += np.add.reduceat(z if v is None else z * v, begin, axis=0)
                own *= value
                out[b * NODES : b * NODES + len(back)] += own.take(back, axis=0, out=held[: len(back)], mode="clip")
        del y
        out *= scale
        return out[:, :width]
