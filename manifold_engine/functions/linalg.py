"""Local numerical kernels: sparse symmetric products, Lanczos, spanning trees, kernel matrices."""

from __future__ import annotations

import heapq

import numpy as np


class SymmetricEdges:
    """Symmetric sparse matrix from upper entries ``i < j`` and a diagonal."""

    def __init__(self, n: int, i: np.ndarray, j: np.ndarray, a: np.ndarray, diagonal: np.ndarray):
        rows, cols, vals = np.concatenate([i, j]), np.concatenate([j, i]), np.concatenate([a, a])
        order = np.lexsort((cols, rows))
        self.n, self.cols, self.vals, self.diagonal = n, cols[order], vals[order], diagonal
        self.ptr = np.zeros(n + 1, np.int64)
        np.add.at(self.ptr, rows + 1, 1)
        self.ptr = np.cumsum(self.ptr)
        self.full = np.flatnonzero(np.diff(self.ptr))

    def row_sums(self) -> np.ndarray:
        return self @ np.ones(self.n)

    def __matmul__(self, x: np.ndarray) -> np.ndarray:
        out = (self.diagonal * x.T).T
        if len(self.vals):
            moved = self.vals[:, None] * x[self.cols] if x.ndim == 2 else self.vals * x[self.cols]
            out[self.full] += np.add.reduceat(moved, self.ptr[self.full], axis=0)
        return out

    def dense(self) -> np.ndarray:
        m = np.diag(self.diagonal.astype(float))
        m[np.repeat(np.arange(self.n), np.diff(self.ptr)), self.cols] += self.vals
        return m

    def scaled(self, s: np.ndarray) -> SymmetricEdges:
        out = object.__new__(SymmetricEdges)
        rows = np.repeat(np.arange(self.n), np.diff(self.ptr))
        out.__dict__ |= self.__dict__ | {"vals": self.vals * s[rows] * s[self.cols], "diagonal": self.diagonal * s * s}
        return out

    def neighbours(self, v: int) -> np.ndarray:
        return self.cols[self.ptr[v] : self.ptr[v + 1]]

    def fresh(self, v: int, depth: np.ndarray) -> np.ndarray:
        """Neighbours of ``v`` that a tree of these depths has not reached."""
        near = self.neighbours(v)
        return near[depth[near] < 0]

    def gains(self, at: np.ndarray, depth: np.ndarray) -> np.ndarray:
        """How many each of ``at`` would reach."""
        return np.array([len(self.fresh(v, depth)) for v in at], np.int64)


class NearPoints:
    """The graph of rows of ``x`` within ``r``, measured when it is asked for: points are held, no edge."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, r: float, block):
        self.n, self.ids, self.x, self.r, self.block = len(x), ids, x, r, block

    def fresh(self, v: int, depth: np.ndarray) -> np.ndarray:
        left = np.flatnonzero(depth < 0)
        return left[self.block(self.x[v : v + 1], self.x[left])[0] <= self.r]

    def gains(self, at: np.ndarray, depth: np.ndarray, strip: int = 1 << 20) -> np.ndarray:
        z = self.x[depth < 0]
        step = max(1, strip // max(1, len(z)))
        return np.concatenate([np.zeros(0, np.int64), *((self.block(self.x[at[s : s + step]], z) <= self.r).sum(1) for s in range(0, len(at), step))])


_P1, _P2, _P3, _P4, _P5 = (np.uint64(v) for v in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * _P2
    h = (h ^ (h >> np.uint64(29))) * _P3
    return h ^ (h >> np.uint64(32))


def _turned(v: np.ndarray, k: int) -> np.ndarray:
    return (v << np.uint64(k)) | (v >> np.uint64(64 - k))


def hash_long(v: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Spark's ``xxhash64`` of longs ``v`` over what the columns before them gave."""
    h = (h + _P5 + np.uint64(8)) ^ (_turned(v.view(np.uint64) * _P2, 31) * _P1)
    return _mixed(_turned(h, 27) * _P1 + _P4)


def seeded_hash(seed: int, ids: np.ndarray) -> np.ndarray:
    """``xxhash64(seed, id)``: with ``hash_long`` of the larger end, the weight of an edge from its smaller end ``id``."""
    h = (np.full(1, 42, np.uint64) + _P5 + np.uint64(4)) ^ (np.full(1, seed & 0xFFFFFFFF, np.uint64) * _P1)
    return hash_long(np.ascontiguousarray(ids, np.int64), _mixed(_turned(h, 23) * _P2 + _P3))


def edge_weights(low: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """``xxhash64(seed, i, j)`` of the edges between ids ``a`` and ``b``, given ``seeded_hash`` of their smaller ends."""
    return hash_long(np.maximum(a, b), low).view(np.int64)


def top_dense(m: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    w, v = np.linalg.eigh(m)
    return w[::-1][:k], v[:, ::-1][:, :k]


def lanczos(matvec, n: int, k: int, first: np.ndarray | None = None, seed: int = 0, tol: float = 1e-10, most: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Leading ``k`` eigenpairs of a symmetric operator: Krylov basis with full reorthogonalisation.

    ``first`` is a known eigenvector to project out (returned as the first pair's vector).
    """
    rng = np.random.default_rng(seed)
    most = min(n, most or max(12 * k + 60, 600))
    basis = np.zeros((most, n))
    q = rng.standard_normal(n)
    known = None if first is None else first / np.linalg.norm(first)
    if known is not None:
        q -= known * (known @ q)
    basis[0] = q / np.linalg.norm(q)
    diag, off = [], []
    want = k - (known is not None)
    for m in range(1, most + 1):
        w = matvec(basis[m - 1])
        diag.append(float(basis[m - 1] @ w))
        for _ in range(2):
            if known is not None:
                w -= known * (known @ w)
            w -= basis[:m].T @ (basis[:m] @ w)
        beta = float(np.linalg.norm(w))
        if m == most or beta < 1e-13 or (m >= want + 2 and m % 20 == 0):
            t = np.diag(diag) + np.diag(off, 1) + np.diag(off, -1)
            val, vec = np.linalg.eigh(t)
            pick = np.argsort(-val)[:want]
            if m == most or beta < 1e-13 or np.all(beta * np.abs(vec[-1, pick]) < tol):
                vectors = basis[:m].T @ vec[:, pick]
                values = val[pick]
                if known is not None:
                    values = np.concatenate([[known @ matvec(known)], values])
                    vectors = np.concatenate([known[:, None], vectors], 1)
                return values, vectors
        off.append(beta)
        basis[m] = w / beta
    raise AssertionError("unreachable")


def block_krylov(product, n: int, k: int, first: np.ndarray, seed: int = 0, extra: int = 4, tol: float = 1e-10, most: int = 100) -> tuple[np.ndarray, np.ndarray]:
    """Leading ``k`` eigenpairs of a symmetric operator of largest value 1, whose vector ``first`` is known; ``product`` takes a block of vectors.

    A block goes through the operator once a round, so an operator that is
    computed anew each time is computed in few rounds.
    """
    known = first / np.linalg.norm(first)

    def clear(q, basis):
        for _ in range(2):
            q = q - known[:, None] * (known @ q)
            if basis is not None:
                q = q - basis @ (basis.T @ q)
            size = np.linalg.norm(q, axis=0)
            q, r = np.linalg.qr(q[:, size > 1e-13])
            q = q[:, np.abs(np.diag(r)) > 1e-13 * max(1e-300, np.abs(np.diag(r)).max(initial=0.0))]
        return q

    want = k - 1
    basis = q = clear(np.random.default_rng(seed).standard_normal((n, min(n - 1, k + extra))), None)
    moved = np.zeros((n, 0))
    for _ in range(most):
        y = product(q)
        moved = np.concatenate([moved, y], 1)
        h = basis.T @ moved
        val, vec = np.linalg.eigh((h + h.T) / 2)
        val, vec = val[::-1][:want], vec[:, ::-1][:, :want]
        out = basis @ vec
        rest = np.linalg.norm(moved @ vec - out * val, axis=0).max(initial=0.0)
        q = clear(y, basis)
        if rest < tol or not q.shape[1]:
            return np.concatenate([[1.0], val]), np.concatenate([known[:, None], out], 1)
        basis = np.concatenate([basis, q], 1)
    raise RuntimeError(f"modes did not settle in {most} rounds: {rest}")


def fix_signs(psi: np.ndarray) -> np.ndarray:
    """Each column's entry of largest absolute value (the first such row) positive."""
    at = np.argmax(np.round(np.abs(psi), 9), axis=0)
    s = np.sign(psi[at, np.arange(psi.shape[1])])
    return psi * np.where(s == 0, 1.0, s)


def bottleneck(d: np.ndarray) -> float:
    """Longest edge of the minimum spanning tree of a dense distance matrix (Prim)."""
    n = len(d)
    near, out, worst = d[0].copy(), np.ones(n, bool), 0.0
    out[0] = False
    for _ in range(n - 1):
        v = int(np.argmin(np.where(out, near, np.inf)))
        worst = max(worst, near[v])
        out[v] = False
        np.minimum(near, d[v], out=near)
    return float(worst)


def bottleneck_rows(x: np.ndarray, block) -> float:
    """The same, with distance rows computed as they are needed: no matrix is held."""
    near, out, worst = block(x[:1], x)[0], np.ones(len(x), bool), 0.0
    out[0] = False
    for _ in range(len(x) - 1):
        v = int(np.argmin(np.where(out, near, np.inf)))
        worst = max(worst, float(near[v]))
        out[v] = False
        np.minimum(near, block(x[v : v + 1], x)[0], out=near)
    return worst


def grow_tree(edges: SymmetricEdges | NearPoints, growth: str = "star_random", root: int = 0, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Parents and depths of a spanning tree of the component of ``root`` (-1 where not reached).

    ``random_edge`` draws among all edges from the tree to the rest; the star
    orders attach all unreached neighbours of one tree node at a time, taking
    the node at random, first-in, last-in, or by most unreached neighbours.
    """
    n = edges.n
    rng = np.random.default_rng(seed)
    parent, depth = np.full(n, -1), np.full(n, -1)
    depth[root] = 0
    if growth == "random_edge":
        ways = np.zeros(n, np.int64)  # edges from the tree to each point outside, one of which, at random, is kept as its parent
        u = root
        while True:
            fresh = edges.fresh(u, depth)
            ways[fresh] += 1
            parent[fresh[rng.random(len(fresh)) * ways[fresh] < 1]] = u
            ends = np.cumsum(ways)
            if not ends[-1]:
                return parent, depth
            u = int(np.searchsorted(ends, rng.integers(ends[-1]), side="right"))
            ways[u], depth[u] = 0, depth[parent[u]] + 1
    ready = [root]
    head = 0
    heap = [(-int(edges.gains(np.array([root]), depth)[0]), root)] if growth == "star_greedy" else []
    while True:
        if growth == "star_greedy":
            if not heap:
                break
            gain, u = heapq.heappop(heap)
            now = len(edges.fresh(u, depth))
            if now == 0:
                continue
            if -gain != now:
                heapq.heappush(heap, (-now, u))
                continue
        elif growth == "star_breadth":
            if head == len(ready):
                break
            u = ready[head]
            head += 1
        elif growth in ("star_depth", "star_random"):
            if not ready:
                break
            at = len(ready) - 1 if growth == "star_depth" else int(rng.integers(len(ready)))
            ready[at], ready[-1] = ready[-1], ready[at]
            u = ready.pop()
        else:
            raise ValueError(f"unknown growth {growth}")
        at = edges.fresh(u, depth)
        parent[at], depth[at] = u, depth[u] + 1
        fresh = at.tolist()
        if growth == "star_greedy":
            for gain, v in zip(edges.gains(at, depth).tolist(), fresh):
                if gain:
                    heapq.heappush(heap, (-gain, v))
        else:
            ready += fresh
    return parent, depth


def boruvka_tree(edges: SymmetricEdges, seed: int = 0, root: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Minimum spanning tree under seeded random weights, rooted: rounds of least edge per component."""
    n = edges.n
    rows = np.repeat(np.arange(n), np.diff(edges.ptr))
    low, high = np.minimum(rows, edges.cols), np.maximum(rows, edges.cols)
    up = rows < edges.cols
    low, high = low[up], high[up]
    weight = np.random.default_rng(seed).permutation(len(low))
    comp = np.arange(n)
    chosen = np.zeros(len(low), bool)
    while True:
        cross = np.flatnonzero(comp[low] != comp[high])
        if not len(cross):
            break
        best: dict[int, int] = {}
        for e in cross[np.argsort(weight[cross])]:
            for c in (comp[low[e]], comp[high[e]]):
                best.setdefault(int(c), int(e))
        for e in best.values():
            a, b = comp[low[e]], comp[high[e]]
            if a != b:
                chosen[e] = True
                comp[comp == max(a, b)] = min(a, b)
    tree = SymmetricEdges(n, low[chosen], high[chosen], np.ones(int(chosen.sum())), np.zeros(n))
    return grow_tree(tree, "star_breadth", root)


def least_tree(points: NearPoints, seed: int = 0, root: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Minimum spanning tree of the component of ``root`` under seeded random weights, rooted; grown by the least edge out of the tree.

    Distinct weights leave one such tree: Boruvka's rounds end in the same.
    """
    low = seeded_hash(seed, points.ids)
    none = np.iinfo(np.int64).max
    parent, depth, least = np.full(points.n, -1), np.full(points.n, -1), np.full(points.n, none)
    depth[root], u = 0, root
    while True:
        at = points.fresh(u, depth)
        first = np.where(points.ids[at] < points.ids[u], at, u)
        w = edge_weights(low[first], points.ids[at], points.ids[u])
        better = w < least[at]
        at = at[better]
        least[at], parent[at] = w[better], u
        u = int(least.argmin())
        if least[u] == none:
            return parent, depth
        least[u], depth[u] = none, depth[parent[u]] + 1


def tree_landmarks(parent: np.ndarray, depth: np.ndarray) -> np.ndarray:
    """Nodes of degree above one; of a tree with one or two nodes the first."""
    inside = np.flatnonzero(depth >= 0)
    degree = np.zeros(len(parent), np.int64)
    kids = inside[parent[inside] >= 0]
    np.add.at(degree, parent[kids], 1)
    degree[kids] += 1
    return np.flatnonzero(degree > 1) if len(inside) > 2 else inside[:1]
