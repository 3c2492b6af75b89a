"""Distances.

Each metric has a Column form, which stays in generated JVM code, and a block
form ``f(X, Y) -> matrix`` for dense NumPy work on Arrow batches.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


FEW = 4  # components up to which distances are made from differences


def _total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda s, x: s + x)


def euclidean(a: Column, b: Column) -> Column:
    return F.sqrt(_total(F.zip_with(a, b, lambda x, y: (x - y) * (x - y))))


def cosine(a: Column, b: Column) -> Column:
    """One minus the cosine of the angle."""
    dot = _total(F.zip_with(a, b, lambda x, y: x * y))

    def norm(v):
        return F.sqrt(_total(F.transform(v, lambda x: x * x)))

    return F.lit(1.0) - dot / (norm(a) * norm(b))


def hamming(a: Column, b: Column) -> Column:
    """Differing bits of two integer codes."""
    return F.bit_count(a.bitwiseXOR(b))


def emd_1d(a: Column, b: Column, bin_width: float = 1.0) -> Column:
    """Earth mover's distance of two histograms on the same bins: area between their running sums."""
    gap = F.zip_with(a, b, lambda x, y: x - y)
    start = F.struct(F.lit(0.0).alias("run"), F.lit(0.0).alias("area"))
    return F.aggregate(gap, start, lambda s, x: F.struct((s["run"] + x).alias("run"), (s["area"] + F.abs(s["run"] + x)).alias("area")), lambda s: s["area"]) * bin_width


def rmsd_raw(a: Column, b: Column, atoms: int) -> Column:
    """Root mean squared deviation without superposition."""
    return euclidean(a, b) / F.sqrt(F.lit(float(atoms)))


def rmsd_planar(a: Column, b: Column) -> Column:
    """RMSD of planar paths ``x1,y1,x2,y2,...`` after the best shift and proper rotation, in closed form.

    With centred coordinates as complex numbers the best rotation turns
    ``sum conj(a) b`` onto the real axis, so its modulus is all that matters.
    """
    n = F.size(a) / 2

    def part(v, odd):
        return F.filter(v, lambda x, i: i % 2 == odd)

    def centred(v, odd):
        p = part(v, odd)
        return F.transform(p, lambda x: x - _total(p) / n)

    ax, ay, bx, by = centred(a, 0), centred(a, 1), centred(b, 0), centred(b, 1)

    def dot(u, v):
        return _total(F.zip_with(u, v, lambda x, y: x * y))

    size = dot(ax, ax) + dot(ay, ay) + dot(bx, bx) + dot(by, by)
    along, across = dot(ax, bx) + dot(ay, by), dot(ax, by) - dot(ay, bx)
    return F.sqrt(F.greatest(size - 2.0 * F.sqrt(along * along + across * across), F.lit(0.0)) / n)


def jaccard(a: Column, b: Column) -> Column:
    """One minus shared over all members of two sets (arrays without repeats); two empty sets are equal."""
    every = F.size(F.array_union(a, b))
    return F.when(every == 0, F.lit(0.0)).otherwise(F.lit(1.0) - F.size(F.array_intersect(a, b)) / every)


# block forms


def euclidean_block(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """All distances between rows: of few components from their differences, else by a product, whose cells that cancel badly are computed again exactly."""
    if 0 < x.shape[1] == y.shape[1] <= FEW:
        d2 = None
        for k in range(x.shape[1]):
            step = np.subtract.outer(x[:, k], y[:, k])
            np.multiply(step, step, out=step)
            d2 = step if d2 is None else np.add(d2, step, out=d2)
        return np.sqrt(d2, out=d2)
    sx, sy = (x * x).sum(1), (y * y).sum(1)
    d2 = sx[:, None] + sy[None, :] - 2.0 * (x @ y.T)
    i, j = np.nonzero(d2 <= 1e-9 * (sx[:, None] + sy[None, :]))
    d2[i, j] = ((x[i] - y[j]) ** 2).sum(1)
    return np.sqrt(np.maximum(d2, 0.0))


def cosine_block(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return 1.0 - (x @ y.T) / (np.linalg.norm(x, axis=1)[:, None] * np.linalg.norm(y, axis=1)[None, :])


def hamming_block(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    a, b = x.astype(np.int64), y.astype(np.int64)
    return np.bitwise_count(a[:, None, :] ^ b[None, :, :]).sum(2).astype(float)


def emd_block(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    cx, cy = np.cumsum(x, 1), np.cumsum(y, 1)
    return np.abs(cx[:, None, :] - cy[None, :, :]).sum(2)


def rmsd_block(x: np.ndarray, y: np.ndarray, dims: int = 3, chunk: int = 256) -> np.ndarray:
    """RMSD after the best rigid motion without reflection.

    In three dimensions the best rotation is the leading eigenvector of a 4x4
    quaternion matrix; its eigenvalue comes from Newton steps on the
    characteristic quartic, started above the largest root.  Cells that have
    not settled, and other dimensions, use singular values with the sign of
    the determinant.
    """

    def centre(v):
        v = v.reshape(len(v), -1, dims)
        return v - v.mean(1, keepdims=True)

    a, b = centre(x), centre(y)
    n = a.shape[1]
    sa, sb = (a * a).sum((1, 2)), (b * b).sum((1, 2))
    out = np.empty((len(a), len(b)))
    right = b.transpose(1, 0, 2).reshape(n, -1)
    for i in range(0, len(a), chunk):
        part = a[i : i + chunk]
        h = (part.transpose(0, 2, 1).reshape(-1, n) @ right).reshape(len(part), dims, len(b), dims).transpose(0, 2, 1, 3)
        half = (sa[i : i + chunk, None] + sb[None, :]) / 2
        best = _leading_root(h, half) if dims == 3 else _signed_sum(h)
        out[i : i + chunk] = np.sqrt(np.maximum(2.0 * (half - best), 0.0) / n)
    return out


def _signed_sum(h: np.ndarray) -> np.ndarray:
    s = np.linalg.svd(h, compute_uv=False)
    return s.sum(-1) - 2.0 * s[..., -1] * (np.linalg.det(h) < 0)


def _leading_root(h: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Largest eigenvalue of the quaternion matrix of each 3x3 cross-covariance."""
    (xx, xy, xz), (yx, yy, yz), (zx, zy, zz) = (tuple(h[..., r, c] for c in range(3)) for r in range(3))
    k = np.empty(h.shape[:-2] + (4, 4))
    k[..., 0, 0], k[..., 1, 1], k[..., 2, 2], k[..., 3, 3] = xx + yy + zz, xx - yy - zz, yy - xx - zz, zz - xx - yy
    for (r, c), v in {(0, 1): yz - zy, (0, 2): zx - xz, (0, 3): xy - yx, (1, 2): xy + yx, (1, 3): zx + xz, (2, 3): yz + zy}.items():
        k[..., r, c] = k[..., c, r] = v
    c2 = -2.0 * (h * h).sum((-1, -2))
    c1 = -8.0 * np.linalg.det(h)
    c0 = np.linalg.det(k)
    root = start.copy()
    for _ in range(40):
        square = root * root
        slope = 4.0 * square * root + 2.0 * c2 * root + c1
        step = np.divide(square * square + c2 * square + c1 * root + c0, slope, out=np.zeros_like(root), where=slope != 0)
        root -= step
        if np.all(np.abs(step) <= 1e-12 * start):
            return root
    open_ = np.abs(step) > 1e-12 * start
    root[open_] = _signed_sum(h[open_])
    return root


def jaccard_block(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Jaccard distance of rows of membership flags (non-zero: a member)."""
    a, b = (x != 0).astype(float), (y != 0).astype(float)
    shared = a @ b.T
    every = a.sum(1)[:, None] + b.sum(1)[None, :] - shared
    return np.where(every == 0, 0.0, 1.0 - shared / np.maximum(every, 1.0))


def rmsd_rows(x: np.ndarray, y: np.ndarray, dims: int = 3) -> np.ndarray:
    """RMSD of row with row after the best rigid motion: one stacked decomposition for the whole batch."""
    a, b = (v.reshape(len(v), -1, dims) for v in (x, y))
    a, b = a - a.mean(1, keepdims=True), b - b.mean(1, keepdims=True)
    best = _signed_sum(a.transpose(0, 2, 1) @ b)
    return np.sqrt(np.maximum((a * a).sum((1, 2)) + (b * b).sum((1, 2)) - 2.0 * best, 0.0) / a.shape[1])


def rmsd_raw_block(x: np.ndarray, y: np.ndarray, dims: int = 3) -> np.ndarray:
    return euclidean_block(x, y) / np.sqrt(x.shape[1] / dims)


@dataclass(frozen=True)
class Metric:
    name: str
    block: Callable[[np.ndarray, np.ndarray], np.ndarray]
    is_metric: bool = True
    column: Callable[[Column, Column], Column] | None = None


METRICS: dict[str, Metric] = {}


def register_metric(name: str, block: Callable, is_metric: bool = True, column: Callable | None = None) -> Metric:
    """Make a distance available by name; ``is_metric`` permits pruning by the triangle inequality."""
    METRICS[name] = Metric(name, block, is_metric, column)
    return METRICS[name]


register_metric("euclidean", euclidean_block, True, euclidean)
register_metric("cosine", cosine_block, False, cosine)
register_metric("hamming", hamming_block)
register_metric("emd", emd_block, True, emd_1d)
register_metric("rmsd", rmsd_block)
register_metric("rmsd2", lambda x, y: rmsd_block(x, y, 2), True, rmsd_planar)
register_metric("rmsd_raw", rmsd_raw_block)
register_metric("jaccard", jaccard_block)


def get(metric: str | Metric) -> Metric:
    return metric if isinstance(metric, Metric) else METRICS[metric]
