"""Eigenpairs of the random walk, and what is read off them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.linalg import SymmetricEdges, fix_signs, lanczos, top_dense
from ..spool import spool
from . import kernel as K


def local_modes(edges: SymmetricEdges, counts: np.ndarray, modes: int, solver: str = "dense", seed: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``lambda, psi, degree`` of the walk ``D^-1 A C`` over weighted points.

    The similar symmetric matrix is ``C^1/2 D^-1/2 A D^-1/2 C^1/2``; a right
    vector is ``v (c deg)^-1/2``, scaled to ``sum c psi^2 = 1``.
    """
    deg = edges @ counts.astype(float)
    scale = np.sqrt(counts / deg)
    s = edges.scaled(scale)
    if solver == "dense":
        lam, v = top_dense(s.dense(), modes)
    else:
        lam, v = lanczos(lambda x: s @ x, edges.n, min(modes, edges.n), np.sqrt(counts * deg), seed)
    psi = v / np.sqrt(counts * deg)[:, None]
    psi /= np.sqrt((counts[:, None] * psi * psi).sum(0))
    return lam, fix_signs(psi), deg


def symmetrised(edges: DataFrame, deg: DataFrame) -> DataFrame:
    """The symmetric conjugate: ``a / sqrt(deg_i deg_j)``."""
    left, right = deg.select("i", F.col("deg").alias("di")), deg.select(F.col("i").alias("j"), F.col("deg").alias("dj"))
    return edges.join(left, "i").join(right, "j").select("i", "j", (F.col("a") / F.sqrt(F.col("di") * F.col("dj"))).alias("a"))


def distributed_modes(edges: DataFrame, deg: DataFrame, modes: int, rounds: int = 200, tol: float = 1e-7, seed: int = 0, extra: int = 4, shift: float = 0.1) -> tuple[np.ndarray, DataFrame]:
    """Block subspace iteration: a product is one join and one sum of ``modes + extra`` columns; only small Gram matrices reach the driver.

    The matrix is shifted by ``shift``: enough for kernels whose eigenvalues are
    not below ``-shift`` (Gaussians of Euclidean distances have none below 0;
    take 1 for any other metric).  Returns the values and ``i, psi``.
    """
    s = spool(K.both_ways(symmetrised(edges, deg)), "conjugate")
    width = modes + extra
    x = deg.select("i", F.array(F.sqrt("deg"), *[F.pmod(F.xxhash64(F.lit(seed), F.lit(c), "i"), F.lit(1 << 20)) / float(1 << 20) - 0.5 for c in range(1, width)]).alias("x"))
    x = spool(x, "block")
    values = np.zeros(modes)

    def gram(a: DataFrame, p: str, q: str) -> np.ndarray:
        row = a.agg(*[F.sum(F.col(p)[r] * F.col(q)[c]) for r in range(width) for c in range(width)]).first()
        return np.array(row, float).reshape(width, width)

    def turn(a: DataFrame, col: str, m: np.ndarray) -> DataFrame:
        return a.select("i", F.array(*[sum((F.col(col)[r] * float(m[r, c]) for r in range(width)), F.lit(0.0)) for c in range(width)]).alias("x"))

    for n in range(rounds):
        moved = s.join(x.withColumnRenamed("i", "j"), "j").groupBy("i").agg(*[F.sum(F.col("a") * F.col("x")[c]).alias(f"y{c}") for c in range(width)])
        both = spool(moved.select("i", F.array(*[f"y{c}" for c in range(width)]).alias("y")).join(x, "i"), "block")
        both = both.withColumn("z", F.zip_with("x", "y", lambda p, q: (shift * p + q) / (1.0 + shift)))
        g = gram(both, "z", "z")
        root = np.linalg.inv(np.linalg.cholesky(g).T)
        x = spool(turn(both, "z", root), "block")
        if n % 5 == 4:
            moved = s.join(x.withColumnRenamed("i", "j"), "j").groupBy("i").agg(*[F.sum(F.col("a") * F.col("x")[c]).alias(f"y{c}") for c in range(width)])
            both = spool(moved.select("i", F.array(*[f"y{c}" for c in range(width)]).alias("y")).join(x, "i"), "block")
            lam, vec = np.linalg.eigh((h := gram(both, "x", "y")) / 2 + h.T / 2)
            order = np.argsort(-lam)
            x = spool(turn(both, "x", vec[:, order]), "block")
            lam = lam[order][:modes]
            if np.abs(lam - values).max() < tol:
                values = lam
                break
            values = lam
    out = x.join(deg, "i").select("i", F.transform(F.slice("x", 1, modes), lambda v: v / F.sqrt("deg")).alias("psi"))
    norm = out.agg(*[F.sqrt(F.sum(F.col("psi")[c] * F.col("psi")[c])) for c in range(modes)]).first()
    return values, spool(out.select("i", F.array(*[F.col("psi")[c] / float(norm[c]) for c in range(modes)]).alias("psi")), "modes")


def mllib_values(edges: DataFrame, deg: DataFrame, modes: int) -> np.ndarray:
    """Leading values by MLlib's SVD of the symmetric conjugate (kernels without negative eigenvalues only)."""
    from pyspark.mllib.linalg import Vectors
    from pyspark.mllib.linalg.distributed import IndexedRow, IndexedRowMatrix

    order = deg.select("i", (F.row_number().over(Window.orderBy("i")) - 1).alias("r"))
    n = order.count()
    s = K.both_ways(symmetrised(edges, deg)).join(order, "i").join(order.toDF("j", "c"), "j")
    rows = s.groupBy("r").agg(F.collect_list(F.struct("c", "a")).alias("es"))
    m = IndexedRowMatrix(rows.rdd.map(lambda r: IndexedRow(r["r"], Vectors.sparse(n, sorted((e["c"], e["a"]) for e in r["es"])))))
    return np.array(m.computeSVD(modes).s.toArray())


def spectrum_table(spark: SparkSession, lam: np.ndarray) -> DataFrame:
    """``l, lambda, gap, timescale``: drop to the next value, and -1/ln(lambda) (null for the trivial mode)."""
    rows = []
    for n, v in enumerate(lam.tolist()):
        gap = v - float(lam[n + 1]) if n + 1 < len(lam) else None
        rows.append((n + 1, v, gap, -1.0 / float(np.log(v)) if n and 0 < v < 1 else None))
    return spark.createDataFrame(rows, "l int, lambda double, gap double, timescale double")


def laplacian_table(spark: SparkSession, lam: np.ndarray) -> DataFrame:
    """``l, mu, gap, relaxation``: the same modes as those of ``1 - M``: values, rise to the next, and 1/mu (null for the trivial mode)."""
    mu = 1.0 - lam
    rows = [(n + 1, float(v), float(mu[n + 1] - v) if n + 1 < len(mu) else None, 1.0 / float(v) if n and v > 0 else None) for n, v in enumerate(mu)]
    return spark.createDataFrame(rows, "l int, mu double, gap double, relaxation double")


def choose_dimension(spectrum: DataFrame, max_k: int = 10, least: float = 0.02, rule: str = "largest_gap") -> int:
    """Modes before the largest gap behind a non-trivial mode; 0 if no gap exceeds ``least`` (a flat spectrum)."""
    if rule != "largest_gap":
        raise ValueError(rule)
    best = spectrum.where((F.col("l") >= 2) & (F.col("l") <= max_k + 1) & F.col("gap").isNotNull()).agg(F.max_by(F.struct(F.col("l"), F.col("gap")), F.struct("gap", -F.col("l")))).first()[0]
    return 0 if best is None or best["gap"] < least else best["l"] - 1


def diffusion_distance(coords: DataFrame, lam: np.ndarray, t: float = 1.0) -> DataFrame:
    """``i, j, dd``: distance of points over modes scaled by ``lambda^t`` (``coords``: id, psi without the trivial mode)."""
    scaled = coords.select("id", F.array(*[F.col("psi")[c] * float(v**t) for c, v in enumerate(lam)]).alias("vec"))
    from ..functions.metrics import euclidean
    from .pairs import theta_pairs

    return theta_pairs(scaled, euclidean).withColumnRenamed("d", "dd")
