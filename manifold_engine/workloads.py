"""The experiments, re-expressed over the given tables.

Maps are fitted on all points while a local solver holds them; of a larger
table they are fitted on the first so many in md5 order, a sample whose size is
a parameter (``FIT_POINTS``, ``FITS``), and every row of the table is embedded
by them and counts in the errors.  Parity needs all modes of the full map, of
which a sample alone is held (``PARITY_POINTS``).

``python -m manifold_engine.workloads [sf_dir]`` prints the error tables.
"""

from __future__ import annotations

import sys
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import metrics as D
from .functions.linalg import bottleneck_rows
from .operators import crossval as C
from .operators import kernel as K
from .operators import landmarks as L
from .operators import maps as M
from .operators import measures as E
from .operators import pairs as P
from .operators import perturbation as B
from .operators.spectrum import choose_dimension
from .operator_queries import plane_stream_cut
from .sources import points as R
from .spool import spool

FIT_POINTS = 16_000
QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(fn):
    QUERIES[fn.__name__] = fn
    return fn


def fit_sample(points: DataFrame, most: int = FIT_POINTS) -> tuple[np.ndarray, np.ndarray]:
    return M.collect_points(R.by_hash_order(points, most), most)


def roll_embedding(s: SparkSession, d: str) -> DataFrame:
    """Landmarks of the roll by a pruned spanning tree, cell counts over all orders, every order embedded."""
    p = R.roll(s, d)
    ids, x = fit_sample(p)
    eps = bottleneck_rows(x, D.euclidean_block) ** 2
    at = C.choose(x, "pst", eps**0.5, "euclidean")
    m = M.fit_reduced(p, ids[at], eps, 4)
    e = M.extend(p, m, 2)
    return e.select("id", F.col("psi")[0].alias("psi2"), F.col("psi")[1].alias("psi3"), "nearest_lid", "d_min", "extrapolated")


@query
def x1_roll(s, d):
    """Roll picture: ``id, split, psi2, psi3, psi2r, psi3r, zeta, angle`` of every order."""
    p = R.roll(s, d)
    ids, x = fit_sample(p)
    train = C.split_folds(ids) != 1
    eps = bottleneck_rows(x[train], D.euclidean_block) ** 2
    full = M.fit_local(ids[train], x[train], eps, 4, drop_below=1e-4)
    at = C.choose(x[train], "pst", eps**0.5, "euclidean")
    red, _ = C.reduced_of(ids[train], x[train], at, eps, 4, "euclidean")
    true, got = full.coordinates(2), M.nystrom(x[train], red, 2)[0]
    red.psi[:, 1:3] *= np.sign((true * got).sum(0))
    span = np.ptp(true, axis=0)
    a = M.extend(p, full, 2).select("id", F.col("psi").alias("t"))
    b = M.extend(p, red, 2).select("id", F.col("psi").alias("r"))
    fitted = F.broadcast(s.createDataFrame(pa.table({"fid": pa.array(ids[train])})))
    out = a.join(b, "id").join(fitted, F.col("id") == F.col("fid"), "left").join(p, "id")
    z = F.lit(100.0) * F.sqrt((F.pow((F.col("r")[0] - F.col("t")[0]) / float(span[0]), 2) + F.pow((F.col("r")[1] - F.col("t")[1]) / float(span[1]), 2)))
    angle = F.sqrt(F.col("vec")[0] * F.col("vec")[0] + F.col("vec")[2] * F.col("vec")[2])
    return out.select("id", F.when(F.col("fid").isNotNull(), "train").otherwise("test").alias("split"), F.col("t")[0].alias("psi2"), F.col("t")[1].alias("psi3"), F.col("r")[0].alias("psi2r"), F.col("r")[1].alias("psi3r"), z.alias("zeta"), angle.alias("angle"))


#: workload: recipe, metric, k, methods, affinities cut below, points fitted
FITS = {
    "roll": (R.roll, "euclidean", 2, ["pst", "medoids:0.125", "medoids:0.25", "medoids:0.5"], 1e-4, 5_000),
    "bead_chain": (R.bead_chain, "rmsd", 4, ["pst", "medoids:0.0063", "medoids:0.0125", "medoids:0.0375"], 1e-6, 1_500),
    "torsion_pair": (R.torsion_pair, "rmsd", 2, ["pst", "medoids:0.01", "medoids:0.02", "medoids:0.05"], 1e-6, 1_500),
}


def error_table(s: SparkSession, d: str, name: str, fit_points: int | None = None, align: str = "procrustes") -> DataFrame:
    """Five-fold errors over every row at each fold's smallest connecting bandwidth, with landmark counts and shares."""
    recipe, metric, k, methods, cut, most = FITS[name]
    e = spool(C.cross_validate(recipe(s, d), methods, None, k, metric, drop_below=cut, align=align, fit_points=fit_points or most), "errors")
    return E.fold_summary(e).crossJoin(e.agg(F.avg("eps").alias("eps"), F.max("points").alias("points")))


@query
def x2_roll(s, d):
    """Error table of the roll (Euclidean, two modes)."""
    return error_table(s, d, "roll")


@query
def x2_chain(s, d):
    """Error table of the bead chain (RMSD in space, four modes)."""
    return error_table(s, d, "bead_chain")


@query
def x2_torsion(s, d):
    """Error table of the torsion pair (RMSD in space, two modes)."""
    return error_table(s, d, "torsion_pair")


LATTICE_METHODS = ["pst", "medoids:0.125", "medoids:0.25", "medoids:0.5", "random:0.25", "medoids:0.25!unweighted"]
LATTICE_FIT = 6_000


@query
def x2_error_table(s, d):
    """A fourth workload with many equal distances, the part lattice, and the ablation without cell counts."""
    e = spool(C.cross_validate(R.lattice(s, d), LATTICE_METHODS, None, 2, drop_below=1e-5, align="procrustes", fit_points=LATTICE_FIT), "errors")
    return E.fold_summary(e)


@query
def x2_folds(s, d):
    """The same, fold by fold."""
    return C.cross_validate(R.lattice(s, d), ["pst", "medoids:0.25"], None, 2, drop_below=1e-5, align="procrustes", fit_points=LATTICE_FIT)


@query
def x3_bandwidth_sweep(s, d):
    """Errors and landmark counts of the torsion pair at multiples of the smallest bandwidth."""
    p = spool(R.torsion_pair(s, d), "torsion")
    _, x = M.collect_points(R.by_hash_order(p, 1_000), 1_000)
    eps = bottleneck_rows(x, D.rmsd_block) ** 2
    e = C.bandwidth_sweep(p, ["pst", "medoids:0.02", "medoids:0.1"], eps, 2, metric="rmsd", drop_below=1e-6, align="procrustes", fit_points=1_000)
    return e.groupBy("method", "split", "eps").agg(F.avg("m").alias("m"), F.avg("z").alias("z"), F.stddev_samp("z").alias("z_sd")).orderBy("method", "split", "eps")


PARITY_POINTS = 1_200


@query
def x4_parity(s, d):
    """Predicted against observed shifts of the roll and the plane for growing landmark counts, both bases and images.

    ``subspace`` is ``kept`` (the shift may spread over the kept modes alone) or
    ``all`` (over every mode of the full map, as many as points).
    """
    rows = []
    for name, points in (("roll", R.roll(s, d)), ("plane", R.plane(s, d))):
        p = spool(R.by_hash_order(points, PARITY_POINTS), "points")
        ids, x = M.collect_points(p, PARITY_POINTS)
        # the plane's outlying values call for a wide kernel; four times the least bandwidth elsewhere
        eps = 4.0 * bottleneck_rows(x, D.euclidean_block) ** 2 if name == "roll" else bottleneck_rows(x, D.euclidean_block) ** 2
        full = M.fit_local(ids, x, eps, len(ids))
        pr = spool(P.all_pairs(p), "pairs")
        for share in (0.1, 0.3, 0.6, 0.9):
            at = L.local_medoids(x, max(4, round(share * len(x))), max_iter=8)
            red, cell = C.reduced_of(ids, x, at, eps, 4, "euclidean")
            z = s.createDataFrame(pa.table({"id": pa.array(red.ids), "vec": pa.array(list(red.vecs), pa.list_(pa.float64()))}))
            cells = s.createDataFrame(pa.table({"id": pa.array(ids), "lid": pa.array(red.ids[cell])}))
            deltas = spool(B.distance_shift(pr, cells, P.all_pairs(z)), "deltas")
            true = full.coordinates(2)
            images = {"collapsed": red.coordinates(2)[cell], "interpolated": M.nystrom(x, red, 2)[0]}
            for basis in ("plain", "stationary"):
                for sub in (None, "all"):
                    got = B.predict(deltas, full, 2, basis, sub)
                    for image, psi in images.items():
                        seen = np.linalg.norm(E.align(true, psi) - true, axis=1)
                        q = B.parity(got["sigma"], seen)
                        shift = E.eigenvalue_error(full.lam, red.lam, 1)[0]
                        rows.append((name, len(at), basis, sub or "kept", image, q["correlation"], q["mean_ratio"], q["rms_log"], float(got["dlambda"][0]), float(shift)))
    return s.createDataFrame(rows, "workload string, m int, basis string, subspace string, image string, correlation double, mean_ratio double, rms_log double, dlambda2 double, dlambda2_observed double")


#: workload: points fitted, bandwidth as a multiple of the smallest connecting one
SPEED = {"roll": (4_000, 4.0), "bead_chain": (2_000, 2.0), "torsion_pair": (2_000, 8.0)}


def speedup_of(s, d, name: str, repeats: int = 3) -> list[tuple]:
    """Wall time of extending the test fold's rows by the full map and by medoids of 25, 4 and 2 percent."""
    recipe, metric, k, _, cut, _ = FITS[name]
    most, factor = SPEED[name]
    p = spool(recipe(s, d), name)
    test = F.crc32(F.col("id").cast("string")) % 5 == 0
    new = spool(p.where(test).repartition(16), "new")
    ids, x = M.collect_points(R.by_hash_order(p.where(~test), most), most)
    eps = factor * bottleneck_rows(x, D.get(metric).block) ** 2
    full = M.fit_local(ids, x, eps, k + 2, metric, drop_below=cut)
    true = full.coordinates(k)
    t_full = E.timed(M.extend(new, full, k), repeats)
    rows = []
    for share in (0.25, 0.04, 0.02):
        red, _ = C.reduced_of(ids, x, L.local_medoids(x, max(k + 2, round(share * len(x))), metric, max_iter=15), eps, k + 2, metric)
        t = E.timed(M.extend(new, red, k), repeats)
        z = E.z_local(E.zeta_local(true, E.align(true, M.nystrom(x, red, k)[0], "procrustes")))
        rows.append((name, full.size, red.size, 100.0 * red.size / full.size, t_full, t, t_full / t, E.ideal_speedup(full.size, red.size), z))
    return rows


SPEEDUP = "workload string, n long, m long, percent double, t_full double, t_landmark double, speedup double, ideal double, z double"


@query
def x5_speedup(s, d):
    """Speedup of the extension on the roll, beside the ideal ratio and the error."""
    return s.createDataFrame(speedup_of(s, d, "roll"), SPEEDUP)


@query
def x5_speedup_chain(s, d):
    """The same on the bead chain, whose distances are dear."""
    return s.createDataFrame(speedup_of(s, d, "bead_chain"), SPEEDUP)


@query
def x5_speedup_torsion(s, d):
    """The same on the torsion pair."""
    return s.createDataFrame(speedup_of(s, d, "torsion_pair"), SPEEDUP)


@query
def x6_tuned(s, d):
    """Fewest medoids of the torsion pair that meet 3 percent on a validation fold of the fitted sample, and what they give over every row."""
    p = spool(R.torsion_pair(s, d), "torsion")
    q = spool(R.by_hash_order(p, 1_250), "sample")
    _, x = M.collect_points(q, 1_250)
    eps = 4.0 * bottleneck_rows(x, D.rmsd_block) ** 2
    out = C.tune_landmarks(q, eps, 2, z_target=3.0, metric="rmsd", start=32, drop_below=1e-6)
    whole = C.cross_validate(p, [f"medoids:{out['m']}"], eps, 2, "rmsd", n_folds=0, drop_below=1e-6, align="procrustes", fit_points=1_250).first()["z"]
    return s.createDataFrame([(m, z, m == out["m"], whole if m == out["m"] else None) for m, z in out["tried"].items()], "m long, z double, chosen boolean, z_every_row double")


@query
def x7_stream(s, d):
    """Fit on the first four fifths of the event time span, embed the rest as a stream: outliers by day."""
    from .streaming import embed as X

    stream, points, cut = plane_stream_cut(s, d)
    first = points.where(F.col("ts") < cut).select("id", "vec")
    ids, _ = L.vectors_of(first, L.random_landmarks(first, 50))
    m = M.fit_reduced(first, ids, 0.05, 4)
    out = X.run_available(X.outlier_rate(X.stream_extend(stream.where(F.col("ts") >= cut), m, 2, reach=0.3)), "rest", "complete")
    return out.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n", "outliers", "mean_psi")


@query
def x8_sparse_kernel(s, d):
    """Affinities kept, leading value and error of the roll's and the vectors' maps against the exact ones as small affinities are cut."""
    rows = []
    for name, points, factor in (("roll", R.roll(s, d), 1.0), ("vectors", R.vectors(s, d), 1.0)):
        ids, x = fit_sample(points, 3_000)
        eps = factor * bottleneck_rows(x, D.euclidean_block) ** 2
        exact = M.fit_local(ids, x, eps, 4)
        for tol in (1e-8, 1e-6, 1e-4, 1e-2, 1e-1):
            m = M.fit_local(ids, x, eps, 4, drop_below=tol)
            kept = sum(int((D.euclidean_block(x[i : i + 1000], x) <= K.cut_radius(eps, tol)).sum()) for i in range(0, len(x), 1000))
            z = E.z_local(E.zeta_local(exact.coordinates(2), E.align(exact.coordinates(2), m.coordinates(2), "procrustes")))
            rows.append((name, tol, kept, len(x) ** 2, float(m.lam[1]), float(exact.lam[1]), z))
    return s.createDataFrame(rows, "workload string, drop_below double, kept long, every long, lambda2 double, lambda2_exact double, z double")


@query
def x9_metrics(s, d):
    """Reduced maps under other metrics, errors over every row: document codes (Hamming), user histograms (earth mover's), user paths (planar RMSD)."""
    sets = [("hamming", _code_points(s, d)), ("emd", R.histograms(s, d)), ("rmsd2", R.planar_paths(s, d))]
    rows = []
    for metric, points in sets:
        p = spool(points, metric)
        ids, x = fit_sample(p, 1_000)
        eps = max(bottleneck_rows(x, D.get(metric).block) ** 2 / 4, 1e-12)
        full = M.fit_local(ids, x, eps, 8, metric)
        k = choose_dimension(full.spectrum(s), 5) or 1
        e = C.cross_validate(p, [f"medoids:{max(4, len(x) // 5)}"], eps, k, metric, n_folds=0, align="procrustes", fit_points=1_000).first()
        rows.append((metric, len(ids), e["points"], e["m"], eps, float(full.lam[1]), k, e["z"]))
    return s.createDataFrame(rows, "metric string, n long, points long, m long, eps double, lambda2 double, k int, z double")


def _code_points(s, d) -> DataFrame:
    """Codes as two words of 30 bits, which doubles hold exactly."""
    c = R.codes(s, d)
    return c.select("id", F.array(F.shiftright("code", 30).cast("double"), F.col("code").bitwiseAND(F.lit((1 << 30) - 1)).cast("double")).alias("vec"))


def main(argv: list[str]) -> None:
    d = argv[0] if argv else "/root/testdata/sf0.01"
    s = SparkSession.builder.master("local[8]").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "8").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    for spec in argv[1:] or list(FITS):
        name, _, n = spec.partition(":")
        t = time.time()
        rows = error_table(s, d, name, int(n) if n else None).orderBy("method", "split").collect()
        print(f"{name} ({time.time() - t:.0f} s)")
        for r in rows:
            print(f"  {r.method:16s} {r.split:5s} M={r.m_mean:8.1f} ({r.percent_mean:.2f} %) Z={r.z_mean:6.2f} ({r.z_sd:.2f}) eps={r.eps:.3g}", flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
