"""Points ``(id BIGINT, vec ARRAY<DOUBLE>)`` from tables.

Every recipe reads its whole table.  Time of day is taken from the clock fields
of a zone-less timestamp, so the session's zone does not matter.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def day_micros(ts: Column) -> Column:
    """Microseconds since midnight."""
    return (F.hour(ts) * 3600 + F.minute(ts) * 60).cast("long") * 1_000_000 + (F.date_part(F.lit("SECOND"), ts) * 1_000_000).cast("long")


def day_fraction(ts: Column) -> Column:
    return day_micros(ts) / F.lit(86_400_000_000.0)


def validate(points: DataFrame, width: int | None = None, vec: str = "vec") -> tuple[DataFrame, DataFrame]:
    """Good points and rejects: a null, a NaN or an infinite component, or another length than ``width``."""
    fine = F.col(vec).isNotNull() & ~F.exists(F.col(vec), lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    if width is not None:
        fine &= F.size(vec) == width
    return points.where(fine), points.where(~F.coalesce(fine, F.lit(False)))


def vectorise(df: DataFrame, id_column: str, columns: list[str]) -> DataFrame:
    """Any numeric, boolean, date or timestamp columns as one vector of doubles."""
    types = dict(df.dtypes)

    def number(c: str) -> Column:
        t = types[c]
        if t.startswith("timestamp"):
            return F.unix_micros(F.col(c).cast("timestamp")) / F.lit(1e6)
        if t == "date":
            return F.unix_date(c).cast("double")
        if t == "boolean":
            return F.col(c).cast("int").cast("double")
        return F.col(c).cast("double")

    return df.select(F.col(id_column).cast("long").alias("id"), F.array(*map(number, columns)).alias("vec"))


# recipes


def roll(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Swiss roll of ``orders``: price is the angle, date the height."""
    t = F.lit(1.5 * math.pi) * (F.lit(1.0) + F.lit(2.0) * F.col("o_totalprice") / 500_000.0)
    h = F.lit(21.0) * F.date_diff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")) / 2404.0
    o = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), t.alias("t"), h.alias("h"))
    return o.select("id", F.array(F.col("t") * F.cos("t"), F.col("h"), F.col("t") * F.sin("t")).alias("vec"))


def plane(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as (value, time of day)."""
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), F.array(F.col("value") / 100.0, F.lit(3.0) * day_fraction(F.col("ts"))).alias("vec"))


def user_plane(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users as (mean value, mean time of day) of all their events."""
    e = table(spark, sf_dir, "events").groupBy(F.col("user_id").alias("id")).agg(F.avg("value").alias("v"), F.avg(day_micros(F.col("ts"))).alias("m"))
    return e.select("id", F.array(F.col("v") / 5.0, F.lit(20.0) * F.col("m") / 86_400_000_000.0).alias("vec"))


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings: isotropic unit vectors, the control without a manifold."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"))


def lattice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts on a price and size grid, with many equal distances."""
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.array((F.col("p_retailprice") - 900.0) / 10.0, F.col("p_size") / 5.0).alias("vec"))


def histograms(spark: SparkSession, sf_dir: str, bins: int = 20, top: float = 200.0) -> DataFrame:
    """Each user's distribution of event values over equal bins; the last bin takes what lies above."""
    b = F.least(F.floor(F.least(F.col("value"), F.lit(top)) / (top / bins)), F.lit(bins - 1)).cast("int")
    e = table(spark, sf_dir, "events").groupBy(F.col("user_id").alias("id")).agg(F.count("*").alias("n"), *[F.sum((b == i).cast("int")).alias(f"b{i}") for i in range(bins)])
    return e.select("id", F.array(*[F.col(f"b{i}") / F.col("n") for i in range(bins)]).alias("vec"))


def planar_paths(spark: SparkSession, sf_dir: str, hours: int = 8) -> DataFrame:
    """Each user's mean value in equal parts of the day, as a planar path of ``hours`` positions (part, value/100)."""
    part = F.floor(day_fraction(F.col("ts")) * hours).cast("int")
    e = table(spark, sf_dir, "events").select(F.col("user_id").alias("id"), part.alias("p"), F.col("value").alias("v"))
    e = e.groupBy("id").agg(*[F.coalesce(F.avg(F.when(F.col("p") == i, F.col("v"))), F.lit(0.0)).alias(f"v{i}") for i in range(hours)])
    return e.select("id", F.array(*[x for i in range(hours) for x in (F.lit(float(i)), F.col(f"v{i}") / 100.0)]).alias("vec"))


def codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(id, code)``: a 60-bit code of each document's whole text, by majority over the bits of its distinct words."""
    d = table(spark, sf_dir, "documents")
    words = d.select(F.col("doc_id").alias("id"), F.explode(F.array_distinct(F.split(F.lower(F.coalesce("text", F.lit(""))), " "))).alias("w"))
    h = words.select("id", F.conv(F.substring(F.md5("w"), 1, 15), 16, 10).cast("long").alias("h"))
    votes = h.groupBy("id").agg(F.count("*").alias("n"), *[F.sum(F.shiftright("h", b).bitwiseAND(F.lit(1))).alias(f"s{b}") for b in range(60)])
    code = F.lit(0).cast("long")
    for b in range(60):
        code = code.bitwiseOR(F.when(F.col(f"s{b}") * 2 > F.col("n"), F.lit(1 << b)).otherwise(F.lit(0)).cast("long"))
    return votes.select("id", code.alias("code"))


# conformations


def build_chain(torsions: np.ndarray, angle: float = 114.0, bond: float = 1.53) -> np.ndarray:
    """Positions of a chain with the given torsions (rows), fixed bond length and angle."""
    n, m = torsions.shape
    theta = math.radians(180.0 - angle)
    pos = np.zeros((n, m + 3, 3))
    pos[:, 1] = (bond, 0, 0)
    pos[:, 2] = pos[:, 1] + (bond * math.cos(theta), bond * math.sin(theta), 0)
    for k in range(m):
        b1, b2 = pos[:, k + 1] - pos[:, k], pos[:, k + 2] - pos[:, k + 1]
        u = b2 / np.linalg.norm(b2, axis=1, keepdims=True)
        w = np.cross(b1, u)
        w /= np.linalg.norm(w, axis=1, keepdims=True)
        v = np.cross(w, u)
        phi = torsions[:, k : k + 1]
        pos[:, k + 3] = pos[:, k + 2] + bond * (math.cos(theta) * u - math.sin(theta) * (np.cos(phi) * v + np.sin(phi) * w) * -1.0)
    return pos


def rigid_motion(pos: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Rotate and shift each conformation by an amount drawn from its id."""
    out = np.empty_like(pos)
    for i, d in enumerate(ids):
        rng = np.random.default_rng(int(d))
        q, r = np.linalg.qr(rng.standard_normal((3, 3)))
        q *= np.sign(np.diag(r))
        if np.linalg.det(q) < 0:
            q[:, 0] *= -1
        out[i] = pos[i] @ q.T + rng.uniform(-5, 5, 3)
    return out


def _conformations(df: DataFrame, torsions) -> DataFrame:
    def run(batches):
        for b in batches:
            pos = rigid_motion(build_chain(torsions(b)), b["id"].to_numpy())
            yield pd.DataFrame({"id": b["id"], "vec": list(pos.reshape(len(b), -1))})

    return df.mapInPandas(run, "id long, vec array<double>")


def bead_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """24-bead chains: four latents of each order (price, date, customer's balance, quantity) bend 21 torsions."""
    lines = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.sum("l_quantity").alias("q"))
    o = table(spark, sf_dir, "orders").join(table(spark, sf_dir, "customer").select("c_custkey", "c_acctbal"), F.col("o_custkey") == F.col("c_custkey"), "left")
    o = o.join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    days = F.date_diff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")) / 2404.0
    x = o.select(F.col("o_orderkey").alias("id"), (F.col("o_totalprice") / 5e5).alias("a"), days.alias("b"), ((F.coalesce("c_acctbal", F.lit(0.0)) + 1000.0) / 11000.0).alias("c"), F.least(F.coalesce("q", F.lit(0.0)) / 300.0, F.lit(1.0)).alias("d"))

    def torsions(b):
        g = 2.0 * np.clip(b[list("abcd")].to_numpy(float), 0, None) ** 1.5 - 1.0
        j = np.arange(21)
        return math.pi + sum(A * g[:, m : m + 1] * np.cos(m * math.pi * (j + 0.5) / 21) for m, A in enumerate((0.9, 0.75, 0.65, 0.55)))

    return _conformations(x, torsions)


def torsion_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    """22-atom chains with two moving torsions: value, and time of day in two basins."""
    e = table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), "value", day_fraction(F.col("ts")).alias("f"))

    def torsions(b):
        f, v = b["f"].to_numpy(), b["value"].to_numpy()
        t = np.full((len(b), 19), math.pi)
        t[:, 8] = -2.6 + 2.2 * (1 - np.exp(-v / 30.0))
        t[:, 11] = np.where(f < 0.75, -0.8 + 0.8 * f, -0.2 + 2.2 * (f - 0.75) / 0.25)
        return t

    return _conformations(e, torsions)


def by_hash_order(points: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """The ``n`` points first in md5 order: a sample that does not depend on the layout (sampling is the feature)."""
    return points.orderBy(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("id"))), "id").limit(n)


def folds(points: DataFrame, k: int = 5, seed: int = 0) -> DataFrame:
    """Equal folds (sizes differ by at most one): ``ntile`` over md5 order, without one task that sorts all.

    The first four digits of the hash deal the points into ranges of that order,
    65,536 at most; ranks count inside a range and start where those before it end.
    """
    from pyspark.sql import Window

    h = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("id")))
    rows = points.withColumn("h__", h).withColumn("p__", F.substring("h__", 1, 4))
    sizes = rows.groupBy(F.col("p__").alias("q__")).agg(F.count("*").alias("n__"))
    before = sizes.withColumn("b__", F.sum("n__").over(Window.orderBy("q__").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("n__")).withColumn("t__", F.sum("n__").over(Window.partitionBy()))
    rank = F.col("b__") + F.row_number().over(Window.partitionBy("p__").orderBy("h__", "id"))
    out = rows.join(before, F.col("p__") == F.col("q__")).withColumn("r__", rank)
    each, more = F.floor(F.col("t__") / k), F.col("t__") % k  # the first ``more`` folds have one point more
    long = more * (each + 1)
    fold = F.when(F.col("r__") <= long, F.ceil(F.col("r__") / (each + 1))).otherwise(more + F.ceil((F.col("r__") - long) / F.greatest(each, F.lit(1))))
    return out.select(*points.columns, fold.cast("int").alias("fold"))


def folds_by_hash(points: DataFrame, k: int = 5, seed: int = 0) -> DataFrame:
    """Near-equal folds without a global sort, for tables of any size."""
    return points.withColumn("fold", (F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(k)) + 1).cast("int"))
