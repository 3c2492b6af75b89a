"""Connected components over edge tables of any size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .spool import spool


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    low = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(low.select("u", F.col("m").alias("v")))


def components(edges: DataFrame, src: str = "u", dst: str = "v", max_rounds: int = 60) -> DataFrame:
    """``(id, comp)`` for every vertex of an undirected edge table; ``comp`` is the smallest id reachable.

    Alternating large-star and small-star contractions: each round joins edges
    with one minimum per vertex, so a hub of any degree costs its own edges
    only, and the rounds grow with the logarithm of the vertex count.  Self
    loops keep their vertex; an empty table gives an empty table.
    """
    named = edges.select(F.col(src).cast("long").alias("u"), F.col(dst).cast("long").alias("v"))
    named = named.where("u is not null and v is not null").distinct()
    loops = named.where("u = v").select(F.col("u").alias("id"))
    now = spool(named.where("u <> v"), "edges")
    mark = None
    for _ in range(max_rounds if now.limit(1).count() else 0):
        now = spool(_small_star(_large_star(now)).distinct(), "edges")
        row = now.agg(F.count("*"), F.sum(F.hash("u", "v").cast("long"))).first()
        if (row[0], row[1]) == mark:
            break
        mark = (row[0], row[1])
    else:
        if mark is not None:
            raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    leaf = now.select(F.col("u").alias("id"), F.col("v").alias("comp"))
    root = now.select(F.col("v").alias("id"), F.col("v").alias("comp")).distinct()
    alone = loops.select("id", F.col("id").alias("comp"))
    return leaf.union(root).union(alone).groupBy("id").agg(F.min("comp").alias("comp"))
