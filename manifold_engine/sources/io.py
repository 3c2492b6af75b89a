"""Stored models, readers and sinks, and a roll generator as a Python data source."""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.maps import Model
from ..operators.pairs import matrix


def save_model(spark: SparkSession, model: Model, path: str) -> None:
    """Landmarks, spectrum and parameters as Parquet, each partitioned by version; other versions stay."""
    rows = pa.table({"lid": pa.array(model.ids), "vec": pa.array(list(model.vecs), pa.list_(pa.float64())), "mult": pa.array(model.counts), "deg": pa.array(model.deg), "psi": pa.array(list(model.psi), pa.list_(pa.float64()))})
    params = json.dumps({"eps": model.eps, "metric": model.metric, "kind": model.kind})
    for name, df in (("landmarks", spark.createDataFrame(rows)), ("spectrum", model.spectrum(spark)), ("params", spark.createDataFrame([(params,)], "params string"))):
        df.withColumn("version", F.lit(model.version)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("version").parquet(f"{path}/{name}")


def load_model(spark: SparkSession, path: str, version: str | None = None) -> Model:
    """A stored model; without ``version`` the greatest one."""
    params = spark.read.parquet(f"{path}/params").withColumn("version", F.col("version").cast("string"))
    version = version or params.agg(F.max("version")).first()[0]
    p = json.loads(params.where(F.col("version") == version).first()["params"])
    t = spark.read.parquet(f"{path}/landmarks").where(F.col("version") == version).orderBy("lid").toArrow()
    s = spark.read.parquet(f"{path}/spectrum").where(F.col("version") == version).orderBy("l").toArrow()
    return Model(t["lid"].to_numpy(), matrix(t["vec"]), t["mult"].to_numpy(), s["lambda"].to_numpy(), matrix(t["psi"]), t["deg"].to_numpy(), p["eps"], p["metric"], version, p["kind"])


def read_points(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Parquet, ORC, JSON or CSV rows (a declared schema for the last two)."""
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_embedding(embedding: DataFrame, path: str, buckets: int = 16) -> None:
    """Embedding rows partitioned by ranges of ids, so that a reader of some ids prunes files."""
    embedding.repartitionByRange(buckets, "id").sortWithinPartitions("id").write.mode("overwrite").parquet(path)


def idempotent_sink(path: str):
    """A ``foreachBatch`` writer: a batch that is run again replaces its own folder."""

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return write


class RollSource(DataSource):
    """``spark.read.format("roll").option("points", n)``: seeded Swiss rolls for load tests."""

    @classmethod
    def name(cls) -> str:
        return "roll"

    def schema(self) -> str:
        return "id long, vec array<double>"

    def reader(self, schema):
        return _RollReader(int(self.options.get("points", 1000)), int(self.options.get("partitions", 4)), int(self.options.get("seed", 0)))


class _RollReader(DataSourceReader):
    def __init__(self, points: int, partitions: int, seed: int):
        self.points, self.parts, self.seed = points, partitions, seed

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        ids = np.arange(partition.value, self.points, self.parts)
        rng = np.random.default_rng([self.seed, partition.value])
        t, h = 1.5 * np.pi * (1 + 2 * rng.random(len(ids))), 21 * rng.random(len(ids))
        for i, a, b in zip(ids.tolist(), t.tolist(), h.tolist()):
            yield i, [a * float(np.cos(a)), b, a * float(np.sin(a))]
