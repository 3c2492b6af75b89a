"""SQL functions: distances, nearest landmark and embedding as UDFs and a UDTF."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .functions import metrics
from .operators.maps import Model, nystrom


def register_distances(spark: SparkSession) -> None:
    """``euclid(a, b)`` and ``rmsd(a, b)`` over arrays of doubles, in Arrow batches."""

    @F.pandas_udf("double")
    def euclid(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series(np.sqrt(((np.stack(a) - np.stack(b)) ** 2).sum(1)) if len(a) else [], dtype=float)

    @F.pandas_udf("double")
    def rmsd(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series(metrics.rmsd_rows(np.stack(a), np.stack(b)) if len(a) else [], dtype=float)

    spark.udf.register("euclid", euclid)
    spark.udf.register("rmsd", rmsd)


def register_model(spark: SparkSession, model: Model, k: int) -> None:
    """``embed(vec)``, ``nearest_landmark(vec)`` and the table function ``embed_point(vec) -> mode, value``."""

    @F.pandas_udf("array<double>")
    def embed(v: pd.Series) -> pd.Series:
        return pd.Series(list(nystrom(np.stack(v), model, k)[0]) if len(v) else [])

    @F.pandas_udf("long")
    def nearest_landmark(v: pd.Series) -> pd.Series:
        return pd.Series(model.ids[nystrom(np.stack(v), model, k)[1]] if len(v) else [], dtype="int64")

    @F.udtf(returnType="mode int, value double")
    class EmbedPoint:
        def eval(self, vec):
            for m, x in enumerate(nystrom(np.array([vec], float), model, k)[0][0].tolist()):
                yield m + 2, x

    spark.udf.register("embed", embed)
    spark.udf.register("nearest_landmark", nearest_landmark)
    spark.udtf.register("embed_point", EmbedPoint)
