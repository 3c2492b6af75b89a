"""Streams of new points: embedding, outlier rates by event time, basin changes, model hot-swap, drift."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..operators.maps import Model, extend


def read_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files of a folder as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def stream_extend(stream: DataFrame, model: Model, k: int, reach: float | None = None, keep: tuple[str, ...] = ("ts", "user_id")) -> DataFrame:
    """Stateless embedding; ``keep`` columns travel in a struct beside the id, so no join is needed."""
    import pyarrow as pa
    from pyspark.sql import types as T

    from ..operators.maps import nystrom
    from ..operators.pairs import matrix

    far = model.eps**0.5 if reach is None else reach
    fields = [stream.schema[c] for c in ("id", *keep)]
    out = T.StructType([*fields, T.StructField("psi", T.ArrayType(T.DoubleType())), T.StructField("nearest_lid", T.LongType()), T.StructField("d_min", T.DoubleType()), T.StructField("extrapolated", T.BooleanType()), T.StructField("model_version", T.StringType())])

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            psi, at, best = nystrom(matrix(b.column("vec")), model, k)
            yield pa.RecordBatch.from_arrays([*[b.column(f.name) for f in fields], pa.array(list(psi), pa.list_(pa.float64())), pa.array(model.ids[at]), pa.array(best), pa.array(best > far), pa.array([model.version] * len(at))], names=out.names)

    return stream.mapInArrow(run, out)


def outlier_rate(embedded: DataFrame, width: str = "1 day", late: str = "1 day", slide: str | None = None) -> DataFrame:
    """Points, outliers and mean first coordinate by window of event time; rows later than the watermark are dropped."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return embedded.withWatermark("ts", late).groupBy(w).agg(F.count("*").alias("n"), F.sum(F.col("extrapolated").cast("long")).alias("outliers"), F.avg(F.col("psi")[0]).alias("mean_psi"))


def sessions(events: DataFrame, gap: str = "2 hours", late: str = "1 day") -> DataFrame:
    """Session windows of each user."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))


def once(stream: DataFrame, late: str = "1 day") -> DataFrame:
    """Each id once within the watermark."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["id"])


def purchases_after_errors(left: DataFrame, right: DataFrame, within: str = "1 hour", late: str = "1 day") -> DataFrame:
    """Stream-stream interval join: a purchase of the same user at most ``within`` after an error."""
    a = left.select(F.col("user_id").alias("u"), F.col("ts").alias("error_ts"), F.col("id").alias("error_id")).withWatermark("error_ts", late)
    b = right.select("user_id", F.col("ts").alias("buy_ts"), F.col("id").alias("buy_id")).withWatermark("buy_ts", late)
    return a.join(b, (F.col("u") == F.col("user_id")) & (F.col("buy_ts") > F.col("error_ts")) & (F.col("buy_ts") <= F.col("error_ts") + F.expr(f"interval {within}")))


class BasinChanges(StatefulProcessor):
    """Remembers each user's last basin (sign of the first coordinate); emits a row when it changes.

    An event-time timer forgets a user whose last event lies ``idle_ms`` behind
    the watermark, so the state holds active users only.
    """

    def __init__(self, idle_ms: int = 7 * 86_400_000):
        self.idle_ms = idle_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.last = handle.getValueState("basin", "basin int, since timestamp")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        data = pd.concat(list(rows)).sort_values(["ts", "id"])
        now = self.last.get() if self.last.exists() else None
        basin = now[0] if now else None
        out = []
        for i, ts, b in zip(data["id"], data["ts"], data["basin"]):
            if basin is not None and b != basin:
                out.append((key[0], int(i), ts, int(basin), int(b)))
            basin = b
        latest = data["ts"].iloc[-1]
        self.last.update((int(basin), latest))
        for t in list(self.handle.listTimers()):
            self.handle.deleteTimer(t)
        self.handle.registerTimer(int(pd.Timestamp(latest).timestamp() * 1000) + self.idle_ms)
        yield pd.DataFrame(out, columns=["user_id", "id", "ts", "was", "now"])

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        self.last.clear()
        yield pd.DataFrame([], columns=["user_id", "id", "ts", "was", "now"])

    def close(self) -> None:
        pass


CHANGES = "user_id long, id long, ts timestamp, was int, now int"


def basin_changes(embedded: DataFrame, late: str = "1 day", idle_ms: int = 7 * 86_400_000) -> DataFrame:
    rows = embedded.withWatermark("ts", late).select("user_id", "id", "ts", (F.col("psi")[0] > 0).cast("int").alias("basin"))
    return rows.groupBy("user_id").transformWithStateInPandas(BasinChanges(idle_ms), outputStructType=CHANGES, outputMode="Append", timeMode="EventTime")


def basin_changes_batch(embedded: DataFrame) -> DataFrame:
    """The same on a table, by a window."""
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("ts", "id")
    rows = embedded.select("user_id", "id", "ts", (F.col("psi")[0] > 0).cast("int").alias("now")).withColumn("was", F.lag("now").over(w))
    return rows.where("was is not null and was <> now").select("user_id", "id", "ts", "was", "now")


def hot_swap(load: Callable[[], Model], k: int, sink: Callable[[DataFrame, int], None]):
    """A ``foreachBatch`` function that embeds each batch by the model current at its start."""

    def run(batch: DataFrame, batch_id: int) -> None:
        sink(extend(batch, load(), k), batch_id)

    return run


def drift(rates: DataFrame, limit: float = 0.05) -> DataFrame:
    """Windows whose outlier rate calls for a refit."""
    return rates.where(F.col("outliers") > limit * F.col("n"))


def run_available(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a stream over what is there into a Parquet table and read it back.

    Complete results replace the table batch by batch; nothing is kept on the driver.
    """
    from ..spool import shared_dir

    import uuid

    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    w = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint or f"{base}/state").trigger(availableNow=True)
    if mode == "append":
        q = w.format("parquet").start(f"{base}/out")
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/{name}")

    w.foreachBatch(keep).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/{name}")
