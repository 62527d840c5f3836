"""Streaming summaries: windowed moments, running Gram and R states, deduplication, scoring."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..session import ship


def event_stream(spark: SparkSession, path: str, schema: StructType, files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def moments(columns: list[Column]) -> list[Column]:
    """Count, sums and sums of products: the additive state of a Gram matrix of a few columns."""
    sums = [F.sum(c).alias(f"s{i}") for i, c in enumerate(columns)]
    return [F.count("*").alias("n"), *sums, *[F.sum(columns[i] * columns[j]).alias(f"s{i}_{j}") for i in range(len(columns)) for j in range(i, len(columns))]]


def windowed(stream: DataFrame, ts: str, columns: list[Column], size: str = "1 day", slide: str | None = None, late: str | None = "2 hours") -> DataFrame:
    """Moments by tumbling or sliding window; rows later than the watermark are dropped."""
    kept = stream.withWatermark(ts, late) if late else stream
    window = F.window(ts, size, slide) if slide else F.window(ts, size)
    return kept.groupBy(window.alias("w")).agg(*moments(columns)).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *[c for c in _names(columns)])


def sessions(stream: DataFrame, ts: str, key: str, columns: list[Column], gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    grouped = stream.withWatermark(ts, late).groupBy(F.session_window(ts, gap).alias("w"), key)
    return grouped.agg(*moments(columns)).select(key, F.col("w.start").alias("start"), *_names(columns))


def _names(columns: list[Column]) -> list[str]:
    k = len(columns)
    return ["n", *[f"s{i}" for i in range(k)], *[f"s{i}_{j}" for i in range(k) for j in range(i, k)]]


def deduplicated(stream: DataFrame, ts: str, key: str, late: str = "2 hours") -> DataFrame:
    return stream.withWatermark(ts, late).dropDuplicatesWithinWatermark([key])


def run_to_table(stream: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Runs over all that is there, then stops.

    Rows are files beside the checkpoint, so results of any size leave the driver alone; a complete result takes the place of the one before.
    """
    writer = stream.writeStream.option("checkpointLocation", f"{checkpoint}/state").queryName(name).trigger(availableNow=True)
    top = f"{checkpoint}/rows"
    if mode == "complete":
        batches = []

        def whole(batch: DataFrame, batch_id: int) -> None:  # two folders in turn: the last whole result stays until the next is written
            batch.write.mode("overwrite").parquet(f"{top}/{batch_id % 2}")
            batches.append(batch_id)

        writer.foreachBatch(whole).outputMode(mode).start().awaitTermination()
        reader = stream.sparkSession.read.schema(stream.schema)
        if batches:
            return reader.parquet(f"{top}/{batches[-1] % 2}")
        return stream.sparkSession.createDataFrame([], stream.schema)
    if mode == "append":
        writer.format("parquet").option("path", top).outputMode(mode).start().awaitTermination()
    else:

        def put(batch: DataFrame, batch_id: int) -> None:  # a batch that is delivered again replaces itself
            batch.write.mode("overwrite").parquet(f"{top}/batch={batch_id}")

        writer.foreachBatch(put).outputMode(mode).start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).option("recursiveFileLookup", True).parquet(top)


class RunningR:
    """The R factor of all rows seen so far: each micro-batch is reduced by the tree, then merged; state is n x n."""

    def __init__(self, n: int):
        self.r = np.zeros((0, n))
        self.n = n
        self.batches: set[int] = set()

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        from ..kernels import r_of
        from ..matrix import RowFrame
        from ..operators.tree_qr import r_factor

        if batch_id in self.batches:  # a batch may be delivered again after a restart
            return
        found = r_factor(RowFrame(batch, self.n))
        self.r = r_of(self.r, found)
        self.batches.add(batch_id)

    @property
    def sigma(self) -> np.ndarray:
        return np.linalg.svd(self.r, compute_uv=False) if len(self.r) else np.zeros(0)


def running_r_by_key(stream: DataFrame, key: str, array: str, n: int) -> DataFrame:
    """(key, rows, sigma): a stateful R factor per key, updated with each micro-batch."""
    ship(stream.sparkSession)

    def update(k, frames, state):
        rows, r = (0, np.zeros((0, n)))
        if state.exists:
            rows, data = state.get
            r = np.frombuffer(data, np.float64).reshape(-1, n)
        for frame in frames:
            x = np.stack(frame["x"].to_numpy()).astype(float)
            rows, r = rows + len(x), np.linalg.qr(np.vstack((r, x)), mode="r")
        state.update((rows, r.tobytes()))
        yield pd.DataFrame({key: [k[0]], "rows": [rows], "sigma": [np.linalg.svd(r, compute_uv=False).tolist()]})

    kind = dict(stream.dtypes)[key]
    grouped = stream.select(key, F.col(array).alias("x")).groupBy(key)
    return grouped.applyInPandasWithState(update, f"{key} {kind}, rows long, sigma array<double>", "rows long, data binary", "update", "NoTimeout")


def followed(left: DataFrame, right: DataFrame, left_key: str, right_key: str, left_ts: str, right_ts: str, within: str, late: str = "2 hours") -> DataFrame:
    """Pairs of rows of two streams with equal keys, the right one at most ``within`` after the left; both states are let go by watermarks."""
    a, b = left.withWatermark(left_ts, late), right.withWatermark(right_ts, late)
    return a.join(b, (F.col(left_key) == F.col(right_key)) & (F.col(right_ts) >= F.col(left_ts)) & (F.col(right_ts) <= F.col(left_ts) + F.expr(f"INTERVAL {within}")))

