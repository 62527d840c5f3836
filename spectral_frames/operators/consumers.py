"""What is done with factors: nearest rows, cells of a reconstruction."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..cost import timed
from ..matrix import RowFrame, rows_of
from ..session import SMALL_BYTES
from .thin import SVDResult

_LIST = "query_id long, row_id long, score double"


def nearest_rows(a: RowFrame, queries: DataFrame, k: int, block: int = 4096) -> DataFrame:
    """(query_id, place, row_id, score): the k rows of a with the largest inner products of each query row, itself left out; ties to smaller ids.

    Queries go to the rows in blocks; a task keeps k rows a query of a block, and emits no other pair.
    """
    n, spark = a.n, a.df.sparkSession
    found = None
    rows = queries.select("row_id", "vec").orderBy("row_id").toLocalIterator(prefetchPartitions=True)
    while True:
        some = [r for _, r in zip(range(max(1, min(block, SMALL_BYTES // (8 * max(n, 1))))), rows, strict=False)]
        if not some:
            break
        sent = spark.sparkContext.broadcast((np.array([r["row_id"] for r in some]), np.array([r["vec"] for r in some])))

        def kernel(batches, sent=sent):
            ids, q = sent.value
            best_id, best = np.zeros((len(ids), 0), np.int64), np.zeros((len(ids), 0))
            for batch in batches:
                of = batch.column("row_id").to_numpy()
                s = np.round(q @ rows_of(batch, n).T, 9)
                s[ids[:, None] == of[None, :]] = -np.inf
                s, of = np.concatenate((best, s), axis=1), np.concatenate((best_id, np.broadcast_to(of, (len(ids), len(of)))), axis=1)
                order = np.lexsort((of, -s), axis=1)[:, :k]
                best, best_id = np.take_along_axis(s, order, 1), np.take_along_axis(of, order, 1)
            at = np.isfinite(best)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, at.sum(axis=1))), pa.array(best_id[at]), pa.array(best[at])], ["query_id", "row_id", "score"])

        part = a.df.select("row_id", "vec").mapInArrow(timed(spark, kernel), _LIST)
        found = part if found is None else found.unionByName(part)
    if found is None:
        return spark.createDataFrame([], "query_id long, place int, row_id long, score double")
    by = Window.partitionBy("query_id").orderBy(F.desc("score"), "row_id")
    return found.withColumn("place", F.row_number().over(by)).where(F.col("place") <= k).select("query_id", "place", "row_id", "score")


def largest_cells(r: SVDResult, k: int) -> DataFrame:
    """(i, j, value): the k largest cells of U diag(sigma) V*; a task makes some rows at a time and passes k cells on."""
    spark, width = r.spark, r.rank
    sent = spark.sparkContext.broadcast(r.sigma[:, None] * r.v_numpy().T)

    def kernel(batches):
        held = pd.DataFrame({"i": np.zeros(0, np.int64), "j": np.zeros(0, np.int64), "value": np.zeros(0)})
        w = sent.value
        for batch in batches:
            u, ids = rows_of(batch, width), batch.column("row_id").to_numpy()
            step = max(1, (1 << 22) // max(w.shape[1], 1))
            for lo in range(0, len(u), step):
                x = u[lo : lo + step] @ w
                at = np.argpartition(-x.ravel(), min(4 * k, x.size - 1))[: 4 * k] if x.size else np.zeros(0, int)
                new = pd.DataFrame({"i": ids[lo : lo + step][at // x.shape[1]], "j": at % x.shape[1], "value": x.ravel()[at]})
                held = pd.concat([held, new]).sort_values(["value", "i", "j"], ascending=[False, True, True]).head(k)
        yield pa.RecordBatch.from_pandas(held, preserve_index=False)

    return r.U.df.mapInArrow(timed(spark, kernel), "i long, j long, value double").orderBy(F.desc("value"), "i", "j").limit(k)
