"""Results on the edge of rounding, and sums that no order of rows changes."""

import os
from fractions import Fraction

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from spectral_frames import kernels, relational, streaming, workloads
from spectral_frames.matrix import RowFrame
from spectral_frames.operators import gram


def test_a_complete_stream_leaves_the_driver_alone(spark, tmp_path):
    """the result is files, replaced whole by each batch."""
    for k in range(3):
        spark.createDataFrame([(1, k), (2 + k, k)], "a int, b int").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    s = streaming.event_stream(spark, str(tmp_path / "in"), spark.read.parquet(str(tmp_path / "in")).schema)
    out = streaming.run_to_table(s.groupBy("a").agg(F.count("*").alias("n")), "frames_whole", "complete", str(tmp_path / "out"))
    assert sorted(map(tuple, out.collect())) == [(1, 3), (2, 1), (3, 1), (4, 1)]
    assert out.inputFiles() and not spark.catalog.tableExists("frames_whole")


def test_exact_sums(spark):
    """naive sums of these differ in whole cents."""
    x = [1e14, 0.29, -1e14, 0.1, 1e13 + 0.01] * 3
    df = spark.createDataFrame([(v,) for v in x], "x double")
    want = round(sum(map(Fraction, x)) * 100)
    assert df.agg(workloads.whole(workloads.exact_sum("x"), 100)).first()[0] == want
    assert df.orderBy("x").agg(workloads.whole(workloads.exact_sum("x"), 100)).first()[0] == want


def test_gram_sums_of_many_rows(spark):
    """F8: a running sum of two million products is off in its thirteenth digit."""
    n = 2_000_000
    a = RowFrame(spark.range(n, numPartitions=1).select(F.col("id").alias("row_id"), F.array(F.lit(0.1), F.lit(0.7)).alias("vec")), 2)
    want = np.array([[0.1 * 0.1, 0.1 * 0.7], [0.1 * 0.7, 0.7 * 0.7]])
    want = np.array([[float(Fraction(x) * n) for x in row] for row in want])
    assert np.abs(gram.gram_catalyst(a) / want - 1).max() < 1e-13


def test_halves_of_a_running_r(spark, tmp_path):
    """sums of squares that end in exactly one half."""
    rng, rows, want = np.random.default_rng(0), [], {}
    for user in range(40):
        cents = rng.integers(0, 30000, 400).tolist()
        while (400 * 10000 + sum(c * c for c in cents)) % 10000 != 5000:
            cents[rng.integers(400)] = int(rng.integers(0, 30000))
        rows += [(user, c / 100) for c in cents]
        want[user] = (400 * 10000 + sum(c * c for c in cents) + 5000) // 10000
    table = {"event_id": pa.array(range(len(rows))), "ts": pa.array(np.arange(len(rows)) * 1_000_000 + 1_700_000_000_000_000, pa.timestamp("us")), "user_id": pa.array([u for u, _ in rows]), "event_type": ["view"] * len(rows), "value": [v for _, v in rows], "props": ["{}"] * len(rows)}
    pq.write_table(pa.table(table), tmp_path / "events.parquet")
    got = {r["user_id"]: r["s2"] for r in relational.stream_r_by_key(spark, str(tmp_path)).collect()}
    assert got == want


@pytest.mark.parametrize("name", workloads.METHODS)
def test_halves_in_reconstructions(spark, tmp_path, name):
    """Odd multiples of 1/128 are halves in millionths."""
    rng = np.random.default_rng(1)
    x = ((2 * rng.integers(-60, 60, (100, 64)) + 1) / 128).astype(np.float32)
    pq.write_table(pa.table({"vec_id": pa.array(range(100)), "embedding": pa.array(list(x), pa.list_(pa.float32())), "label": pa.array([0] * 100, pa.int32())}), os.path.join(tmp_path, "embeddings.parquet"))
    got = np.zeros(x.shape)
    for r in workloads.QUERIES[f"thin_{name}_reconstruct"](spark, str(tmp_path)).collect():
        got[r["row_id"], r["j"]] = r["value"]
    y = x.astype(float) * 1e6
    assert (got == np.sign(y) * np.floor(np.abs(y) + 0.5)).all()


def test_a_column_of_zeros_has_no_share_in_eigenvectors():
    """rank at working precision 0."""
    rng = np.random.default_rng(0)
    for _ in range(50):
        x = np.stack([rng.integers(1, 51, 50), np.zeros(50), rng.integers(0, 9, 50) / 100], axis=1)
        assert (np.linalg.norm(x @ kernels.eigen(x.T @ x), axis=0) > 0).tolist() == [True, True, False]
