"""Layouts of wide sparse matrices are as large as their entries."""

import numpy as np
import pytest

from spectral_frames.matrix import EntryFrame, SparseRowFrame
from spectral_frames.operators import low_rank, products
from spectral_frames.sources import interop

M, N = 300_000, 400_000


def wide(spark):
    rng = np.random.default_rng(0)
    rows = sorted({(int(i), int(j)): float(v) for i, j, v in zip(rng.integers(0, M, 500), rng.integers(0, N, 500), rng.integers(1, 9, 500), strict=True)}.items())
    return EntryFrame(spark.createDataFrame([(i, j, v) for (i, j), v in rows], "i long, j long, v double"), N, M), {k: v for k, v in rows}


def entries(a):
    return {(r["i"], r["j"]): r["v"] for r in a.df.collect()}


def test_a_transpose_goes_through_tiles_of_any_size(spark):
    """dense tiles of this matrix would hold a thousand million numbers."""
    a, x = wide(spark)
    tiles = a.to_tiles(2000, 1500)
    assert tiles.df.selectExpr("sum(size(data))").first()[0] == len(x)
    assert entries(tiles.transpose().to_entries()) == {(j, i): v for (i, j), v in x.items()}


def test_products_by_sparse_rows_and_tiles(spark):
    """a dense row would hold 400,000 numbers."""
    a, x = wide(spark)
    q = low_rank.gaussian_frame(spark, M, 3)
    want = {r["row_id"]: r["vec"] for r in products.multiply_t(a, q).df.collect()}
    for b in (a.to_sparse_rows(), a.to_tiles(64, 16)):
        got = {r["row_id"]: r["vec"] for r in products.multiply_t(b, q).df.collect()}
        assert set(got) == set(want) and all(np.allclose(got[k], want[k]) for k in want)


def test_mllib_keeps_sparse_layouts_sparse(spark):
    """back and forth without a dense row or block."""
    a, x = wide(spark)
    for b in (a.to_sparse_rows(), a.to_tiles(2000, 1500), a):
        back = interop.from_mllib(spark, interop.to_mllib(b))
        assert type(back) is type(b)
        assert entries(back if isinstance(back, EntryFrame) else back.to_entries()) == x
    assert isinstance(interop.from_mllib(spark, interop.to_mllib(a.to_sparse_rows())), SparseRowFrame)


def test_low_rank_of_sparse_tiles_is_that_of_entries(spark):
    """F4."""
    a, _ = wide(spark)
    one = low_rank.low_rank_svd(a, 3, 1).sigma
    two = low_rank.low_rank_svd(a.to_tiles(256, 256), 3, 1).sigma
    assert np.allclose(one, two, rtol=1e-9)


def sent_to_workers(df):
    """Bytes that the plan of a collected table has sent to Python workers."""

    def walk(node):
        kind = node.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            return walk(node.executedPlan())
        if kind.endswith("QueryStageExec"):
            return walk(node.plan())
        metric = node.metrics().get("pythonDataSent")
        kids = node.children()
        return (metric.get().value() if metric.isDefined() else 0) + sum(walk(kids.apply(k)) for k in range(kids.size()))

    return walk(df._jdf.queryExecution().executedPlan())


def test_a_product_by_tiles_sends_a_band_once_not_with_every_tile(spark):
    """400 tiles of an entry each stand in one band of 5000 columns."""
    e = EntryFrame(spark.createDataFrame([(10 * i, 7 * i, 1.0 + i) for i in range(400)], "i long, j long, v double"), 5000, 4000)
    q = low_rank.gaussian_frame(spark, 5000, 3)
    q.df = spark.createDataFrame(q.df.toArrow())
    found = products.multiply(e.to_tiles(10, 5000), q).df
    x, got = q.collect(), {r["row_id"]: r["vec"] for r in found.collect()}
    assert set(got) == set(range(0, 4000, 10)) and all(np.allclose(got[10 * i], (1.0 + i) * x[7 * i]) for i in range(400))
    assert 0 < sent_to_workers(found) < 20 * x.nbytes


@pytest.mark.parametrize("rows", [1, 3, 10_000])
def test_products_by_tiles_whatever_the_batches_and_parts(spark, monkeypatch, rows):
    monkeypatch.setattr(products, "BAND_TILES", 2)
    rng = np.random.default_rng(rows)
    x = rng.standard_normal((40, 30)) * (rng.random((40, 30)) < 0.3)
    e = EntryFrame(spark.createDataFrame([(int(i), int(j), float(x[i, j])) for i, j in zip(*np.nonzero(x), strict=True)], "i long, j long, v double"), 30, 40)
    tiles, name = e.to_tiles(4, 7), "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, rows)
    try:
        for f, a, n in ((products.multiply, x, 30), (products.multiply_t, x.T, 40)):
            q = rng.standard_normal((n, 3))
            q[::5] = 0
            some = EntryFrame(spark.createDataFrame([(i, k, float(q[i, k])) for i in range(n) for k in range(3) if q[i, k]], "i long, j long, v double"), 3, n).to_rows()  # rows of zeros are absent
            got = np.zeros((len(a), 3))
            for r in f(tiles, some).df.collect():
                got[r["row_id"]] = r["vec"]
            assert np.allclose(got, a @ q)
    finally:
        spark.conf.set(name, before)
