"""Files, distributed types, grouped factors, samples, cost."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from spectral_frames import functions as fn
from spectral_frames.cost import CostMeter
from spectral_frames.matrix import from_numpy
from spectral_frames.operators import consumers, low_rank, pca, thin
from spectral_frames.sources import interop, tables


@pytest.mark.parametrize("kind", ["csv", "json", "orc", "parquet"])
def test_rows_from_files(spark, tmp_path, kind):
    df = spark.createDataFrame([(3, 1.5, -2.0), (1, 0.0, 4.0)], "id long, x double, y double")
    df.write.format(kind).save(str(tmp_path / kind))
    a = interop.read_rows(spark, str(tmp_path / kind), kind, ["x", "y"], "id")
    assert sorted(map(tuple, ((r["row_id"], *r["vec"]) for r in a.df.collect()))) == [(1, 0.0, 4.0), (3, 1.5, -2.0)]


def test_rows_from_arrays_and_unknown_formats(spark, tmp_path):
    spark.createDataFrame([(0, [1.0, 2.0])], "id long, v array<double>").write.json(str(tmp_path / "a"))
    assert interop.read_rows(spark, str(tmp_path / "a"), "json", "v", "id").collect().tolist() == [[1.0, 2.0]]
    with pytest.raises(ValueError):
        interop.read_rows(spark, "x", "xml", ["a"])


def test_distributed_types(spark):
    x = np.random.default_rng(0).standard_normal((11, 5))
    a = from_numpy(spark, x, 2)
    for b in (a, a.to_entries(), a.to_tiles(4, 3)):
        back = interop.from_mllib(spark, interop.to_mllib(b))
        rows = back if back is not b and hasattr(back, "collect") else back.to_rows()
        assert np.allclose(rows.collect(), x)
    assert np.allclose(interop.from_ml_vectors(interop.to_ml_vectors(a), "row_id", "features", 5).collect(), x)
    r = low_rank.low_rank_svd(interop.from_mllib(spark, interop.to_mllib(a.to_tiles(4, 3))), 4, 2)
    assert np.allclose(r.sigma[0], np.linalg.svd(x, compute_uv=False)[0], rtol=0.2)


def test_a_saved_pca_keeps_its_mean(spark, tmp_path):
    x = np.random.default_rng(1).standard_normal((40, 3)) * [1, 5, 2] + 50
    p = pca.pca(from_numpy(spark, x, 2), 2, scale=True)
    p.save(str(tmp_path / "p"))
    back = pca.PCAResult.load(spark, str(tmp_path / "p"))
    new = from_numpy(spark, x[:5] + 1)
    assert np.allclose(back.transform(new).collect(), p.transform(new).collect()) and back.m == 40


def test_groups_larger_than_their_partials(spark, monkeypatch):
    monkeypatch.setattr(fn, "HELD_BYTES", 100)
    rng = np.random.default_rng(2)
    rows = [("hot" if k % 3 else f"k{k % 7}", rng.standard_normal(4).tolist()) for k in range(300)]
    df = spark.createDataFrame(rows + [(None, [1.0, 0.0, 0.0, 0.0]), ("hot", None)], "name string, v array<double>").repartition(5)
    by: dict = {}
    for k, v in rows:
        by.setdefault(k, []).append(v)
    by[None] = [[1.0, 0.0, 0.0, 0.0]]
    sigma: dict = {}
    for r in fn.svd_by_group(df, "name", "v").orderBy("sigma").collect():
        sigma.setdefault(r["name"], []).append(r["sigma"])
    gram = {r["name"]: r["gram"] for r in fn.gram_by_group(df, "name", "v").collect()}
    assert sigma.keys() == gram.keys() == by.keys()
    for k, v in by.items():
        x = np.array(v)
        assert np.allclose(sorted(sigma[k])[::-1][: min(x.shape)], np.linalg.svd(x, compute_uv=False)) and np.allclose(gram[k], (x.T @ x)[np.triu_indices(4)])
    with pytest.raises(ValueError):
        fn.svd_by_group(df.withColumnRenamed("name", "k"), "k", "v")


def test_samples(spark):
    df = spark.range(20_000).repartition(7)
    one = {r["id"] for r in fn.sample_rows(df, 0.1, "id", seed=1).collect()}
    assert abs(len(one) - 2000) < 200 and one == {r["id"] for r in fn.sample_rows(df.repartition(3), 0.1, "id", seed=1).collect()}
    x = np.ones((500, 2))
    x[:5] = 100
    kept = {r["row_id"]: r["p"] for r in fn.sample_by_length(from_numpy(spark, x, 2), 20).collect()}
    assert set(range(5)) <= set(kept) and all(kept[k] == 1 for k in range(5))


def test_row_numbers_and_columns(spark):
    x = np.arange(60.0).reshape(20, 3)
    a = from_numpy(spark, x, 4)
    odd = thin.RowFrame(a.df.select((F.col("row_id") * 17 - 100).alias("row_id"), "vec").repartition(6), 3).renumbered()
    assert np.array_equal(odd.collect(), x) and sorted(r["row_id"] for r in odd.df.collect()) == list(range(20))
    assert np.array_equal(a.columns([2, 0]).collect(), x[:, [2, 0]])
    with pytest.raises(ValueError):
        a.columns([3])


def test_categories_are_never_cut(spark):
    df = spark.range(150).selectExpr("cast(id as string) as c")
    assert len(tables.categories(df, "c")) == 150
    with pytest.raises(ValueError):
        tables.categories(df, "c", 100)


def test_nearest_rows_and_cells(spark):
    rng = np.random.default_rng(5)
    x = rng.standard_normal((60, 4))
    a = from_numpy(spark, x, 4)
    got: dict = {}
    for r in consumers.nearest_rows(a, a.df.where("row_id % 20 = 0"), 3, block=2).orderBy("place").collect():
        got.setdefault(r["query_id"], []).append(r["row_id"])
    for q in (0, 20, 40):
        s = x @ x[q]
        s[q] = -np.inf
        assert got[q] == np.argsort(-s, kind="stable")[:3].tolist()
    cells = consumers.largest_cells(thin.thin_svd(a), 5).collect()
    order = np.argsort(-x.ravel(), kind="stable")[:5]
    assert [(r["i"], r["j"]) for r in cells] == [(int(k) // 4, int(k) % 4) for k in order]


def test_cost_counts_python_workers(spark):
    a = from_numpy(spark, np.random.default_rng(0).standard_normal((4000, 40)), 2)
    with CostMeter(spark) as m:
        thin.thin_svd(a, "mixed_qr", 1)
        with m.pause():
            spark.range(10).count()
    assert m.report.python_cpu_s > 0 and m.report.cpu_s >= m.report.python_cpu_s and 0 < m.report.reserved_s < 10 * m.report.elapsed_s
