"""Queries that name a method run all of it, on what a table holds."""

import duckdb
import numpy as np
import pytest

from spectral_frames import workloads
from spectral_frames.cost import CostMeter
from spectral_frames.operators import reduce, thin, tree_qr
from spectral_frames.sources import synth, tables

SF = "/root/testdata/sf0.001"


@pytest.fixture
def found(monkeypatch):
    """What thin_svd gave, call by call."""
    results, real = [], thin.thin_svd

    def spy(*args, **kwargs):
        results.append(real(*args, **kwargs))
        return results[-1]

    monkeypatch.setattr(thin, "thin_svd", spy)
    return results


def test_geo_thin_sigma_is_an_svd(spark, found):
    rows = sorted(map(tuple, workloads.geo_thin_sigma(spark, SF).select("k", "micro_log").collect()))
    c = duckdb.connect()
    c.sql(f"create view orders as select * from '{SF}/orders.parquet'")
    assert rows == sorted(c.sql(f"select k, micro_log from ({workloads.ORACLES['geo_thin_sigma']})").fetchall())
    assert len(found) == 1 and found[0].rank == len(rows)
    assert sorted(m for _, m in rows)[::-1] == [round(x * 1e6) for x in np.log10(found[0].sigma)]


def test_units_of_spend_are_one_matrix(spark):
    """Columns of disjoint rows whose lengths are the spectrum, in as many tasks as are asked for."""
    a = tables.spend(spark, SF, 60, 7, synth.geometric(7), 1, right="unit")
    x = a.collect()
    assert a.df.rdd.getNumPartitions() == 1 and x.shape == (60, 7) and ((x != 0).sum(axis=1) == 1).all()
    assert np.allclose(np.linalg.norm(x, axis=0), synth.geometric(7), rtol=1e-12, atol=0)


def test_sums_of_partials():
    xs = [np.full((2, 3), float(k)) for k in range(3)]
    for x in xs:
        x.flags.writeable = False
    assert np.array_equal(reduce.added(xs), np.sum(xs, axis=0)) and reduce.added(xs[:1]).flags.writeable


def test_geo_thin_sigma_without_orders(spark, tmp_path):
    spark.read.parquet(f"{SF}/orders.parquet").limit(0).write.parquet(str(tmp_path / "orders.parquet"))
    assert workloads.geo_thin_sigma(spark, str(tmp_path)).count() == 0


def test_cost_scaling_counts_left_vectors(spark, found, monkeypatch):
    """Each counted run sweeps the tree for Q (mixed QR) and writes U, within what is metered."""
    log, enter, leave, stored, direct = [], CostMeter.__enter__, CostMeter.__exit__, thin.stored, tree_qr.q_direct
    monkeypatch.setattr(CostMeter, "__enter__", lambda m: (log.append("begin"), enter(m))[1])
    monkeypatch.setattr(CostMeter, "__exit__", lambda m, *x: (log.append("end"), leave(m, *x))[1])
    monkeypatch.setattr(tree_qr, "q_direct", lambda *x, **y: (log.append("tree"), direct(*x, **y))[1])
    monkeypatch.setattr(thin, "stored", lambda a: (log.append("U" if found and a is found[-1].U else "matrix"), stored(a))[1])
    assert workloads.cost_scaling(spark, SF).count() == 2
    runs = " ".join(log).split("begin ")[1:]
    assert [r.split("end")[0].split() for r in runs] == [["U"], ["tree", "U"]] * 3


def test_functions_of_two_cogroups_are_timed(spark):
    from spectral_frames.cost import timed, worker_cpu

    def busy(left, right):
        return left[["id"]].assign(x=float(np.linalg.svd(np.ones((400, 400)))[1][0]) * len(right))

    a, before = spark.range(4), worker_cpu(spark).value
    assert a.groupBy("id").cogroup(a.groupBy("id")).applyInPandas(timed(spark, busy), "id long, x double").count() == 4
    assert worker_cpu(spark).value > before


def test_direct_form_sweeps_the_tree_in_each_pass(spark, monkeypatch):
    calls, direct = [], tree_qr.q_direct
    monkeypatch.setattr(tree_qr, "q_direct", lambda *x, **y: (calls.append(x), direct(*x, **y))[1])
    a = thin.stored(synth.geo_thin(spark, 700, 24, 3))
    r = thin.thin_svd(a, "mixed_qr", 2, q_form="direct")
    assert len(calls) == 2
    u = r.U.collect()
    assert r.rank == thin.thin_svd(a, "mixed_qr", 2).rank and np.abs(u.T @ u - np.eye(r.rank)).max() < 1e-13
    assert np.allclose(r.reconstruct().collect(), a.collect(), atol=1e-10)


def test_ablation_table_has_the_trackers(spark):
    rows = workloads.ablation_table(spark, SF).collect()
    assert len(rows) == 23 and [r["tracker"] for r in rows[20:]] == ["svd", "q_only", "lu"] and not any(r["tracker"] for r in rows[:20])
    assert all(r["u_defect"] < 1e-12 and 0 < r["rank"] < 40 for r in rows[20:])


def test_ablation_table_without_orders(spark, tmp_path):
    """No sketch fits a matrix without rows, so there are no trackers."""
    spark.read.parquet(f"{SF}/orders.parquet").limit(0).write.parquet(str(tmp_path / "orders.parquet"))
    assert [(r["rank"], r["u_defect"]) for r in workloads.ablation_table(spark, str(tmp_path)).collect()] == [(0, 0.0)] * 20
