"""Matrices of known spectrum are made of a given table."""

import inspect

import numpy as np

from spectral_frames import experiments, workloads
from spectral_frames.sources import synth, tables

SF = "/root/testdata/sf0.001"
MOVED = ["ablation_table", "cost_scaling", "geo_low_entries", "geo_low_sigma", "geo_thin_sigma", "low_rank_accuracy_table", "low_rank_by_height", "low_rank_by_partitions", "low_rank_cost_scaling", "low_rank_full_rank_reconstruct", "low_rank_gram_full_rank_reconstruct"]


def test_spend_has_the_spectrum(spark):
    a = tables.spend(spark, SF, 300, 20, synth.geometric(5), 3)
    s = np.linalg.svd(a.collect(), compute_uv=False)
    assert np.allclose(s[:4], synth.geometric(5)[:4], rtol=1e-6, atol=1e-16) and a.height() == 300
    assert [f for f in a.df.inputFiles() if f.endswith("orders.parquet")]


def test_moved_queries_read_a_table():
    assert workloads.QUERIES["low_rank_by_height"] is experiments.low_rank_by_height
    for name in MOVED:
        assert "tables.spend" in inspect.getsource(workloads.QUERIES[name])
