"""Labelled junk that passes the base rule is rejected, and clean documents stay."""

import duckdb
import pytest
from pyspark.sql import functions as F

from spectral_frames.llm import quality


def test_symbol_junk_goes_and_clean_documents_stay(spark):
    sf = "/root/testdata/sf0.01"
    labels = dict(duckdb.sql(f"select doc_id, quality from '{sf}/labels.parquet'").fetchall())
    out = {r["doc_id"]: r for r in quality.judged(spark.read.parquet(f"{sf}/documents.parquet")).collect()}
    passed = [i for i in labels if not out[i]["base_failed"]]
    junk, clean = ([i for i in passed if labels[i] == v] for v in (0, 1))
    assert junk and not any(out[i]["kept"] for i in junk)
    assert sum(out[i]["kept"] for i in clean) >= 0.98 * len(clean)


@pytest.mark.parametrize("share", [0.04, 0.08, 0.12])
def test_any_clear_share_of_symbols_is_far_out(spark, share):
    rows = [(i, " ".join(f"w{(i * 37 + k * k) % 991}" for k in range(60 + i % 90)), "en", "a") for i in range(200)]
    n = int(len(rows[0][1]) * share)
    rows.append((1000, rows[0][1] + " " + "# " * n, "en", "a"))
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    assert [r["kept"] for r in quality.judged(docs).where(F.col("doc_id") == 1000).collect()] == [False]
