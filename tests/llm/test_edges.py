"""Nulls in any column, empty and very long texts, ties, repeated rows, empty tables and clashing extra columns, for every operator and stage."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from spectral_frames.llm import langid, licenses, linededup, mixing, packing, pii, quality, simhash, suffixdedup, topk

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, TEXT string, size int, rank int, fp string, grade int, target string, part int, grp int, names string, line int, doc string, kept string"
LONG = "the quick brown fox jumps over the lazy dog and runs away from it all day long " * 3000


def rows():
    texts = [(1, "one two three four five six", "en", "a"), (2, None, "en", "a"), (3, "", None, None), (4, " \n\t ", "en", None), (None, "a b c", None, "a"), (None, "a b c", None, "a"), (5, "one two three four five six", "en", "a"), (5, "one two three four five six", "en", "a"), (6, LONG, "en", "b"), (7, "é\nß\n\n日本語 текст", "fr", "b"), (8, "x", None, "é"), (9, LONG, None, "b")]
    return [(*t, None if t[1] is None else len(t[1]), "T", 1, 2, "f", 3, "t", 4, 5, "n", 6, "d", "k") for t in texts]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def model():
    texts = [b"the and of to in is that", b"le la les des une est dans"] * 20
    return langid.fit(texts, ["en", "fr"] * 20)


PATH = pytest.importorskip("public_tokenizers").path("word_bpe_49k.json")
PER_ROW = {
    "mixing": lambda d, m: mixing.mix_sizes(d),
    "simhash": lambda d, m: simhash.near_components(d, 4),
    "licenses": lambda d, m: licenses.scan(d),
    "pii": lambda d, m: pii.scan(d),
    "quality": lambda d, m: quality.judged(d),
    "linededup": lambda d, m: linededup.removed(d),
    "suffixdedup": lambda d, m: suffixdedup.removed(d),
    "langid": lambda d, m: langid.predict(d, m),
}


@pytest.mark.parametrize("name", PER_ROW)
def test_one_row_per_row(docs, empty, model, name):
    out = PER_ROW[name](docs, model).collect()
    assert sorted(str(r["doc_id"]) for r in out) == sorted(str(r[0]) for r in rows())
    assert PER_ROW[name](empty, model).count() == 0


def test_same_answer_for_repeated_rows(docs, model):
    for name, f in PER_ROW.items():
        five = [r for r in f(docs, model).collect() if r["doc_id"] == 5]
        assert len(five) == 2 and five[0] == five[1], name


def test_packing(docs, empty):
    out = packing.pack(docs, PATH).collect()
    assert {str(r["doc_id"]) for r in out} == {str(r[0]) for r in rows()}
    assert all(r["length"] == 1 for r in out if r["doc_id"] in (2, 3, 4))
    assert sum(r["length"] for r in out if r["doc_id"] == 6) > 4096
    assert packing.pack(empty, PATH).count() == 0


@pytest.mark.parametrize("name", ["mixing", "linededup", "simhash", "langid", "pii"])
def test_filters_keep_all_columns(docs, empty, model, name):
    f = {"mixing": mixing.mix, "linededup": linededup.dedup, "simhash": simhash.near_dedup, "langid": lambda d: langid.keep_identified(d, model), "pii": pii.masked}[name]
    assert f(docs).columns == docs.columns and f(docs).count() >= 1
    assert f(empty).columns == docs.columns and f(empty).count() == 0


def test_near_dedup_keeps_one_of_a_group(docs):
    kept = [r["doc_id"] for r in simhash.near_dedup(docs).select("doc_id").collect()]
    assert kept.count(1) == 1 and 5 not in kept and 9 not in kept and kept.count(6) == 1


def test_suffix_dedup_text(docs):
    out = {r["doc_id"]: r["text"] for r in suffixdedup.dedup(docs).collect()}
    assert out[9] == "" and out[1] == "one two three four five six" and out[2] is None


def test_topk_rows_that_take_no_part(spark):
    nan = float("nan")
    v = spark.createDataFrame([(0, [1.0, 0.0], 1), (1, None, 1), (2, [nan, 1.0], 1), (3, [None, 1.0], 1), (4, [float("inf"), 0.0], 1), (5, [0.5, 0.5], 1), (6, [0.5, 0.5], 1), (7, [1.0], 1), (None, [1.0, 1.0], 1), (8, [1e300, 0.0], 1)], "vec_id long, embedding array<double>, rank int")
    out = topk.top_k(v.where("vec_id = 0"), v.where("vec_id < 8"), k=3)
    assert [(r["rank"], r["vec_id"], r["score"]) for r in out.orderBy("rank").collect()] == [(1, 5, 1024 * 512), (2, 6, 1024 * 512)]
    assert topk.top_k(v.where("vec_id = 0"), v, k=1).first()["score"] == 2**63 - 1
    assert topk.top_k(v.limit(0), v.limit(0)).count() == 0


def test_stages_on_empty_and_odd_tables(spark, tmp_path):
    cols = ["doc_id", "text", "lang", "source", "n_chars"]
    for name, table in (("odd", spark.createDataFrame([r[:5] for r in rows()], "doc_id long, text string, lang string, source string, n_chars long")), ("none", spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long"))):
        docs = table
        for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
            out = stage(spark, docs, "unused")
            if k < 4:
                assert out.columns == cols
                out.write.parquet(str(tmp_path / f"{name}{k}"))
                docs = spark.read.parquet(str(tmp_path / f"{name}{k}"))
        assert out.count() >= 0


def test_missing_column_is_named(spark):
    with pytest.raises(ValueError, match="text"):
        mixing.mix_sizes(spark.range(1).select(F.col("id").alias("doc_id"), F.lit("s").alias("source")))
