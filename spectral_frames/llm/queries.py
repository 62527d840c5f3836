"""The queries of the ten operators, one each, and their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from . import langid, licenses, linededup, mixing, packing, pii, quality, simhash, suffixdedup, topk
from .common import documents


def op1_mixing(spark, sf_dir):
    mixed = mixing.mix_sizes(documents(spark, sf_dir))
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"), "copies")


def op3_packing(spark, sf_dir):
    import public_tokenizers

    return packing.pack(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"), capacity=4096, end_id=1)


def op2_simhash(spark, sf_dir):
    found = simhash.near_components(documents(spark, sf_dir), words=4, radius=4)
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op4_licenses(spark, sf_dir):
    return licenses.scan(documents(spark, sf_dir)).drop("text_key")


def op5_pii(spark, sf_dir):
    return pii.scan(documents(spark, sf_dir))


def op6_quality(spark, sf_dir):
    return quality.judged(documents(spark, sf_dir)).drop("text_key")


def op7_linededup(spark, sf_dir):
    return linededup.removed(documents(spark, sf_dir))


def op8_suffixdedup(spark, sf_dir):
    return suffixdedup.removed(documents(spark, sf_dir), length=50)


def op9_topk(spark, sf_dir):
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return topk.top_k(vectors.where("vec_id % 100 = 0"), vectors, k=10, scale=1024)


def held_out():
    """crc32 of the doc_id as text leaves 1 when divided by 3; a null doc_id is not held out."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False))


def op10_langid(spark, sf_dir):
    docs = documents(spark, sf_dir)
    model = langid.train(docs.where(~held_out()))
    return langid.predict(docs, model).select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "rejected")


QUERIES = {f.__name__: f for f in (op1_mixing, op2_simhash, op3_packing, op4_licenses, op5_pii, op6_quality, op7_linededup, op8_suffixdedup, op9_topk, op10_langid)}
ORACLES: dict[str, str] = {
    "op9_topk": """WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)) AS e FROM embeddings
WHERE embedding IS NOT NULL AND vec_id IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.e, c.e) AS BIGINT) AS score FROM v q JOIN v c ON q.vec_id % 100 = 0 AND c.vec_id <> q.vec_id AND len(c.e) = len(q.e))
SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s QUALIFY rank <= 10""",
}
