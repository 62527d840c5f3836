"""Pipeline over ``documents``: language ID, line dedup, near dedup, mixing and packing.

Each stage takes (spark, docs, sf_dir) and works on all that the one before kept; all but the last return the
columns of ``documents``.  A stage's result is written as Parquet and reread as the next one's docs.
"""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from spectral_frames.llm import langid, linededup, mixing, packing, simhash
from spectral_frames.llm.queries import held_out
from spectral_frames.session import shared_folder

#: Neither the trained classifier nor the order of mixing can be told in SQL; tests compare with brute force.
ORACLE_SQL = None


def _counted(docs):
    return docs.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else docs


def identify_language(spark, docs, sf_dir):
    """Documents whose language is not recognised with confidence go."""
    return langid.keep_identified(docs, langid.train(docs.where(~held_out())))


def drop_repeated_lines(spark, docs, sf_dir):
    """Later copies of repeated line runs go; documents left without a word go."""
    return _counted(linededup.dedup(docs))


def drop_near_copies(spark, docs, sf_dir):
    """Of each group of near copies (similarity of five-word shingle sets 0.8 or more) the document with the smallest doc_id stays."""
    return simhash.near_dedup(docs, words=5, similarity=0.8)


def mix_sources(spark, docs, sf_dir):
    """Every document as often as the mix takes it."""
    return mixing.mix(docs)


def pack_sequences(spark, docs, sf_dir):
    """The place of every piece of every document in sequences of 4096 tokens."""
    import public_tokenizers

    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("language ID", identify_language),
    ("line dedup", drop_repeated_lines),
    ("near dedup", drop_near_copies),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]


def run(spark, sf_dir):
    """All stages on ``documents``, with a written table between two of them."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs.write.parquet(f"{folder}/{k}")
            docs = spark.read.parquet(f"{folder}/{k}")
    return docs
