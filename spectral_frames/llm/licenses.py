"""License scan with a positional rare-token index, in DataFrame operations only.

One scan makes a row's word count, the places of the base phrases and the positional postings of its license
words (the rare words of the templates below; whole texts).  Document frequencies over all rows weigh the words.  All
license words of a row are looked up in the template postings; the difference of the two positions is where
the template would start, and places on which enough weight agrees are candidates.  A candidate counts if the
mandatory phrase of its template stands at its very place.  Texts are not shuffled.

Null or empty text: no words, no labels, score 0.  Repeated rows: each gets its row.  Empty table: no rows.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import durable, pick

#: Base phrases and their labels.
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

#: Templates: label, notice, mandatory phrase within it.
TEMPLATES = [
    ("apache-2.0", "licensed under the apache license version 2 0", "apache license"),
    ("apache-2.0", "apache software license version 2 0", "apache software license"),
    ("mit", "released under the mit license", "mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software", "hereby granted"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "binary forms"),
    ("bsd", "licensed under the bsd license", "bsd license"),
    ("gpl", "this work is licensed under the gnu general public license version 3", "general public license"),
    ("lgpl", "gnu lesser general public license version 3", "lesser general public license"),
    ("agpl", "gnu affero general public license version 3", "affero general public license"),
    ("mpl-2.0", "mozilla public license version 2 0", "mozilla public license"),
    ("epl", "eclipse public license version 2 0", "eclipse public license"),
    ("cc-by", "licensed under creative commons attribution 4 0 international", "creative commons attribution"),
    ("cc-by", "licensed under cc by 4 0", "cc by"),
    ("cc-by-sa", "licensed under cc by sa 4 0", "cc by sa"),
    ("cc-by-nc", "licensed under cc by nc 4 0", "cc by nc"),
    ("cc-by-nd", "licensed under cc by nd 4 0", "cc by nd"),
    ("cc0", "dedicated to the public domain under cc0 1 0 universal", "cc0"),
    ("public-domain", "released into the public domain", "public domain"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose", "copy modify"),
    ("reserved", "copyright all rights reserved", "all rights reserved"),
    ("proprietary", "proprietary and confidential unauthorized copying is prohibited", "confidential unauthorized"),
]

#: Words of the notices that common prose is full of; they are not indexed.
COMMON = {"the", "of", "and", "to", "in", "is", "this", "or", "are", "for", "a", "any", "with", "under", "use", "0", "1", "2", "3", "4", "by", "all", "into", "at", "version", "work", "free"}
INDEXED = sorted({w for _, notice, _ in TEMPLATES for w in notice.split() if w not in COMMON})


def required(notice: str, phrase: str) -> list[tuple[str, int]]:
    """What must stand where, counted from the start of the notice: the phrase's indexed words, and a base phrase where it begins with one."""
    words, parts = notice.split(), phrase.split()
    at = next(k for k in range(len(words)) if words[k : k + len(parts)] == parts)
    base = [(f"#{p}", at) for p in BASE if phrase == p or phrase.startswith(p + " ")]
    return base + [(w, at + k) for k, w in enumerate(parts) if w not in COMMON]


_GAPS = "[\\x00-\\x2F\\x3A-\\x40\\x5B-\\x60\\x7B-\\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def folded(text: Column) -> Column:
    """A-Z to lower case.  lower() is faster and differs in ASCII letters only for texts with U+0130 or U+212A."""
    return F.when(text.rlike("[İK]"), F.translate(text, _UPPER, _LOWER)).otherwise(F.lower(text))


def words_of(text: Column) -> Column:
    plain = F.trim(F.regexp_replace(folded(F.coalesce(text, F.lit(""))), _GAPS, " "))
    return F.when(plain == "", F.array().cast("array<string>")).otherwise(F.split(plain, " "))


def starts(words: Column, phrase: str) -> Column:
    """Places at which the words of the phrase stand one after the other."""
    parts = phrase.split()
    fits = lambda i: reduce(lambda a, b: a & b, [F.get(words, i + k) == w for k, w in enumerate(parts)])
    found = F.filter(F.sequence(F.lit(0), F.size(words) - len(parts)), fits)
    return F.when((F.size(words) >= len(parts)) & F.array_contains(words, parts[-1]), found).otherwise(F.array().cast("array<int>"))


def indexed(docs: DataFrame) -> DataFrame:
    """(doc_id, text_key, n_words, p0.., hits): places of each base phrase, and positions of indexed words."""
    rows = pick(docs, "doc_id", "text").select("doc_id", F.xxhash64("text").alias("text_key"), words_of(F.col("text")).alias("w"))
    w = F.col("w")
    at = F.filter(F.sequence(F.lit(0), F.size(w) - 1), lambda i: F.get(w, i).isin(*INDEXED))
    at = F.when(F.size(w) > 0, at).otherwise(F.array().cast("array<int>"))
    hits = F.transform(at, lambda i: F.struct(i.alias("pos"), F.get(w, i).alias("word")))
    return rows.select("doc_id", "text_key", F.size(w).cast("long").alias("n_words"), *[starts(w, p).alias(f"p{k}") for k, p in enumerate(BASE)], hits.alias("hits"))


def _literal_rows(spark, rows: list[tuple], schema: list[str]) -> DataFrame:
    table = F.array(*[F.struct(*[F.lit(v).alias(n) for v, n in zip(r, schema, strict=True)]) for r in rows])
    return spark.range(1).select(F.inline(table))


def matches(rows: DataFrame, agree: float = 0.5) -> DataFrame:
    """(doc_id, text_key, label, score): templates found in ``rows`` of indexed()."""
    spark = rows.sparkSession
    total = rows.select(F.count("*").alias("docs"))
    distinct = rows.select(F.explode(F.array_distinct("hits.word")).alias("word"))
    known = _literal_rows(spark, [(w,) for w in INDEXED], ["word"])
    seen = known.join(distinct.groupBy("word").agg(F.count("*").alias("df")), "word", "left").crossJoin(F.broadcast(total))
    idf = durable(seen.select("word", F.log((F.col("docs") + 2) / (F.coalesce("df", F.lit(0)) + 1)).alias("idf")))  # one row per indexed word
    postings = [(t, label, w, pos) for t, (label, notice, _) in enumerate(TEMPLATES) for pos, w in enumerate(notice.split()) if w in INDEXED]
    template = _literal_rows(spark, postings, ["template", "label", "word", "tpos"]).join(F.broadcast(idf), "word")
    template = durable(template.withColumn("full", F.sum("idf").over(Window.partitionBy("template"))))  # as many rows as the notices have words
    key = ["doc_id", "text_key"]
    flat = rows.where(F.size("hits") > 0).select(*key, F.inline("hits"))

    def marked(column: str, word: str) -> Column:
        return F.transform(column, lambda i: F.struct(i.alias("pos"), F.lit(word).alias("word")))

    based = [marked(f"p{k}", f"#{p}") for k, p in enumerate(BASE)]
    places = rows.where(F.size(F.concat(*[F.col(f"p{k}") for k in range(len(BASE))])) > 0).select(*key, F.inline(F.concat(*based)))
    # all indexed words of a row at all their places: a word has as many postings as the notices hold it
    placed = flat.distinct().join(F.broadcast(template), "word").withColumn("begin", F.col("pos") - F.col("tpos"))
    votes = placed.groupBy(*key, "template", "label", "begin").agg((F.sum("idf") / F.first("full")).alias("score")).where(F.col("score") >= agree)
    # every required word at its place
    needs = [(t, w, at, len(required(notice, phrase))) for t, (_, notice, phrase) in enumerate(TEMPLATES) for w, at in required(notice, phrase)]
    need = _literal_rows(spark, needs, ["template", "word", "at", "needed"])
    wanted = votes.join(F.broadcast(need), "template").withColumn("pos", (F.col("begin") + F.col("at")).cast("int"))
    there = flat.unionByName(places).distinct().withColumnsRenamed({"doc_id": "_id", "text_key": "_key", "pos": "_pos", "word": "_word"})
    match = F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("text_key") == F.col("_key")) & (F.col("pos") == F.col("_pos")) & (F.col("word") == F.col("_word"))
    met = wanted.join(there, match, "left_semi")
    found = met.groupBy(*key, "template", "label", "begin", "needed").agg(F.max("score").alias("score"), F.count("*").alias("met")).where("met = needed")
    return found.groupBy("doc_id", "text_key", "label").agg(F.max("score").alias("score"), F.min("begin").alias("begin"))


def scan(docs: DataFrame, agree: float = 0.5) -> DataFrame:
    """(doc_id, text_key, n_words, n_base, first_word, last_word, base_labels, labels, score): one row per row of docs."""
    rows = durable(indexed(docs))
    found = matches(rows, agree).groupBy("doc_id", "text_key").agg(F.collect_set("label").alias("more"), F.max("score").alias("best"))
    found = durable(found.withColumnsRenamed({"doc_id": "_id", "text_key": "_key"}))
    places = F.concat(*[F.col(f"p{k}") for k in range(len(BASE))])
    base = F.filter(F.array(*[F.when(F.size(f"p{k}") > 0, F.lit(label)) for k, label in enumerate(BASE.values())]), lambda x: x.isNotNull())
    joined = rows.select("doc_id", "text_key", "n_words", places.alias("places"), base.alias("base")).join(found, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("text_key") == F.col("_key")), "left")
    both = F.array_union("base", F.coalesce("more", F.array().cast("array<string>")))
    score = F.least(F.lit(1.0), F.greatest(F.when(F.size("places") > 0, 1.0).otherwise(0.0), F.coalesce("best", F.lit(0.0))))
    return joined.select(
        "doc_id", "text_key", "n_words", F.size("places").cast("long").alias("n_base"), F.array_min("places").cast("long").alias("first_word"), F.array_max("places").cast("long").alias("last_word"),
        F.array_join(F.array_sort(F.array_distinct("base")), ",").alias("base_labels"), F.array_join(F.array_sort(both), ",").alias("labels"), score.alias("score"),
    )
