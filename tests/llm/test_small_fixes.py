"""Ranks over batch borders, keys of any length, components that are not finished."""

import random

import numpy as np
import pytest

from spectral_frames.llm import common, langid, linededup, packing, pii, topk


def test_ranks_run_on_over_batch_borders(spark):
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        v = spark.createDataFrame([(i, [float(i % 5), 1.0]) for i in range(60)], "vec_id long, embedding array<double>")
        out = topk.top_k(v.where("vec_id < 20"), v, k=10).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    for q in range(20):
        assert sorted(r["rank"] for r in out if r["query_id"] == q) == list(range(1, 11))


@pytest.mark.parametrize("times", [2, 8, 40])
def test_long_keys_are_secrets(times):
    key = "24be64439e3e49cf46b2d7c90f3602a3" * times
    found = pii.find([f'the word token = "{key}" and more'], pii.Tagger(pii.fit(pii.examples())))
    assert found[0][1] == [(18, 18 + len(key), "secret")]


def test_unfinished_components_raise(spark):
    chain = spark.createDataFrame([(i, i + 1) for i in range(40)], "a long, b long")
    with pytest.raises(RuntimeError, match="rounds"):
        common.components(chain, most_rounds=1)
    assert {r["root"] for r in common.components(chain).collect()} == {0}


def test_long_runs_of_digits_are_no_crash():
    for t in ("0" * 5000 + ".1.1.1", "9" * 6000 + ".1.1.1", "1." * 4000, "4 " * 9000, "@" * 5000 + "a@b.c", "+" * 4000 + "1" * 5000, "a" * 100_000 + "@b.c " + "-" * 50_000):
        pii.find([t], pii.Tagger(pii.Field(moves=np.zeros((6, 6)))))
    assert pii.base_spans("0" * 5000 + ".1.1.1") == [(0, 5006, "ip")] and pii.base_spans("9" * 6000 + ".1.1.1") == []


def test_random_unicode_is_encoded_as_the_tokenizer_does():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    rng = random.Random(1)
    pool = "aZéÉßİıΣσςÅKक़़שׁ́,,..!? 1²Ⅷ日本ﬁǅñ́̇‍﻿\xad 's\n\t\r\x0b\x0c\x1c\x85\xa0 _-"
    blocks = [(32, 126), (160, 0x24F), (0x370, 0x52F), (0x900, 0xFFF), (0x1E00, 0x1FFF), (0x20, 0xD7FF)]
    texts = ["".join(rng.choice(pool) if rng.random() < 0.6 else chr(rng.randint(*rng.choice(blocks))) for _ in range(rng.randint(0, 14))) for _ in range(4000)]
    common.worker_cache()
    ids = [np.frombuffer(b, "<u4").tolist() for b in packing.encoded(texts + ["İ,", "क़."], path)]
    assert ids == [e.ids for e in Tokenizer.from_file(path).encode_batch(texts + ["İ,", "क़."], add_special_tokens=False)]


def test_words_held_are_bounded():
    import public_tokenizers
    from tokenizers import Tokenizer

    words = packing.Words(Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")), most=40_000)
    ids = {w: words[w] for w in [f"w{k}x" for k in range(2000)] + ["abc", "abc,", "Abc"]}
    assert len(words) + len(words.old) < 400 and words.held <= 20_000
    assert all(words[w] == x for w, x in ids.items()) and ids["Abc"] == ids["abc"]


def test_language_sample_is_bounded_and_takes_a_text_once(spark):
    rows = [("the of and to in that", "en")] * 300 + [(f"the of and {k} to", "en") for k in range(30)] + [(f"le la les {k} des", "fr") for k in range(30)] + [("x" * 1000, "long")] + [(None, "en"), ("t", None)]
    model = langid.train(spark.createDataFrame(rows, "text string, lang string"), longest=500)
    assert model.languages == ["en", "fr"]
    assert langid.train(spark.createDataFrame(rows, "text string, lang string"), most_languages=1, longest=500).languages == ["en"]


def test_many_lines_are_rebuilt_in_linear_time(spark):
    lines = "\n".join(f"a line of text with its own number {k}" for k in range(30_000))
    docs = spark.createDataFrame([(1, lines), (2, "start\n" + lines + "\nend")], "doc_id long, text string")
    assert {r["doc_id"]: r["text"] for r in linededup.dedup(docs).collect()} == {1: lines, 2: "start\nend"}


def test_hubs_do_not_change_components(spark):
    edges = spark.range(3000).selectExpr("id + 10 as a", "cast(if(id < 2900, 3, id) as long) as b")
    found = {r["node"]: r["root"] for r in common.components(edges).collect()}
    parent = {i: i for i in range(3011)}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(3000):
        a, b = find(i + 10), find(3 if i < 2900 else i)
        parent[max(a, b)] = min(a, b)
    assert found == {i: find(i) for i in found} and len(found) == 3001
