"""Operators against brute force on the smallest given table."""

import collections
import hashlib
import re
import zlib

import duckdb
import numpy as np
import pytest

from spectral_frames.llm import langid, packing, pii, queries, simhash, suffixdedup

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def texts():
    return dict(duckdb.sql(f"select doc_id, text from '{SF}/documents.parquet'").fetchall())


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


def components(ids, linked):
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in linked:
        a, b = find(a), find(b)
        if a != b:
            parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_mixing(spark, texts):
    out = by_id(queries.op1_mixing(spark, SF))
    assert all(out[i]["size"] == len(t.encode().split()) for i, t in texts.items())
    source = dict(duckdb.sql(f"select doc_id, source from '{SF}/documents.parquet'").fetchall())
    size, taken, target = collections.Counter(), collections.Counter(), {}
    for i, r in out.items():
        size[source[i]] += r["size"]
        taken[source[i]] += r["taken"]
        target[source[i]] = r["target"]
        assert r["taken"] in (0, r["size"], 2 * r["size"])
    names = sorted(size)
    weight = {s: (3, 1, 2)[k % 3] for k, s in enumerate(names)}
    full: dict = {}
    while True:
        level = (1.5 * sum(size.values()) - sum(full.values())) / sum(weight[s] for s in names if s not in full)
        over = [s for s in names if s not in full and level * weight[s] > 2 * size[s]]
        if not over:
            break
        full |= {s: 2.0 * size[s] for s in over}
    for s in names:
        assert np.isclose(target[s], full.get(s, level * weight[s]))
        longest = max(out[i]["size"] for i in out if source[i] == s)
        assert abs(taken[s] - target[s]) <= longest / 2 + 1
    again = by_id(queries.op1_mixing(spark, SF))
    assert all(again[i] == r for i, r in out.items())


def test_simhash(spark, texts):
    out = by_id(queries.op2_simhash(spark, SF))
    fp = {i: simhash.majority(simhash.shingle_hashes(t.encode(), 4)) for i, t in texts.items()}
    assert all(out[i]["fingerprint"] == f"{f:016x}" for i, f in fp.items())
    linked = [(a, b) for a in fp for b in fp if a < b and bin(fp[a] ^ fp[b]).count("1") <= 4]
    assert {i: r["component_id"] for i, r in out.items()} == components(fp, linked)


@pytest.mark.parametrize("tile", [2, 1024])
@pytest.mark.parametrize("n", [300, 1 << 40])
def test_near_links_lose_nothing(spark, tile, n):
    rng = np.random.default_rng(4)
    base = rng.integers(0, 2**63, 60)
    fps = np.unique(np.concatenate([base] + [base[:30] ^ (1 << rng.integers(0, 62, 30)) ^ (1 << rng.integers(0, 62, 30)) for _ in range(4)]))
    nodes = spark.createDataFrame([(int(f),) for f in fps], "fp long")
    links = [(r["a"], r["b"]) for r in simhash.near_links(nodes, n, 4, tile).collect()]
    assert all(bin(a ^ b).count("1") <= 64 for a, b in links)
    true = [(int(a), int(b)) for a in fps for b in fps if a < b and bin(int(a) ^ int(b)).count("1") <= 4]
    assert components(fps.tolist(), links) == components(fps.tolist(), true)


def test_packing_round_trip(spark, texts):
    from tokenizers import Tokenizer
    import public_tokenizers

    tokenizer = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    ids = {i: np.array(tokenizer.encode(t, add_special_tokens=False).ids + [1], "<u4") for i, t in texts.items()}
    rows = queries.op3_packing(spark, SF).collect()
    total, bins = collections.Counter(), collections.defaultdict(list)
    for r in rows:
        part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(part) == r["length"] <= 4096 and zlib.crc32(part.tobytes()) == r["ids_crc32"] and r["start"] == 4096 * r["piece"]
        total[r["doc_id"]] += r["length"]
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    assert total == {i: len(x) for i, x in ids.items()}
    for b in bins.values():
        at = 0
        for offset, length in sorted(b):
            assert offset == at
            at += length
        assert at <= 4096
    assert len(bins) <= -(-sum(total.values()) // 4096) + 2


def test_odd_words_are_encoded_as_the_tokenizer_does():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    odd = ["don't STOP... a,b. É. ß, Éa, İx. ΣΑΣ. <|endoftext|> x<|startoftext|>y \x1c z q 日本. ñ, I'll a'.", ".", ", .", "", "Ünï. éa.  x y"]
    ids = [np.frombuffer(b, "<u4").tolist() for b in packing.encoded(odd, path)]
    assert ids == [e.ids for e in Tokenizer.from_file(path).encode_batch(odd, add_special_tokens=False)]


@pytest.mark.parametrize("score", ["norm", "dot"])
def test_fitting_obeys_every_limit(score):
    counts = {50: 7, 30: 11, 20: 5, 9: 40}
    made = packing.fitted(counts, (100, 6, 5200.0), (1.0, 0.5, 0.5), score)
    load = collections.defaultdict(lambda: np.zeros(3))
    for k, (length, rank, first, per, _) in enumerate(made.tolist()):
        stop = made[k + 1][1] if k + 1 < len(made) and made[k + 1][0] == length else counts[length]
        for x in range(stop - rank):
            load[first + x // per] += [length, 1, length**2]
    assert sum(x[1] for x in load.values()) == sum(counts.values())
    assert all((x <= [100, 6, 5200]).all() for x in load.values())
    with pytest.raises(ValueError):
        packing.fitted({80: 1}, (100, 6, 5200.0))


def test_licenses(spark, texts):
    out = by_id(queries.op4_licenses(spark, SF))
    base = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
    for i, t in texts.items():
        words = re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", t.translate({c: c + 32 for c in range(65, 91)}))
        places = [(k, label) for p, label in base.items() for k in range(len(words)) if words[k : k + len(p.split())] == p.split()]
        r = out[i]
        assert (r["n_words"], r["n_base"], r["base_labels"]) == (len(words), len(places), ",".join(sorted({x for _, x in places})))
        assert (r["first_word"], r["last_word"]) == ((min(places)[0], max(places)[0]) if places else (None, None))
        assert set(r["base_labels"].split(",")) <= set(r["labels"].split(",")) | {""} and 0 <= r["score"] <= 1


def test_license_templates(spark):
    notices = {1: "Licensed under CC BY-NC 4.0.", 2: "x y. Released under the MIT License. z", 3: "Licensed under the Apache License, Version 2.0.", 4: "license apache mit general", 5: "cc nc by 4.0 licensed"}
    from spectral_frames.llm import licenses

    out = {r["doc_id"]: r["labels"] for r in licenses.scan(spark.createDataFrame(list(notices.items()), "doc_id long, text string")).collect()}
    assert out == {1: "cc-by,cc-by-nc", 2: "mit", 3: "apache-2.0", 4: "", 5: ""}


def test_personal_data_patterns(spark, texts):
    kinds = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}

    def brute(t):
        found = []
        for n, (kind, p) in enumerate(kinds.items()):
            for m in re.finditer(p, t):
                digits = re.sub("[^0-9]", "", m[0])
                if kind == "ip" and any(int(x) > 255 for x in m[0].split(".")) or kind == "card" and not (14 <= len(digits) <= 19 and pii.luhn(digits)) or kind == "phone" and not 10 <= len(digits) <= 15:
                    continue
                found.append((m.start(), n, f"{kind}:{m.start()}:{m.end()}"))
        return ",".join(x[2] for x in sorted(found))

    odd = ["a@b.c.d%x@y.z", "a@@b.co", "x@y @z.w a@b", "1.2.3.4.5.6.7.8", "0001.2.3.4 256.1.1.1", "4111 1111 1111 1111", "4111-1111-1111-1111 9", "+1 (017) 555-7713.", "+12", "a+b@c-d.e-f.g", "é@a.b", "12 34 56 78 90 12 34 56"]
    out = by_id(queries.op5_pii(spark, SF))
    for i, t in texts.items():
        assert out[i]["base_sha256"] == hashlib.sha256(brute(t).encode()).hexdigest()
        assert set(brute(t).split(",")) <= set(out[i]["spans"].split(",")) | {""}
    for t in odd:
        assert pii.written(pii.base_spans(t)) == brute(t), t


def test_viterbi_equals_enumeration():
    from itertools import product

    rng = np.random.default_rng(0)
    tagger = pii.Tagger(pii.Field(moves=rng.standard_normal((6, 6))))
    e = rng.standard_normal((4, 6)) * 2
    best = max(product(range(6), repeat=4), key=lambda y: sum(e[t, y[t]] for t in range(4)) + sum(tagger.model.moves[a, b] for a, b in zip((0, *y), (*y, 0), strict=True)))
    assert tagger.viterbi(np.arange(4), e).tolist() == list(best)


def test_field_finds_keys_and_leaves_prose():
    tagger = pii.Tagger(pii.fit(pii.examples()))
    key = "24be64439e3e49cf46b2d7c90f3602a3d0b907ff"
    found = pii.find([f'the word token = "{key}" and more', "plain words only, nothing else at all. 23904", "call (017) 555-7713 now"], tagger)
    assert found[0][1] == [(18, 58, "secret")] and found[1][1] == [] and [x[2] for x in found[2][1]] == ["phone"]


def test_quality(spark, texts):
    out = by_id(queries.op6_quality(spark, SF))
    for i, t in texts.items():
        w = t.encode().split()
        windows = collections.Counter(zip(w, w[1:], w[2:]))
        covered = {k + d for k in range(len(w) - 2) if windows[tuple(w[k : k + 3])] > 1 for d in range(3)}
        lines = [x for x in t.split("\n") if x.encode().split()]
        r = out[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(w), sum(len(x.decode()) for x in w), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(covered))
        assert r["base_failed"] == (len(w) < 50 or 2 * len(covered) > len(w)) and not (r["base_failed"] and r["kept"])
    good = {r[0] for r in duckdb.sql(f"select doc_id from '{SF}/labels.parquet' where quality = 1").fetchall()}
    clean = [out[i]["kept"] for i in good if not out[i]["base_failed"]]
    assert np.mean(clean) > 0.97


def test_line_dedup(spark, texts):
    out = by_id(queries.op7_linededup(spark, SF))
    lines = {i: [x.strip(" \t\r\x0b\x0c") for x in t.split("\n")] for i, t in texts.items()}
    places: dict = collections.defaultdict(list)  # of lines with a word: (document, place among those)
    words = {}
    for i in sorted(lines):
        words[i] = [k for k, x in enumerate(lines[i]) if x]
        for p, k in enumerate(words[i]):
            places[lines[i][k]].append((i, p))
    for i, r in out.items():
        gone = set()
        for p, k in enumerate(words[i]):  # the longest run from here that starts earlier
            best = 0
            for j, q in places[lines[i][k]]:
                n = 0
                if (j, q) < (i, p):
                    while p + n < len(words[i]) and q + n < len(words[j]) and lines[i][words[i][p + n]] == lines[j][words[j][q + n]]:
                        n += 1
                best = max(best, n)
            if sum(len(lines[i][words[i][p + d]]) for d in range(best)) >= 40:
                gone |= set(range(p, p + best))
        rows = {words[i][p] for p in gone} | {k for p in gone if p + 1 in gone for k in range(words[i][p], words[i][p + 1])}
        assert {x for s in r["removed"].split(",") if s for x in range(int(s.split("-")[0]), int(s.split("-")[1]) + 1)} == rows


def test_suffix_dedup(spark, texts):
    out = by_id(queries.op8_suffixdedup(spark, SF))
    seen: set = set()
    for i in sorted(texts):
        b = texts[i].encode()
        strings = [b[k : k + 50] for k in range(len(b) - 49)]
        cover = np.zeros(len(b) + 1, int)
        for k, s in enumerate(strings):
            if s in seen:
                cover[k] += 1
                cover[k + 50] -= 1
        seen.update(strings)
        cut = np.cumsum(cover[:-1]) > 0
        r = out[i]
        assert (r["n_bytes"], r["n_removed"], r["kept_sha256"]) == (len(b), int(cut.sum()), hashlib.sha256(np.frombuffer(b, np.uint8)[~cut].tobytes()).hexdigest())
        assert r["n_spans"] == int(cut[:1].sum() + (cut[1:] & ~cut[:-1]).sum())


def test_window_hashes_name_equal_strings_alike():
    b = np.frombuffer(b"abcabcabcabcabcabcabcabcabcabcabcabc-abcabcabcabcabc", np.uint8)
    for size in (1, 2, 3, 7, 25):
        h = suffixdedup.window_hashes(b, size)
        s = [b[k : k + size].tobytes() for k in range(len(b) - size + 1)]
        assert len(h) == len(s) and all((h[i] == h[j]) == (s[i] == s[j]) for i in range(len(s)) for j in range(len(s)))


def test_topk(spark):
    rows = duckdb.sql(f"select vec_id, embedding from '{SF}/embeddings.parquet'").fetchall()
    ids, x = np.array([r[0] for r in rows]), np.floor(1024 * np.array([r[1] for r in rows], float)).astype(int)
    found = collections.defaultdict(list)
    for r in queries.op9_topk(spark, SF).orderBy("rank").collect():
        found[r["query_id"]].append((-r["score"], r["vec_id"]))
    for q in ids[ids % 100 == 0]:
        s = x @ x[ids == q][0]
        assert found[q] == sorted((-v, i) for v, i in zip(s.tolist(), ids.tolist(), strict=True) if i != q)[:10]


def test_language_identification(spark, texts):
    out = by_id(queries.op10_langid(spark, SF))
    lang = dict(duckdb.sql(f"select doc_id, lang from '{SF}/documents.parquet'").fetchall())
    held = [i for i in texts if zlib.crc32(str(i).encode()) % 3 == 1]
    assert all(out[i]["held_out"] == (i in set(held)) for i in texts)
    assert np.mean([out[i]["lang_pred"] == lang[i] for i in held]) > 0.95
    model = langid.fit([b"the of and to in"] * 5 + [b"le la les des du"] * 5, ["en"] * 5 + ["fr"] * 5)
    rows = spark.createDataFrame([(1, None), (2, "123 !?"), (3, "the and of")], "doc_id long, text string")
    got = by_id(langid.predict(rows, model))
    assert got[1]["lang_pred"] == got[2]["lang_pred"] == "und" and got[1]["score"] == 0 and got[3]["lang_pred"] == "en"
