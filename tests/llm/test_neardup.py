"""The near-dedup stage against brute force at similarity 0.8."""

import duckdb
import numpy as np
import pytest

import corpus_pipeline
from spectral_frames.llm import neardup


def brute(texts):
    """doc_ids that stay: all pairs of five-word shingle sets compared as strings."""
    sets = {}
    for i, t in texts.items():
        w = t.lower().split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    parent = {i: i for i in texts}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    pairs = 0
    ids = sorted(texts)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            both = len(sets[a] & sets[b])
            if 5 * both >= 4 * (len(sets[a]) + len(sets[b]) - both):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
                pairs += 1
    return {find(i) for i in texts}, pairs


def kept(spark, texts):
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(3)
    return {r["doc_id"] for r in corpus_pipeline.drop_near_copies(spark, docs, "unused").collect()}


def edited(seed=1):
    """Texts and copies with a few words changed; similarities lie on both sides of 0.8."""
    rng = np.random.default_rng(seed)
    texts, n = {}, 0
    for _ in range(40):
        words = [f"w{x}" for x in rng.integers(0, 5000, int(rng.integers(3, 300)))]
        texts[n], n = " ".join(words), n + 1
        for _ in range(int(rng.integers(0, 5))):
            copy = list(words)
            for k in rng.integers(0, len(words), int(rng.integers(0, 1 + len(words) // 40))):
                copy[k] = f"e{rng.integers(0, 10**6)}"
            texts[n], n = " ".join(copy), n + 1
    return texts


def test_all_pairs_at_similarity_are_linked_and_no_others(spark):
    texts = edited()
    stay, pairs = brute(texts)
    assert pairs > 20 and kept(spark, texts) == stay


def test_pairs_that_share_no_smallest_row_are_found(spark):
    rng = np.random.default_rng(2)
    base = [f"w{x}" for x in rng.integers(0, 5000, 200)]
    texts = {}
    for i in range(40):  # one text, four words of each copy changed: some pairs lie below 0.8
        copy = list(base)
        for k in rng.integers(0, 200, 4):
            copy[k] = f"e{i}x{k}"
        texts[i] = " ".join(copy)
    assert kept(spark, texts) == brute(texts)[0]


def test_given_table(spark):
    texts = dict(duckdb.sql("select doc_id, text from '/root/testdata/sf0.001/documents.parquet'").fetchall())
    assert kept(spark, texts) == brute(texts)[0]


@pytest.mark.parametrize("n", [1, 4, 5, 6, 10, 99, 100])
def test_prefixes_of_similar_sets_meet(n):
    from fractions import Fraction

    rng = np.random.default_rng(n)
    a = np.unique(rng.integers(0, 2**63, n).astype(np.uint64))
    s = Fraction(4, 5)
    for drop in range(n // 5 + 1):
        b = np.sort(np.delete(a, rng.permutation(n)[:drop]))
        if neardup.similar(a, b, s):
            assert len(np.intersect1d(neardup.prefix(a, a[:3], s), neardup.prefix(b, a[:3], s)))


def test_fingerprints_rule_no_similar_pair_out():
    from fractions import Fraction

    rng, s, out = np.random.default_rng(0), Fraction(4, 5), 0
    for _ in range(2000):
        n, m, both = (int(x) for x in rng.integers(1, 400, 3))
        both = both if both > 20 else both % 5 + 1
        pool = np.unique(rng.integers(0, 2**63, n + m + both).astype(np.uint64))
        a, b = np.sort(pool[: both + n // 8]), np.sort(np.concatenate((pool[:both], pool[both + n // 8 :][: m // 8])))
        may = neardup.may_be_similar([neardup.fingerprint(a)], [neardup.fingerprint(b)], s)[0]
        out += not may
        assert may or not neardup.similar(a, b, s)
    assert out > 20


@pytest.mark.parametrize("radius", [0, 3, 96, 200])
def test_bit_slices_count_as_popcounts_do(radius):
    from spectral_frames.llm import simhash

    rng = np.random.default_rng(radius)
    a = rng.integers(0, 2**64, (300, 4), np.uint64)
    b = a ^ (rng.integers(0, 2**64, (300, 4), np.uint64) & rng.integers(0, 2**64, (300, 4), np.uint64) * np.uint64(radius > 3))
    b[::3] = a[::3] ^ np.uint64(5)
    assert np.array_equal(simhash.within(a, b, radius), np.bitwise_count(a ^ b).sum(axis=1) <= radius)
    assert len(simhash.within(a[:0], b[:0], radius)) == 0


def test_common_shingles_are_counted_over_all_rows(spark):
    """30,000 rows, three of each text; a sample of 20,000 misses most of what three rows have."""
    docs = spark.range(30_000).selectExpr("id doc_id", "concat('w', id div 3) text")
    want = {int(neardup.shingle_set(f"w{k}".encode(), 5)[0]) for k in range(10_000)}
    assert set(neardup.common_shingles(docs, 5).tolist()) == want


@pytest.mark.parametrize("most", [3, 40, 10**6])
def test_common_shingles_are_those_of_a_share_of_all_pairs(spark, most):
    from collections import Counter

    texts = [None, "", *edited().values(), *["a b c d e f", "A B c d e F"] * 20]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    n = Counter(h for t in texts for h in neardup.shingle_set(t and t.encode(), 5).tolist())
    want = sorted(h for h, k in n.items() if k >= 3 and k * most >= sum(n.values()))
    for per_group in (50, 1 << 20):
        assert neardup.common_shingles(docs, 5, most, per_group).tolist() == want
    assert len(want) <= most


def test_no_rows_have_no_common_shingles(spark):
    assert len(neardup.common_shingles(spark.createDataFrame([], "doc_id long, text string"), 5)) == 0


def shuffled(spark):
    """Bytes that the stages of the session have shuffled so far."""
    sc = spark.sparkContext
    stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
    return sum(stages.apply(i).shuffleWriteBytes() for i in range(stages.size()))


def test_counting_sends_less_than_a_shingle_each(spark):
    """The pipeline's near dedup was stopped at 3000 MB of an executor: counting sent all shingles, 12 bytes each, through a shuffle."""
    rng = np.random.default_rng(5)
    texts = [" ".join(map(str, rng.integers(0, 10**6, 300))) for _ in range(2000)]
    texts += [texts[0]] * 40
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3).localCheckpoint()
    before = shuffled(spark)
    found = neardup.common_shingles(docs, 5)
    assert found.tolist() == neardup.shingle_set(texts[0].encode(), 5).tolist()
    assert 0 < shuffled(spark) - before < 4 * 296 * len(texts)


def test_shingles_that_share_buckets_are_counted_apart(spark, monkeypatch):
    monkeypatch.setattr(neardup, "BUCKET_BITS", 3)
    docs = spark.range(3000).selectExpr("id doc_id", "if(id % 3 = 0, 'x', concat('w', id)) text")
    assert neardup.common_shingles(docs, 5, most=10).tolist() == neardup.shingle_set(b"x", 5).tolist()


def test_sets_are_held_for_some_rows_at_a_time():
    import pyarrow as pa

    batch = pa.RecordBatch.from_pydict({"k": list(range(1000))})
    parts = list(neardup._cut([batch, batch.slice(0, 0), batch.slice(10, 5)]))
    assert max(p.num_rows for p in parts) <= neardup.ROWS
    assert [k for p in parts for k in p.column("k").to_pylist()] == [*range(1000), *range(10, 15)]
