"""Suffix dedup against brute force: groups, split groups, rounds, nulls and repeated rows."""

import hashlib

import numpy as np
import pytest

from spectral_frames.llm import suffixdedup


def brute(rows, length):
    """By (id, text): bytes, removed bytes, runs and digest of what is left."""
    seen, out = set(), {}
    order = sorted({i for i, _ in rows}, key=lambda i: (i is None, i))
    for i in order:
        mine = set()
        for t in {t for j, t in rows if j == i}:
            b = (t or "").encode()
            strings = [b[k : k + length] for k in range(len(b) - length + 1)]
            gone = np.zeros(len(b), bool)
            for k, s in enumerate(strings):
                if s in seen:
                    gone[k : k + length] = True
            mine.update(strings)
            runs = int(gone[:1].sum() + (gone[1:] & ~gone[:-1]).sum())
            out[i, t] = len(b), int(gone.sum()), runs, hashlib.sha256(np.frombuffer(b, np.uint8)[~gone].tobytes()).hexdigest()
        seen |= mine
    return out


def made(seed):
    rng = np.random.default_rng(seed)
    letters = np.array(list("abcdé \n"))
    passages = ["".join(rng.choice(letters, int(rng.integers(5, 120)))) for _ in range(12)]
    rows = []
    for k in range(120):
        parts = [passages[rng.integers(0, 12)] if rng.random() < 0.4 else "".join(rng.choice(letters, int(rng.integers(0, 60)))) for _ in range(rng.integers(0, 6))]
        rows.append((None if k % 3 == 0 else int(rng.integers(-40, 80)), "".join(parts) if k % 17 else None))
    rows += rows[:5] + [(7, "a" * 500), (8, "a" * 300), (2**63 - 1, passages[0] * 3)]
    return rows


@pytest.mark.parametrize(("seed", "length", "first", "group_bytes"), [(0, 50, None, 6 << 20), (1, 50, None, 900), (2, 50, 7, 2500), (3, 13, 1, 700), (4, 8, 8, 1000)])
def test_equals_brute_force(spark, seed, length, first, group_bytes):
    rows = made(seed)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    true = brute(rows, length)
    found = suffixdedup.repeated_spans(docs, length, first, group_bytes).collect()
    got = sorted((str(None if r["none"] else r["doc"]), r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in found)
    assert got == sorted((str(i), *true[i, t]) for i, t in rows)


@pytest.mark.parametrize("top", [1, 300, 2**20, 2**62])
def test_packed_blocks_come_back(top):
    rng = np.random.default_rng(1)
    for n in (0, 1, 5, 3000):
        names = np.unique(rng.integers(0, top, n, dtype=np.uint64))
        names = np.append(names, np.uint64(2**63 + 5)) if n == 5 else names
        data = suffixdedup.pack_sorted(names)
        back, end = suffixdedup.unpack_sorted(data + b"more")
        assert np.array_equal(back, names) and end == len(data)


def test_bounds(spark):
    with pytest.raises(ValueError):
        suffixdedup.repeated_spans(spark.createDataFrame([], "doc_id long, text string"), 50, 51)
