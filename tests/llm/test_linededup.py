"""Line dedup against a brute force of maximal repeated runs."""

import duckdb
import numpy as np
import pytest

from spectral_frames.llm import linededup


def brute(texts, least=40):
    """Lines of every run of 40 characters or more that occurs earlier, of any length; blank lines between two of them too."""
    seen, gone = set(), {}
    for i in sorted(texts):
        lines = [x.strip(" \t\r\x0b\x0c") for x in texts[i].split("\n")]
        at = [k for k, x in enumerate(lines) if x]
        out = set()
        for p in range(len(at)):
            for q in range(p, len(at)):
                run = tuple(lines[k] for k in at[p : q + 1])
                if sum(map(len, run)) >= least:
                    if run in seen:
                        out |= set(range(p, q + 1))
                    seen.add(run)
        gone[i] = {at[p] for p in out} | {k for p in out if p + 1 in out for k in range(at[p], at[p + 1])}
    return gone


def removed(spark, texts):
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(3)
    return {r["doc_id"]: {x for s in r["removed"].split(",") if s for x in range(int(s.split("-")[0]), int(s.split("-")[1]) + 1)} for r in linededup.removed(docs).collect()}


LONG, OTHER = "a line that holds well over forty characters in all", "another line that holds well over forty characters"


def test_short_ends_of_runs_go(spark):
    texts = {1: f"{LONG}\nshort end\n", 2: f"x\n{LONG}\nshort end\ny", 3: f"{LONG}\nshort end"}
    out = removed(spark, texts)
    assert out == {1: set(), 2: {1, 2}, 3: {0, 1}}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    assert {r["doc_id"]: r["text"] for r in linededup.dedup(docs).collect()} == {1: texts[1], 2: "x\ny"}


def test_runs_step_over_blank_lines(spark):
    texts = {1: "twenty characters aa\n\ntwenty characters bb\n \t\nend", 2: "new\ntwenty characters aa\ntwenty characters bb\n\n\nend\n\nrest", 3: f"{LONG}\n\n{OTHER}", 4: f"{OTHER}\n\nnew line\n{LONG}"}
    assert removed(spark, texts) == {1: set(), 2: {1, 2, 3, 4, 5}, 3: set(), 4: {0, 3}} == brute(texts)


@pytest.mark.parametrize("seed", range(3))
def test_random_lines(spark, seed):
    rng = np.random.default_rng(seed)
    kinds = ["", " ", "a", "bb", "c" * 15, "d" * 24, "e" * 39, "f" * 45, "a"]
    texts = {i: "\n".join(kinds[k] if k < 9 else f"own {i} {k}" for k in rng.integers(0, 10, int(rng.integers(1, 25)))) for i in range(40)}
    assert removed(spark, texts) == brute(texts)


def test_given_table(spark):
    texts = dict(duckdb.sql("select doc_id, text from '/root/testdata/sf0.001/documents.parquet'").fetchall())
    texts = {i: t for i, t in texts.items() if t.count("\n") < 200}
    assert removed(spark, texts) == brute(texts)
