"""Quality rules and robust multivariate outliers of document statistics.

One scan of whole texts counts words, symbols, repeated lines and repeated three-word windows.  Transformed, they form
a vector per document; every (language, source) gets a minimum-covariance-determinant estimate and documents at a
large Mahalanobis distance are rejected.  The estimates are found by concentration steps over all rows: a step
sums moments by group and by narrow bins of squared distance (pre-aggregated on the map side), takes the bins in
rising order until they hold ``share`` of the group, and re-estimates from those, until determinants settle; two starts compete
by determinant.  Every estimate then shrinks towards that of its language, and a language's towards that of all, as though ``prior``
rows of the parent were in the group: the smaller a group, the more it follows its parent, at every size by one rule.  A language has
its own robust estimate over all its rows; that of all pools the rows that the languages' estimates rest on.

Variances have floors, so that a statistic that is constant in most of a group doesn't reject all others.
Null or empty text: no words, base_failed.  Null language or source: a group like any other.  Repeated rows: each is
judged, alike.  Empty table: no rows.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, pick, small_join

#: Statistics of the vector, and the least standard deviation of each: it holds only where the data vary less.
STATISTICS = {"length": 0.25, "word_length": 0.06, "symbols": 0.03, "dup_lines": 0.2, "repeats": 0.2, "line_length": 0.25}
NAMES, FLOOR = list(STATISTICS), np.array(list(STATISTICS.values()))
P = len(NAMES)
#: Median of the chi-square distribution with len(NAMES) = 6 degrees of freedom.
CHI2_MEDIAN = 5.348
#: Bins of squared distance per doubling.
BINS = 8
_SPACE = " \t\n\r\x0b\x0c"
_COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]


def repeated_words(words: list[bytes]) -> int:
    """Words inside a three-word window that occurs twice or more."""
    n = len(words)
    if n < 4:
        return 0
    h = np.fromiter(map(hash, words), np.int64, n).view(np.uint64)
    w = (h[:-2] * np.uint64(0x9E3779B97F4A7C15) ^ h[1:-1]) * np.uint64(0xC2B2AE3D27D4EB4F) ^ h[2:] * np.uint64(0x165667B19E3779F9)
    w ^= w >> np.uint64(29)
    order = np.argsort(w)
    ordered = w[order]
    equal = ordered[1:] == ordered[:-1]
    if not equal.any():
        return 0
    twice = np.zeros(n - 2, bool)
    twice[order[1:][equal]] = True
    twice[order[:-1][equal]] = True
    cover = np.zeros(n, bool)
    cover[:-2] |= twice
    cover[1:-1] |= twice
    cover[2:] |= twice
    return int(cover.sum())


def measures(text: str | None) -> tuple[int, int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and the number of lines with a word."""
    if not text:
        return 0, 0, 0, 0, 0, 0
    words = text.encode().split()
    seen: set = set()
    lines = [x for x in text.split("\n") if x.strip(_SPACE)]
    seen.update(lines)
    return len(words), len(text) - sum(map(text.count, _SPACE)), sum(map(text.count, "#*$%&|<>")), len(lines) - len(seen), repeated_words(words), len(lines)


def vectors(m: np.ndarray) -> np.ndarray:
    """The transformed statistics of rows of measures."""
    words, chars, symbols, dups, repeats, lines = (m[:, k].astype(float) for k in range(6))
    one = np.maximum(words, 1)
    return np.stack([np.log1p(words), np.log(np.maximum(chars, 1) / one), np.sqrt(symbols / np.maximum(chars, 1)), np.sqrt(dups / np.maximum(lines, 1)), np.sqrt(repeats / one), np.log1p(words / np.maximum(lines, 1))], axis=1)


def statistics(docs: DataFrame) -> DataFrame:
    """(doc_id, text_key, lang, source, the five counts, the transformed statistics): one row per row of docs."""

    def kernel(batches):
        for batch in batches:
            m = np.array([measures(t) for t in batch.column("text").to_pylist()], np.int64).reshape(-1, 6)
            v = vectors(m)
            yield pa.RecordBatch.from_arrays([batch.column(c) for c in ("doc_id", "text_key", "lang", "source")] + [pa.array(m[:, k]) for k in range(5)] + [pa.array(v[:, k]) for k in range(P)], ["doc_id", "text_key", "lang", "source", *_COUNTS, *NAMES])

    rows = pick(docs, "doc_id", "lang", "source", "text").select("doc_id", F.xxhash64("text").alias("text_key"), "lang", "source", "text")
    kinds = dict(rows.dtypes)
    return rows.mapInArrow(kernel, f"doc_id {kinds['doc_id']}, text_key long, lang {kinds['lang']}, source {kinds['source']}, " + ", ".join([f"{c} long" for c in _COUNTS] + [f"{c} double" for c in NAMES]))


def distance(mean: str = "mean", inverse: str = "inverse"):
    """Squared Mahalanobis distance as an expression of the statistics and two array columns (inverse: lower triangle)."""
    d = [F.col(n) - F.col(mean)[i] for i, n in enumerate(NAMES)]
    terms = [d[i] * d[j] * F.col(inverse)[i * (i + 1) // 2 + j] * (1.0 if i == j else 2.0) for i in range(P) for j in range(i + 1)]
    return reduce(lambda a, b: a + b, terms)


def group_key(*columns: str):
    """The name of a row's group by these columns, nulls told apart from texts."""
    shown = [F.coalesce(F.concat(F.lit("="), F.col(c).cast("string")), F.lit("?")) for c in columns]
    return F.concat_ws("\x1f", F.lit(str(len(columns))), *shown)


def _tri(m: np.ndarray) -> list[float]:
    return m[np.tril_indices(P)].tolist()


def _inverse(cov: np.ndarray) -> tuple[list[float], float]:
    cov = (cov + cov.T) / 2
    cov = cov + np.diag(np.maximum(FLOOR**2 - np.diag(cov), 1e-8))
    return _tri(np.linalg.inv(cov)), float(np.linalg.slogdet(cov)[1])


def _packed(group, start, n, mean, cov, held=0, s1=(), s2=(), scale=1.0) -> dict:
    inverse, logdet = _inverse(cov)
    return {"grp": group, "start": start, "n": int(n), "mean": mean.tolist(), "inverse": inverse, "logdet": logdet, "held": int(held), "s1": list(s1), "s2": list(s2), "scale": float(scale)}


#: held, s1, s2: how many rows the estimate rests on, and their sums and sums of products.
_ESTIMATE = "grp string, start int, n long, mean array<double>, inverse array<double>, logdet double, held long, s1 array<double>, s2 array<double>, scale double"


def _moments() -> list:
    squares = [F.sum(F.col(NAMES[i]) * F.col(NAMES[j])) for i in range(P) for j in range(i + 1)]
    return [F.count("*").alias("n"), F.array(*[F.sum(c) for c in NAMES]).alias("s1"), F.array(*squares).alias("s2")]


def _estimate(n: float, s1: np.ndarray, s2: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    mean = s1 / n
    full = np.zeros((P, P))
    full[np.tril_indices(P)] = s2
    full = full + np.tril(full, -1).T
    return mean, full / n - np.outer(mean, mean)


def estimates(rows: DataFrame, share: float = 0.75, most_steps: int = 8, settled: float = 1e-3) -> DataFrame:
    """(grp, n, held, s1, s2, scale): what the estimate of each group of ``rows(grp, statistics)`` rests on."""
    groups = rows.groupBy("grp")

    def first(frame: pd.DataFrame) -> pd.DataFrame:
        out = []
        for r in frame.itertuples():
            mean, cov = _estimate(r.n, np.array(r.s1), np.array(r.s2))
            out.append(_packed(r.grp, 0, r.n, mean, cov))
            q = np.array([list(x) for x in r.quartiles])
            out.append(_packed(r.grp, 1, r.n, q[:, 1], np.diag(((q[:, 2] - q[:, 0]) / 1.349) ** 2)))
        return pd.DataFrame(out, columns=[c.split()[0] for c in _ESTIMATE.split(", ")])

    quartiles = F.array(*[F.percentile_approx(c, [0.25, 0.5, 0.75], 1000) for c in NAMES]).alias("quartiles")
    start = groups.agg(*_moments(), quartiles)
    now = durable(start.mapInPandas(lambda frames: map(first, frames), _ESTIMATE))
    n = now.count()

    def step(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("bin")
        total = frame.n.sum()
        upto = frame.n.cumsum().to_numpy()
        take = frame.iloc[: int(np.searchsorted(upto, share * total)) + 1]
        held, s1, s2 = take.n.sum(), np.sum(take.s1.tolist(), axis=0), np.sum(take.s2.tolist(), axis=0)
        mean, cov = _estimate(held, s1, s2)
        middle = float(frame.bin.iloc[int(np.searchsorted(upto, total / 2))])
        return pd.DataFrame([_packed(frame.grp.iloc[0], int(frame.start.iloc[0]), total, mean, cov, held, s1, s2, max(1.0, 2 ** ((middle + 1) / BINS) / CHI2_MEDIAN))])

    before = None
    for _ in range(most_steps):
        at = small_join(rows, now.select("grp", "start", "mean", "inverse"), ["grp"], rows=n)
        binned = at.withColumn("bin", F.floor(F.log2(F.greatest(distance(), F.lit(2.0**-20))) * BINS).cast("int"))
        sums = binned.groupBy("grp", "start", "bin").agg(*_moments())
        now = durable(sums.groupBy("grp", "start").applyInPandas(step, _ESTIMATE))
        level = now.agg(F.avg("logdet")).first()[0]
        if level is None or before is not None and abs(level - before) < settled:
            break
        before = level
    chosen = now.groupBy("grp").agg(F.min_by(F.struct("n", "held", "s1", "s2", "scale"), F.struct("logdet", "start")).alias("e"))
    return durable(chosen.select("grp", "e.*"))


def shrunk(made: DataFrame, groups: DataFrame, prior: float) -> DataFrame:
    """(grp, mean, inverse, scale): the estimates of ``groups(grp, of)``, each drawn towards that of its language ``of`` by ``prior`` rows, as that is towards all."""

    own = groups.join(made, "grp")
    langs = durable(groups.select("of").distinct().join(made.withColumnRenamed("grp", "of"), "of"))
    sums = [F.array(*[F.sum(F.col(c)[i]) for i in range(k)]).alias(f"a{c}") for c, k in (("s1", P), ("s2", P * (P + 1) // 2))]
    every = langs.agg(F.sum("held").alias("an"), *sums, (F.sum(F.col("scale") * F.col("held")) / F.sum("held")).alias("ascale"))
    renamed = langs.select("of", *[F.col(c).alias(f"l{n}") for c, n in (("held", "n"), ("s1", "s1"), ("s2", "s2"), ("scale", "scale"))])
    both = small_join(own, renamed, ["of"]).crossJoin(F.broadcast(every))  # one row

    def blend(frames):
        for frame in frames:
            out = []
            for r in frame.itertuples():
                n, s1, s2, scale = float(r.an), np.array(r.as1), np.array(r.as2), r.ascale
                for m, t1, t2, own_scale in ((float(r.ln), np.array(r.ls1), np.array(r.ls2), r.lscale), (float(r.held), np.array(r.s1), np.array(r.s2), r.scale)):
                    s1, s2, scale, n = t1 + s1 / n * prior, t2 + s2 / n * prior, (m * own_scale + prior * scale) / (m + prior), m + prior
                mean, cov = _estimate(n, s1, s2)
                out.append((r.grp, mean.tolist(), _inverse(cov)[0], float(scale)))
            yield pd.DataFrame(out, columns=["grp", "mean", "inverse", "scale"])

    columns = ["grp", "held", "s1", "s2", "scale", *[f"{of}{c}" for of in "la" for c in ("n", "s1", "s2", "scale")]]
    return durable(both.select(*columns).mapInPandas(blend, "grp string, mean array<double>, inverse array<double>, scale double"))


def judged(docs: DataFrame, cutoff: float = 27.86, prior: float = 60.0, share: float = 0.75) -> DataFrame:
    """(doc_id, text_key, counts, base_failed, kept, distance): distance is squared and scaled to its group's median.

    ``cutoff`` is a squared distance: under normality one row in 10,000 lies beyond the default.
    """
    rows = durable(statistics(docs).withColumns({"grp": group_key("lang", "source"), "of": group_key("lang")}))
    made = estimates(rows.select(F.explode(F.array("grp", "of")).alias("grp"), *NAMES), share)
    final = shrunk(made, rows.select("grp", "of").distinct(), prior)
    at = small_join(rows, final, ["grp"])
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    out = at.select("doc_id", "text_key", *_COUNTS, failed.alias("base_failed"), (distance() / F.col("scale")).alias("distance"))
    return out.withColumn("kept", ~F.col("base_failed") & (F.col("distance") <= cutoff))
