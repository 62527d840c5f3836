"""Language identification: averaged hashed subword embeddings and a linear softmax.

Training: stochastic gradient descent in numpy on a bounded sample of labelled rows (about ``per_language`` texts a
language, drawn by a hash of the text so that reruns agree).  Prediction: embeddings and softmax weights
fold into one table of scores per subword, so a text costs one look-up and one sum per subword, over the whole
text.  A temperature fitted on a calibration part of the sample makes the largest softmax a probability; texts
below ``least`` are rejected.

Subwords are runs of 3 and 4 bytes within a word with its two borders; A-Z are folded, other ASCII
characters than letters are borders, bytes above 0x7F count as letters.  Null text, or none of its characters a
letter: ``und`` with score 0, rejected.  No labelled rows: every prediction is ``und``.  Equal probabilities: the
language that comes first by code point.  Repeated rows: each is predicted, alike.  Empty table: no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ship import ship
from .common import let_go, pick, worker_cache

BITS = 15
_FOLD = bytes(b if b >= 128 or chr(b).islower() else b + 32 if chr(b).isupper() else 32 for b in range(256))


def subwords(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of each subword of the texts together, and where each text's begin; masked runs have the bucket 2**BITS."""
    text = b"  ".join([b" ", *[t.translate(_FOLD) for t in texts], b"   "])
    starts = np.cumsum([3] + [len(t) + 2 for t in texts[:-1]]) - 1 if texts else np.zeros(0, int)
    b = np.frombuffer(text, np.uint8)
    space = b == 32
    w = b.astype(np.uint32)
    n = len(b) - 3
    three = w[:n] | w[1 : n + 1] << np.uint32(8) | w[2 : n + 2] << np.uint32(16)
    four = three | w[3 : n + 3] << np.uint32(24)
    out = np.empty((n, 2), np.uint32)
    for k, (v, inner) in enumerate(((three, space[1 : n + 1]), (four ^ np.uint32(0x5BD1E995), space[1 : n + 1] | space[2 : n + 2]))):
        h = v * np.uint32(2654435761)
        h ^= h >> np.uint32(15)
        h *= np.uint32(2246822519)
        h >>= np.uint32(32 - BITS)
        h[inner] = 1 << BITS
        out[:, k] = h
    return out, starts


def has_letter(text: str | None) -> bool:
    return bool(text) and any(c.isalpha() for c in text)


@dataclass
class Model:
    """table: scores by subword (the last row, for masked runs, is zero); bias and temperature of the softmax; least: probability below which a text is rejected."""

    languages: list[str]
    table: np.ndarray
    bias: np.ndarray
    temperature: float = 1.0
    least: float = 0.5

    def scores(self, texts: list[bytes]) -> np.ndarray:
        out = np.zeros((len(texts), len(self.languages)))
        begin = 0
        while begin < len(texts):  # some 256 KB of text at a time
            end, held = begin, 0
            while end < len(texts) and (held < 1 << 18):
                held += len(texts[end])
                end += 1
            grams, starts = subwords(texts[begin:end])
            part = np.zeros((end - begin, len(self.languages)))
            count = np.zeros(end - begin)
            for k in range(grams.shape[1]):
                part += np.add.reduceat(np.take(self.table, grams[:, k], axis=0), starts, axis=0, dtype=np.float64)
                count += np.add.reduceat(grams[:, k] < 1 << BITS, starts, dtype=np.int64)
            out[begin:end] = part / np.maximum(count, 1)[:, None]
            begin = end
        return out + self.bias

    def probabilities(self, texts: list[bytes]) -> np.ndarray:
        return softmax(self.scores(texts) / self.temperature)


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def fit(texts: list[bytes], labels: list[str], width: int = 12, epochs: int = 4, least_steps: int = 400, rate: float = 4.0, batch: int = 16, seed: int = 7, least: float = 0.5) -> Model:
    """Plain SGD on embeddings and softmax weights together, ``least_steps`` steps at least; every fifth text is left for the calibration."""
    languages = sorted(set(labels))
    rng = np.random.default_rng(seed)
    if not languages:
        return Model([], np.zeros(((1 << BITS) + 1, 0), np.float32), np.zeros(0), least=least)
    k = len(languages)
    emb = rng.uniform(-1, 1, ((1 << BITS) + 1, width)) / width
    emb[-1] = 0
    weights = rng.normal(0, 1 / np.sqrt(width), (width, k))
    bias = np.zeros(k)
    truth = np.array([languages.index(x) for x in labels])
    bags = []
    for t in texts:
        grams, _ = subwords([t])
        ids, counts = np.unique(grams, return_counts=True)
        real = ids < 1 << BITS
        bags.append((ids[real], counts[real] / max(1, counts[real].sum())))
    training = [i for i in range(len(texts)) if len(texts) < 20 or i % 5]
    held = [i for i in range(len(texts)) if i % 5 == 0] or training
    per_epoch = -(-len(training) // batch)
    epochs = max(epochs, -(-least_steps // per_epoch))
    steps, step = epochs * per_epoch, 0
    for _ in range(epochs):
        order = rng.permutation(training)
        for lo in range(0, len(order), batch):
            some = order[lo : lo + batch]
            ids = np.concatenate([bags[i][0] for i in some])
            share = np.concatenate([bags[i][1] for i in some])
            of = np.repeat(np.arange(len(some)), [len(bags[i][0]) for i in some])
            mean = np.zeros((len(some), width))
            np.add.at(mean, of, emb[ids] * share[:, None])
            slope = softmax(mean @ weights + bias)
            slope[np.arange(len(some)), truth[some]] -= 1
            eta = rate * (1 - step / steps)
            back = slope @ weights.T
            weights -= eta * mean.T @ slope / len(some)
            bias -= 0.1 * eta * slope.mean(axis=0)
            np.add.at(emb, ids, -eta * back[of] * share[:, None])
            step += 1
    model = Model(languages, (emb @ weights).astype(np.float32), bias, least=least)
    z = model.scores([texts[i] for i in held])
    losses = {t: -np.log(softmax(z / t)[np.arange(len(held)), truth[held]] + 1e-12).mean() for t in np.geomspace(0.02, 5, 40)}
    model.temperature = float(min(losses, key=losses.get))
    return model


def train(labelled: DataFrame, per_language: int = 400, most_languages: int = 1000, longest: int = 200_000, **options) -> Model:
    """Fits on a bounded sample of ``labelled(text, lang)``: about ``per_language`` different texts, of at most ``longest`` characters each, of every language.

    The bound of the sample is documented by its parameters: should there be more lang values than ``most_languages``, those with the most
    different texts (ties: by code point) are learned.  A text is drawn by its hash, so reruns agree, and once, however many copies it has.
    """
    rows = pick(labelled, "text", "lang").where("text is not null and lang is not null").where(F.length("text") <= longest).withColumn("h", F.xxhash64("text", F.lit(99)))
    different = rows.groupBy("lang").agg(F.approx_count_distinct("h", 0.02).alias("n"))
    totals = {r["lang"]: r["n"] for r in different.orderBy(F.desc("n"), "lang").limit(most_languages).collect()}
    if not totals:
        return fit([], [], **options)
    share = F.create_map(*[x for lang, n in totals.items() for x in (F.lit(lang), F.lit(per_language / max(n, 1)))])
    sample = rows.where(F.col("h") / 2.0**64 + 0.5 < share[F.col("lang")]).groupBy("lang", "h").agg(F.min("text").alias("text")).collect()
    sample.sort(key=lambda r: (r["text"], r["lang"]))
    order = np.random.default_rng(3).permutation(len(sample))
    return fit([sample[i]["text"].encode() for i in order], [sample[i]["lang"] for i in order], **options)


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, text_key, lang_pred, score, rejected) of every row of docs, from its text alone."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # 2**BITS rows, whatever the input

    def kernel(batches):
        worker_cache()
        m = sent.value
        for batch in batches:
            texts = batch.column("text").to_pylist()
            rows = [i for i, t in enumerate(texts) if has_letter(t)] if m.languages else []
            named = np.full(len(texts), "und", object)
            score = np.zeros(len(texts))
            if rows:
                p = m.probabilities([texts[i].encode() for i in rows])
                named[rows] = np.array(m.languages, object)[p.argmax(axis=1)]
                score[rows] = p.max(axis=1)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("text_key"), pa.array(named, pa.string()), pa.array(score), pa.array((score < m.least) | (named == "und"))],
                ["doc_id", "text_key", "lang_pred", "score", "rejected"],
            )

    rows = pick(docs, "doc_id", "text").select("doc_id", F.xxhash64("text").alias("text_key"), "text")
    return rows.mapInArrow(kernel, f"doc_id {dict(rows.dtypes)['doc_id']}, text_key long, lang_pred string, score double, rejected boolean")


def keep_identified(docs: DataFrame, model: Model) -> DataFrame:
    """docs without the rows that are rejected, in one scan; all columns stay."""
    ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(model)
    names = docs.columns
    at = names.index("text")

    def kernel(batches):
        worker_cache()
        m = sent.value
        for whole in batches:
            for lo in range(0, whole.num_rows, 1024):  # texts that a worker holds at once
                batch = whole.slice(lo, 1024)
                texts = batch.column(at).to_pylist()
                rows = [i for i, t in enumerate(texts) if has_letter(t)] if m.languages else []
                keep = np.zeros(len(texts), bool)
                if rows:
                    keep[rows] = m.probabilities([texts[i].encode() for i in rows]).max(axis=1) >= m.least
                yield batch.filter(pa.array(keep))
        let_go()

    plain = docs.toDF(*[f"_c{i}" for i in range(len(names))])
    return plain.mapInArrow(kernel, plain.schema).toDF(*names)
