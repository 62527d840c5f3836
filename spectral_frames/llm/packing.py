"""Best-fit packing of tokenised documents into sequences, under token, document-count and attention-cost limits.

Documents of one length are alike to a packer, so bins are planned on the counts of each length (at most
``capacity`` numbers, whatever the input), longest first: the bins that can take the length under every limit compete,
by the smallest weighted norm of what they would have left or by the largest weighted dot product of demand and
room, and the winners - ranges of equal bins - are filled together.  The plan is a few assignments a
length; each piece finds its own by its rank among pieces of its length, which is an offset of its input
partition and a count within it.  Texts are read once; neither texts nor ids are shuffled.

Null or empty text: the one id ``end_id``.  Repeated rows: packed each.  Longer documents than ``capacity``
are cut; every other document stays whole.  Empty table: no rows.
"""

from __future__ import annotations

import os
import unicodedata
import zlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import durable, pick, worker_cache

#: Bytes that a worker may hold of words met before and their ids, by estimate; half of it for the words met of late.
CACHED_BYTES = 112 << 20

# The vocabulary spells a byte that prints as the character of its number, and the others, in order, as those from 256 on.
_PRINTS = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
_SPELLING = dict(zip((b for b in range(256) if b not in _PRINTS), range(256, 512), strict=False))


class Words(dict):
    """Ids of words as bytes, made when first asked for; letters in lower case, as the vocabulary sees them.

    What was not asked for while words of half of ``most`` bytes came in is forgotten.
    """

    def __init__(self, tokenizer, most: int | None = None):
        self.tokenizer, self.model = tokenizer, tokenizer.model
        self.most, self.held = most or CACHED_BYTES, 0
        self.old: dict[str, bytes] = {}

    def __missing__(self, word: str) -> bytes:
        ids = self.old.get(word)
        if ids is None:
            ids = self.made(word)
        self.held += 165 + 2 * len(word) + len(ids)
        if self.held > self.most // 2:
            self.old, self.held = dict(self), 0
            self.clear()
        self[word] = ids
        return ids

    def made(self, word: str) -> bytes:
        if not word:
            return b""
        if word[0] == " ":  # a run of letters as the vocabulary spells it: the merges alone
            return array("I", [t.id for t in self.model.tokenize(word[1:])]).tobytes()
        core, tail = (word[:-1], word[-1]) if len(word) > 1 and word[-1] in ",." else (word, "")
        if core.isascii() and core.isalpha():
            run = core.lower()
            if run == word:
                return array("I", [t.id for t in self.model.tokenize(run)]).tobytes()
        else:
            plain = unicodedata.normalize("NFC", core).lower()
            # letters that become other than letters join with what follows; sigma's lower case depends on its place
            if "Σ" in core or not plain.isalpha():
                return array("I", self.tokenizer.encode(word, add_special_tokens=False).ids).tobytes()
            run = " " + plain.encode().decode("latin-1").translate(_SPELLING)
        return self[run] + (self[tail] if tail else b"")


def encoded(texts: list[str | None], path: str) -> list[bytes]:
    """Ids of each text, as unsigned 32-bit numbers in little-endian order.

    The vocabulary drops white space and never joins across it, nor letters with what follows them, so a text's ids are those of
    its words, one after the other; words met before are looked up.
    """
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    cache = worker_cache("packing")
    if path not in cache:
        cache[path] = Words(Tokenizer.from_file(path))
    get = cache[path].__getitem__
    return [b"".join(map(get, t.replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" "))) if t else b"" for t in texts]


def pieces(docs: DataFrame, path: str, capacity: int = 4096, end_id: int = 1) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, part, nth): nth counts the pieces of a length within input partition ``part``."""
    end = int(end_id).to_bytes(4, "little")

    def kernel(batches):
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        seen = np.zeros(capacity + 1, np.int64)
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                some = batch.slice(lo, 256)
                of, piece, length, crc = [], [], [], []
                for i, ids in enumerate(encoded(some.column("text").to_pylist(), path)):
                    ids += end
                    for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                        cut = ids[at : at + 4 * capacity]
                        of.append(i)
                        piece.append(k)
                        length.append(len(cut) // 4)
                        crc.append(zlib.crc32(cut))
                sizes, piece_ = np.array(length), np.array(piece)
                order = np.argsort(sizes, kind="stable")
                ordered = sizes[order]
                first = np.searchsorted(ordered, ordered)
                nth = np.empty(len(sizes), np.int64)
                nth[order] = seen[ordered] + np.arange(len(sizes)) - first
                seen += np.bincount(sizes, minlength=capacity + 1)
                yield pa.RecordBatch.from_arrays(
                    [some.column("doc_id").take(pa.array(of)), pa.array(piece_.astype(np.int32)), pa.array(piece_.astype(np.int64) * capacity), pa.array(sizes.astype(np.int64)), pa.array(np.array(crc, np.int64)), pa.array(np.full(len(sizes), part, np.int32)), pa.array(nth)],
                    ["doc_id", "piece", "start", "length", "ids_crc32", "part", "nth"],
                )

    rows = pick(docs, "doc_id", "text")
    return rows.mapInArrow(kernel, f"doc_id {dict(rows.dtypes)['doc_id']}, piece int, start long, length long, ids_crc32 long, part int, nth long")


def fitted(counts: dict[int, int], limits: tuple[float, float, float], weights=(1.0, 0.01, 0.01), score: str = "norm") -> np.ndarray:
    """Assignments (length, first rank, first bin, pieces a bin, first offset), sorted by length and rank.

    ``limits``: tokens, documents and attention cost (sum of squared lengths) of a bin.  A piece that alone is over a
    limit raises ValueError.  Open bins are kept as ranges of bins in equal states.
    """
    limit, weight = np.array(limits, float), np.array(weights, float)
    first, many, room = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros((0, 3))
    made, bins = [], 0
    lengths = sorted((n for n, c in counts.items() if c), reverse=True)
    for length in lengths:
        demand, rank, left = np.array([length, 1, float(length) ** 2]), 0, counts[length]
        if (demand > limit).any():
            raise ValueError(f"a piece of {length} tokens is over the limits {limits}")
        while left:
            fits = np.flatnonzero((room >= demand).all(axis=1))
            if len(fits):
                if score == "norm":
                    best = (((room[fits] - demand) / limit) ** 2 @ weight).argmin()
                else:
                    best = ((room[fits] / limit * (demand / limit)) @ weight).argmax()
                at = fits[best]
            else:
                k = int((limit // demand).min())
                at = len(first)
                n = -(-left // k)
                first, many, room = np.append(first, bins), np.append(many, n), np.vstack([room, limit])
                bins += n
            k = int((room[at] // demand).min())
            n = int(min(many[at], left // k))
            if n == 0:
                k, n = left, 1
            made.append((length, rank, first[at], k, int(limit[0] - room[at, 0])))
            rank, left = rank + n * k, left - n * k
            after = room[at] - k * demand
            if n < many[at]:
                first, many, room = np.append(first, first[at] + n), np.append(many, many[at] - n), np.vstack([room, room[at]])
            many[at] = n
            room[at] = after
        shortest = lengths[-1]
        keep = (room >= np.array([shortest, 1, float(shortest) ** 2])).all(axis=1)
        first, many, room = first[keep], many[keep], room[keep]
    return np.array(sorted(made), np.int64).reshape(-1, 5)


def pack(docs: DataFrame, path: str, capacity: int = 4096, end_id: int = 1, most_docs: int | None = None, most_cost: float | None = None, weights=(1.0, 0.01, 0.01), score: str = "norm") -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset): where each piece of each document stands."""
    made = durable(pieces(docs, path, capacity, end_id))
    by_part = durable(made.groupBy("part", "length").agg(F.count("*").alias("n")))
    counts = {r["length"]: r["n"] for r in by_part.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most ``capacity`` rows
    limits = (capacity, most_docs or capacity, most_cost or float(capacity) ** 2)
    found = docs.sparkSession.sparkContext.broadcast(fitted(counts, limits, weights, score))  # a few rows a length
    before = F.sum("n").over(Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    starts = by_part.select("part", "length", F.coalesce(before, F.lit(0)).cast("long").alias("before"))
    ranked = made.join(starts, ["part", "length"])

    def kernel(batches):
        table = found.value
        keys = (table[:, 0] << 48) + table[:, 1]
        for batch in batches:
            length, rank = batch.column("length").to_numpy(), batch.column("nth").to_numpy() + batch.column("before").to_numpy()
            row = table[np.searchsorted(keys, (length << 48) + rank, side="right") - 1]
            into = rank - row[:, 1]
            columns = [batch.column(c) for c in ("doc_id", "piece", "start", "length", "ids_crc32")]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(row[:, 2] + into // row[:, 3]), pa.array(row[:, 4] + into % row[:, 3] * length)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.mapInArrow(kernel, f"doc_id {dict(made.dtypes)['doc_id']}, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
