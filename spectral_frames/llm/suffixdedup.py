"""Removal of byte strings that also start in an earlier document, by distributed prefix doubling over all positions.

A round names every open position by its next h bytes, deals the sorted names out by range, and closes the positions whose name
no second document has: nothing longer that starts there can be repeated.  h doubles from ``first`` until it reaches
``length``: the name of h bytes is made of the ranks' names of the pair (here, at the offset), both of which must be open.
The last round also asks which documents come first.

What is dealt.  Documents form groups: ranges of doc_id of some ``group_bytes``, so that of two groups one is the earlier; a range
that holds more (one doc_id or null for much of the table, or very long texts) is split by a hash of the text, and its groups tell their
documents too.  A group's texts meet in one task, which sorts its names and sends one packed block a range of names: gaps of
sorted names, their lower bytes as they are and the others pressed, 1.3 bytes a name at first.  The task of a range merges the sorted
blocks and answers a bit a name.  Names of rounds before the last are short (one of eight that is not shared may stay open by chance,
which costs a little and changes nothing); those of the last have 64 bits: wrongly removed are about M * M / 2**65 of
M open positions, none in 10,000 tables of 1 GB.

Null or empty text: no bytes.  Null doc_id: after all others, all alike.  Rows of one doc_id: none is earlier than
another; equal rows get equal results.  Empty table: no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, pick

_BASE = np.uint64(0x9E3779B97F4A7C15)
_ODD = 0x5851F42D4C957F2D


def _mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(31))
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(29)
    return h


_BYTES = _mix(_mix(np.arange(1, 257, dtype=np.uint64) * _BASE) + _BASE)
#: Ranges of doc_id that the driver knows; beyond them, ranges are split by hashes.
MOST_RANGES = 10_000
#: Positions hashed together: what they need stays in the processor's cache.
_CHUNK = 1 << 15
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def window_hashes(b: np.ndarray, size: int) -> np.ndarray:
    """Hash of every string of ``size`` bytes: differences of sums of terms by position, brought to a common origin by inverse powers."""
    n = len(b) - size + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    if size not in _powers:
        ones = [np.full(_CHUNK + size, x, np.uint64) for x in (_ODD, pow(_ODD, -1, 1 << 64))]
        for x in ones:
            x[0] = 1
        _powers[size] = tuple(np.cumprod(x, dtype=np.uint64) for x in ones)
    up, down = _powers[size]
    out = np.empty(n, np.uint64)
    sums = np.zeros(_CHUNK + size, np.uint64)
    for lo in range(0, n, _CHUNK):
        part = b[lo : lo + _CHUNK + size - 1]
        k = len(part)
        np.cumsum(_BYTES[part] * up[:k], out=sums[1 : k + 1])
        m = k - size + 1
        out[lo : lo + m] = _mix((sums[size : size + m] - sums[:m]) * down[:m])
    return out


# Packed blocks


def pack_sorted(names: np.ndarray) -> bytes:
    """Rising numbers as gaps: lower bytes as they are, the upper one pressed, and what does not fit it apart."""
    gaps = np.diff(names, prepend=np.uint64(0))
    low = max(0, (int(gaps.mean()) if len(gaps) else 0).bit_length() - 1) // 8
    high = gaps >> np.uint64(8 * low)
    far = np.flatnonzero(high >= 255)
    excess = high[far]
    high[far] = 255
    plain = gaps.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :low].tobytes()
    pressed = zstandard.ZstdCompressor(level=1).compress(high.astype(np.uint8).tobytes())
    head = np.array([len(names), low, len(far), len(pressed)], "<u8").tobytes()
    return head + far.astype("<u4").tobytes() + excess.astype("<u8").tobytes() + plain + pressed


def unpack_sorted(data: bytes) -> tuple[np.ndarray, int]:
    """The numbers, and where the block ends."""
    n, low, k, size = np.frombuffer(data, "<u8", 4).tolist()
    at = 32
    far = np.frombuffer(data, "<u4", k, at)
    excess = np.frombuffer(data, "<u8", k, at + 4 * k)
    at += 12 * k
    end = at + n * low + size
    gaps = np.frombuffer(zstandard.ZstdDecompressor().decompress(data[end - size : end], max_output_size=max(n, 1)), np.uint8).astype(np.uint64)
    gaps[far] = excess
    if low:
        gaps <<= np.uint64(8 * low)
        plain = np.zeros((n, 8), np.uint8)
        plain[:, :low] = np.frombuffer(data, np.uint8, n * low, at).reshape(n, low)
        gaps |= plain.view("<u8").ravel()
    return np.cumsum(gaps, dtype=np.uint64), end


def _press_bits(bits: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(np.packbits(bits).tobytes())


def press_texts(doc: np.ndarray, none: np.ndarray, key: np.ndarray, texts: list[bytes]) -> bytes:
    size = np.fromiter(map(len, texts), np.int64, len(texts))
    raw = b"".join([len(texts).to_bytes(8, "little"), doc.astype("<i8").tobytes(), key.astype("<i8").tobytes(), size.tobytes(), none.astype(np.uint8).tobytes(), *texts])
    return zstandard.ZstdCompressor(level=3).compress(raw)


class Group:
    """The texts of a group, one after the other: names of positions round by round."""

    def __init__(self, blocks: list[bytes]):
        parts: list[list] = [[], [], [], [], []]
        for data in blocks:
            raw = zstandard.decompress(data)
            n = int.from_bytes(raw[:8], "little")
            for k in range(3):
                parts[k].append(np.frombuffer(raw, "<i8", n, 8 + 8 * n * k))
            parts[3].append(np.frombuffer(raw, np.uint8, n, 8 + 24 * n))
            parts[4].append(np.frombuffer(raw, np.uint8, offset=8 + 25 * n))
        self.doc, self.key, size, none, self.b = (np.concatenate(x) for x in parts)
        self.none = none.astype(bool)
        self.end = np.cumsum(size)
        self.begin = self.end - size
        order = np.lexsort((self.doc, self.none))
        apart = (np.diff(self.doc[order], prepend=self.doc[order[:1]]) != 0) | (np.diff(none[order], prepend=none[order[:1]]) != 0)
        rank = np.empty(len(order), np.int32)
        rank[order] = np.cumsum(apart)
        self.rank = np.repeat(rank, size)  # of its document, by position
        self.ranked = np.zeros(int(rank.max(initial=0)) + 1, np.int64)
        self.ranked[rank] = self.doc

    def inside(self, size: int) -> np.ndarray:
        """Positions from which ``size`` bytes lie in one document."""
        edge = np.zeros(len(self.b) + 1, np.int32)
        np.add.at(edge, np.maximum(self.begin, self.end - size + 1), 1)
        np.add.at(edge, self.end, -1)
        return np.cumsum(edge[:-1]) == 0

    def walk(self, lengths: list[int], bits: list[int], ranges: int, answers: dict[int, dict[int, bytes]]):
        """Through the rounds that are answered.

        Of the first that is not: its names (distinct, rising), where ranges begin among them and each name's earliest document.
        After the last: the positions whose string starts in an earlier document too.
        """
        value = window_hashes(self.b, lengths[0])
        open_ = self.inside(lengths[0])[: len(value)]
        for k, h in enumerate(lengths):
            if k:
                step = h - lengths[k - 1]
                n = max(0, len(value) - step)
                at = np.flatnonzero(open_[:n] & open_[step:] & self.inside(h)[:n])
                longer = np.zeros(n, np.uint64)
                longer[at] = _mix(value[at] * _BASE + value[at + step])
                value = longer
            else:
                at = np.flatnonzero(open_)
            places = np.uint64(max(1, len(self.b).bit_length()))
            if bits[k] + int(places) <= 64:  # place and name in one number
                both = (value[at] >> np.uint64(64 - bits[k])) << places | at.astype(np.uint64)
                both.sort()
                at = (both & (np.uint64(1) << places) - np.uint64(1)).astype(np.int64)
                names = both >> places
            else:
                names = value[at] >> np.uint64(64 - bits[k])
                order = np.argsort(names, kind="stable")
                at, names = at[order], names[order]
            new = np.ones(len(names), bool)
            new[1:] = names[1:] != names[:-1]
            first = np.flatnonzero(new)
            doc = self.rank[at]
            least = np.minimum.reduceat(doc, first) if len(first) else doc
            distinct = names[first]
            cuts = np.append(np.searchsorted(distinct, np.arange(ranges, dtype=np.uint64) << np.uint64(bits[k] - ranges.bit_length() + 1)), len(distinct))
            if k not in answers:
                return distinct, cuts, self.ranked[least]
            said = np.zeros(len(distinct), bool)
            for p, data in answers[k].items():
                lo, hi = cuts[p], cuts[p + 1]
                said[lo:hi] = np.unpackbits(np.frombuffer(zstandard.decompress(data), np.uint8), count=hi - lo)
            which = np.cumsum(new) - 1
            if k == len(lengths) - 1:
                return np.sort(at[said[which] | (least[which] < doc)])
            if len(first):
                said |= least != np.maximum.reduceat(doc, first)
            open_ = np.zeros(len(value), bool)
            open_[at[said[which]]] = True

    def cut(self, starts: np.ndarray, length: int, texts_too: bool) -> list[tuple]:
        """A row a document: what the strings that start at ``starts`` leave of it."""
        cover = np.zeros(len(self.b) + 1, np.int32)
        cover[starts] += 1
        cover[starts + length] -= 1
        gone = np.cumsum(cover[:-1]) > 0
        head = gone.copy()
        head[1:] &= ~gone[:-1]
        begins = self.begin[self.begin < self.end]
        head[begins] = gone[begins]
        count, runs = (np.concatenate(([0], np.cumsum(x))) for x in (gone, head))
        out = []
        for i, (lo, hi) in enumerate(zip(self.begin.tolist(), self.end.tolist(), strict=True)):
            n = int(count[hi] - count[lo])
            rest = (self.b[lo:hi][~gone[lo:hi]] if n else self.b[lo:hi]).tobytes()
            out.append((int(self.doc[i]), bool(self.none[i]), int(self.key[i]), hi - lo, n, int(runs[hi] - runs[lo]), hashlib.sha256(rest).hexdigest(), rest if n and texts_too else None))
        return out


def shared(blocks: list[tuple[int, int, bytes]], last: bool) -> list[tuple[int, bytes]]:
    """(grp, bits) for the (grp, place, block)s of a range of names: which names two groups have, or which a document before has (``last``)."""
    names, place, doc, cuts = [], [], [], [0]
    for _, at, data in blocks:
        found, end = unpack_sorted(data)
        names.append(found)
        cuts.append(cuts[-1] + len(found))
        if last:
            place.append(np.full(len(found), at))
            doc.append(np.frombuffer(data, "<i8", offset=end) if len(data) > end else np.zeros(len(found), np.int64))
    h = np.concatenate(names)
    index = np.uint64(max(1, len(h).bit_length()))
    said = np.zeros(len(h), bool)
    if not last and int(h.max(initial=0)).bit_length() + int(index) <= 64:
        both = h << index | np.arange(len(h), dtype=np.uint64)
        both.sort()
        order, h = (both & (np.uint64(1) << index) - np.uint64(1)).astype(np.int64), both >> index
        same = h[1:] == h[:-1]
    elif not last:
        order = np.argsort(h, kind="stable")
        same = h[order][1:] == h[order][:-1]
    if last:
        p, d = np.concatenate(place), np.concatenate(doc)
        order = np.lexsort((d, p, h)) if d.any() else np.lexsort((p, h))
        h, p, d = h[order], p[order], d[order]
        new = np.ones(len(h), bool)
        new[1:] = h[1:] != h[:-1]
        low = np.flatnonzero(new)[np.cumsum(new) - 1]
        said[order] = (p != p[low]) | (d != d[low])
    else:
        said[order[1:][same]] = True
        said[order[:-1][same]] = True
    return [(g, _press_bits(said[lo:hi])) for (g, _, _), lo, hi in zip(blocks, cuts, cuts[1:], strict=False) if said[lo:hi].any()]


def _runs(batches, key: str, columns: tuple[str, ...]):
    """(key, rows) of batches sorted by key."""
    now, held = None, []
    for batch in batches:
        for g, *row in zip(*(batch.column(c).to_pylist() for c in (key, *columns)), strict=True):
            if g != now and held:
                yield now, held
                held = []
            now = g
            held.append(row)
    if held:
        yield now, held


_KEPT = {"doc": pa.int64(), "none": pa.bool_(), "text_key": pa.int64(), "n_bytes": pa.int64(), "n_removed": pa.int64(), "n_spans": pa.int64(), "kept_sha256": pa.string(), "kept": pa.binary()}
_BLOCK = {"grp": pa.int32(), "place": pa.int32(), "round": pa.int32(), "rng": pa.int32(), "data": pa.binary()}
_SQL = {pa.int32(): "int", pa.int64(): "long", pa.string(): "string", pa.binary(): "binary", pa.bool_(): "boolean"}


def _ddl(columns: dict) -> str:
    return ", ".join(f"{k} {_SQL[v]}" for k, v in columns.items())


def _batch(rows: list[tuple], columns: dict) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kind) for k, kind in enumerate(columns.values())], list(columns))


def _dealing(rows: DataFrame, group_bytes: int) -> tuple[np.ndarray, np.ndarray]:
    """Upper ends of ranges of doc_id that hold about ``group_bytes``, and how many groups each is split into; the last is that of nulls."""
    total = rows.agg(F.sum(F.length("text")).alias("bytes")).first()["bytes"] or 0
    n = max(1, min(-(-total // group_bytes), MOST_RANGES))
    ends = np.zeros(0, np.int64)
    if n > 1:
        found = rows.where("not none").agg(F.percentile_approx("doc", [k / n for k in range(1, n)], 20 * n)).first()[0]
        ends = np.unique(np.array(found or [], np.int64))

    def kernel(batches):
        held = np.zeros(len(ends) + 2, np.int64)
        for batch in batches:
            held += np.bincount(_places(batch, ends), batch.column("size").to_numpy(), len(held)).astype(np.int64)
        at = np.flatnonzero(held)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(held[at])], ["place", "bytes"])

    sizes = rows.select("doc", "none", F.length("text").cast("long").alias("size")).mapInArrow(kernel, "place int, bytes long")
    split = np.ones(len(ends) + 2, np.int64)
    for r in sizes.groupBy("place").agg(F.sum("bytes").alias("bytes")).collect():  # as many rows as there are ranges
        split[r["place"]] = 1 if r["bytes"] <= 2 * group_bytes else -(-r["bytes"] // group_bytes)
    return ends, split


def _places(batch: pa.RecordBatch, ends: np.ndarray) -> np.ndarray:
    return np.where(batch.column("none").to_numpy(zero_copy_only=False), len(ends) + 1, np.searchsorted(ends, batch.column("doc").to_numpy()))


def repeated_spans(docs: DataFrame, length: int = 50, first: int | None = None, group_bytes: int = 4 << 20, texts_too: bool = True) -> DataFrame:
    """(doc, none, text_key, n_bytes, n_removed, n_spans, kept_sha256, kept binary only where bytes were removed and ``texts_too``): one row per row of docs.

    ``first`` is what the first round compares, half of ``length`` unless it is given.
    """
    if length < 2 or not 0 < (first or 1) <= length:
        raise ValueError("length is 2 or more, first lies between 1 and length")
    lengths = [first or -(-length // 2)]
    while lengths[-1] < length:
        lengths.append(min(2 * lengths[-1], length))
    rows = pick(docs, "doc_id", "text").select(F.coalesce(F.col("doc_id").cast("long"), F.lit(0)).alias("doc"), F.col("doc_id").isNull().alias("none"), F.xxhash64("text").alias("text_key"), F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("text"))
    ends, split = _dealing(rows, group_bytes)
    sc = docs.sparkSession.sparkContext
    sent = sc.broadcast((ends, split, np.cumsum(split) - split))  # a few numbers a range
    groups = int(split.sum())
    ranges = 1 << max(4, (groups - 1).bit_length())
    open_bits = max((groups * group_bytes * 8 - 1).bit_length(), ranges.bit_length())
    bits = [min(64, open_bits)] * (len(lengths) - 1) + [64]

    def pressed(batches):
        ends, split, offset = sent.value
        for batch in batches:
            if not batch.num_rows:
                continue
            place, key = _places(batch, ends), batch.column("text_key").to_numpy()
            grp = offset[place] + (key.view(np.uint64) % split[place].astype(np.uint64)).astype(np.int64)
            doc, none, text = batch.column("doc").to_numpy(), batch.column("none").to_numpy(zero_copy_only=False), batch.column("text")
            order = np.argsort(grp, kind="stable")
            cuts = np.flatnonzero(np.diff(grp[order], prepend=-1, append=-1))
            for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                some = order[lo:hi]
                yield _batch([(int(grp[some[0]]), int(place[some[0]]), -1, 0, press_texts(doc[some], none[some], key[some], text.take(pa.array(some)).to_pylist()))], _BLOCK)

    def dealt(answers: list[DataFrame]) -> DataFrame:
        """Groups' texts, and behind each the answers it has."""
        out = rows.mapInArrow(pressed, _ddl(_BLOCK))
        for a in answers:
            out = out.unionByName(a)
        return out.repartition(groups, "grp").sortWithinPartitions("grp", "round")

    def each(batches):
        for g, found in _runs(batches, "grp", ("place", "round", "rng", "data")):
            answers: dict = {}
            for _, k, p, data in found:
                answers.setdefault(k, {})[p] = data
            yield g, found[0][0], Group([data for _, k, _, data in found if k < 0]), {k: v for k, v in answers.items() if k >= 0}

    def asking(k: int):
        def kernel(batches):
            split = sent.value[1]
            for g, place, group, answers in each(batches):
                names, cuts, doc = group.walk(lengths, bits, ranges, {j: answers.get(j, {}) for j in range(k)})
                out = []
                for p in np.flatnonzero(np.diff(cuts)).tolist():
                    lo, hi = cuts[p], cuts[p + 1]
                    data = pack_sorted(names[lo:hi] - (np.uint64(p) << np.uint64(bits[k] - ranges.bit_length() + 1)))
                    if k == len(lengths) - 1 and split[place] > 1:
                        data += doc[lo:hi].astype("<i8").tobytes()
                    out.append((g, place, k, p, data))
                yield _batch(out, _BLOCK)

        return kernel

    def answering(k: int):
        def kernel(batches):
            for p, found in _runs(batches, "rng", ("grp", "place", "data")):
                yield _batch([(g, 0, k, p, data) for g, data in shared([tuple(x) for x in found], k == len(lengths) - 1)], _BLOCK)

        return kernel

    answers: list[DataFrame] = []
    for k in range(len(lengths)):
        asked = dealt(answers).mapInArrow(asking(k), _ddl(_BLOCK))
        answers.append(durable(asked.repartition(ranges, "rng").sortWithinPartitions("rng").mapInArrow(answering(k), _ddl(_BLOCK))))

    def final(batches):
        for _, _, group, found in each(batches):
            starts = group.walk(lengths, bits, ranges, {j: found.get(j, {}) for j in range(len(lengths))})
            yield _batch(group.cut(starts, length, texts_too), _KEPT)

    return dealt(answers).mapInArrow(final, _ddl(_KEPT))


def removed(docs: DataFrame, length: int = 50) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256): one row per row of docs; a null doc_id stays null."""
    found = repeated_spans(docs, length, texts_too=False)
    return found.select(F.when(~F.col("none"), F.col("doc")).alias("doc_id"), "n_bytes", "n_removed", "n_spans", "kept_sha256")


def dedup(docs: DataFrame, length: int = 50) -> DataFrame:
    """(doc_id, text): what is left of each text; bytes that a cut left of a character become replacement characters."""
    found = repeated_spans(docs, length).select("doc", "none", "text_key", "kept", "n_spans").where("n_spans > 0").dropDuplicates(["doc", "none", "text_key"])
    rows = pick(docs, "doc_id", "text").withColumn("doc", F.coalesce(F.col("doc_id").cast("long"), F.lit(0))).withColumn("none", F.col("doc_id").isNull()).withColumn("text_key", F.xxhash64("text"))
    return rows.join(found, ["doc", "none", "text_key"], "left").select("doc_id", F.when(F.col("n_spans") > 0, F.decode("kept", "UTF-8")).otherwise(F.col("text")).alias("text"))
