"""SimHash fingerprints of word shingles and exact linking within a Hamming radius by bit-sliced comparison.

Plan: one scan makes fingerprints (whole texts, Arrow batches); the distinct fingerprints are dealt into
buckets such that any two within the radius share one (some blocks of bits are equal in both); a kernel
turns each bucket into bit planes and compares a row with 64 others at a time by carry-save counters; the links
of a bucket are reduced to a forest before they leave it, and components are found by star rounds.
Buckets beyond ``tile`` rows are cut into tiles and every pair of tiles is a group of its own, so that a
bucket of any size is compared in full by many tasks and no link is lost.

Nulls and empty texts: fingerprint zero, linked as any other.  Repeated rows: each gets its row.  A null doc_id
is kept, and never is a component's smallest id unless all ids are null.  Empty table: no rows.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, durable, pick, spread_join, worker_cache


def shingle_hashes(text: bytes | None, words: int) -> np.ndarray:
    """XXH64 (seed 42) of each run of ``words`` words, repeats included; fewer words make one shingle."""
    import xxhash

    parts = text.lower().split() if text else []
    if not parts:
        return np.zeros(0, np.uint64)
    line = b" ".join(parts)
    if len(parts) <= words:
        return np.array([xxhash.xxh64_intdigest(line, 42)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    digest = xxhash.xxh64_intdigest
    pairs = zip(starts[: 1 - words].tolist(), ends[words - 1 :].tolist(), strict=True)
    return np.fromiter((digest(line[s:e], 42) for s, e in pairs), np.uint64, len(parts) - words + 1)


def majorities(hashes: np.ndarray) -> np.ndarray:
    """For each column of (n, words) hashes the bits that are set in over half of them."""
    n, words = hashes.shape
    total = np.zeros(64 * words, np.int64)
    for k in range(0, n, 255):  # sums of up to 255 bits in bytes
        bits = np.unpackbits(np.ascontiguousarray(hashes[k : k + 255], "<u8").view(np.uint8), axis=1, bitorder="little")
        total += np.add.reduce(bits, axis=0, dtype=np.uint8)
    return np.packbits((2 * total > n).astype(np.uint8), bitorder="little").view("<u8")


def majority(hashes: np.ndarray) -> int:
    """The 64 bits that are set in over half of the hashes."""
    return int(majorities(hashes[:, None])[0]) if len(hashes) else 0


def wide(hashes: np.ndarray, words: int) -> np.ndarray:
    """A fingerprint of ``words`` times 64 bits: majorities over the hashes and over what further rounds of mixing make of them."""
    every = hashes[:, None] + (np.arange(words, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))[None, :]
    every = (every ^ every >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
    every = (every ^ every >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
    every ^= every >> np.uint64(31)
    return majorities(every) if len(hashes) else np.zeros(words, np.uint64)


def within(a: np.ndarray, b: np.ndarray, radius: int) -> np.ndarray:
    """Which of the pairs (rows of a and of b, some words of 64 bits each) differ in at most ``radius`` bits.

    64 pairs are the lanes of a word; planes of the bits in which they differ go through carry-save counters, and words all of whose
    lanes are over the radius are abandoned after every 64 planes.
    """
    n, words = a.shape
    if n == 0:
        return np.zeros(0, bool)
    x = np.zeros((-(-n // 64) * 64, words), np.uint64)
    x[:n] = a ^ b
    bits = np.unpackbits(x.view(np.uint8).reshape(len(x), -1), axis=1, bitorder="little")
    planes = np.packbits(np.ascontiguousarray(bits.T).reshape(64 * words, -1, 64), axis=2, bitorder="little").view("<u8")[:, :, 0]
    alive = np.full(planes.shape[1], ~np.uint64(0))
    at = np.arange(planes.shape[1])
    counters = [np.zeros(len(at), np.uint64) for _ in range((64 * words).bit_length())]
    for k in range(64 * words):
        carry = planes[k, at]
        for c, held in enumerate(counters):
            counters[c], carry = held ^ carry, held & carry
        if k & 63 == 63:
            over = np.zeros(len(at), np.uint64)
            equal = ~over
            for c in reversed(range(len(counters))):  # counters compared with the radius, from the top digit
                over, equal = (over, equal & counters[c]) if radius >> c & 1 else (over | equal & counters[c], equal & ~counters[c])
            alive[at] &= ~over
            stay = alive[at] != 0
            at, counters = at[stay], [c[stay] for c in counters]
    return np.unpackbits(alive.view(np.uint8), bitorder="little")[:n].astype(bool)


def fingerprints(docs: DataFrame, words: int = 4) -> DataFrame:
    """(doc_id, text_key, fp): one row per row of docs; text_key is a hash of the text that tells rows of one id apart."""

    def kernel(batches):
        worker_cache()
        for batch in batches:
            texts = batch.column("text")
            values = np.fromiter((majority(shingle_hashes(t.as_py(), words)) for t in texts), np.uint64, len(texts))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text_key"), pa.array(values.view(np.int64))], ["doc_id", "text_key", "fp"])

    rows = pick(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_key"), F.col("text").cast("binary").alias("text"))
    return rows.mapInArrow(kernel, "doc_id long, text_key long, fp long")


def link(parent: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Joins the trees of a[i] and b[i], all at once; the smaller index becomes the root."""
    while True:
        while True:
            up = parent[parent]
            if np.array_equal(up, parent):
                break
            parent[:] = up
        ra, rb = parent[a], parent[b]
        apart = ra != rb
        if not apart.any():
            return
        np.minimum.at(parent, np.maximum(ra, rb)[apart], np.minimum(ra, rb)[apart])


def forest(groups: np.ndarray, fps: np.ndarray, radius: int, most_items: int = 1 << 16) -> np.ndarray:
    """parent of each row: rows of one group (contiguous) within the radius, directly or by others, share a root.

    Every 64 rows of a group are a word of 64 lanes in each of 64 bit planes.  A work item is a row and a word
    of its group; one operation on an item moves 64 distances.  Items all of whose lanes exceed the radius are
    abandoned after every 8 planes.
    """
    n = len(fps)
    parent = np.arange(n)
    if n < 2:
        return parent
    first = np.flatnonzero(np.concatenate(([True], groups[1:] != groups[:-1])))
    size = np.diff(np.append(first, n))
    group_of = np.repeat(np.arange(len(first)), size)
    within = np.arange(n) - first[group_of]
    lane = (within & 63).astype(np.uint64)
    word_start = np.flatnonzero(lane == 0)
    word_of = np.repeat(np.arange(len(word_start)), np.diff(np.append(word_start, n)))
    last_word = word_of[first + size - 1][group_of]
    one = np.uint64(1)
    bits = [((fps >> np.uint64(b)) & one) for b in range(64)]
    planes = [np.bitwise_or.reduceat(b << lane, word_start) for b in bits]
    order = np.argsort([abs(2 * int(b.sum()) - n) for b in bits], kind="stable")
    masks = [np.uint64(0) - b for b in bits]
    valid = np.bitwise_or.reduceat(one << lane, word_start)
    width = radius.bit_length()
    todo = last_word - word_of + 1
    todo[size[group_of] < 2] = 0
    cuts = np.searchsorted(np.cumsum(todo), np.arange(most_items, int(todo.sum()) + most_items, most_items), side="left") + 1
    begin = 0
    for end in np.unique(np.minimum(cuts, n)).tolist():
        reps = todo[begin:end]
        row = np.repeat(np.arange(begin, end), reps)
        if len(row):
            word = word_of[row] + np.arange(len(row)) - np.repeat(np.cumsum(reps) - reps, reps)
            # lanes above the row's own in its own word, all lanes of later words
            alive = np.where(word == word_of[row], valid[word] & ~((np.uint64(2) << lane[row]) - one), valid[word])
            alive[(word == word_of[row]) & (lane[row] == 63)] = 0
            counters = [np.zeros(len(row), np.uint64) for _ in range(width)]
            for k, b in enumerate(order):
                carry = planes[b][word] ^ masks[b][row]
                for c in range(width):
                    counters[c], carry = counters[c] ^ carry, counters[c] & carry
                over = carry
                above = np.zeros(len(row), np.uint64)
                equal = ~above
                for c in reversed(range(width)):  # counters compared with the radius, from the top digit
                    if radius >> c & 1:
                        equal = equal & counters[c]
                    else:
                        above |= equal & counters[c]
                        equal = equal & ~counters[c]
                alive = alive & ~(over | above)
                if k & 7 == 7 or k == 63:
                    stay = alive != 0
                    if not stay.all():
                        row, word, alive = row[stay], word[stay], alive[stay]
                        counters = [c[stay] for c in counters]
                    if not len(row):
                        break
            if len(row):
                at, bit = np.nonzero(np.unpackbits(alive.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
                link(parent, row[at], word_start[word[at]] + bit)
        begin = end
    link(parent, np.arange(n), parent.copy())
    return parent


def block_masks(radius: int, n: int) -> list[int]:
    """Masks of bits of which two fingerprints within the radius share at least one whole.

    ``radius + c`` blocks leave c of them untouched; c grows with n so that buckets stay short.
    """
    chosen = 1
    while chosen < 3 and n > 1 << (64 * chosen // (radius + chosen) + 9):
        chosen += 1
    edges = np.linspace(0, 64, radius + chosen + 1).round().astype(int).tolist()
    blocks = [sum(1 << b for b in range(lo, hi)) for lo, hi in zip(edges, edges[1:], strict=False)]
    return [sum(c) for c in combinations(blocks, chosen)]


def split_buckets(dealt: DataFrame, row: str, tile: int) -> DataFrame:
    """``dealt(bucket, row, ...)`` with a gid for bucket: any two rows of a bucket share a gid, and none has more than some 2 * tile rows.

    A bucket with more rows is cut into tiles by a hash of ``row``, and every two of its tiles are a group.
    """
    hot = dealt.groupBy("bucket").agg(F.count("*").alias("rows")).where(F.col("rows") > 2 * tile)
    hot = durable(hot.select("bucket", F.ceil(F.col("rows") / tile).cast("int").alias("tiles")))
    rest = [c for c in dealt.columns if c != "bucket"]
    if not hot.take(1):
        return dealt.select(F.col("bucket").alias("gid"), *rest)
    mine = F.pmod(F.xxhash64(row, F.lit(7)), F.col("tiles")).cast("int")
    other = F.explode(F.sequence(F.lit(0), F.col("tiles") - 1))
    tiled = dealt.join(hot, "bucket").select("bucket", *rest, mine.alias("mine"), other.alias("other"))
    tiled = tiled.select(F.xxhash64("bucket", F.least("mine", "other"), F.greatest("mine", "other")).alias("gid"), *rest)
    return dealt.join(hot, "bucket", "left_anti").select(F.col("bucket").alias("gid"), *rest).unionByName(tiled)


def near_links(nodes: DataFrame, n: int, radius: int = 4, tile: int = 1024) -> DataFrame:
    """(a, b): edges that join all pairs of distinct ``nodes.fp`` within the radius, a forest per bucket.

    ``n`` is the number of nodes; it sets how many blocks of bits a bucket key takes, not what is found.
    """
    masks = block_masks(radius, n)
    signed = [m - (1 << 64) if m >> 63 else m for m in masks]
    keys = F.array(*[F.xxhash64(F.lit(i), F.col("fp").bitwiseAND(F.lit(m))) for i, m in enumerate(signed)])
    dealt = nodes.select("fp", F.explode(keys).alias("bucket"))
    groups = split_buckets(dealt, "fp", tile)
    groups = groups.repartition("gid").sortWithinPartitions("gid")

    def kernel(batches):
        def found(g, f):
            p = forest(g, f.view(np.uint64), radius)
            own = p != np.arange(len(p))
            return pa.RecordBatch.from_arrays([pa.array(f[own]), pa.array(f[p[own]])], ["a", "b"])

        held: list = [np.zeros(0, np.int64), np.zeros(0, np.int64)]
        for batch in batches:
            held = [np.concatenate((h, batch.column(c).to_numpy())) for h, c in zip(held, ("gid", "fp"), strict=True)]
            if len(held[0]):
                cut = int(np.searchsorted(held[0], held[0][-1]))
                if cut:
                    yield found(held[0][:cut], held[1][:cut])
                    held = [h[cut:] for h in held]
        if len(held[0]):
            yield found(*held)

    return groups.mapInArrow(kernel, "a long, b long")


def near_components(docs: DataFrame, words: int = 4, radius: int = 4, tile: int = 1024) -> DataFrame:
    """(doc_id, text_key, fp, root, component_id): root is a fingerprint of the component, component_id its smallest doc_id."""
    rows = durable(fingerprints(docs, words))
    nodes = durable(rows.groupBy("fp").agg(F.min("doc_id").alias("low"), F.count("*").alias("n")))
    total = nodes.agg(F.count("*").alias("fps"), F.coalesce(F.sum("n"), F.lit(0)).alias("rows")).first()
    links = near_links(nodes.select("fp"), total["fps"], radius, tile)
    found = durable(components(links))
    named = durable(nodes.join(found.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "low", F.coalesce("root", "fp").alias("root")))
    least = durable(named.groupBy("root").agg(F.min("low").alias("component_id"), F.count("*").alias("n")))
    named = durable(spread_join(named, least.select("root", "component_id"), "root", least, total["fps"]).select("fp", "root", "component_id"))
    return spread_join(rows, named, "fp", nodes.select("fp", "n"), total["rows"])


def near_dedup(docs: DataFrame, words: int = 5, radius: int = 4, tile: int = 1024, similarity: float | None = None) -> DataFrame:
    """docs without near copies: of each component the row with the smallest doc_id stays (nulls last), all columns kept.

    Linked are fingerprints within ``radius`` or, if a ``similarity`` is given, texts whose shingle sets have that Jaccard
    similarity or more: such texts' 64 bits differ too much to be found by blocks of equal bits, see ``neardup``.
    """
    if similarity is not None:
        from . import neardup

        return neardup.near_dedup(docs, words, similarity)
    rows = durable(near_components(docs, words, radius, tile).select("doc_id", "text_key", "root", "component_id"))
    kept = rows.where(F.col("doc_id").eqNullSafe(F.col("component_id")))
    one = durable(kept.groupBy("root").agg(F.min(F.struct("doc_id", "text_key")).alias("r"), F.count("*").alias("n")))
    names = docs.columns
    plain = docs.toDF(*[f"_c{i}" for i in range(len(names))])
    doc_id, text = f"_c{names.index('doc_id')}", f"_c{names.index('text')}"
    keep = one.select(F.col("r.doc_id").alias("_id"), F.col("r.text_key").alias("_key")).distinct()
    match = F.col(doc_id).cast("long").eqNullSafe(F.col("_id")) & (F.xxhash64(text) == F.col("_key"))
    out = plain.join(keep, match, "left_semi")
    if one.where("n > 1").limit(1).count():  # repeated rows: one of them stays
        out = out.withColumn("_key", F.xxhash64(text)).dropDuplicates([doc_id, "_key"]).drop("_key")
    return out.toDF(*names)
