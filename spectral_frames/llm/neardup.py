"""SimHash near copies at a Jaccard similarity of word-shingle sets; candidates share a rare shingle, an exact check follows.

Two sets of similarity s or more share a shingle among the first n - ceil(s n) + 1 of each, whatever fixed order shingles
are put in; so every row deals that prefix of its set out by shingle, and rows that meet are candidates.  The order
is by hash, with shingles that many of all rows have last: it decides how many candidates there are, never what is found.
Where a pair meets at its first common shingle, what follows it in either set bounds what they share: sizes and places rule most
pairs out.  The others' SimHash fingerprints of 512 bits are compared by bit planes and carry-save counters, and only pairs within the
radius leave the bucket to have their whole sets compared.  A bit of two sets of similarity 0.8 differs with a probability below 0.1875 (sets of
fewer than 16 shingles) or 0.159 (computed for all sizes); the radius lies 6.5 standard deviations above, so a similar pair is missed once in 1e9 or less.

First every row that shares a shingle is compared with the smallest that has it; what is joined by then needs no more pairs, and all
pairs that still lie in different components are compared after that.  So a large group costs a pair a row.  Buckets beyond
``tile`` rows are cut into tiles, and every two tiles are compared by a task.

Sets and shingles go by 64-bit hashes.  Null and empty texts: empty sets, equal to each other.  Under ``words`` words: one
shingle.  Repeated rows: one stays.  A null doc_id comes after all others.  Empty table: no rows.
"""

from __future__ import annotations

import zlib
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SMALL_ROWS, components, durable, let_go, pick, spread_join, worker_cache
from .simhash import shingle_hashes, split_buckets, wide, within

_ID = ["doc_id", "text_key"]


def shingle_set(text: bytes | None, words: int) -> np.ndarray:
    """Distinct shingle hashes, sorted."""
    return np.unique(shingle_hashes(text, words))


def set_key(s: np.ndarray) -> int:
    import xxhash

    return int(np.array([xxhash.xxh64_intdigest(s.astype("<u8").tobytes(), 7)], np.uint64).view(np.int64)[0])


def prefix(s: np.ndarray, common: np.ndarray, similarity: Fraction) -> np.ndarray:
    """The shingles of which two similar sets share one; ``common`` (sorted) come last."""
    n = len(s)
    if len(common) and n:
        late = common[np.minimum(np.searchsorted(common, s), len(common) - 1)] == s
        s = np.concatenate((s[~late], s[late]))
    return s[: n - int(-(-n * similarity.numerator // similarity.denominator)) + 1]


def similar(a: np.ndarray, b: np.ndarray, similarity: Fraction) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return similarity.denominator * both >= similarity.numerator * (len(a) + len(b) - both)


#: Words of 64 bits of a fingerprint.
WORDS = 8
#: Shingles of a set above which the probability that a bit differs is lower.
FEW = 16


def radius_at(similarity: Fraction, small: bool) -> int:
    """Bits that may differ: 6.5 standard deviations above the mean at 0.8, and in proportion to the angle for other similarities."""
    s = float(similarity)
    p = (0.1875 if small else 0.159) * np.arccos(2 * s / (1 + s)) / np.arccos(1.6 / 1.8)
    return int(64 * WORDS * min(0.5, p) + 6.5 * np.sqrt(64 * WORDS * p * (1 - p)))


def fingerprint(s: np.ndarray) -> bytes:
    """The size of the set, then its bits."""
    return len(s).to_bytes(8, "little") + wide(s, WORDS).tobytes()


def close(x: np.ndarray, y: np.ndarray, similarity: Fraction) -> np.ndarray:
    """By pair of fingerprints (rows of 1 + WORDS words): whether they differ in at most as many bits as their sizes allow."""
    small = np.minimum(x[:, 0], y[:, 0]) < FEW
    out = np.empty(len(x), bool)
    for kind in (True, False):
        at = np.flatnonzero(small == kind)
        out[at] = within(x[at, 1:], y[at, 1:], radius_at(similarity, kind))
    return out


def may_be_similar(a: list[bytes], b: list[bytes], similarity: Fraction) -> np.ndarray:
    return close(*(np.frombuffer(b"".join(v), np.uint64).reshape(-1, 1 + WORDS) for v in (a, b)), similarity)


def all_similar(a: list[bytes], b: list[bytes], similarity: Fraction) -> np.ndarray:
    """By pair: whether the whole sets have the similarity."""
    return np.array([similar(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), similarity) for x, y in zip(a, b, strict=True)], bool)


def _texts(docs: DataFrame) -> DataFrame:
    return pick(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_key"), F.col("text").cast("binary").alias("text"))


#: A shingle, and how many rows have it.
COUNT = [("h", "<u8"), ("n", "<u4")]
#: Buckets, as a power of two, whose rows are counted first, and how many of them go in a block.
BUCKET_BITS, BLOCK_BITS = 22, 14
#: Rows of a batch whose sets a worker holds at once.
ROWS = 256


def _cut(batches, rows: int = ROWS):
    """Batches of at most so many rows."""
    for batch in batches:
        for lo in range(0, batch.num_rows, rows):
            yield batch.slice(lo, rows)


def _sets(batches, words: int):
    """The set of each text; one is held at a time."""
    for batch in batches:
        for t in batch.column("text"):
            yield shingle_set(t.as_py(), words)


def _slices(sets, size: int):
    """Sets joined until they hold ``size`` shingles."""
    held, n = [], 0
    for s in sets:
        held.append(s)
        n += len(s)
        if n >= size:
            yield np.concatenate(held)
            held, n = [], 0
    if n:
        yield np.concatenate(held)


def _by_gid(batches, summed):
    """``summed`` of the blocks of each gid; batches are sorted by it."""
    gid, held = None, []
    for batch in batches:
        for g, b in zip(batch.column("gid").to_pylist(), batch.column("block").to_pylist(), strict=True):
            if g != gid and held:
                yield summed(gid, held)
                held = []
            gid = g
            held.append(b)
    if held:
        yield summed(gid, held)


def full_buckets(texts: DataFrame, words: int, most: int, bits: int, per_deal: int) -> tuple[int, int, np.ndarray]:
    """The count from which a shingle is common, how many (row, shingle) pairs lie in buckets that have as many, and those 2**bits buckets as a map of bits.

    A bucket has all shingles with the same first ``bits`` bits, so no shingle is in more rows than its bucket has pairs.  A task sends a number a bucket, not one a shingle.
    """
    block = 1 << min(bits, BLOCK_BITS)

    def count(batches):
        worker_cache()
        n = np.zeros(1 << bits, np.uint32)
        for h in _slices(_sets(batches, words), per_deal):
            at, more = np.unique(h >> np.uint64(64 - bits), return_counts=True)
            n[at] += more.astype(np.uint32)
        gid = np.flatnonzero(n.reshape(-1, block).any(axis=1))
        for g in gid.tolist():
            some = n[g * block : (g + 1) * block]
            least = some.astype(np.min_scalar_type(some.max()))
            yield pa.RecordBatch.from_arrays([pa.array([g], pa.int32()), pa.array([bytes([least.itemsize]) + zlib.compress(least.tobytes(), 1)], pa.binary())], ["gid", "block"])
        let_go()

    def summed(gid, blocks):
        n = np.zeros(block, np.uint64)
        for b in blocks:
            n += np.frombuffer(zlib.decompress(b[1:]), f"<u{b[0]}")
        return pa.RecordBatch.from_arrays([pa.array([gid], pa.int32()), pa.array([int(n.sum())], pa.int64()), pa.array([zlib.compress(n.tobytes(), 1)], pa.binary())], ["gid", "pairs", "block"])

    dealt = texts.select("text").mapInArrow(count, "gid int, block binary").repartition("gid").sortWithinPartitions("gid")
    counts = durable(dealt.mapInArrow(lambda batches: _by_gid(batches, summed), "gid int, pairs long, block binary"))
    least = max(3, -(-(counts.agg(F.sum("pairs")).first()[0] or 0) // most))

    def full(batches):
        for batch in batches:
            n = [np.frombuffer(zlib.decompress(b.as_py()), np.uint64) for b in batch.column("block")]
            yield pa.RecordBatch.from_arrays([batch.column("gid"), pa.array([int(x[x >= least].sum()) for x in n], pa.int64()), pa.array([np.packbits(x >= least).tobytes() for x in n], pa.binary())], ["gid", "pairs", "bits"])

    found = counts.mapInArrow(full, "gid int, pairs long, bits binary").where("pairs > 0").toArrow()
    out = np.zeros((1 << bits) // 8, np.uint8)
    for g, b in zip(found.column("gid").to_pylist(), found.column("bits").to_pylist(), strict=True):
        out[g * block // 8 : (g + 1) * block // 8] = np.frombuffer(b, np.uint8)
    return least, sum(found.column("pairs").to_pylist()), out


def common_shingles(docs: DataFrame, words: int, most: int = 1_000_000, per_group: int = 1 << 18, per_deal: int = 1 << 18) -> np.ndarray:
    """Shingles that three rows or more have, and a ``most``-th of all (row, shingle) pairs or more, sorted.

    All rows are counted, exactly, in two scans: first by buckets of the hash; then one by one those shingles whose bucket has pairs enough, as every common one's has.
    They go in blocks by ranges of the hash, and a worker holds some ``per_deal`` or ``per_group`` of them.  No more than ``most`` shingles can be so common.
    """
    texts = _texts(docs)
    total = texts.agg(F.sum(F.length("text"))).first()[0] or 0
    bits = min(BUCKET_BITS, max(3, (total // 3).bit_length()))  # a word takes some six bytes: two buckets or more a shingle, as long as there are few
    least, pairs, full = full_buckets(texts, words, most, bits, per_deal)
    if not pairs:
        return np.zeros(0, np.uint64)
    groups = max(64, -(-pairs // per_group))  # work for as many tasks
    sent = docs.sparkSession.sparkContext.broadcast(full)  # 512 kB, whatever the input

    def deal(batches):
        worker_cache()
        full = sent.value

        def candidates():
            for s in _sets(batches, words):
                at = s >> np.uint64(64 - bits)
                yield s[(full[at >> np.uint64(3)] >> (np.uint64(7) - (at & np.uint64(7))).astype(np.uint8)) & 1 == 1]

        for found in _slices(candidates(), per_deal):
            h, n = np.unique(found, return_counts=True)
            table = np.zeros(len(h), COUNT)
            table["h"], table["n"] = h, n
            g = ((h & np.uint64(0xFFFFFFFF)) % np.uint64(groups)).astype(np.int32)
            order = np.argsort(g, kind="stable")
            at = np.flatnonzero(np.diff(g[order], prepend=-1))
            blocks = np.split(table[order], at[1:])
            yield pa.RecordBatch.from_arrays([pa.array(g[order][at], pa.int32()), pa.array([b.tobytes() for b in blocks], pa.binary())], ["gid", "block"])
        let_go()

    def summed(gid, blocks):
        t = np.concatenate([np.frombuffer(b, COUNT) for b in blocks])
        t = t[np.argsort(t["h"])]
        first = np.flatnonzero(np.concatenate(([True], t["h"][1:] != t["h"][:-1])))
        n = np.add.reduceat(t["n"].astype(np.int64), first)
        return pa.RecordBatch.from_arrays([pa.array([t["h"][first][n >= least].tobytes()], pa.binary())], ["h"])

    dealt = texts.select("text").mapInArrow(deal, "gid int, block binary").repartition("gid").sortWithinPartitions("gid")
    found = dealt.mapInArrow(lambda batches: _by_gid(batches, summed), "h binary").toArrow().column("h")
    return np.sort(np.frombuffer(b"".join(x.as_py() for x in found), np.uint64))


def prefixes(docs: DataFrame, words: int, similarity: Fraction) -> DataFrame:
    """(doc_id, text_key, key, n, first, fp): key names the set of n shingles, first holds its prefix, fp its fingerprint."""
    late = docs.sparkSession.sparkContext.broadcast(common_shingles(docs, words))

    def kernel(batches):
        worker_cache()
        for batch in _cut(batches):
            sets = [shingle_set(t.as_py(), words) for t in batch.column("text")]
            keys, n = pa.array([set_key(s) for s in sets], pa.int64()), pa.array([len(s) for s in sets], pa.int32())
            first = pa.array([prefix(s, late.value, similarity).tobytes() for s in sets], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text_key"), keys, n, first, pa.array([fingerprint(s) for s in sets], pa.binary())], ["doc_id", "text_key", "key", "n", "first", "fp"])
        let_go()

    return _texts(docs).mapInArrow(kernel, "doc_id long, text_key long, key long, n int, first binary, fp binary")


#: A shingle of a prefix, the set that has it and its size, and the place of the shingle in the set's order.
POST = [("h", "<u8"), ("key", "<i8"), ("n", "<i4"), ("at", "<i4")]


def met(rows: DataFrame, per_group: int = 1 << 19) -> DataFrame:
    """(h, key, n, at): prefix shingles that two sets or more have, and their places in them.  Dealt out in blocks by ranges of the hash."""
    total = rows.agg(F.sum(F.length("first"))).first()[0] or 0
    groups = max(1, -(-total // 8 // per_group))

    def deal(batches):
        for batch in _cut(batches, 8 * ROWS):
            first = [np.frombuffer(x, np.uint64) for x in batch.column("first").to_pylist()]
            sizes = [len(x) for x in first]
            h = np.concatenate([np.zeros(0, np.uint64), *first])
            table = np.zeros(len(h), POST)
            table["h"], table["key"], table["n"] = h, np.repeat(batch.column("key").to_numpy(), sizes), np.repeat(batch.column("n").to_numpy(), sizes)
            table["at"] = np.concatenate([np.zeros(0, np.int64), *map(np.arange, sizes)])
            g = ((h & np.uint64(0xFFFFFFFF)) % np.uint64(groups)).astype(np.int32)
            order = np.argsort(g, kind="stable")
            at = np.flatnonzero(np.diff(g[order], prepend=-1))
            blocks = np.split(table[order], at[1:]) if len(at) else []
            yield pa.RecordBatch.from_arrays([pa.array(g[order][at], pa.int32()), pa.array([b.tobytes() for b in blocks], pa.binary())], ["gid", "block"])

    def kernel(batches):
        def found(gid, blocks):
            t = np.concatenate([np.frombuffer(b, POST) for b in blocks])
            t = t[np.lexsort((t["key"], t["h"]))]
            new_h = np.concatenate(([True], t["h"][1:] != t["h"][:-1]))
            t = t[new_h | np.concatenate(([True], t["key"][1:] != t["key"][:-1]))]
            same = t["h"][1:] == t["h"][:-1]
            t = t[np.concatenate(([False], same)) | np.concatenate((same, [False]))]
            return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(t["h"]).view(np.int64)), pa.array(np.ascontiguousarray(t["key"])), pa.array(np.ascontiguousarray(t["n"])), pa.array(np.ascontiguousarray(t["at"]))], ["h", "key", "n", "at"])

        yield from _by_gid(batches, found)

    dealt = rows.where("n > 0").select("key", "n", "first").mapInArrow(deal, "gid int, block binary")
    return dealt.repartition("gid").sortWithinPartitions("gid").mapInArrow(kernel, "h long, key long, n int, at int")


def _fits(n, at, m, to, similarity: Fraction):
    """Whether sets of n and m shingles whose first common ones stand at ``at`` and ``to`` can have the similarity; for columns and arrays alike."""
    p, q = similarity.numerator, similarity.denominator
    # both that hold: n - at or more common, of p / (p + q) (n + m) needed
    return ((n - at) * (p + q) >= p * (n + m)) & ((m - to) * (p + q) >= p * (n + m))


def linked(pairs: DataFrame, sets: DataFrame, test, per_block: int = 64) -> DataFrame:
    """The ``pairs(a, b)`` whose ``sets(key, s)`` pass ``test(left, right)``, lists of both ends of pairs.  The end with more pairs is sent to blocks of the others."""
    degree = pairs.select(F.col("a").alias("k")).unionByName(pairs.select(F.col("b").alias("k"))).groupBy("k").agg(F.count("*").alias("d"))
    both = pairs.join(degree.withColumnsRenamed({"k": "a", "d": "da"}), "a").join(degree.withColumnsRenamed({"k": "b", "d": "db"}), "b")
    swap = F.col("db") > F.col("da")
    hubs = both.select(F.when(swap, F.col("b")).otherwise(F.col("a")).alias("hub"), F.when(swap, F.col("a")).otherwise(F.col("b")).alias("key"), F.greatest("da", "db").alias("d"))
    hubs = durable(hubs.select("hub", "key", F.pmod(F.xxhash64("key"), F.ceil(F.col("d") / per_block)).alias("part")))
    sent = hubs.select("hub", "part", F.lit(1).alias("role"), "key").unionByName(hubs.select("hub", "part").distinct().select("hub", "part", F.lit(0).alias("role"), F.col("hub").alias("key")))

    def kernel(batches):
        hub, own = None, None
        for batch in batches:
            a, b, left, right = [], [], [], []
            for h, role, key, s in zip(*(batch.column(c).to_pylist() for c in ("hub", "role", "key", "s")), strict=True):
                if role == 0:
                    hub, own = h, s
                elif h == hub:
                    a.append(h)
                    b.append(key)
                    left.append(own)
                    right.append(s)
            passed = pa.array(test(left, right), pa.bool_())
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"]).filter(passed)

    dealt = sent.join(sets, "key").select("hub", "part", "role", "key", "s").repartition("hub", "part").sortWithinPartitions("hub", "part", "role")
    return durable(dealt.mapInArrow(kernel, "a long, b long"))


def apart(posts: DataFrame, prints: DataFrame, similarity: Fraction, tile: int = 1024, most: int = 1 << 14) -> DataFrame:
    """(a, b): pairs of ``posts(h, key, n, at, root)`` in different components whose sizes, places and fingerprints allow the similarity."""
    mixed = posts.groupBy("h").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi").select("h")
    dealt = posts.join(mixed, "h", "left_semi").join(prints, "key").select(F.col("h").alias("bucket"), "key", "n", "at", "root", "s")
    groups = split_buckets(durable(dealt), "key", tile).repartition("gid").sortWithinPartitions("gid")
    names = ("gid", "key", "n", "at", "root")

    def found(gid, key, n, at, root, s):
        last = np.searchsorted(gid, gid, side="right")  # sorted by gid
        todo = last - np.arange(len(gid)) - 1
        upto = np.cumsum(todo)
        lo = 0
        while lo < len(gid):  # rows with some ``most`` pairs at a time
            hi = max(lo + 1, int(np.searchsorted(upto, (upto[lo - 1] if lo else 0) + most, side="right")))
            reps = todo[lo:hi]
            i = np.repeat(np.arange(lo, hi), reps)
            j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(reps) - reps, reps)
            may = (root[i] != root[j]) & _fits(n[i], at[i], n[j], at[j], similarity)
            i, j = i[may], j[may]
            near = close(s[i], s[j], similarity)
            i, j = i[near], j[near]
            if len(i):
                pairs = np.unique(np.stack((np.minimum(key[i], key[j]), np.maximum(key[i], key[j]))), axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(pairs[0]), pa.array(pairs[1])], ["a", "b"])
            lo = hi

    def kernel(batches):
        held = None
        for batch in batches:
            new = [batch.column(c).to_numpy().astype(np.int64) for c in names]
            new.append(np.frombuffer(b"".join(batch.column("s").to_pylist()), np.uint64).reshape(-1, 1 + WORDS))
            held = new if held is None else [np.concatenate(x) for x in zip(held, new, strict=True)]
            cut = int(np.searchsorted(held[0], held[0][-1])) if len(held[0]) else 0
            if cut:
                yield from found(*[x[:cut] for x in held])
                held = [x[cut:] for x in held]
        if held is not None and len(held[0]):
            yield from found(*held)

    return durable(groups.mapInArrow(kernel, "a long, b long").distinct())


def _few(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.count() <= SMALL_ROWS else df


def near_components(docs: DataFrame, words: int = 5, similarity: float = 0.8) -> DataFrame:
    """(doc_id, text_key, key, root): rows of one root are joined by pairs of the similarity or more."""
    least = Fraction(similarity).limit_denominator(1000)
    rows = durable(prefixes(docs, words, least))
    posts = durable(met(rows))
    prints = durable(rows.join(posts.select("key").distinct(), "key", "left_semi").select("key", F.col("fp").alias("s")).dropDuplicates(["key"]))
    rows = rows.select(*_ID, "key")
    first = posts.groupBy("h").agg(F.min(F.struct("key", "n", "at")).alias("o"), F.count("*").alias("n"))
    hubs = spread_join(posts, first.select("h", "o"), "h", first.select("h", "n"), posts.count())
    may = (F.col("key") != F.col("o.key")) & _fits(F.col("n").cast("long"), F.col("at"), F.col("o.n").cast("long"), F.col("o.at"), least)
    stars = durable(hubs.where(may).select(F.col("o.key").alias("a"), F.col("key").alias("b")).distinct())

    def kernel(batches):
        for batch in _cut(batches):
            yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array([shingle_set(t.as_py(), words).tobytes() for t in batch.column("text")], pa.binary())], ["key", "s"])
        let_go()

    def sets(pairs):  # whole sets, one row each, of what the bitmaps left
        wanted = pairs.select(F.col("a").alias("key")).unionByName(pairs.select(F.col("b").alias("key"))).distinct()
        wanted = durable(wanted.join(rows, "key").groupBy("key").agg(F.min(F.struct(*_ID)).alias("r")).select("key", F.col("r.doc_id").alias("_id"), F.col("r.text_key").alias("_key")))
        match = F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("text_key") == F.col("_key"))
        return durable(_texts(docs).join(_few(wanted), match).select("key", "text").mapInArrow(kernel, "key long, s binary").dropDuplicates(["key"]))

    def verified(pairs):
        return linked(pairs, sets(pairs), lambda a, b: all_similar(a, b, least))

    edges = verified(linked(stars, prints, lambda a, b: may_be_similar(a, b, least)))
    roots = durable(components(edges))
    named = posts.join(roots.withColumnRenamed("node", "key"), "key", "left").select("h", "key", "n", "at", F.coalesce("root", "key").alias("root"))
    more = verified(apart(durable(named), prints, least))
    if more.count():
        roots = durable(components(edges.unionByName(more)))
    return rows.join(roots.withColumnRenamed("node", "key"), "key", "left").select(*_ID, "key", F.coalesce("root", "key").alias("root"))


def near_dedup(docs: DataFrame, words: int = 5, similarity: float = 0.8) -> DataFrame:
    """docs without near copies: of each component the row with the smallest doc_id stays (nulls last), all columns kept."""
    rows = durable(near_components(docs, words, similarity))
    order = F.struct(F.col("doc_id").isNull().alias("none"), *_ID)
    stay = rows.groupBy("root").agg(F.min(order).alias("r"), F.count("*").alias("rows")).where("rows > 1")
    joined = durable(rows.join(stay, "root").select(*_ID, "r"))
    own = F.col("doc_id").eqNullSafe(F.col("r.doc_id")) & (F.col("text_key") == F.col("r.text_key"))
    go = durable(joined.where(~own).select(F.col("doc_id").alias("_id"), F.col("text_key").alias("_key")).distinct())
    names = docs.columns
    plain = docs.toDF(*[f"_c{i}" for i in range(len(names))])
    doc_id, text = f"_c{names.index('doc_id')}", f"_c{names.index('text')}"
    out = plain.join(_few(go), F.col(doc_id).cast("long").eqNullSafe(F.col("_id")) & (F.xxhash64(text) == F.col("_key")), "left_anti")
    if joined.where(own).groupBy(*_ID).count().where("count > 1").limit(1).count():  # repeated rows: one of them stays
        out = out.withColumn("_key", F.xxhash64(text)).dropDuplicates([doc_id, "_key"]).drop("_key")
    return out.toDF(*names)
