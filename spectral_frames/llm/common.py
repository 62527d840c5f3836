"""Helpers shared by the operators: column picking, joins by small tables and by hot keys, components."""

from __future__ import annotations

import ctypes
import gc
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import durable, ship

__all__ = ["SMALL_ROWS", "WORD_CLASS", "components", "documents", "durable", "let_go", "pick", "same", "small_join", "spread_join", "worker_cache"]

#: Rows up to which a table of keys counts as small; larger ones are joined by a shuffle.
SMALL_ROWS = 20_000

#: The six ASCII white-space characters, as a Java class: what stands outside it is a word.
WORD_CLASS = "[^\\x20\\x09-\\x0D]+"


def pick(df: DataFrame, *names: str) -> DataFrame:
    """The named columns only, by exact name, whatever else the table holds (``TEXT`` beside ``text`` included)."""
    ship(df.sparkSession)
    columns = df.columns
    missing = [n for n in names if n not in columns]
    if missing:
        raise ValueError(f"columns {missing} are missing from {columns}")
    plain = df.toDF(*[f"_c{i}" for i in range(len(columns))])
    return plain.select(*[F.col(f"_c{columns.index(n)}").alias(n) for n in names])


_caches: dict[str, dict] = {}


def worker_cache(owner: str = "") -> dict:
    """What an operator keeps in a Python worker between batches; others' caches in this worker, which later stages use again, are let go."""
    full = [k for k, c in _caches.items() if c and k != owner]
    for k in full:
        _caches[k].clear()
    if full:
        let_go()
    return _caches.setdefault(owner, {})


def let_go() -> None:
    """Gives the memory that is free in this worker back; a worker waits for its next task with all that it has."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def documents(spark, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def same(left: Column, right: Column) -> Column:
    return left.eqNullSafe(right)


def small_join(big: DataFrame, small: DataFrame, on: list[str], how: str = "inner", rows: int | None = None) -> DataFrame:
    """Null-safe equi-join with a table that is broadcast only if it is counted to be small.

    A larger one is joined by a shuffle in which every key is spread over 32 salts, so that a hot key stays divided.
    """
    names = [f"_k{i}" for i in range(len(on))]
    right = small.withColumnsRenamed(dict(zip(on, names, strict=True)))
    match = reduce(lambda a, b: a & b, [same(big[k], right[n]) for k, n in zip(on, names, strict=True)])
    if (small.count() if rows is None else rows) <= SMALL_ROWS:
        return big.join(F.broadcast(right), match, how).drop(*names)
    salt = 32
    spread = right.withColumn("_s2", F.explode(F.sequence(F.lit(0), F.lit(salt - 1))))
    left = big.withColumn("_s1", F.pmod(F.xxhash64(*[big[c] for c in big.columns]), F.lit(salt)).cast("int"))
    match = reduce(lambda a, b: a & b, [same(left[k], spread[n]) for k, n in zip(on, names, strict=True)], left["_s1"] == spread["_s2"])
    return left.join(spread, match, how).drop("_s1", "_s2", *names)


def spread_join(big: DataFrame, small: DataFrame, on: str, counts: DataFrame, total: int) -> DataFrame:
    """``big.join(small, on)`` where some keys may hold much of ``big``; ``small`` has a row a key, ``counts(on, n)`` are big's rows by key.

    Keys that hold over a thousandth of the ``total`` rows (there are fewer than a thousand) meet their row by broadcast; only the others are shuffled.
    """
    hot = durable(counts.where(F.col("n") > max(1000, total // 1000)).select(on))
    if not hot.take(1):
        return big.join(small, on)
    few = small.join(F.broadcast(hot), on, "left_semi")
    return big.join(F.broadcast(few), on).unionByName(big.join(F.broadcast(hot), on, "left_anti").join(small, on))


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """Connected components of ``edges(a, b)`` (longs) by alternating large-star and small-star rounds.

    Returns (node, root) for every node that has an edge, root being the smallest node.  Each round is two
    group-wise minima and two equi-joins that keep hubs divided, and is written out; nothing is gathered on the driver but a count
    and a checksum, equal in two rounds once only stars are left.  If ``most_rounds`` do not get there, RuntimeError.
    """
    now = durable(edges.where("a != b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    before = None
    for _ in range(most_rounds):
        seen = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("s")).first()
        if seen["n"] == 0 or seen == before:
            break
        before = seen
        # large star: every larger neighbour of a node goes to the least node in its neighbourhood
        both = now.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(now.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = durable(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"), F.count("*").alias("n")))
        stars = spread_join(both.where("v > u"), least.select("u", "m"), "u", least, 2 * seen["n"])
        stars = durable(stars.select(F.col("v").alias("a"), F.col("m").alias("b")).distinct())
        # small star: a node and its smaller neighbours go to the least of them
        low = durable(stars.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")))
        moved = spread_join(stars, low.select("a", "m"), "a", low, seen["n"]).where("b != m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        now = durable(moved.unionByName(low.select("a", F.col("m").alias("b"))).distinct())
    else:
        raise RuntimeError(f"components: no two of {most_rounds} rounds agree; the edges are not reduced to stars")
    roots = now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct()
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(roots)
