"""Exact top-k search by inner product: tiled matrix products of queries and shards.

Vectors become integers floor(scale * x).  Queries and candidates are packed into tiles of rows; a grid deals
every pair of tile groups to a task; a task multiplies its tiles and keeps k partial bests per query; two merge levels
of a tree make the final lists.  No vector is broadcast and no pair is emitted but the partial bests.

Vectors that are null, or hold a null or non-finite component, take no part; vectors of another length than a
query's are no candidates of it.  Ties go to the smaller vec_id.  Repeated rows are candidates each.  Scores are exact up to
64 bits; beyond, they are taken at the ends of the long range.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, pick


def whole_vectors(table: DataFrame, id_col: str, vec_col: str, scale: int) -> DataFrame:
    """(vec_id, v array<double>) with v = floor(scale * x), rows that take no part left out."""
    v = pick(table, id_col, vec_col).select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("v"))
    v = v.where("v is not null and vec_id is not null").where(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))))
    def scaled(x):  # floor() of a double gives a long and cuts off beyond it; such values are whole already
        return F.when(F.abs(x) < 2.0**52, F.floor(x).cast("double")).otherwise(x)
    return v.select("vec_id", F.transform("v", lambda x: scaled(x * float(scale))).alias("v"))


#: Tiles of a group: what a task's join holds of one side, some 16 MB at 64 components.
GROUP_TILES = 16


def cores_of(df: DataFrame) -> int:
    return df.sparkSession.sparkContext.defaultParallelism


def packed(vectors: DataFrame, rows: int) -> DataFrame:
    """Tiles of up to ``rows`` vectors of one width: (width int, n int, ids binary, data binary)."""

    def kernel(batches):
        for batch in batches:
            ids = batch.column("vec_id").to_numpy()
            column = batch.column("v")
            sizes = np.diff(column.offsets.to_numpy())
            flat = column.flatten().to_numpy()
            begins = np.concatenate(([0], np.cumsum(sizes)))
            for width in np.unique(sizes).tolist():
                mine = np.flatnonzero(sizes == width)
                for k in range(0, len(mine), rows):
                    some = mine[k : k + rows]
                    data = flat[(begins[some][:, None] + np.arange(width)[None, :]).ravel()]
                    yield pa.RecordBatch.from_pydict({"width": pa.array([width], pa.int32()), "n": pa.array([len(some)], pa.int32()), "ids": [ids[some].tobytes()], "data": [data.tobytes()]})

    return vectors.mapInArrow(kernel, "width int, n int, ids binary, data binary")


def products(q: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Exact inner products of whole numbers: in doubles where every sum stays below 2**53, else in Python integers."""
    bound = (np.abs(q).max(initial=0) * np.abs(c).max(initial=0)) * q.shape[1]
    if bound < 2.0**53:
        return (q @ c.T).astype(np.int64)
    exact = np.array([[int(x) for x in r] for r in q], object) @ np.array([[int(x) for x in r] for r in c], object).T
    return np.clip(exact, -(2**63), 2**63 - 1).astype(np.int64)


def best(group: np.ndarray, ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Indices of the k best of each group, best first: higher scores, then smaller ids."""
    order = np.lexsort((ids, ~scores, group))  # ~score = -score - 1 has no overflow
    g = group[order]
    first = np.concatenate(([True], g[1:] != g[:-1])) if len(g) else np.zeros(0, bool)
    rank = np.arange(len(g)) - np.flatnonzero(first)[np.cumsum(first) - 1]
    return order[rank < k]


_LIST = "query_id long, vec_id long, score long"


def _table(q, v, s):
    return pa.RecordBatch.from_arrays([pa.array(q), pa.array(v), pa.array(s)], ["query_id", "vec_id", "score"])


def merged(lists: DataFrame, k: int, *keys: str) -> DataFrame:
    """The k best per key of partial lists; a partition keeps k rows per key it has met, whatever it reads."""

    def kernel(batches):
        held = [np.zeros(0, np.int64)] * 3
        for batch in batches:
            held = [np.concatenate((h, batch.column(c).to_numpy())) for h, c in zip(held, ("query_id", "vec_id", "score"), strict=True)]
            keep = best(*held, k)
            held = [h[keep] for h in held]
        yield _table(*held)

    return lists.repartition(*keys).select("query_id", "vec_id", "score").mapInArrow(kernel, _LIST)


def top_k(queries: DataFrame, candidates: DataFrame, k: int = 10, scale: int = 1024, id_col: str = "vec_id", vec_col: str = "embedding", tile: int = 2048, skip_self: bool = True) -> DataFrame:
    """(query_id, rank, vec_id, score): the k candidates with the largest scores of each query, all if fewer."""
    few = whole_vectors(queries, id_col, vec_col, scale)
    few = few.repartition(max(1, -(-few.count() // tile)))  # full tiles: each is multiplied with every candidate
    q = durable(packed(few, tile)).withColumnsRenamed({"ids": "q_ids", "data": "q_data", "n": "q_n"})
    c = durable(packed(whole_vectors(candidates, id_col, vec_col, scale), tile))
    # a vector is sent to every group of the other side: groups as large as a task may hold, but enough for all cores
    cores = cores_of(queries)
    groups_q = max(1, -(-q.count() // GROUP_TILES))
    tiles_c = c.count()
    groups_c = max(1, -(-tiles_c // GROUP_TILES), min(tiles_c, -(-2 * cores // groups_q)))
    deal = lambda n, ids: F.pmod(F.xxhash64(ids), F.lit(n)).cast("int")
    left = q.select("*", deal(groups_q, "q_ids").alias("gq"), F.explode(F.sequence(F.lit(0), F.lit(groups_c - 1))).alias("gc"))
    right = c.select("*", deal(groups_c, "ids").alias("gc"), F.explode(F.sequence(F.lit(0), F.lit(groups_q - 1))).alias("gq"))
    pairs = left.join(right, ["gq", "gc", "width"])

    def kernel(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                width = batch.column("width")[i].as_py()
                qi, ci = (np.frombuffer(batch.column(x)[i].as_py(), np.int64) for x in ("q_ids", "ids"))
                qv, cv = (np.frombuffer(batch.column(x)[i].as_py(), np.float64).reshape(-1, width) for x in ("q_data", "data"))
                for lo in range(0, len(qi), 256):
                    ids = qi[lo : lo + 256]
                    s = products(qv[lo : lo + 256], cv)
                    own = ids[:, None] == ci[None, :] if skip_self else np.zeros(s.shape, bool)
                    if s.shape[1] > k + 1:  # partial selection: all that reach the k-th score of those that are not the query's own
                        kth = np.partition(np.where(own, np.int64(-(2**63)), s), s.shape[1] - k, axis=1)[:, s.shape[1] - k]
                        own |= s < kth[:, None]
                    r, col = np.nonzero(~own)
                    keep = best(ids[r], ci[col], s[r, col], k)
                    yield _table(ids[r][keep], ci[col][keep], s[r, col][keep])

    part = pairs.mapInArrow(kernel, _LIST)
    part = part.withColumn("branch", F.pmod(F.xxhash64("vec_id"), F.lit(16)))
    final = merged(merged(part, k, "query_id", "branch"), k, "query_id")

    def ranked(batches):
        # batches may cut a query's list in two: a partition, which holds whole lists, is ranked at once
        parts = [[batch.column(x).to_numpy() for x in ("query_id", "vec_id", "score")] for batch in batches]
        if parts:
            q_, v_, s_ = (np.concatenate(x) for x in zip(*parts, strict=True))
            o = best(q_, v_, s_, k)
            g = q_[o]
            first = np.concatenate(([True], g[1:] != g[:-1])) if len(g) else np.zeros(0, bool)
            rank = np.arange(len(g)) - np.flatnonzero(first)[np.cumsum(first) - 1] + 1
            yield pa.RecordBatch.from_arrays([pa.array(g), pa.array(rank.astype(np.int32)), pa.array(v_[o]), pa.array(s_[o])], ["query_id", "rank", "vec_id", "score"])

    return final.mapInArrow(ranked, "query_id long, rank int, vec_id long, score long")
