"""Gram matrices: additive, in one reduction, in three physical forms."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..matrix import EntryFrame, RowFrame, rows_of
from . import reduce as tree

#: Width up to which the sums stay in Catalyst expressions.
CATALYST_WIDTH = 16
#: Rows of a first sum.
GROUP_ROWS = 1024


def gram_catalyst(a: RowFrame) -> np.ndarray:
    """n (n + 1) / 2 sums of products in whole-stage code; partial sums before the shuffle.

    Sums of GROUP_ROWS rows are summed again, so that rounding errors don't grow with the height.
    """
    pairs = [(i, j) for i in range(a.n) for j in range(i, a.n)]
    bad = F.col("vec").isNull() | (F.size("vec") != a.n) | F.exists("vec", lambda x: x.isNull())
    group = F.floor(F.monotonically_increasing_id() / GROUP_ROWS).alias("g")
    parts = a.df.select(group, "vec").groupBy("g").agg(*[F.sum(F.get("vec", F.lit(i)) * F.get("vec", F.lit(j))).alias(f"s{i}_{j}") for i, j in pairs], F.count("*").alias("m"), F.sum(bad.cast("int")).alias("bad"))
    again = [F.sum(c).alias(c) for c in parts.columns[1:]]
    found = parts.groupBy(F.floor(F.col("g") / 128)).agg(*again).agg(*again).first()
    a.m = found["m"] or 0
    out = np.full((a.n, a.n), np.nan if found["bad"] else 0.0)
    for (i, j), s in zip(pairs, found, strict=False):
        if not found["bad"]:
            out[i, j] = out[j, i] = s or 0.0
    return tree.finite(out)


def gram_arrow(a: RowFrame) -> np.ndarray:
    """One n x n partial per task by matrix products on Arrow batches; a tree sums them."""
    return tree.total(a, lambda s, x: s + x.T @ x, (a.n, a.n))


def gram_relational(a: EntryFrame):
    """(i, j, v) of the upper triangle of A*A by a self-join on the row; for sparse matrices of any width.

    A row of k entries makes k (k + 1) / 2 products, so this is for rows of bounded length; beyond, use gram_arrow().
    """
    left, right = a.df.alias("l"), a.df.alias("r")
    joined = left.join(right, (F.col("l.i") == F.col("r.i")) & (F.col("l.j") <= F.col("r.j")))
    return joined.groupBy(F.col("l.j").alias("i"), F.col("r.j").alias("j")).agg(F.sum(F.col("l.v") * F.col("r.v")).alias("v"))


def gram_matrix(a: RowFrame) -> np.ndarray:
    return gram_catalyst(a) if a.n <= CATALYST_WIDTH else gram_arrow(a)


def projected_norms(a: RowFrame, w: np.ndarray) -> np.ndarray:
    """Euclidean norms of the columns of A W, in one scan that keeps nothing of A W."""
    sent = a.df.sparkSession.sparkContext.broadcast(w)
    return np.sqrt(tree.total(a, lambda s, x: s + ((x @ sent.value) ** 2).sum(axis=0, keepdims=True), (1, w.shape[1]))[0])


def column_norms(a: RowFrame) -> np.ndarray:
    return projected_norms(a, np.eye(a.n))


__all__ = ["column_norms", "gram_arrow", "gram_catalyst", "gram_matrix", "gram_relational", "projected_norms", "rows_of"]
