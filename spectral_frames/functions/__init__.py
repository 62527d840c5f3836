"""Functions for SQL users: vector expressions, grouped factorisations and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType

from ..cost import timed
from ..kernels import r_of
from ..matrix import RowFrame
from ..mixing import MixingPlan
from ..session import ship


def vec_dot(a, b) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def vec_norm(a) -> Column:
    return F.sqrt(vec_dot(a, a))


def vec_axpy(c: float, a, b) -> Column:
    return F.zip_with(a, b, lambda x, y: x * c + y)


def projector(spark: SparkSession, v: np.ndarray):
    """An Arrow UDF: scores of an array column under a saved V."""
    ship(spark)
    sent = spark.sparkContext.broadcast(v)

    @F.pandas_udf("array<double>")
    def spectral_project(x: pd.Series) -> pd.Series:
        return pd.Series(list(np.stack(x.to_numpy()).astype(float) @ sent.value))

    return spectral_project


def mixer(spark: SparkSession, plan: MixingPlan):
    """An Arrow UDF: an array column mixed by a plan."""
    ship(spark)
    sent = spark.sparkContext.broadcast(plan)

    @F.pandas_udf("array<double>")
    def spectral_mix(x: pd.Series) -> pd.Series:
        return pd.Series(list(sent.value.forward(np.stack(x.to_numpy()).astype(float))))

    return spectral_mix


@F.pandas_udf(ArrayType(DoubleType()))
def gram_agg(x: pd.Series) -> list:
    """Upper triangle, by rows, of the Gram matrix of a group's vectors, for SQL.  A group must fit in a task; gram_by_group() has no such bound."""
    a = np.stack(x.to_numpy()).astype(float)
    g = a.T @ a
    return g[np.triu_indices(g.shape[0])].tolist()


#: Bytes of partial results that a task holds before it passes them on.
HELD_BYTES = 64 << 20


def _by_group(df: DataFrame, key: str, array: str, step, merge, fan_in: int = 64) -> DataFrame:
    """(key, part, data): one matrix a key.  A task folds its rows key by key and passes on what exceeds HELD_BYTES; a key's partials
    are merged in two levels, so a key that holds most rows meets fan_in partials at a time."""
    spark = df.sparkSession
    ship(spark)
    kind = dict(df.dtypes)[key]
    schema = f"{key} {kind}, part int, cols int, data binary"

    def fold(batches):
        from pyspark import TaskContext

        part, held, size = TaskContext.get().partitionId(), {}, 0

        def out():
            rows = list(held.items())
            return pa.RecordBatch.from_arrays([pa.array([k for k, _ in rows], field), pa.array([part] * len(rows), pa.int32()), pa.array([x.shape[1] for _, x in rows], pa.int32()), pa.array([x.tobytes() for _, x in rows], pa.binary())], [key, "part", "cols", "data"])

        field = None
        for batch in batches:
            field = batch.schema.field(0).type
            keys, column = batch.column(0).to_pylist(), batch.column(1)
            flat, at = np.asarray(column.flatten(), float), column.offsets.to_numpy() - column.offsets[0].as_py()
            by: dict = {}
            for i, k in enumerate(keys):
                by.setdefault(k, []).append(flat[at[i] : at[i + 1]])
            for k, rows in by.items():
                x = np.stack(rows)
                size -= held[k].nbytes if k in held else 0
                held[k] = np.ascontiguousarray(step(held.get(k, np.zeros((0, x.shape[1]))), x))
                size += held[k].nbytes
            if size > HELD_BYTES:
                yield out()
                held, size = {}, 0
        if held:
            yield out()

    def node(frame: pd.DataFrame) -> pd.DataFrame:
        first = frame.iloc[0]
        x = merge([np.frombuffer(d, float).reshape(-1, c) for d, c in zip(frame["data"], frame["cols"], strict=True)])
        return pd.DataFrame({key: [first[key]], "part": [0], "cols": [x.shape[1]], "data": [np.ascontiguousarray(x).tobytes()]})

    partials = df.select(key, F.transform(array, lambda x: x.cast("double")).alias("x")).where("x is not null").mapInArrow(timed(spark, fold), schema)
    some = partials.withColumn("bucket", F.floor(F.col("part") / fan_in)).groupBy(key, "bucket").applyInPandas(timed(spark, node), schema)
    return some.groupBy(key).applyInPandas(timed(spark, node), schema)


def gram_by_group(df: DataFrame, key: str, array: str) -> DataFrame:
    """(key, gram): the upper triangle, by rows, of each key's Gram matrix."""

    def triangle(batches):
        for batch in batches:
            found = [np.frombuffer(d, float).reshape(-1, c) for d, c in zip(batch.column("data").to_pylist(), batch.column("cols").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([g[np.triu_indices(len(g))] for g in found], pa.list_(pa.float64()))], [key, "gram"])

    sums = _by_group(df, key, array, lambda g, x: x.T @ x + (g if len(g) else 0.0), lambda gs: np.sum(gs, axis=0))
    return sums.mapInArrow(triangle, f"{key} {dict(df.dtypes)[key]}, gram array<double>")


def svd_by_group(df: DataFrame, key: str, array: str) -> DataFrame:
    """(key, k, sigma): the singular values of each key's rows, from its merged R factor."""
    if key in ("k", "sigma"):
        raise ValueError(f"a key named {key!r} would clash with the result's columns")

    def values(batches):
        for batch in batches:
            for k, d, c in zip(*(batch.column(x) for x in (key, "data", "cols")), strict=True):
                s = np.linalg.svd(np.frombuffer(d.as_py(), float).reshape(-1, c.as_py()), compute_uv=False)
                yield pa.RecordBatch.from_arrays([pa.array([k.as_py()] * len(s), batch.schema.field(key).type), pa.array(np.arange(1, len(s) + 1, dtype=np.int32)), pa.array(s)], [key, "k", "sigma"])

    factors = _by_group(df, key, array, lambda r, x: r_of(r, x), lambda rs: r_of(*rs))
    return factors.mapInArrow(values, f"{key} {dict(df.dtypes)[key]}, k int, sigma double")


def sample_rows(df: DataFrame, share: float, *key: str, seed: int = 0) -> DataFrame:
    """Each row with probability ``share``, by a hash of its key: the same rows in every run, however they are dealt out."""
    return df.where(F.xxhash64(*key, F.lit(seed)) / 2.0**64 + 0.5 < share)


def sample_by_length(a: RowFrame, rows: int, seed: int = 0) -> DataFrame:
    """(row_id, vec, p): rows kept with probability in proportion to their squared length, some ``rows`` of them."""
    total = a.df.agg(F.sum(vec_dot("vec", "vec"))).first()[0] or 1.0
    p = F.least(F.lit(1.0), vec_dot("vec", "vec") * (rows / total))
    return a.df.select("row_id", "vec", p.alias("p")).where(F.xxhash64("row_id", F.lit(seed)) / 2.0**64 + 0.5 < F.col("p"))


class _Spectrum:
    """Singular values of the numeric columns of a table argument, held as the upper factor of what was read."""

    def __init__(self):
        self.r = None
        self.held: list = []

    def _fold(self):
        if self.held:
            x = np.array(self.held, float)
            self.r = np.linalg.qr(x if self.r is None else np.vstack((self.r, x)), mode="r")
            self.held = []

    def eval(self, row):
        self.held.append([float(x) for x in row])
        if len(self.held) >= 4096:
            self._fold()

    def _sigma(self):
        self._fold()
        return np.zeros(0) if self.r is None else np.linalg.svd(self.r, compute_uv=False)


class SingularValues(_Spectrum):
    def terminate(self):
        for k, s in enumerate(self._sigma()):
            yield k + 1, float(s)


class ExplainedVariance(_Spectrum):
    def terminate(self):
        s = self._sigma() ** 2
        for k, x in enumerate(s):
            yield k + 1, float(x / s.sum()) if s.sum() else 0.0


class GeometricSpectrum:
    def eval(self, d: int):
        for j in range(d):
            yield j + 1, 10.0 ** (-20.0 * j / (d - 1)) if d > 1 else 1.0


class StaircaseSpectrum:
    def eval(self, k: int):
        from spectral_frames.sources.synth import staircase

        for j, s in enumerate(staircase(k)):
            yield j + 1, float(s)


def register(spark: SparkSession) -> None:
    """SQL names.  A table argument without PARTITION BY is read by one task: for small matrices, or one matrix per key."""
    ship(spark)
    for name, cls in (("spectral_singular_values", SingularValues), ("spectral_explained_variance", ExplainedVariance)):
        spark.udtf.register(name, F.udtf(cls, returnType="k int, sigma double" if cls is SingularValues else "k int, share double"))
    spark.udtf.register("spectrum_geometric", F.udtf(GeometricSpectrum, returnType="k int, sigma double"))
    spark.udtf.register("spectrum_staircase", F.udtf(StaircaseSpectrum, returnType="k int, sigma double"))
    spark.udf.register("spectral_gram", gram_agg)
