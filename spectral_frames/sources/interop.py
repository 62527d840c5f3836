"""Matrices from and to files of other formats and MLlib's distributed types."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..matrix import EntryFrame, RowFrame, SparseRowFrame, TileFrame
from ..session import ship
from .tables import from_array, from_columns


def read_rows(spark: SparkSession, path: str, kind: str, columns: list[str] | str, key: str | None = None, **options) -> RowFrame:
    """A matrix by rows from csv, json, orc or parquet: named columns, or one array column with its key.

    The schema is given, not guessed, so nothing is read twice: csv and json columns are doubles, the key a long.
    """
    if isinstance(columns, str):
        schema, names = f"{columns} array<double>", [columns]
    else:
        schema, names = ", ".join(f"`{c}` double" for c in columns), list(columns)
    if key:
        schema = f"`{key}` long, {schema}"
    reader = spark.read.options(**options)
    if kind in ("csv", "json"):
        df = reader.schema(schema).format(kind).load(path)
    elif kind in ("orc", "parquet"):
        df = reader.format(kind).load(path).select(*([key] if key else []), *names)
    else:
        raise ValueError(f"format {kind!r} is none of csv, json, orc, parquet")
    return from_array(df, key, columns) if isinstance(columns, str) else from_columns(df, names, key)


def read_entries(spark: SparkSession, path: str, kind: str, n: int, m: int | None = None, **options) -> EntryFrame:
    """A matrix by entries (i, j, v) from csv, json, orc or parquet; a text file of triples is csv with its separator."""
    reader = spark.read.options(**options)
    df = reader.schema("i long, j long, v double").format(kind).load(path) if kind in ("csv", "json") else reader.format(kind).load(path).select("i", "j", "v")
    return EntryFrame(df, n, m)


def _tile_rows(batches):
    """Unwrapped MLlib matrices (compressed by columns, or by rows if transposed) to sparse tiles; dense ones hold every place."""
    for batch in batches:
        out = []
        for r in batch.to_pylist():
            m, n, turned = r["numRows"], r["numCols"], r["isTransposed"]
            values = np.array(r["values"], float)
            if r["colPtrs"] is None:
                out.append((np.arange(m * n), values if turned else values.reshape(n, m).T.ravel()))
                continue
            line, across = np.repeat(np.arange(len(r["colPtrs"]) - 1), np.diff(r["colPtrs"])), np.array(r["rowIndices"], np.int64)
            at = line * n + across if turned else across * n + line
            order = np.argsort(at, kind="stable")
            out.append((at[order], values[order]))
        sizes = np.cumsum([0, *(len(at) for at, _ in out)]).astype(np.int32)
        lists = [pa.ListArray.from_arrays(pa.array(sizes), pa.array(np.concatenate(x) if out else np.zeros(0), kind)) for x, kind in (([np.asarray(v, float) for _, v in out], pa.float64()), ([at.astype(np.int32) for at, _ in out], pa.int32()))]
        yield pa.RecordBatch.from_arrays([batch.column(c) for c in ("bi", "bj", "numRows", "numCols")] + lists, ["bi", "bj", "nrows", "ncols", "data", "at"])


def from_mllib(spark: SparkSession, matrix) -> RowFrame | SparseRowFrame | EntryFrame | TileFrame:
    """An IndexedRowMatrix or RowMatrix by rows (sparse ones, if it has a sparse vector), a BlockMatrix by tiles, a CoordinateMatrix by entries.

    Entries and vectors stay in the JVM; only blocks pass through Python, a block at a time.
    """
    from pyspark.mllib.common import callMLlibFunc

    kind = type(matrix).__name__
    if kind == "RowMatrix":
        rows = matrix.rows.zipWithIndex().map(lambda r: (r[1], r[0].toArray().tolist()))
        return RowFrame(spark.createDataFrame(rows, "row_id long, vec array<double>"), matrix.numCols(), None)
    if kind not in ("IndexedRowMatrix", "CoordinateMatrix", "BlockMatrix"):
        raise ValueError(f"{kind} is no distributed matrix")
    model = matrix._java_matrix_wrapper._java_model
    if kind == "IndexedRowMatrix":
        rows = callMLlibFunc("getIndexedRows", model)
        rows = rows.select(F.col("index").alias("row_id"), F.unwrap_udt("vector").alias("x"))
        if not rows.where("x.type = 0").limit(1).count():
            return RowFrame(rows.select("row_id", F.col("x.values").alias("vec")), matrix.numCols(), None)
        every = F.when(F.size("x.values") > 0, F.sequence(F.lit(0), F.size("x.values") - 1)).otherwise(F.array().cast("array<int>"))
        at = F.when(F.col("x.type") == 0, F.col("x.indices")).otherwise(every).cast("array<long>")
        return SparseRowFrame(rows.select("row_id", at.alias("at"), F.col("x.values").alias("val")), matrix.numCols(), matrix.numRows())
    if kind == "CoordinateMatrix":
        e = callMLlibFunc("getMatrixEntries", model)
        return EntryFrame(e.select("i", "j", F.col("value").alias("v")), matrix.numCols(), matrix.numRows())
    ship(spark)
    blocks = callMLlibFunc("getMatrixBlocks", model).toDF("at", "m")
    flat = blocks.select(F.col("at._1").alias("bi"), F.col("at._2").alias("bj"), F.unwrap_udt("m").alias("m")).select("bi", "bj", *[F.col(f"m.{c}").alias(c) for c in ("numRows", "numCols", "colPtrs", "rowIndices", "values", "isTransposed")])
    tiles = flat.mapInArrow(_tile_rows, "bi int, bj int, nrows int, ncols int, data array<double>, at array<int>")
    return TileFrame(tiles, matrix.numCols(), matrix.numRows(), matrix.rowsPerBlock, matrix.colsPerBlock)


def to_mllib(a: RowFrame | SparseRowFrame | EntryFrame | TileFrame):
    """The MLlib type of the same layout; sparse rows and tiles give sparse vectors and matrices."""
    from pyspark.ml.functions import array_to_vector
    from pyspark.mllib.common import callMLlibFunc
    from pyspark.mllib.linalg import DenseMatrix, MatrixUDT, SparseMatrix, SparseVector, VectorUDT
    from pyspark.mllib.linalg.distributed import BlockMatrix, CoordinateMatrix, IndexedRowMatrix
    from pyspark.mllib.util import MLUtils

    if isinstance(a, EntryFrame):
        e = a.df.select("i", "j", F.col("v").alias("value"))
        return CoordinateMatrix(callMLlibFunc("createCoordinateMatrix", e, a.height(), a.n), a.height(), a.n)
    n = a.n
    if isinstance(a, RowFrame):
        rows = MLUtils.convertVectorColumnsFromML(a.df.select(F.col("row_id").alias("index"), array_to_vector("vec").alias("vector")), "vector")
        return IndexedRowMatrix(callMLlibFunc("createIndexedRowMatrix", rows, a.height(), n), a.height(), n)
    if isinstance(a, SparseRowFrame):
        vector = F.udf(lambda at, val: SparseVector(n, at, val), VectorUDT())
        rows = a.df.select(F.col("row_id").alias("index"), vector("at", "val").alias("vector"))
        return IndexedRowMatrix(callMLlibFunc("createIndexedRowMatrix", rows, a.height(), n), a.height(), n)

    def matrix(nrows, ncols, data, at=None):
        if at is None:
            return DenseMatrix(nrows, ncols, data, True)
        at = np.array(at, np.int64)
        return SparseMatrix(nrows, ncols, np.searchsorted(at // ncols, np.arange(nrows + 1)), at % ncols, data, True)

    made = F.udf(matrix, MatrixUDT())("nrows", "ncols", "data", *(["at"] if a.sparse else []))
    blocks = a.df.select(F.struct(F.col("bi").cast("long").alias("_1"), F.col("bj").cast("long").alias("_2")).alias("_1"), made.alias("_2"))
    return BlockMatrix(callMLlibFunc("createBlockMatrix", blocks, a.rows, a.cols, a.height(), n), a.rows, a.cols, a.height(), n)


def from_ml_vectors(df: DataFrame, key: str, vector: str, n: int) -> RowFrame:
    from pyspark.ml.functions import vector_to_array

    return RowFrame(df.select(F.col(key).cast("long").alias("row_id"), vector_to_array(vector).alias("vec")), n)


def to_ml_vectors(a: RowFrame) -> DataFrame:
    """(row_id, features): for the estimators of the ML package."""
    from pyspark.ml.functions import array_to_vector

    return a.df.select("row_id", array_to_vector("vec").alias("features"))
