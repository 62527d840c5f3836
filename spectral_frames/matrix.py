"""Matrices as tables: by rows, by tiles and by entries, and the ways between them."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .session import durable, ship

ROW_SCHEMA = "row_id long, vec array<double>"
TILE_SCHEMA = "bi int, bj int, nrows int, ncols int, data array<double>"


def rows_of(batch: pa.RecordBatch, n: int, column: str = "vec") -> np.ndarray:
    """The arrays of a column as a (rows, n) matrix."""
    return np.asarray(batch.column(column).flatten(), dtype=np.float64).reshape(-1, n)


def sound_rows(batch: pa.RecordBatch, n: int, column: str = "vec") -> np.ndarray | None:
    """rows_of() where every array is there, n long and without nulls; else None."""
    col = batch.column(column)
    if col.null_count or (len(col) and (np.diff(col.offsets.to_numpy()) != n).any()):
        return None
    flat = col.flatten()
    return None if flat.null_count else np.asarray(flat, dtype=np.float64).reshape(-1, n) if n else np.zeros((len(col), 0))


def list_array(x: np.ndarray) -> pa.Array:
    """The rows of x as an Arrow column of lists."""
    x = np.ascontiguousarray(x, dtype=np.float64)
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel()))


def row_batch(ids, x: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([ids if isinstance(ids, pa.Array) else pa.array(ids, pa.int64()), list_array(x)], ["row_id", "vec"])


@dataclass
class RowFrame:
    """A matrix by rows: df(row_id long, vec array<double>), every vec n long, row_id unique."""

    df: DataFrame
    n: int
    m: int | None = None
    names: list[str] = field(default_factory=list)
    #: Tasks that read it, where they are known.
    tasks: int | None = None

    def __post_init__(self):
        ship(self.df.sparkSession)

    def height(self) -> int:
        if self.m is None:
            self.m = self.df.count()
        return self.m

    def checked(self, on_null: str = "error") -> RowFrame:
        """Nulls by policy ("error", "zero" or "drop"); ragged rows, NaN and infinities raise ValueError."""
        v = F.col("vec")
        df = self.df
        if on_null == "zero":
            df = df.withColumn("vec", F.transform(v, lambda x: F.coalesce(x, F.lit(0.0))))
        elif on_null == "drop":
            df = df.where(v.isNotNull() & ~F.exists(v, lambda x: x.isNull()))
        elif on_null != "error":
            raise ValueError(f"null policy {on_null!r} is none of error, zero, drop")
        bad = df.where(v.isNull() | (F.size(v) != self.n) | F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))).limit(1).count()
        if bad:
            raise ValueError("a row is ragged, or holds null, NaN or infinity")
        return RowFrame(df, self.n, None, self.names)

    def columns(self, which: list[int]) -> RowFrame:
        """The matrix of some columns, in the order given."""
        if not all(0 <= j < self.n for j in which):
            raise ValueError(f"columns {which} are not all within 0 and {self.n - 1}")
        names = [self.names[j] for j in which] if self.names else []
        picked = F.array(*[F.get("vec", F.lit(j)) for j in which]) if which else F.array().cast("array<double>")
        return RowFrame(self.df.select("row_id", picked.alias("vec")), len(which), self.m, names, self.tasks)

    def renumbered(self) -> RowFrame:
        """row_id 0 to m - 1 in the order of the old ones: sorted ranges, each numbered from the rows before it; no single task sees all rows."""
        placed = durable(self.df.select("row_id", "vec").orderBy("row_id").withColumn("part", F.spark_partition_id()))
        by = Window.orderBy("part")  # a row a partition
        starts = placed.groupBy("part").agg(F.count("*").alias("n")).select("part", (F.sum("n").over(by) - F.col("n")).alias("first"))
        inside = F.row_number().over(Window.partitionBy("part").orderBy("row_id"))
        numbered = placed.withColumn("k", inside).join(F.broadcast(starts), "part")
        return RowFrame(numbered.select((F.col("first") + F.col("k") - 1).alias("row_id"), "vec"), self.n, self.m, self.names)

    def to_entries(self) -> EntryFrame:
        df = self.df.select(F.col("row_id").alias("i"), F.posexplode("vec").alias("j", "v")).where("v <> 0")
        return EntryFrame(df.select("i", F.col("j").cast("long").alias("j"), "v"), self.n, self.m)

    def to_tiles(self, rows: int = 1024, cols: int = 1024) -> TileFrame:
        n = self.n

        def tiles(table: pa.Table) -> pa.Table:
            table = table.sort_by("row_id")
            x = np.asarray(table.column("vec").combine_chunks().flatten(), dtype=np.float64).reshape(-1, n)
            bi = table.column("bi")[0].as_py()
            full = np.zeros((int(table.column("row_id")[-1].as_py()) - bi * rows + 1, n))
            full[table.column("row_id").to_numpy() - bi * rows] = x
            parts = [full[:, lo : lo + cols] for lo in range(0, n, cols)]
            return pa.table({"bi": pa.array([bi] * len(parts), pa.int32()), "bj": pa.array(range(len(parts)), pa.int32()), "nrows": pa.array([len(full)] * len(parts), pa.int32()), "ncols": pa.array([p.shape[1] for p in parts], pa.int32()), "data": pa.array([p.ravel() for p in parts], pa.list_(pa.float64()))})

        df = self.df.withColumn("bi", F.floor(F.col("row_id") / rows).cast("int")).groupBy("bi").applyInArrow(tiles, TILE_SCHEMA)
        return TileFrame(df, self.n, self.m, rows, cols)

    def collect(self) -> np.ndarray:
        """The matrix in the driver's memory, rows by row_id; for small factors and tests."""
        table = self.df.select("row_id", "vec").toArrow().sort_by("row_id")
        return np.asarray(table.column("vec").combine_chunks().flatten(), dtype=np.float64).reshape(-1, self.n)


@dataclass
class EntryFrame:
    """A matrix by entries: df(i long, j long, v double), (i, j) unique, absent entries zero."""

    df: DataFrame
    n: int
    m: int | None = None

    def transpose(self) -> EntryFrame:
        return EntryFrame(self.df.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), self.m, self.n)

    def height(self) -> int:
        if self.m is None:
            self.m = int((self.df.agg(F.max("i")).first()[0] or 0) + 1)
        return self.m

    def to_rows(self) -> RowFrame:
        """Dense rows, those without entries left out."""
        n = self.n
        grouped = self.df.groupBy("i").agg(F.collect_list(F.struct("j", "v")).alias("e"))

        def kernel(batches):
            for batch in batches:
                e = batch.column("e")
                flat = e.flatten()
                x = np.zeros((batch.num_rows, n))
                of = np.repeat(np.arange(batch.num_rows), np.diff(e.offsets.to_numpy()))
                np.add.at(x, (of, flat.field("j").to_numpy()), flat.field("v").to_numpy())
                yield row_batch(batch.column("i"), x)

        ship(self.df.sparkSession)
        return RowFrame(grouped.mapInArrow(kernel, ROW_SCHEMA), n, None)

    def to_sparse_rows(self) -> SparseRowFrame:
        """A row's entries beside each other, in the order of columns: for matrices of any width."""
        grouped = self.df.groupBy("i").agg(F.sort_array(F.collect_list(F.struct("j", "v"))).alias("e"))
        return SparseRowFrame(grouped.select(F.col("i").alias("row_id"), F.col("e.j").alias("at"), F.col("e.v").alias("val")), self.n, self.m)

    def to_tiles(self, rows: int = 1024, cols: int = 1024) -> TileFrame:
        """Sparse tiles: as large as their entries, in the order of places."""
        m, n = self.height(), self.n
        keyed = self.df.select(F.floor(F.col("i") / rows).cast("int").alias("bi"), F.floor(F.col("j") / cols).cast("int").alias("bj"), "i", "j", "v")
        size = lambda b, step, all_: F.least(F.lit(step), F.lit(all_) - F.col(b).cast("long") * step).cast("int")
        keyed = keyed.withColumns({"nrows": size("bi", rows, m), "ncols": size("bj", cols, n)})
        place = ((F.col("i") - F.col("bi").cast("long") * rows) * F.col("ncols") + F.col("j") - F.col("bj").cast("long") * cols).cast("int")
        tiles = keyed.groupBy("bi", "bj", "nrows", "ncols").agg(F.sort_array(F.collect_list(F.struct(place.alias("p"), "v"))).alias("e"))
        return TileFrame(tiles.select("bi", "bj", "nrows", "ncols", F.col("e.v").alias("data"), F.col("e.p").alias("at")), n, m, rows, cols)


@dataclass
class SparseRowFrame:
    """A matrix by sparse rows: df(row_id long, at array<long>, val array<double>): columns and their values; rows of zeros may be absent."""

    df: DataFrame
    n: int
    m: int | None = None

    def height(self) -> int:
        if self.m is None:
            self.m = int((self.df.agg(F.max("row_id")).first()[0] or 0) + 1)
        return self.m

    def to_entries(self) -> EntryFrame:
        e = self.df.select(F.col("row_id").alias("i"), F.explode(F.arrays_zip("at", "val")).alias("e"))
        return EntryFrame(e.select("i", F.col("e.at").alias("j"), F.col("e.val").alias("v")).where("v <> 0"), self.n, self.m)


@dataclass
class TileFrame:
    """A matrix by tiles: df(bi, bj, nrows, ncols, data row-major), (bi, bj) unique, absent tiles zero.

    With a column ``at`` (array<int>) tiles are sparse: data holds the values of those row-major places only.
    """

    df: DataFrame
    n: int
    m: int | None = None
    rows: int = 1024
    cols: int = 1024

    def height(self) -> int:
        if self.m is None:
            self.m = int(self.df.agg(F.max(F.col("bi").cast("long") * self.rows + F.col("nrows"))).first()[0] or 0)
        return self.m

    @property
    def sparse(self) -> bool:
        return "at" in self.df.columns

    def to_entries(self) -> EntryFrame:
        if self.sparse:
            e = self.df.select("bi", "bj", "ncols", F.explode(F.arrays_zip("at", "data")).alias("e")).select("bi", "bj", "ncols", F.col("e.at").alias("p"), F.col("e.data").alias("v")).where("v <> 0")
        else:
            e = self.df.select("bi", "bj", "ncols", F.posexplode("data").alias("p", "v")).where("v <> 0")
        i = F.col("bi").cast("long") * self.rows + F.floor(F.col("p") / F.col("ncols"))
        return EntryFrame(e.select(i.alias("i"), (F.col("bj").cast("long") * self.cols + F.col("p") % F.col("ncols")).alias("j"), "v"), self.n, self.m)

    def to_rows(self) -> RowFrame:
        """Tiles of one band joined into rows; the height of blocks is kept as the group."""
        n, rows, cols = self.n, self.rows, self.cols

        def band(table: pa.Table) -> pa.Table:
            bi = table.column("bi")[0].as_py()
            x = np.zeros((max(table.column("nrows").to_pylist()), n))
            for r in table.to_pylist():
                if r.get("at") is None:
                    x[: r["nrows"], r["bj"] * cols : r["bj"] * cols + r["ncols"]] = np.array(r["data"]).reshape(r["nrows"], r["ncols"])
                else:
                    at = np.array(r["at"], np.int64)
                    x[at // r["ncols"], r["bj"] * cols + at % r["ncols"]] = r["data"]
            return pa.Table.from_batches([row_batch(np.arange(len(x)) + bi * rows, x)])

        ship(self.df.sparkSession)
        return RowFrame(self.df.groupBy("bi").applyInArrow(band, ROW_SCHEMA), n, self.m)

    def transpose(self) -> TileFrame:
        if self.sparse:
            moved = F.transform("at", lambda p: ((p % F.col("ncols")) * F.col("nrows") + F.floor(p / F.col("ncols"))).cast("int"))
            df = self.df.withColumn("moved", moved).select(F.col("bj").alias("bi"), F.col("bi").alias("bj"), F.col("ncols").alias("nrows"), F.col("nrows").alias("ncols"), "data", F.col("moved").alias("at"))
            return TileFrame(df, self.height(), self.n, self.cols, self.rows)
        turned = F.transform(F.sequence(F.lit(0), F.size("data") - 1), lambda p: F.get("data", ((p % F.col("nrows")) * F.col("ncols") + F.floor(p / F.col("nrows"))).cast("int")))
        # first the data, then the names: in one select the lambda would meet the new nrows and ncols
        df = self.df.withColumn("turned", turned).select(F.col("bj").alias("bi"), F.col("bi").alias("bj"), F.col("ncols").alias("nrows"), F.col("nrows").alias("ncols"), F.col("turned").alias("data"))
        return TileFrame(df, self.height(), self.n, self.cols, self.rows)


def from_numpy(spark: SparkSession, x: np.ndarray, partitions: int = 1) -> RowFrame:
    table = pa.Table.from_batches([row_batch(np.arange(len(x)), np.asarray(x, float))])
    df = spark.createDataFrame(table)
    return RowFrame(df.repartition(partitions) if partitions > 1 else df, x.shape[1], len(x))
