"""Matrices from relational, event, text and embedding tables, columns pruned and filters pushed to the scan."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..matrix import ROW_SCHEMA, EntryFrame, RowFrame, row_batch
from ..session import ship


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def from_columns(df: DataFrame, columns: list[str | Column], key: str | None = None) -> RowFrame:
    """Columns as a row each; without a key, rows are numbered by partition and place.  -0.0 becomes 0.0."""
    values = [(F.col(c) if isinstance(c, str) else c).cast("double") + F.lit(0.0) for c in columns]
    row_id = F.col(key).cast("long") if key else F.monotonically_increasing_id()
    return RowFrame(df.select(row_id.alias("row_id"), F.array(*values).alias("vec")), len(columns), names=[str(c) for c in columns])


def from_array(df: DataFrame, key: str, array: str, n: int | None = None) -> RowFrame:
    """An array column, cast to double before any arithmetic."""
    rows = df.select(F.col(key).cast("long").alias("row_id"), F.transform(array, lambda x: x.cast("double")).alias("vec"))
    return RowFrame(rows, n or rows.agg(F.max(F.size("vec"))).first()[0])


def from_triples(df: DataFrame, i: Column, j: Column, v: Column, n: int | None = None, m: int | None = None) -> EntryFrame:
    """Sums of v by (i, j)."""
    e = df.select(i.cast("long").alias("i"), j.cast("long").alias("j"), v.cast("double").alias("v")).groupBy("i", "j").agg(F.sum("v").alias("v"))
    return EntryFrame(e, n or int((df.agg(F.max(j.cast("long"))).first()[0] or 0) + 1), m)


def emb(spark, d) -> RowFrame:
    return from_array(table(spark, d, "embeddings"), "vec_id", "embedding", 64)


LINE4 = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]


def line4(spark, d) -> RowFrame:
    return from_columns(table(spark, d, "lineitem"), LINE4)


def line_dup(spark, d) -> RowFrame:
    return from_columns(table(spark, d, "lineitem"), [*LINE4, "l_quantity", F.col("l_discount") + F.col("l_tax")])


def line_poly(spark, d, degree: int = 15) -> RowFrame:
    return from_columns(table(spark, d, "lineitem"), [F.pow(F.col("l_quantity") / 50, F.lit(float(p))) for p in range(degree + 1)])


PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
STATUSES = ["F", "O", "P"]


def one_hot(column: str, values: list[str]) -> list[Column]:
    return [F.when(F.col(column) == v, 1.0).otherwise(0.0) for v in values]


def categories(df: DataFrame, column: str, most: int = 10_000) -> list:
    """All values of a column that are not null, sorted; ValueError if there are more than ``most``, as each becomes a column."""
    found = sorted(r[0] for r in df.select(column).where(F.col(column).isNotNull()).distinct().limit(most + 1).collect())
    if len(found) > most:
        raise ValueError(f"{column} has more than {most} values")
    return found


def order_onehot(spark, d) -> RowFrame:
    orders = table(spark, d, "orders")
    priorities, statuses = categories(orders, "o_orderpriority"), categories(orders, "o_orderstatus")
    return from_columns(orders, one_hot("o_orderpriority", priorities) + one_hot("o_orderstatus", statuses), "o_orderkey")


def month_index(ts: str) -> Column:
    return (F.year(ts) - 1995) * 12 + F.month(ts) - 1


def cust_month(spark, d) -> EntryFrame:
    return from_triples(table(spark, d, "orders"), F.col("o_custkey"), month_index("o_orderdate"), F.col("o_totalprice"), 80)


def user_hour(spark, d) -> EntryFrame:
    return from_triples(table(spark, d, "events"), F.col("user_id"), F.hour("ts"), F.lit(1.0), 24)


def part_supp(spark, d) -> EntryFrame:
    return from_triples(table(spark, d, "lineitem"), F.col("l_partkey"), F.col("l_suppkey"), F.col("l_quantity"))


def cust_part(spark, d) -> EntryFrame:
    joined = table(spark, d, "orders").select("o_orderkey", "o_custkey").join(table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_extendedprice"), F.col("o_orderkey") == F.col("l_orderkey"))
    return from_triples(joined, F.col("o_custkey"), F.col("l_partkey"), F.col("l_extendedprice"))


def words(text: str) -> Column:
    return F.explode(F.filter(F.split(F.lower(text), "[^a-zß-ÿ]+"), lambda w: w != ""))


def doc_term(spark, d, buckets: int = 512) -> EntryFrame:
    terms = table(spark, d, "documents").select("doc_id", words("text").alias("w"))
    return from_triples(terms, F.col("doc_id"), F.pmod(F.xxhash64("w"), F.lit(buckets)), F.lit(1.0), buckets)


def nation_trade(spark, d) -> EntryFrame:
    line, orders = table(spark, d, "lineitem"), table(spark, d, "orders").select("o_orderkey", "o_custkey")
    customer, supplier = table(spark, d, "customer").select("c_custkey", "c_nationkey"), table(spark, d, "supplier").select("s_suppkey", "s_nationkey")
    joined = line.select("l_orderkey", "l_suppkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue")).join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    joined = joined.join(customer, F.col("o_custkey") == F.col("c_custkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
    return from_triples(joined, F.col("c_nationkey"), F.col("s_nationkey"), F.col("revenue"), 25, 25)


TAGS = ["p", "div", "a", "span", "li", "h1", "script", "nav"]


def page_shape(spark, d) -> EntryFrame:
    pages = table(spark, d, "pages")
    counts = F.posexplode(F.array(*[F.regexp_count(F.lower("html"), F.lit(f"<{t}[ >]")) for t in TAGS])).alias("j", "v")
    return from_triples(pages.select("page_id", counts).where("v > 0"), F.col("page_id"), F.col("j"), F.col("v"), len(TAGS))


def conv_role(spark, d) -> EntryFrame:
    turns = table(spark, d, "conversations")
    role = F.when(F.col("role") == "assistant", 0).when(F.col("role") == "user", 1).otherwise(2)
    counted = turns.select("conv_id", F.posexplode(F.array(F.lit(1.0), F.length("text").cast("double"))).alias("what", "v"), role.alias("r"))
    return from_triples(counted, F.col("conv_id"), F.col("what") * 3 + F.col("r"), F.col("v"), 6)


#: Spend of the orders whose key leaves i when divided by {0}, and its share u in the length of class i mod {1}: columns of shares are orthonormal.
SPEND_SQL = """s AS (SELECT o_orderkey % {0} AS i, sum(CAST(round(o_totalprice * 100) AS BIGINT))::DOUBLE AS s FROM orders GROUP BY 1), u AS (SELECT i, i % {1} AS k, s / sqrt(sum(s * s) OVER (PARTITION BY i % {1})) AS u FROM s)"""


def spend_shares(spark, d, m: int, classes: int) -> tuple[DataFrame, np.ndarray]:
    """(i, s) as in SPEND_SQL, and the lengths of the classes; cents are added as whole numbers, so no order of rows changes a sum."""
    cents = F.round(F.col("o_totalprice") * 100).cast("long")
    s = table(spark, d, "orders").groupBy(F.pmod("o_orderkey", F.lit(m)).alias("i")).agg(F.sum(cents).cast("double").alias("s"))
    lengths = np.ones(classes)
    for r in s.groupBy((F.col("i") % classes).alias("k")).agg(F.sqrt(F.sum(F.col("s") * F.col("s"))).alias("x")).collect():  # a row a class
        lengths[r["k"]] = r["x"] or 1.0
    return s, lengths


def spend(spark, d, m: int, n: int, sigma: np.ndarray, partitions: int | None = None, right: str = "cosine") -> RowFrame:
    """At most m rows of n columns with singular values ``sigma``: left vectors are shares of spend, right ones cosines, or ("unit") unit vectors."""
    from .synth import cosine_rows

    ship(spark)
    l = len(sigma)  # noqa: E741
    s, lengths = spend_shares(spark, d, m, l)
    scale = sigma / lengths
    sent = spark.sparkContext.broadcast(scale if right == "unit" else scale[:, None] * cosine_rows(np.arange(n), n, l).T)

    def block(ids, x):
        if right != "unit":
            return x[:, None] * sent.value[ids % l]
        out = np.zeros((len(ids), n))
        out[np.arange(len(ids)), ids % l] = x * sent.value[ids % l]
        return out

    def kernel(batches):
        for batch in batches:
            ids, x = batch.column("i").to_numpy(), batch.column("s").to_numpy()
            for lo in range(0, len(ids), 2048):
                some = ids[lo : lo + 2048]
                yield row_batch(some, block(some, x[lo : lo + 2048]))

    rows = s.repartition(partitions) if partitions else s
    return RowFrame(rows.mapInArrow(kernel, ROW_SCHEMA), n)
