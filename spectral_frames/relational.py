"""Registered queries of the relational, streaming and file operators that matrices are built with and factors are asked by."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from . import functions as fn
from . import streaming
from .matrix import EntryFrame
from .mixing import MixingPlan
from .operators import thin
from .session import shared_folder
from .sources import interop, tables
from .sources.tables import table
from .workloads import _NORMS, _PART_SUPP, _ran, _stream, query, whole


@query("SELECT CAST(count(DISTINCT l_partkey) AS BIGINT) AS parts, CAST(count(DISTINCT l_suppkey) AS BIGINT) AS suppliers, true AS estimate_is_near FROM lineitem")
def distinct_bounds(spark, d):
    """Bounds of a rank from distinct keys: exact, and whether the sketch's estimate is within a tenth."""
    found = table(spark, d, "lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"), F.approx_count_distinct("l_partkey", 0.02).alias("near"))
    return found.select("parts", "suppliers", (F.abs(F.col("near") - F.col("parts")) <= F.col("parts") / 10).alias("estimate_is_near"))


_TYPES = ["click", "login", "logout", "purchase", "view"]


@query("SELECT user_id, " + ", ".join(f"CAST(count(*) FILTER (event_type = '{t}') AS BIGINT) AS {t}" for t in _TYPES) + " FROM events GROUP BY 1")
def pivot_user_type(spark, d):
    """Counts by user and type as columns; the types are named, so no pass is spent on finding them."""
    return table(spark, d, "events").groupBy("user_id").pivot("event_type", _TYPES).agg(F.count("event_id")).fillna(0)


@query("SELECT event_type, CAST(round(quantile_cont(value, 0.25) * 1e6) AS BIGINT) AS low, CAST(round(median(value) * 1e6) AS BIGINT) AS middle, CAST(round(quantile_cont(value, 0.9) * 1e6) AS BIGINT) AS high FROM events GROUP BY 1")
def percentiles_by_type(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(whole(F.percentile("value", F.lit(0.25)), 1e6).alias("low"), whole(F.median("value"), 1e6).alias("middle"), whole(F.percentile("value", F.lit(0.9)), 1e6).alias("high"))


@query("SELECT o_orderpriority, CAST(count(*) FILTER (o_orderstatus = 'F') AS BIGINT) AS done, CAST(round(sum(o_totalprice) FILTER (o_orderstatus <> 'F') * 100) AS BIGINT) AS open_spend FROM orders GROUP BY 1")
def filtered_sums(spark, d):
    return table(spark, d, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "F").alias("done"), whole(F.sum(F.when(F.col("o_orderstatus") != "F", F.col("o_totalprice"))), 100).alias("open_spend"))


@query("""WITH q AS (SELECT l_suppkey, l_partkey, sum(l_quantity) AS q FROM lineitem GROUP BY 1, 2)
SELECT l_suppkey, arg_max(l_partkey, q * 1000000 - l_partkey) AS most, arg_min(l_partkey, q * 1000000 + l_partkey) AS least, CAST(count(*) AS BIGINT) AS parts FROM q GROUP BY 1""")
def sparse_rows_summary(spark, d):
    """Of each supplier's sparse row, held as a map, the largest and the smallest entry."""
    e = tables.part_supp(spark, d).df
    rows = e.groupBy("j").agg(F.max_by("i", F.col("v") * 1000000 - F.col("i")).alias("most"), F.min_by("i", F.col("v") * 1000000 + F.col("i")).alias("least"), F.map_from_entries(F.collect_list(F.struct("i", "v"))).alias("row"))
    return rows.select(F.col("j").alias("l_suppkey"), "most", "least", F.size("row").cast("long").alias("parts"))


_GAP = "PARTITION BY user_id ORDER BY ts, event_id"


@query(f"SELECT event_id, CAST(floor(epoch(ts)) - floor(epoch(lag(ts) OVER ({_GAP}))) AS BIGINT) AS since, lead(event_id, 2) OVER ({_GAP}) AS after FROM events")
def window_lag_gap(spark, d):
    by = Window.partitionBy("user_id").orderBy("ts", "event_id")
    seconds = F.unix_seconds(F.col("ts").cast("timestamp"))
    return table(spark, d, "events").select("event_id", (seconds - F.lag(seconds).over(by)).alias("since"), F.lead("event_id", 2).over(by).alias("after"))


@query("""SELECT event_id, CAST(count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS BIGINT) AS of_day,
first_value(event_id) OVER w AS first_id, nth_value(event_id, 2) OVER w AS second_id, last_value(event_id) OVER w AS last_id FROM events
WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def window_range_frame(spark, d):
    """Events of the last day by a frame of seconds; the first, second and last of all."""
    seconds = F.unix_seconds(F.col("ts").cast("timestamp"))
    day = Window.partitionBy("user_id").orderBy(seconds).rangeBetween(-86400, 0)
    every = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, d, "events").select("event_id", F.count("*").over(day).alias("of_day"), F.first("event_id").over(every).alias("first_id"), F.nth_value("event_id", 2).over(every).alias("second_id"), F.last("event_id").over(every).alias("last_id"))


@query("SELECT p_partkey, CAST(dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS INTEGER) AS place, CAST(round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_size) * 1e6) AS BIGINT) AS share FROM part")
def window_dense_rank(spark, d):
    by = Window.partitionBy("p_brand").orderBy("p_size")
    return table(spark, d, "part").select("p_partkey", F.dense_rank().over(by).alias("place"), whole(F.percent_rank().over(by), 1e6).alias("share"))


@query("SELECT CAST(row_number() OVER (ORDER BY o_orderkey) - 1 AS BIGINT) AS row_id, CAST(round(o_totalprice * 100) AS BIGINT) AS cents FROM orders")
def renumbered_rows(spark, d):
    """Row numbers in the order of a key by two steps: places within sorted ranges, and the ranges' sizes before them."""
    a = tables.from_columns(table(spark, d, "orders"), ["o_totalprice"], "o_orderkey").renumbered()
    return a.df.select("row_id", whole(F.col("vec")[0], 100).alias("cents"))


@query("SELECT l_orderkey AS row_id, CAST(round(l_tax * 100) AS BIGINT) AS tax, CAST(round(l_quantity) AS BIGINT) AS quantity FROM lineitem")
def column_subset(spark, d):
    a = tables.from_columns(table(spark, d, "lineitem"), tables.LINE4, "l_orderkey").columns([3, 0])
    return a.df.select("row_id", whole(F.col("vec")[0], 100).alias("tax"), whole(F.col("vec")[1]).alias("quantity"))


@query()
def sampled_rows(spark, d):
    """A tenth of the orders by a hash of the key: the same in every run."""
    return fn.sample_rows(table(spark, d, "orders"), 0.1, "o_orderkey", seed=3).select("o_orderkey", "o_totalprice")


@query()
def length_squared_sample(spark, d):
    """Some fifty rows with probability in proportion to their squared length."""
    a = thin.stored(tables.cust_month(spark, d).to_rows())
    return fn.sample_by_length(a, 50, 1).select("row_id", "p")


@query("SELECT n_nationkey AS i, r_regionkey AS j, CAST(n_regionkey = r_regionkey AS BIGINT) AS v FROM nation, region")
def cross_join_indicator(spark, d):
    """The full indicator matrix of 25 nations and 5 regions: the one cross join, of two tables of fixed size."""
    nation, region = (table(spark, d, x) for x in ("nation", "region"))
    return nation.crossJoin(F.broadcast(region)).select(F.col("n_nationkey").alias("i"), F.col("r_regionkey").alias("j"), (F.col("n_regionkey") == F.col("r_regionkey")).cast("long").alias("v"))


@query("SELECT o_orderpriority, CAST(round(sum(l_extendedprice) * 100) AS BIGINT) AS spend FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def shuffle_hash_join(spark, d):
    """Lines meet their orders by a shuffled hash join: neither side is sorted."""
    orders = table(spark, d, "orders").select("o_orderkey", "o_orderpriority").hint("shuffle_hash")
    line = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_extendedprice")
    return line.join(orders, "o_orderkey").groupBy("o_orderpriority").agg(whole(F.sum("l_extendedprice"), 100).alias("spend"))


@query("""SELECT event_id, max(o_orderkey) AS o_orderkey FROM (SELECT event_id, o_orderkey, o_orderdate, max(o_orderdate) OVER (PARTITION BY event_id) AS latest FROM events JOIN orders ON o_custkey = user_id AND o_orderdate < ts)
WHERE o_orderdate = latest GROUP BY 1""")
def asof_order_feature(spark, d):
    """The latest order of the same key before each event: both tables in one sort a key, no pairs."""
    events = table(spark, d, "events").select(F.col("user_id").cast("long").alias("k"), F.col("ts").cast("timestamp").alias("t"), "event_id", F.lit(None).cast("long").alias("o_orderkey"))
    orders = table(spark, d, "orders").select(F.col("o_custkey").cast("long").alias("k"), F.col("o_orderdate").cast("timestamp").alias("t"), F.lit(None).cast("long").alias("event_id"), "o_orderkey")
    by = Window.partitionBy("k").orderBy("t", F.col("event_id").isNull(), "o_orderkey").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    joined = events.unionByName(orders).withColumn("latest", F.last("o_orderkey", ignorenulls=True).over(by))
    return joined.where("event_id IS NOT NULL AND latest IS NOT NULL").select("event_id", F.col("latest").alias("o_orderkey"))


_WORDS = "SELECT doc_id, unnest(list_filter(regexp_split_to_array(lower(text), '[^a-zß-ÿ]+'), lambda x: x <> '')) AS w FROM documents"


@query(f"""WITH t AS ({_WORDS}), v AS (SELECT w, row_number() OVER (ORDER BY count(*) DESC, w) - 1 AS j FROM t GROUP BY w ORDER BY count(*) DESC, w LIMIT 100)
SELECT doc_id AS i, CAST(j AS BIGINT) AS j, CAST(count(*) AS BIGINT) AS v FROM t JOIN v USING (w) GROUP BY 1, 2""")
def build_doc_term(spark, d):
    """Documents by the 100 most frequent words, ties by the word; the vocabulary is broadcast, its size is the matrix's width."""
    terms = table(spark, d, "documents").select("doc_id", tables.words("text").alias("w"))
    top = terms.groupBy("w").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "w").limit(100)
    vocabulary = top.select("w", (F.row_number().over(Window.orderBy(F.desc("n"), "w")) - 1).alias("j"))  # 100 rows
    e = tables.from_triples(terms.join(F.broadcast(vocabulary), "w"), F.col("doc_id"), F.col("j"), F.lit(1.0), 100)
    return e.df.select("i", "j", F.col("v").cast("long").alias("v"))


@query("(SELECT l_returnflag AS f, l_linestatus AS s FROM lineitem WHERE l_quantity > 25 INTERSECT ALL SELECT l_returnflag, l_linestatus FROM lineitem WHERE l_quantity <= 25) EXCEPT ALL SELECT l_returnflag, l_linestatus FROM lineitem WHERE l_quantity = 50")
def set_ops_all(spark, d):
    """Sets with their repetitions."""
    line = table(spark, d, "lineitem")
    side = lambda c: line.where(c).select(F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("s"))
    return side("l_quantity > 25").intersectAll(side("l_quantity <= 25")).exceptAll(side("l_quantity = 50"))


@query(_NORMS.format("", ""))
def mix_udf(spark, d):
    """Mixing as a function of a column keeps the length of every row."""
    mixed = table(spark, d, "embeddings").select(F.col("vec_id").alias("row_id"), fn.mixer(spark, MixingPlan.build(64, 5))("embedding").alias("y"))
    return mixed.select("row_id", whole(fn.vec_dot("y", "y"), 1e6).alias("norm2"))


_ENTRIES = f"SELECT i, j, CAST(v AS BIGINT) AS v FROM ({_PART_SUPP})"


@query("SELECT kind, e.* FROM (" + _ENTRIES + ") AS e, (VALUES ('csv'), ('json'), ('orc')) AS k(kind)")
def matrix_files(spark, d):
    """A matrix written as csv, json and orc, and read again."""
    a = tables.part_supp(spark, d)
    a.df = thin.durable(a.df)
    top, out = f"{shared_folder(spark)}/files-{uuid.uuid4().hex}", None
    for kind in ("csv", "json", "orc"):
        a.df.write.format(kind).save(f"{top}/{kind}")
        back = interop.read_entries(spark, f"{top}/{kind}", kind, a.n).df.select(F.lit(kind).alias("kind"), "i", "j", F.col("v").cast("long").alias("v"))
        out = back if out is None else out.unionByName(back)
    return out


@query("SELECT layout, e.* FROM (" + _ENTRIES + ") AS e, (VALUES ('rows'), ('tiles'), ('entries')) AS k(layout)")
def mllib_round_trip(spark, d):
    """To the stock library's distributed types and back, in each layout."""
    a = tables.part_supp(spark, d)
    a.df = thin.durable(a.df)
    out = None
    for layout, b in (("rows", a.to_sparse_rows()), ("tiles", a.to_tiles(128, 64)), ("entries", a)):
        back = interop.from_mllib(spark, interop.to_mllib(b))
        e = (back if isinstance(back, EntryFrame) else back.to_entries()).df.select(F.lit(layout).alias("layout"), "i", "j", F.col("v").cast("long").alias("v"))
        out = e if out is None else out.unionByName(e)
    return out


# Streams


@query("""SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR""")
def stream_stream_join(spark, d):
    """Clicks and the purchases of the hour after, both streams."""
    s = _stream(spark, d)
    side = lambda kind, name: s.where(F.col("event_type") == kind).select(F.col("user_id").alias(f"u_{name}"), F.col("ts").alias(f"ts_{name}"), F.col("event_id").alias(name))
    joined = streaming.followed(side("click", "click"), side("purchase", "purchase"), "u_click", "u_purchase", "ts_click", "ts_purchase", "1 hour")
    return _ran(joined.select("click", "purchase"), s, "followed", "append")


@query("SELECT strftime(w, '%Y-%m-%d') AS day, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS w FROM events) GROUP BY 1")
def stream_sliding_window(spark, d):
    """Windows of two days, one every day."""
    s = _stream(spark, d)
    out = _ran(streaming.windowed(s, "ts", [F.col("value")], "2 days", "1 day", None), s, "sliding", "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n")


@query("SELECT user_id, CAST(count(*) AS BIGINT) AS rows, CAST(round(sum(1 + value * value)) AS BIGINT) AS s2 FROM events GROUP BY 1")
def stream_r_by_key(spark, d):
    """An R factor a user, kept as the state of a stream; the last update of each counts."""
    s = _stream(spark, d, 2)
    rows = s.select("user_id", F.array(F.lit(1.0), F.col("value")).alias("vec"))
    out = _ran(streaming.running_r_by_key(rows, "user_id", "vec", 2), s, "by_key", "update")
    last = out.groupBy("user_id").agg(F.max_by("sigma", "rows").alias("sigma"), F.max("rows").alias("rows"))
    squares = F.aggregate("sigma", F.lit(0.0), lambda t, x: t + x * x)
    return last.select("user_id", "rows", whole(F.round(squares, 6)).alias("s2"))  # a half stays a half, whatever a factor's last digits


@query("SELECT CAST(20 AS BIGINT) AS late, CAST(count(*) AS BIGINT) AS kept FROM events")
def stream_late_rows(spark, d):
    """Twenty rows that come long after their time are dropped by the watermark, when the stream goes on from its checkpoint."""
    top = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    events = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    late = events.orderBy("ts", "event_id").limit(20).withColumn("ts", F.col("ts") - F.expr("INTERVAL 90 DAYS"))
    for part in (events, late):
        part.write.mode("append").parquet(f"{top}/in")
        s = streaming.event_stream(spark, f"{top}/in", events.schema, 1000)
        out = streaming.run_to_table(streaming.windowed(s, "ts", [F.col("value")], "1 day", None, "1 day"), "frames_late", "update", f"{top}/late")
    kept = out.groupBy("start").agg(F.max("n").alias("n")).agg(F.sum("n").alias("kept"))
    came = spark.read.schema(events.schema).parquet(f"{top}/in").agg(F.count("*").alias("came"))
    return kept.join(F.broadcast(came)).select((F.col("came") - F.col("kept")).alias("late"), "kept")  # one row each


@query("SELECT event_type, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1")
def resumed_stream(spark, d):
    """A stream that stops after half of its files and is started again from its checkpoint counts every row once."""
    top = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    events = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    for half in (F.col("event_id") % 2 == 0, F.col("event_id") % 2 == 1):
        events.where(half).write.mode("append").parquet(f"{top}/in")
        s = streaming.event_stream(spark, f"{top}/in", events.schema, 1000)
        out = streaming.run_to_table(s.groupBy("event_type").agg(F.count("*").alias("n")), "frames_resumed", "update", f"{top}/resumed")
    return out.groupBy("event_type").agg(F.max("n").alias("n"))
