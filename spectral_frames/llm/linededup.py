"""Removal of repeated line runs by a suffix array over line-ID sequences, in DataFrame operations only.

Lines with a word become IDs; a line that occurs once in the corpus is unique at depth one and leaves at once.
Ranks double: the rank of a run of 2h lines comes from sorting the distinct pairs of ranks of its halves, and
pairs met once leave.  Runs step over blank lines and over no others.  A maximal repeated run of ``least_chars`` characters
or more is the union of the windows within it that hold so many characters in the fewest lines from their first line on, or in
the fewest lines up to their last: a line with enough characters of the run before it ends a window of the second kind, any other
lies in the first kind's window at the run's start.  So both kinds are named, at all lines; the least (doc_id, line) of
a window is the copy that stays, and all lines that later copies cover are deleted: the maximal repeated runs, whole.
A blank line between two deleted lines goes with them.

Null or empty text: no lines, kept as it is.  Null doc_id: after all others.  Repeated rows (same doc_id and text):
treated alike, none is a later copy of the other.  Empty table: no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import durable, pick

_KEY = ["doc", "text_key"]


def lines_of(docs: DataFrame) -> DataFrame:
    """(doc, text_key, line, raw, a, b, chars): lines with a word, by their place among those and among all lines; a and b are hashes."""
    rows = pick(docs, "doc_id", "text").select(F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id")).alias("doc"), F.xxhash64("text").alias("text_key"), "text")
    every = F.transform(F.split("text", "\n", -1), lambda s, i: F.struct(i.alias("raw"), F.trim(F.translate(s, "\t\r\x0b\x0c", "    ")).alias("t")))
    rows = rows.select(*_KEY, F.posexplode(F.filter(every, lambda x: x["t"] != "")).alias("line", "x")).select(*_KEY, "line", "x.raw", "x.t")
    return rows.select(*_KEY, "line", "raw", F.xxhash64("t").alias("a"), F.xxhash64(F.lit(5), "t").alias("b"), F.length("t").cast("long").alias("chars"))


def ranked(pairs: DataFrame, *by: str) -> DataFrame:
    """Distinct pairs that occur more than once, with ranks in their order."""
    repeated = pairs.groupBy(*by).agg(F.count("*").alias("_n")).where("_n > 1").select(*by)
    return durable(repeated.orderBy(*by).withColumn("rank", F.monotonically_increasing_id()))


def later_copies(docs: DataFrame, least_chars: int = 40) -> DataFrame:
    """(doc, text_key, gone): the lines of each row that later copies cover, sorted."""
    every = durable(lines_of(docs))
    first = ranked(every, "a", "b")
    now = every.join(first, ["a", "b"]).select(*_KEY, "line", "raw", F.col("rank").alias("r0"), "chars").distinct()
    now = durable(now)
    by_row = Window.partitionBy(*_KEY).orderBy("line")
    # islands of repeated lines with none but blank ones between them
    run = now.withColumn("island", F.col("line") - F.row_number().over(by_row))
    inside = Window.partitionBy(*_KEY, "island").orderBy("line")
    upto = F.sum("chars").over(inside.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    run = run.withColumn("end", upto).withColumn("begin", F.col("end") - F.col("chars"))
    reach = Window.partitionBy(*_KEY, "island").orderBy("begin").rangeBetween(0, least_chars - 1)
    run = run.withColumn("m", F.when(F.max("end").over(reach) - F.col("begin") >= least_chars, F.count("*").over(reach)))
    behind = Window.partitionBy(*_KEY, "island").orderBy("end").rangeBetween(1 - least_chars, 0)
    run = run.withColumn("back", F.when(F.col("end") - F.min("begin").over(behind) >= least_chars, F.count("*").over(behind)))
    run = durable(run.select(*_KEY, "line", "raw", "island", "r0", "m", "back"))
    longest = run.agg(F.max(F.greatest("m", "back"))).first()[0] or 0
    depth, level = 1, 0
    while depth * 2 <= longest:
        ahead = F.lead(f"r{level}", depth).over(inside)
        pairs = run.withColumn("ahead", ahead)
        names = ranked(pairs.where(F.col("ahead").isNotNull()), f"r{level}", "ahead").withColumnRenamed("rank", f"r{level + 1}")
        run = durable(pairs.join(names, [f"r{level}", "ahead"], "left").drop("ahead"))
        depth, level = depth * 2, level + 1
    # a run of m lines is named by the ranks of the two longest powers of two that cover it
    names = F.array(*[F.col(f"r{k}") for k in range(level + 1)])
    run = durable(run.select(*_KEY, "line", "raw", "m", "back", names.alias("names")))
    power = F.floor(F.log2(F.col("m").cast("double")) + 1e-9).cast("int")
    ahead = run.where("m is not null").select(*_KEY, "line", "m", "names")
    # windows up to a line, but for those that are windows from a line too (a single line always is)
    upto = run.where("back > 1").select(*_KEY, (F.col("line") - F.col("back") + 1).cast("int").alias("line"), "back")
    upto = upto.join(run.select(*_KEY, "line", "m", "names"), [*_KEY, "line"]).where("not m <=> back").select(*_KEY, "line", F.col("back").alias("m"), "names")
    begins = ahead.unionByName(upto).withColumn("k", power).withColumn("at", (F.col("line") + F.col("m") - F.pow(F.lit(2.0), F.col("k")).cast("int")).cast("int"))
    head = begins.select(*_KEY, "line", "m", "at", "k", F.get("names", F.col("k")).alias("head")).where("head is not null")
    second = head.where("at <> line").join(run.select(*_KEY, F.col("line").alias("at"), "names"), [*_KEY, "at"])
    columns = [*_KEY, "line", "m", "head"]
    named = head.where("at = line").select(*columns, F.col("head").alias("tail")).unionByName(second.select(*columns, F.get("names", F.col("k")).alias("tail")).where("tail is not null"))
    named = durable(named)
    earliest = durable(named.groupBy("m", "head", "tail").agg(F.min(F.struct("doc", "text_key", "line")).alias("low"), F.count("*").alias("n")).where("n > 1"))
    own = F.struct("doc", "text_key", "line")
    later = named.join(earliest, ["m", "head", "tail"]).where(own > F.col("low"))
    gone = later.select(*_KEY, F.explode(F.sequence(F.col("line"), (F.col("line") + F.col("m") - 1).cast("int"))).alias("line"))
    placed = gone.distinct().join(run.select(*_KEY, "line", "raw"), [*_KEY, "line"])
    gone = placed.groupBy(*_KEY).agg(F.array_sort(F.collect_list(F.struct("line", "raw"))).alias("at"))

    def through(x, i):  # blank lines up to the next deleted line, if no other lies between
        after = F.get("at", i + 1)
        return F.when(after["line"] == x["line"] + 1, F.sequence(x["raw"], after["raw"] - 1)).otherwise(F.array(x["raw"]))

    return durable(gone.select(*_KEY, F.flatten(F.transform("at", through)).alias("gone")))


def _with_gone(rows: DataFrame, gone: DataFrame, doc_id: str, text: str) -> DataFrame:
    g = gone.select(F.col("doc.id").alias("_id"), F.col("text_key").alias("_key"), "gone")
    return rows.join(g, F.col(doc_id).eqNullSafe(F.col("_id")) & (F.xxhash64(text) == F.col("_key")), "left").drop("_id", "_key")


def removed(docs: DataFrame, least_chars: int = 40) -> DataFrame:
    """(doc_id, n_lines, n_removed, n_runs, removed): one row per row of docs; ``removed`` lists line ranges, ends included."""
    gone = later_copies(docs, least_chars)
    rows = pick(docs, "doc_id", "text").select("doc_id", F.xxhash64("text").alias("text_key"), F.coalesce(F.size(F.split("text", "\n", -1)), F.lit(0)).cast("long").alias("n_lines"))
    g = gone.select(F.col("doc.id").alias("_id"), F.col("text_key").alias("_key"), "gone")
    joined = rows.join(g, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("text_key") == F.col("_key")), "left")
    lines = F.coalesce("gone", F.array().cast("array<int>"))
    begins = F.filter(lines, lambda x, i: (i == 0) | (F.get(lines, i - 1) != x - 1))
    ends = F.filter(lines, lambda x, i: (i == F.size(lines) - 1) | (F.get(lines, i + 1) != x + 1))
    spans = F.zip_with(begins, ends, lambda s, e: F.concat_ws("-", s.cast("string"), e.cast("string")))
    return joined.select("doc_id", "n_lines", F.size(lines).cast("long").alias("n_removed"), F.size(begins).cast("long").alias("n_runs"), F.array_join(spans, ",").alias("removed"))


def dedup(docs: DataFrame, least_chars: int = 40) -> DataFrame:
    """docs with the lines of later copies taken out of ``text``; a row that had words and keeps none leaves.  All columns stay."""
    gone = later_copies(docs, least_chars)
    names = docs.columns
    plain = docs.toDF(*[f"_c{i}" for i in range(len(names))])
    text = f"_c{names.index('text')}"
    joined = _with_gone(plain, gone, f"_c{names.index('doc_id')}", text)
    lines = F.split(text, "\n", -1)
    stay = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), "gone")  # by a hash set: linear in the lines
    left = F.array_join(F.transform(stay, lambda i: F.get(lines, i)), "\n")
    joined = joined.where(F.col("gone").isNull() | left.rlike("[^\\x20\\x09-\\x0D]")).withColumn(text, F.when(F.col("gone").isNull(), F.col(text)).otherwise(left))
    return joined.drop("gone").toDF(*names)
