"""Mixing sources to target weights by Pareto order sampling, in DataFrame operations only.

Every source gets a target in words: a share of the budget by weight, at most ``most_copies`` times its size, the
excess shared out again.  Within a source, strata of documents (by length) get expected copies e <= most_copies in
proportion to their grade; floor(e) copies are certain and the fraction p = e - floor(e) is an inclusion
probability.  Documents are ranked by the odds of a uniform hash over the odds of p, and the first ones are
taken until their words come nearest to what the certain copies leave of the target: a sample of fixed size in words.

The place of the cut is found by radix descent over 48-bit ranks: four grouped sums, pre-aggregated before
their shuffle, of at most 4096 rows a source each.  A row's copies then follow from its own hash and its source's few numbers,
so texts are never shuffled.

Null text: size 0.  Null source: a source of its own, last.  Null doc_id: hashed as null.  Repeated rows (same
doc_id, source and size) share a rank and are taken or left together.  Empty table: no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_CLASS, durable, pick, same, small_join

#: Bits of a rank, and bits that one descent step fixes.
RANK_BITS, STEP_BITS = 48, 12


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_CLASS)), F.lit(0)).cast("long")


def filled(strata: DataFrame, group: list[str], total: Column, cap: Column, weight: Column) -> DataFrame:
    """Adds ``fill``: each row gets min(cap, level * weight), the level of a group such that they sum to its total (or all caps)."""
    rows = strata.select("*", cap.cast("double").alias("_cap"), weight.cast("double").alias("_weight"), total.cast("double").alias("_total"))
    by = Window.partitionBy(*group)
    steep = by.orderBy(F.try_divide(F.col("_cap"), F.col("_weight")), *[c for c in strata.columns if c not in group])
    done = F.coalesce(F.sum("_cap").over(steep.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    left = F.sum("_weight").over(steep.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    rows = rows.withColumn("_level", F.try_divide(F.col("_total") - done, left))
    # rows are ordered by the level at which they are full: the first that stays below its own sets the level
    level = F.min(F.when(F.col("_level") <= F.try_divide(F.col("_cap"), F.col("_weight")), F.struct(F.try_divide(F.col("_cap"), F.col("_weight")), F.col("_level")))).over(by)
    fill = F.coalesce(F.least(F.col("_cap"), level.getField("_level") * F.col("_weight")), F.col("_cap"))
    return rows.withColumn("fill", F.greatest(F.lit(0.0), fill)).drop("_cap", "_weight", "_total", "_level")


def targets(sizes: DataFrame, weights: tuple = (3, 1, 2), budget: float = 1.5, most_copies: int = 2) -> DataFrame:
    """(source, source_size, target) of ``sizes(source, size)``: one row per source."""
    sources = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = Window.partitionBy("_all").orderBy(F.col("source").asc_nulls_last())
    turn = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int"))
    rows = sources.withColumn("_all", F.lit(1)).withColumn("_w", turn).withColumn("_sum", F.sum("source_size").over(Window.partitionBy("_all")))
    rows = filled(rows, ["_all"], F.col("_sum") * budget, F.col("source_size") * most_copies, F.col("_w"))
    return rows.select("source", "source_size", F.col("fill").alias("target"))


def grade_by_size(size: Column) -> Column:
    """Short documents are wanted half as much as others."""
    return F.when(size < 50, 0.5).otherwise(1.0)


def rank_code(p: Column, seed: int, *key: Column) -> Column:
    """Pareto rank of a row as a whole number below 2**48: q / (1 + q) for q = odds(u) / odds(p)."""
    u = (F.xxhash64(*key, F.lit(seed)).bitwiseAND(F.lit((1 << 52) - 1)) + F.lit(0.5)) / float(1 << 52)
    v = u * (1 - p) / (u * (1 - p) + (1 - u) * p)
    return F.least(F.floor(v * float(1 << RANK_BITS)), F.lit((1 << RANK_BITS) - 1))


def plan(sizes: DataFrame, weights=(3, 1, 2), budget=1.5, most_copies=2, seed=17, grade=grade_by_size) -> tuple[DataFrame, int]:
    """(source, grade, source_size, target, whole, p, cut) by stratum, and how many strata there are.

    ``sizes`` holds doc_id, source and size.  A row takes ``whole`` copies, and one more if its rank is at most ``cut``.
    """
    rows = sizes.withColumn("grade", grade(F.col("size")))
    aims = durable(targets(rows, weights, budget, most_copies))
    strata = rows.groupBy("source", "grade").agg(F.sum("size").alias("words"))
    strata = strata.join(aims.withColumnRenamed("source", "_s"), same(F.col("source"), F.col("_s"))).drop("_s")
    strata = filled(strata, ["source"], F.col("target"), F.col("words") * most_copies, F.col("grade") * F.col("words"))
    copies = F.round(F.when(F.col("words") > 0, F.col("fill") / F.col("words")).otherwise(0.0), 12)
    strata = durable(strata.withColumn("_e", copies).withColumn("whole", F.floor("_e").cast("int")).withColumn("p", F.col("_e") - F.col("whole")))
    n = strata.count()
    rest = strata.groupBy("source").agg((F.first("target") - F.sum(F.col("whole") * F.col("words"))).alias("rest"))
    ranked = small_join(rows, strata.select("source", "grade", "p"), ["source", "grade"], rows=n).where("p > 0 and size > 0")
    ranked = durable(ranked.select("source", "size", rank_code(F.col("p"), seed, F.col("doc_id"), F.col("size")).alias("code")).groupBy("source", "code").agg(F.sum("size").alias("size")))
    state = rest.where("rest > 0").select("source", "rest", F.lit(0).cast("long").alias("prefix"), F.lit(0).cast("long").alias("base"), F.lit(0).cast("long").alias("words"))
    for step in range(RANK_BITS // STEP_BITS):
        shift = RANK_BITS - STEP_BITS * (step + 1)
        open_ = small_join(ranked, state.select("source", "prefix", "base", "rest"), ["source"], rows=n)
        open_ = open_.where(F.shiftright("code", shift + STEP_BITS) == F.col("prefix"))
        sums = open_.groupBy("source", "rest", "base", F.shiftright("code", shift).alias("bucket")).agg(F.sum("size").alias("words"))
        upto = F.sum("words").over(Window.partitionBy("source").orderBy("bucket"))
        sums = sums.withColumn("upto", F.col("base") + upto)
        at = F.coalesce(F.min(F.when(F.col("upto") >= F.col("rest"), F.struct("bucket", "upto", "words"))), F.max(F.struct("bucket", "upto", "words")))
        state = durable(sums.groupBy("source", "rest").agg(at.alias("at")).select("source", "rest", F.col("at.bucket").alias("prefix"), (F.col("at.upto") - F.col("at.words")).alias("base"), F.col("at.words").alias("words")))
    over, under = F.col("base") + F.col("words") - F.col("rest"), F.col("rest") - F.col("base")
    cuts = state.select(F.col("source").alias("_s"), F.when(over <= under, F.col("prefix")).otherwise(F.col("prefix") - 1).alias("cut"))
    made = strata.join(cuts, same(F.col("source"), F.col("_s")), "left").drop("_s")
    return durable(made.select("source", "grade", "source_size", "target", "whole", "p", F.coalesce("cut", F.lit(-1).cast("long")).alias("cut"))), n


def with_copies(sizes: DataFrame, made: DataFrame, n: int, seed: int = 17, grade=grade_by_size) -> DataFrame:
    """``sizes`` (any columns besides doc_id, source, size) with source_size, target and copies."""
    rows = small_join(sizes.withColumn("grade", grade(F.col("size"))), made, ["source", "grade"], rows=n)
    drawn = (F.col("p") > 0) & (F.col("size") > 0)
    code = F.when(drawn, rank_code(F.col("p"), seed, F.col("doc_id"), F.col("size")))
    return rows.withColumn("copies", F.col("whole") + F.coalesce((code <= F.col("cut")).cast("int"), F.lit(0))).drop("grade", "whole", "p", "cut")


def mix_sizes(docs: DataFrame, **options) -> DataFrame:
    """(doc_id, size, source_size, target, copies): one row per row of docs."""
    sizes = durable(pick(docs, "doc_id", "source", "text").select("doc_id", "source", n_words(F.col("text")).alias("size")))
    made, n = plan(sizes, **options)
    return with_copies(sizes, made, n, options.get("seed", 17), options.get("grade", grade_by_size))


def mix(docs: DataFrame, **options) -> DataFrame:
    """docs with each row as often as the mix takes it, all columns kept; documents without a word are left out."""
    sizes = durable(pick(docs, "doc_id", "source", "text").select("doc_id", "source", n_words(F.col("text")).alias("size")))
    made, n = plan(sizes, **options)
    names = docs.columns
    plain = docs.toDF(*[f"_c{i}" for i in range(len(names))])
    col = lambda c: F.col(f"_c{names.index(c)}")
    rows = plain.select("*", col("doc_id").alias("doc_id"), col("source").alias("source"), n_words(col("text")).alias("size"))
    taken = with_copies(rows, made, n, options.get("seed", 17), options.get("grade", grade_by_size)).where("copies > 0")
    return taken.withColumn("_i", F.explode(F.sequence(F.lit(1), F.col("copies")))).select(*plain.columns).toDF(*names)
