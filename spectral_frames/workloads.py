"""Registered queries: methods, variants, baselines, measures and workloads on the given tables, each beside its SQL.

Singular vectors are never compared raw: what is compared are reconstructions, power sums, ranks and other numbers that do not
depend on signs or on the choice of a basis, rounded far above rounding noise.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import functions as fn
from . import kernels, plans, streaming
from .cost import CostMeter
from .matrix import EntryFrame, RowFrame
from .mixing import MixingPlan
from .operators import accuracy, consumers, gram, low_rank, pca, products, stock, thin, tree_qr
from .session import shared_folder
from .sources import synth, tables
from .sources.tables import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def put(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return put


def frame(spark: SparkSession, schema: str, rows: list[tuple]) -> DataFrame:
    names = [c.split()[0] for c in schema.split(", ")]
    return spark.createDataFrame(pd.DataFrame(rows, columns=names), schema)


def whole(c, scale: float = 1.0):
    """A number as a whole one: rounded and free of -0.0."""
    return F.round(c * scale).cast("long")


def exact_sum(c):
    """A sum that no order of rows changes: eight decimals are added as whole numbers, what they leave of a double (below 1e-8) as doubles."""
    c = F.col(c) if isinstance(c, str) else c
    head = c.cast("decimal(28,8)")
    return F.sum(head).cast("decimal(38,8)") + F.sum(c - head.cast("double")).cast("decimal(28,12)")


METHODS = {"mixed_qr_1": ("mixed_qr", 1), "mixed_qr_2": ("mixed_qr", 2), "gram_1": ("gram", 1), "gram_2": ("gram", 2)}

_E = "e AS (SELECT vec_id, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) - 1 AS j FROM embeddings)"
_POWER_SUMS = f"""WITH {_E}, g AS (SELECT a.j AS i, b.j AS j, sum(a.v * b.v) AS v FROM e a JOIN e b USING (vec_id) GROUP BY 1, 2)
SELECT CAST(round((SELECT sum(v * v) FROM e) * 1000) AS BIGINT) AS s2, CAST(round(sum(v * v) * 1000) AS BIGINT) AS s4 FROM g"""
_RECONSTRUCT = f"WITH {_E} SELECT vec_id AS row_id, CAST(j AS INTEGER) AS j, CAST(round(v * 1000000) AS BIGINT) AS value FROM e"
_TWO = """WITH g AS (SELECT sum(l_quantity * l_quantity) AS a, sum(l_quantity * l_discount * 100) AS b, sum(l_discount * l_discount * 10000) AS c FROM lineitem)
SELECT k, CAST(round(sqrt((a + c) / 2 + s * sqrt((a - c) * (a - c) / 4 + b * b)) * 1000) AS BIGINT) AS sigma FROM g, (VALUES (1, 1), (2, -1)) AS t(k, s)"""


def _two(spark, d) -> RowFrame:
    return tables.from_columns(table(spark, d, "lineitem"), [F.col("l_quantity"), F.col("l_discount") * 100])


def _register_methods() -> None:
    for name, (core, passes) in METHODS.items():

        def power_sums(spark, d, core=core, passes=passes):
            s = thin.thin_svd(tables.emb(spark, d), core, passes).sigma
            return frame(spark, "s2 long, s4 long", [(round((s**2).sum() * 1000), round((s**4).sum() * 1000))])

        def reconstruct(spark, d, core=core, passes=passes):
            rows = thin.thin_svd(tables.emb(spark, d), core, passes).reconstruct()
            v = F.col("v").cast("float").cast("double")  # the input is of floats, far coarser than the error of a reconstruction
            return rows.df.select("row_id", F.posexplode("vec").alias("j", "v")).select("row_id", "j", whole(v, 1e6).alias("value"))

        def two_column(spark, d, core=core, passes=passes):
            s = thin.thin_svd(_two(spark, d), core, passes).sigma
            return frame(spark, "k int, sigma long", [(k + 1, round(x * 1000)) for k, x in enumerate(s)])

        def v_identity(spark, d, core=core, passes=passes):
            v = thin.thin_svd(tables.emb(spark, d), core, passes).v_numpy()
            g = np.round(v.T @ v, 9) + 0.0
            return frame(spark, "i int, j int, value long", [(i, j, int(g[i, j])) for i in range(64) for j in range(64)])

        identity = "SELECT CAST(i AS INTEGER) AS i, CAST(j AS INTEGER) AS j, CAST(i = j AS BIGINT) AS value FROM range(64) AS a(i), range(64) AS b(j)"
        for kind, f, sql in (("power_sums", power_sums, _POWER_SUMS), ("reconstruct", reconstruct, _RECONSTRUCT), ("two_column", two_column, _TWO), ("v_identity", v_identity, identity)):
            query(sql, f"thin_{name}_{kind}")(f)


_register_methods()


@query("SELECT core, CAST(i AS INTEGER) AS i, CAST(j AS INTEGER) AS j, CAST(i = j AS BIGINT) AS value FROM range(64) AS a(i), range(64) AS b(j), (VALUES ('mixed_qr'), ('gram')) AS c(core)")
def thin_2pass_u_identity(spark, d):
    rows = []
    for core in ("mixed_qr", "gram"):
        u = thin.stored(thin.thin_svd(tables.emb(spark, d), core, 2).U)
        g = np.round(gram.gram_matrix(u), 9) + 0.0
        rows += [(core, i, j, int(g[i, j])) for i in range(64) for j in range(64)]
    return frame(spark, "core string, i int, j int, value long", rows)


def _ranks(spark, matrix: Callable, methods, wp: float = 1e-11):
    a = thin.stored(matrix())
    rows = [(name, thin.thin_svd(a, *METHODS[name], working_precision=wp).rank) for name in methods]
    return frame(spark, "method string, rank int", rows)


def _constant(rows: str, names: str) -> str:
    return f"SELECT * FROM (VALUES {rows}) AS t({names})"


@query(_constant("('mixed_qr_1', 4), ('mixed_qr_2', 4), ('gram_1', 2), ('gram_2', 2)", "method, rank"))
def rank_line4_by_core(spark, d):
    """On four columns of very different sizes the Gram cores lose the two small ones at working precision 1e-11."""
    return _ranks(spark, lambda: tables.line4(spark, d), METHODS)


@query(_constant("('mixed_qr_2', 4), ('gram_2', 2)", "method, rank"))
def rank_duplicates(spark, d):
    return _ranks(spark, lambda: tables.line_dup(spark, d), ["mixed_qr_2", "gram_2"])


@query("SELECT method, CAST(count(DISTINCT o_orderpriority) + count(DISTINCT o_orderstatus) - 1 AS INTEGER) AS rank FROM orders, (VALUES ('mixed_qr_1'), ('mixed_qr_2'), ('gram_1'), ('gram_2')) AS t(method) GROUP BY method")
def rank_onehot(spark, d):
    """Two families of indicators that each sum to one: one column is a combination of the others."""
    return _ranks(spark, lambda: tables.order_onehot(spark, d), METHODS)


@query(_constant("('mixed_qr_2', 16)", "method, rank"))
def rank_polynomial(spark, d):
    return _ranks(spark, lambda: tables.line_poly(spark, d), ["mixed_qr_2"], 1e-13)


#: Working precisions midway between neighbours of ten values that fall from 1 to 1e-20.
_CUTS = [5e-4, 3e-6, 1e-7, 1e-10]


@query("""SELECT core, cut, CAST(count(*) AS INTEGER) AS rank FROM (VALUES ('mixed_qr'), ('gram')) AS c(core), (VALUES (1, 5e-4), (2, 3e-6), (3, 1e-7), (4, 1e-10)) AS w(cut, wp), range(10) AS j(j)
WHERE power(10, -20.0 * j / 9) >= CASE WHEN core = 'gram' AND cut > 2 THEN 3e-6 ELSE wp END GROUP BY 1, 2""")
def rank_by_precision(spark, d):
    """The kept rank follows the working precision: directly for mixed QR, by its square root for Gram (whose two finest settings are one here)."""
    a = thin.stored(synth.geo_low(spark, 600, 60, 10, 2))
    rows = []
    for k, cut in enumerate(_CUTS):
        rows.append(("mixed_qr", k + 1, thin.thin_svd(a, "mixed_qr", 2, cut).rank))
        rows.append(("gram", k + 1, thin.thin_svd(a, "gram", 2, _CUTS[min(k, 1)] ** 2).rank))
    return frame(spark, "core string, cut int, rank int", rows)


# Spectra and synthetic matrices


@query("SELECT CAST(j + 1 AS INTEGER) AS k, CAST(round(-20.0 * j / 1999 * 1e6) AS BIGINT) AS micro_log FROM (SELECT DISTINCT o_orderkey % 2000 AS j FROM orders)")
def geo_thin_sigma(spark, d):
    """The geometric spectrum by a thin SVD of spend, every value down to 1e-20.

    Right vectors are unit ones: sums of columns, as with cosines, lose in doubles what is 16 digits below the largest.  k is the column of a value's right vector.
    One task holds the 4000 rows (64 MB) at most that orders are folded into, as each task's Gram matrix has half their size.
    """
    a = thin.stored(tables.spend(spark, d, 4000, 2000, synth.geometric(2000), 1, right="unit"))
    r = thin.thin_svd(a, "gram", 1, working_precision=0.0, wide="keep")
    thin.stored(r.U)
    ks = np.abs(r.v_numpy()).argmax(axis=0) + 1
    return frame(spark, "k int, micro_log long", [(int(k), round(x * 1e6)) for k, x in zip(ks, np.log10(r.sigma).tolist(), strict=True)])


@query("SELECT CAST(j + 1 AS INTEGER) AS k, CAST(round(-20.0 * j / 19 * 1e6) AS BIGINT) AS micro_log FROM (SELECT DISTINCT o_orderkey % 20 AS j FROM orders)")
def geo_low_sigma(spark, d):
    """The spectrum as a table function gives it, measured on columns of spend."""
    fn.register(spark)
    s, lengths = tables.spend_shares(spark, d, 400, 20)
    s.createOrReplaceTempView("frames_spend")
    frame(spark, "k int, x double", [(k + 1, float(x)) for k, x in enumerate(lengths)]).createOrReplaceTempView("frames_lengths")
    return spark.sql("""SELECT g.k, CAST(round(log10(sqrt(sum(power(g.sigma * s / x, 2)))) * 1e6) AS BIGINT) AS micro_log FROM frames_spend
    JOIN frames_lengths AS n ON n.k = i % 20 + 1 JOIN spectrum_geometric(20) AS g ON g.k = n.k GROUP BY g.k""")


_STAIR = """WITH w AS (SELECT kk, CAST(floor(CAST(CAST(j AS FLOAT) * CAST(262144 AS FLOAT) / CAST(kk AS FLOAT) AS DOUBLE) + 0.5) AS BIGINT) AS w FROM (VALUES (10), (20), (2000)) AS t(kk), LATERAL range(kk) AS r(j)),
v AS (SELECT kk, (SELECT sum(CASE WHEN (w >> (3 * b)) & 7 > 0 THEN 1 << b ELSE 0 END) FROM range(7) AS t(b)) AS bits FROM w)
SELECT CAST(kk AS INTEGER) AS size, CAST(round(bits / 63.0 * 1e9) AS BIGINT) AS sigma, count(*) AS multiplicity FROM v GROUP BY 1, 2"""


@query(_STAIR)
def stair_sigma(spark, d):
    """The staircase spectrum as values and multiplicities, three sizes."""
    rows = [(k, round(float(s) * 1e9), int(n)) for k in (10, 20, 2000) for s, n in zip(*np.unique(synth.staircase(k), return_counts=True), strict=True)]
    return frame(spark, "size int, sigma long, multiplicity long", rows)


#: Entries of spend by 4 classes: rows, columns, exponent.
_SPEND_ENTRIES = "WITH " + tables.SPEND_SQL.format("{0}", 4) + """ SELECT i, CAST(c AS INTEGER) AS j, CAST(round(power(10, {2}) * u * CASE WHEN k = 0 THEN sqrt(1.0 / {1}) ELSE sqrt(2.0 / {1}) END
 * cos(pi() * (2 * c + 1) * k / (2 * {1})) * 1e9) AS BIGINT) AS value FROM u, range({1}) AS b(c)"""


@query(_SPEND_ENTRIES.format(40, 12, "-20.0 * k / 3"))
def geo_low_entries(spark, d):
    a = tables.spend(spark, d, 40, 12, synth.geometric(4))
    return a.df.select(F.col("row_id").alias("i"), F.posexplode("vec").alias("j", "v")).select("i", "j", whole(F.col("v"), 1e9).alias("value"))


@query(_SPEND_ENTRIES.format(60, 30, "-1.0 * k"))
def low_rank_full_rank_reconstruct(spark, d):
    """A sketch wider than the true rank gives back the matrix, and fewer vectors than asked for."""
    a = thin.stored(tables.spend(spark, d, 60, 30, 10.0 ** -np.arange(4.0), 2))
    rows = low_rank.low_rank_svd(a, 8, 2, "mixed_qr").reconstruct()
    return rows.df.select(F.col("row_id").alias("i"), F.posexplode("vec").alias("j", "v")).select("i", "j", whole(F.col("v"), 1e9).alias("value"))


# Low rank


@query("SELECT 10 AS l, 5 AS rank, CAST(round(power(10, -20.0 * 5 / 9) * 1e13) AS BIGINT) AS residual, true AS u_orthonormal, true AS v_orthonormal")
def low_rank_mixed_qr_residual(spark, d):
    """The residual is the first singular value that the working precision cuts off."""
    a = thin.stored(synth.geo_low(spark, 1000, 200, 10, 2))
    r = low_rank.low_rank_svd(a, 10, 2, "mixed_qr", working_precision=1e-10)
    r.U = thin.stored(r.U)
    m = accuracy.report(a, r)
    return frame(spark, "l int, rank int, residual long, u_orthonormal boolean, v_orthonormal boolean", [(10, r.rank, round(m.residual * 1e13), m.u_defect < 1e-12, m.v_defect < 1e-12)])


@query("SELECT 10 AS l, 3 AS rank, CAST(round(power(10, -20.0 * 3 / 9) * 1e9) AS BIGINT) AS residual, true AS u_orthonormal, true AS v_orthonormal")
def low_rank_gram_residual(spark, d):
    a = thin.stored(synth.geo_low(spark, 1000, 200, 10, 2))
    r = low_rank.low_rank_svd(a, 10, 2, "gram", working_precision=1e-11)
    r.U = thin.stored(r.U)
    m = accuracy.report(a, r)
    return frame(spark, "l int, rank int, residual long, u_orthonormal boolean, v_orthonormal boolean", [(10, r.rank, round(m.residual * 1e9), m.u_defect < 1e-12, m.v_defect < 1e-12)])


@query("SELECT true AS defect_above_half, true AS residual_small")
def stock_low_rank_defect(spark, d):
    """The stock low-rank call reconstructs well from left vectors that are not orthonormal."""
    a = thin.stored(synth.geo_low(spark, 1000, 200, 20, 2))
    r = stock.stock_low_rank(a, 20)
    r.U = thin.stored(r.U)
    return frame(spark, "defect_above_half boolean, residual_small boolean", [(accuracy.gram_defect(r.U) > 0.5, accuracy.spectral_residual(a, r) < 1e-8)])


@query(_constant("('explicit', true), ('stock', false), ('eigenvalue', false)", "method, orthonormal"))
def normalisation_ablation(spark, d):
    """Left vectors by measured norms, by the stock call, and by eigenvalues."""
    a = thin.stored(synth.geo_low(spark, 1000, 200, 20, 2))
    found = {"explicit": thin.thin_svd(a, "gram", 2), "stock": stock.stock_thin(a, 20), "eigenvalue": thin.thin_svd(a, "gram", 1, normalise="eigenvalue")}
    return frame(spark, "method string, orthonormal boolean", [(k, accuracy.gram_defect(thin.stored(r.U)) < 1e-10) for k, r in found.items()])


@query(_constant("('merge_tree', true), ('stock', false)", "method, orthonormal"))
def stock_tsqr_unstable(spark, d):
    """Without full rank the stock tree QR loses orthogonality; the merge tree's direct factor keeps it."""
    a = thin.stored(synth.geo_low(spark, 400, 40, 10, 2))
    q, _ = tree_qr.q_direct(a, 40)
    stock_q, _ = stock.stock_tsqr(a)
    with np.errstate(all="ignore"):
        bad = float(np.abs(stock_q.T @ stock_q - np.eye(stock_q.shape[1])).max())
    return frame(spark, "method string, orthonormal boolean", [("merge_tree", accuracy.gram_defect(q) < 1e-12), ("stock", bool(bad < 1e-6))])


def _power_iteration(entries: str, n: str, steps: int = 30) -> str:
    """sigma_1 by power iteration on the Gram matrix, one row per step."""
    return f"""WITH RECURSIVE e AS ({entries}), g AS (SELECT a.j AS i, b.j AS j, sum(a.v * b.v) AS v FROM e a JOIN e b USING (i) GROUP BY 1, 2),
f AS (SELECT x.i, y.j, coalesce(g.v, 0) AS v FROM range({n}) AS x(i) CROSS JOIN range({n}) AS y(j) LEFT JOIN g ON g.i = x.i AND g.j = y.j),
m AS (SELECT list(r ORDER BY i) AS m FROM (SELECT i, list(v ORDER BY j) AS r FROM f GROUP BY i)),
p AS (SELECT 0 AS t, list_transform(range({n}), lambda z: 1.0::DOUBLE) AS x, 0.0::DOUBLE AS s
UNION ALL SELECT t + 1, list_transform(y, lambda z: z / sqrt(list_dot_product(y, y))), list_dot_product(y, x) FROM (SELECT t, x, list_transform(m.m, lambda r: list_dot_product(r, x)) AS y FROM p, m WHERE t < {steps}))"""


_PART_SUPP = "SELECT l_partkey AS i, l_suppkey AS j, sum(l_quantity) AS v FROM lineitem GROUP BY 1, 2"
_USER_HOUR = "SELECT user_id AS i, hour(ts) AS j, count(*)::DOUBLE AS v FROM events GROUP BY 1, 2"
_TOP = _power_iteration(_PART_SUPP, "(SELECT max(l_suppkey) + 1 FROM lineitem)") + " SELECT {0} CAST(round(sqrt(s) * 100) AS BIGINT) AS sigma1 FROM p{1} WHERE t = 30"


def _top_sigma(core):
    def f(spark, d):
        a = tables.part_supp(spark, d)
        a.df = thin.durable(a.df)
        l_ = min(20, a.n // 2)
        r = low_rank.low_rank_svd(a, l_, 2, core)
        return frame(spark, "sigma1 long", [(round(r.sigma[0] * 100),)])

    return f


for _core in ("mixed_qr", "gram"):
    query(_TOP.format("", ""), f"low_rank_{_core}_top_sigma")(_top_sigma(_core))


@query(_TOP.format("tracker,", ", (VALUES ('svd'), ('q_only'), ('lu')) AS c(tracker)"))
def tracker_variants_agree(spark, d):
    a = tables.part_supp(spark, d)
    a.df = thin.durable(a.df)
    rows = [(t, round(low_rank.low_rank_svd(a, min(20, a.n // 2), 2, tracker=t).sigma[0] * 100)) for t in ("svd", "q_only", "lu")]
    return frame(spark, "tracker string, sigma1 long", rows)


@query("SELECT true AS agree")
def low_rank_entry_vs_tile(spark, d):
    """Entries and tiles of one matrix give the same leading singular values."""
    a = tables.cust_part(spark, d)
    a.df = thin.durable(a.df)
    l_ = 10
    one = low_rank.low_rank_svd(a, l_, 2).sigma
    tiles = a.to_tiles(256, 256)
    tiles.df = thin.durable(tiles.df)  # six products read it
    two = low_rank.low_rank_svd(tiles, l_, 2).sigma
    return frame(spark, "agree boolean", [(bool(np.allclose(one[:3], two[:3], rtol=1e-9)),)])


@query(_constant("(0, true), (1, true), (2, true)", "iterations, small"))
def range_error_small(spark, d):
    """The range is found with any number of iterations, none included, when the rank is below the sketch's width."""
    a = thin.stored(synth.cosine_matrix(spark, 300, 80, 10.0 ** -np.arange(6.0), 2))
    return frame(spark, "iterations int, small boolean", [(i, bool(accuracy.range_residual(a, low_rank.range_finder(a, 10, i)) < 1e-9)) for i in range(3)])


# Mixing

_NORMS = f"WITH {_E} SELECT {{0}} vec_id AS row_id, CAST(round(sum(v * v) * 1e6) AS BIGINT) AS norm2 FROM e{{1}} GROUP BY ALL"


@query(_NORMS.format("kind,", ", (VALUES ('fourier'), ('gaussian'), ('none')) AS k(kind)"))
def mixing_orthogonal(spark, d):
    a = tables.emb(spark, d)
    out = None
    for kind in ("fourier", "gaussian", "none"):
        plan = MixingPlan.build(64, 3, 2, kind)
        rows = tree_qr.apply_rows(a, plan.forward, plan.width).df.select(F.lit(kind).alias("kind"), "row_id", whole(fn.vec_dot("vec", "vec"), 1e6).alias("norm2"))
        out = rows if out is None else out.unionByName(rows)
    return out


@query(_NORMS.format("rounds,", ", (VALUES (1), (2), (6)) AS k(rounds)"))
def mixing_rounds(spark, d):
    """One round, two, and as many as the logarithm of the width; there and back again."""
    a = tables.emb(spark, d)
    out = None
    for label, rounds in ((1, 1), (2, 2), (6, "log")):
        plan = MixingPlan.build(64, 3, rounds)
        rows = tree_qr.apply_rows(a, lambda x, p=plan: p.inverse(p.forward(x)), 64).df.select(F.lit(label).alias("rounds"), "row_id", whole(fn.vec_dot("vec", "vec"), 1e6).alias("norm2"))
        out = rows if out is None else out.unionByName(rows)
    return out


# Principal components and what is asked of factors

_M6 = "e AS (SELECT o_custkey AS i, (year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS j, sum(o_totalprice) AS v FROM orders GROUP BY 1, 2)"


def _cust_month_rows(spark, d) -> RowFrame:
    return thin.stored(tables.cust_month(spark, d).to_rows())


@query(f"""WITH {_M6}, n AS (SELECT count(DISTINCT i) AS n FROM e), c AS (SELECT j, sum(v) AS s, sum(v * v) AS q FROM e GROUP BY j)
SELECT CAST(round(sum((q - s * s / n) / (n - 1)) / 1e4) AS BIGINT) AS total_variance FROM c, n""")
def pca_explained_total(spark, d):
    p = pca.pca(_cust_month_rows(spark, d))
    return frame(spark, "total_variance long", [(round(p.explained_variance.sum() / 1e4),)])


@query("SELECT CAST(k AS INTEGER) AS k, CAST(0 AS BIGINT) AS mean_score FROM range(64) AS t(k)")
def pca_score_means(spark, d):
    p = pca.pca(tables.emb(spark, d), passes=1, core="gram")
    scores = p.scores().df.select(F.posexplode("vec").alias("k", "v"))
    return scores.groupBy("k").agg(whole(F.avg("v"), 1e6).alias("mean_score"))


@query()
def pca_scree(spark, d):
    p = pca.pca(_cust_month_rows(spark, d))
    rows = frame(spark, "k int, variance double", [(k + 1, float(x)) for k, x in enumerate(p.explained_variance)])
    total = F.sum("variance").over(Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return rows.select("k", "variance", (F.sum("variance").over(Window.orderBy("k")) / total).alias("cumulative"), (F.col("variance") / F.lead("variance").over(Window.orderBy("k"))).alias("gap"))


@query(_power_iteration(_USER_HOUR, "24") + """, scores AS (SELECT i AS user_id, abs(sum(e.v * x[j + 1])) AS score FROM e, (SELECT x FROM p WHERE t = 30) GROUP BY 1)
SELECT user_id FROM scores ORDER BY round(score * 1e6) DESC, user_id LIMIT 10""")
def pca_top_component_users(spark, d):
    """Ten users with the largest scores on the leading direction of hourly activity."""
    a = thin.stored(tables.user_hour(spark, d).to_rows())
    r = thin.thin_svd(a, "mixed_qr", 2)
    scores = r.project(a).df.select(F.col("row_id").alias("user_id"), F.abs(F.col("vec")[0]).alias("score"))
    return scores.orderBy(F.round(F.col("score") * 1e6).desc(), "user_id").limit(10).select("user_id")


_PARTS = "x AS (SELECT l_partkey, sum(l_quantity) AS q, sum(l_discount * 100) AS c FROM lineitem GROUP BY 1), g AS (SELECT sum(q * q) AS a, sum(q * c) AS b, sum(c * c) AS d FROM x)"


def _part_sums(spark, d) -> RowFrame:
    x = table(spark, d, "lineitem").groupBy("l_partkey").agg(F.sum("l_quantity").alias("q"), F.sum(F.col("l_discount") * 100).alias("c"))
    return thin.stored(tables.from_columns(x, ["q", "c"], "l_partkey"))


@query(f"WITH {_PARTS} SELECT l_partkey, CAST(round((d * q * q - 2 * b * q * c + a * c * c) / (a * d - b * b) * 1e9) AS BIGINT) AS leverage FROM x, g")
def leverage_two_column(spark, d):
    u = thin.thin_svd(_part_sums(spark, d), "mixed_qr", 2).U
    return u.df.select(F.col("row_id").alias("l_partkey"), whole(fn.vec_dot("vec", "vec"), 1e9).alias("leverage"))


@query("SELECT 64000000 AS total")
def leverage_total(spark, d):
    u = thin.thin_svd(tables.emb(spark, d), "gram", 2).U
    return u.df.agg(whole(F.sum(fn.vec_dot("vec", "vec")), 1e6).cast("int").alias("total"))


@query("SELECT CAST(round(regr_intercept(l_extendedprice, l_quantity) * 100) AS BIGINT) AS intercept, CAST(round(regr_slope(l_extendedprice, l_quantity) * 100) AS BIGINT) AS slope FROM lineitem")
def least_squares_price(spark, d):
    """Coefficients V diag(1 / sigma) U* b of price on a constant and the quantity."""
    line = table(spark, d, "lineitem")
    a = tables.from_columns(line, [F.lit(1.0), F.col("l_quantity"), F.col("l_extendedprice")])
    fixed = thin.stored(a)
    r = thin.thin_svd(RowFrame(fixed.df.select("row_id", F.slice("vec", 1, 2).alias("vec")), 2), "mixed_qr", 2)
    b = RowFrame(fixed.df.select("row_id", F.slice("vec", 3, 1).alias("vec")), 1)
    ub = products.multiply_t(r.U, b).collect()
    x = (r.v_numpy() / r.sigma) @ ub
    return frame(spark, "intercept long, slope long", [(round(float(x[0, 0]) * 100), round(float(x[1, 0]) * 100))])


@query("SELECT CAST(k AS INTEGER) AS i, CAST(j AS INTEGER) AS j, CAST(k = j AS BIGINT) AS value FROM range(8) AS a(k), range(8) AS b(j)")
def whitened_identity(spark, d):
    """Whitened scores have the identity as covariance."""
    p = pca.pca(tables.emb(spark, d), 8)
    w = thin.scale_columns(p.svd.U, np.full(8, np.sqrt(p.m - 1.0)))
    g = np.round(gram.gram_matrix(w) / (p.m - 1), 9) + 0.0
    return frame(spark, "i int, j int, value long", [(i, j, int(g[i, j])) for i in range(8) for j in range(8)])


@query("SELECT CAST(2 AS BIGINT) AS null_vectors, CAST(0 AS BIGINT) AS product")
def collinear_columns(spark, d):
    """Null vectors of the matrix with a repeated column and a sum of two: the matrix times them is zero."""
    a = thin.stored(tables.line_dup(spark, d))
    v = thin.thin_svd(a, "mixed_qr", 2).v_numpy()
    null = np.linalg.svd(np.eye(6) - v @ v.T)[0][:, : 6 - v.shape[1]]
    return frame(spark, "null_vectors long, product long", [(null.shape[1], round(float(gram.projected_norms(a, null).max()) / 1e3))])


@query()
def outlier_rows(spark, d):
    """Rows that five components reconstruct worst."""
    a = tables.emb(spark, d)
    fixed = thin.stored(a)
    r = pca.pca(fixed, 5)
    mean, v = r.mean, r.svd.v_numpy()
    rest = tree_qr.apply_rows(fixed, lambda x: (x - mean) - (x - mean) @ v @ v.T, 64)
    return rest.df.select(F.col("row_id").alias("vec_id"), fn.vec_norm("vec").alias("error")).orderBy(F.desc("error"), "vec_id").limit(20)


@query()
def similar_in_latent_space(spark, d):
    """The ten nearest documents by cosine, in ten latent dimensions, of every document whose id is divisible by 20, against all."""
    a = tables.doc_term(spark, d)
    a.df = thin.durable(a.df)
    r = low_rank.low_rank_svd(a, 10, 1)
    unit = thin.stored(tree_qr.apply_rows(thin.scale_columns(r.U, r.sigma), lambda x: x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300), r.rank))
    return consumers.nearest_rows(unit, unit.df.where("row_id % 20 = 0"), 10).withColumnsRenamed({"query_id": "query_doc", "row_id": "doc_id", "score": "cosine"})


@query()
def denoised_top_cells(spark, d):
    a = tables.part_supp(spark, d)
    a.df = thin.durable(a.df)
    r = low_rank.low_rank_svd(a, min(5, a.n // 2), 2, "gram")
    return consumers.largest_cells(r, 20).select(F.col("i").alias("part"), F.col("j").cast("int").alias("supplier"), F.col("value").alias("v"))


@query("SELECT true AS agrees")
def condition_number(spark, d):
    s = thin.thin_svd(tables.emb(spark, d)).sigma
    t = np.linalg.svd(tables.emb(spark, d).collect(), compute_uv=False)
    return frame(spark, "agrees boolean", [(bool(abs(s[0] / s[-1] - t[0] / t[-1]) < 1e-9),)])


@query(_constant("('pca', true), ('mllib', true), ('ml', true)", "method, agrees"))
def stock_pca_agrees(spark, d):
    """Principal subspaces of the stock implementations and ours on well-conditioned rows."""
    a = thin.stored(tables.user_hour(spark, d).to_rows())
    x = a.collect()
    v = np.linalg.svd(x - x.mean(axis=0), full_matrices=False)[2][:1].T
    found = {"pca": pca.pca(a, 1).svd.v_numpy(), "mllib": stock.stock_pca(a, 1), "ml": stock.ml_pca(a, 1)}
    return frame(spark, "method string, agrees boolean", [(k, bool(kernels.subspace_gap(v, y) < 1e-5)) for k, y in found.items()])


@query("SELECT true AS independent")
def pivoted_columns(spark, d):
    """A tournament picks four independent columns of six."""
    a = thin.stored(tables.line_dup(spark, d))
    cols = stock.pivoted_tree_qr(a, 4)
    r = tree_qr.r_factor(a)[:, cols]
    r = r / np.linalg.norm(r, axis=0)
    return frame(spark, "independent boolean", [(bool(np.linalg.svd(r, compute_uv=False)[-1] > 1e-6),)])


# Building blocks

_GRAM_LINE = """WITH x AS (SELECT row_number() OVER () AS r, [l_quantity, l_extendedprice, l_discount, l_tax] AS v FROM lineitem)
SELECT CAST(i - 1 AS INTEGER) AS i, CAST(j - 1 AS INTEGER) AS j, CAST(round(sum(v[i] * v[j]) / CASE WHEN i = 2 AND j = 2 THEN 1e4 WHEN i = 2 OR j = 2 THEN 1.0 ELSE 1e-4 END) AS BIGINT) AS value FROM x, range(1, 5) AS a(i), range(1, 5) AS b(j) GROUP BY 1, 2, i, j"""


def _gram_rows(spark, g):
    unit = lambda i, j: 1e4 if i == j == 1 else 1.0 if 1 in (i, j) else 1e-4
    return frame(spark, "i int, j int, value long", [(i, j, round(g[i, j] / unit(i, j))) for i in range(4) for j in range(4)])


@query(_GRAM_LINE)
def gram_catalyst(spark, d):
    return _gram_rows(spark, gram.gram_catalyst(tables.line4(spark, d)))


@query(_GRAM_LINE)
def gram_arrow(spark, d):
    return _gram_rows(spark, gram.gram_arrow(tables.line4(spark, d)))


@query(f"WITH e AS ({_PART_SUPP}) SELECT a.j AS i, b.j AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM e a JOIN e b ON a.i = b.i AND a.j <= b.j GROUP BY 1, 2")
def gram_relational(spark, d):
    return gram.gram_relational(tables.part_supp(spark, d)).withColumn("v", F.col("v").cast("long"))


@query("SELECT CAST(j AS INTEGER) AS j, CAST(round(sqrt(s) * 1e6) AS BIGINT) AS norm FROM (SELECT j, sum(v * v) AS s FROM (WITH " + _E + " SELECT * FROM e) GROUP BY j)")
def column_norms(spark, d):
    return frame(spark, "j int, norm long", [(j, round(x * 1e6)) for j, x in enumerate(gram.column_norms(tables.emb(spark, d)))])


@query(f"WITH {_E} SELECT CAST(j AS INTEGER) AS j, CAST(round(avg(v) * 1e9) AS BIGINT) AS mean FROM e GROUP BY j")
def column_means(spark, d):
    total, _, m = pca.column_sums(tables.emb(spark, d))
    return frame(spark, "j int, mean long", [(j, round(x / m * 1e9)) for j, x in enumerate(total)])


@query("SELECT CAST(round(var_samp(l_quantity) * 1e6) AS BIGINT) AS var_quantity, CAST(round(covar_samp(l_quantity, l_extendedprice) * 10) AS BIGINT) AS cov_quantity_price, CAST(round(corr(l_quantity, l_discount) * 1e9) AS BIGINT) AS corr_discount FROM lineitem")
def covariance(spark, d):
    line = table(spark, d, "lineitem")
    return line.agg(whole(F.var_samp("l_quantity"), 1e6).alias("var_quantity"), whole(F.covar_samp("l_quantity", "l_extendedprice"), 10).alias("cov_quantity_price"), whole(F.corr("l_quantity", "l_discount"), 1e9).alias("corr_discount"))


def _fixed(spark, n: int, r: int = 3) -> RowFrame:
    """A factor of small whole numbers."""
    return RowFrame(spark.range(n).select(F.col("id").alias("row_id"), F.array(*[(F.pmod(F.col("id") * (k + 2) + k, F.lit(7)) - 3).cast("double") for k in range(r)]).alias("vec")), r, n)


_FIXED = "CAST(({0} * (k + 2) + k) % 7 - 3 AS BIGINT)"


@query(f"SELECT l_partkey AS i, CAST(k AS INTEGER) AS k, CAST(sum(l_quantity * {_FIXED.format('l_suppkey')}) AS BIGINT) AS value FROM lineitem, range(3) AS t(k) GROUP BY 1, 2")
def multiply_entries(spark, d):
    a = tables.part_supp(spark, d)
    return products.multiply(a, _fixed(spark, a.n)).df.select(F.col("row_id").alias("i"), F.posexplode("vec").alias("k", "v")).select("i", "k", F.col("v").cast("long").alias("value"))


@query(f"SELECT l_suppkey AS i, CAST(k AS INTEGER) AS k, CAST(sum(l_quantity * {_FIXED.format('l_partkey')}) AS BIGINT) AS value FROM lineitem, range(3) AS t(k) GROUP BY 1, 2")
def multiply_t_entries(spark, d):
    a = tables.part_supp(spark, d)
    return products.multiply_t(a, _fixed(spark, a.height())).df.select(F.col("row_id").alias("i"), F.posexplode("vec").alias("k", "v")).select("i", "k", F.col("v").cast("long").alias("value"))


@query(f"SELECT layout, i, k, value FROM (SELECT l_suppkey AS i, CAST(k AS INTEGER) AS k, CAST(sum(l_quantity * {_FIXED.format('l_partkey')}) AS BIGINT) AS value FROM lineitem, range(3) AS t(k) GROUP BY 1, 2), (VALUES ('rows'), ('tiles')) AS c(layout)")
def multiply_t_layouts(spark, d):
    a = tables.part_supp(spark, d)
    a.df = thin.durable(a.df)
    out = None
    for name, b in (("rows", a.to_sparse_rows()), ("tiles", a.to_tiles(64, 16))):
        got = products.multiply_t(b, _fixed(spark, a.height())).df.select(F.lit(name).alias("layout"), F.col("row_id").alias("i"), F.posexplode("vec").alias("k", "v")).select("layout", "i", "k", F.col("v").cast("long").alias("value"))
        out = got if out is None else out.unionByName(got)
    return out


@query("SELECT l_suppkey AS i, l_partkey AS j, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY 1, 2")
def transpose_entries(spark, d):
    a = tables.part_supp(spark, d)
    return a.to_tiles(128, 32).transpose().to_entries().df.select("i", "j", F.col("v").cast("long").alias("v"))


@query("SELECT 'rows[64] * 64x3)' AS fused, true AS same")
def fused_products(spark, d):
    """Two factors and a scaling become one product; the Gram matrix comes from one scan."""
    rng = np.random.default_rng(0)
    a = tables.emb(spark, d)
    w, s, x = rng.standard_normal((64, 5)), rng.random(5), rng.standard_normal((5, 3))
    e = plans.Source(a).times(w).scaled(s).times(x)
    b = a.collect() @ w * s @ x
    return frame(spark, "fused string, same boolean", [(str(plans.optimise(e)).lstrip("("), bool(np.allclose(e.gram(), b.T @ b)))])


# Ingest

_CENT = "CAST(round(sum({0}) * 100) AS BIGINT)"


def _cents(a: EntryFrame) -> DataFrame:
    return a.df.select("i", "j", whole(F.col("v"), 100).alias("v"))


for _name, _sql in {
    "cust_month": f"SELECT o_custkey AS i, (year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS j, {_CENT.format('o_totalprice')} AS v FROM orders GROUP BY 1, 2",
    "user_hour": "SELECT user_id AS i, hour(ts) AS j, count(*) * 100 AS v FROM events GROUP BY 1, 2",
    "part_supp": f"SELECT l_partkey AS i, l_suppkey AS j, {_CENT.format('l_quantity')} AS v FROM lineitem GROUP BY 1, 2",
    "cust_part": f"SELECT o_custkey AS i, l_partkey AS j, {_CENT.format('l_extendedprice')} AS v FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2",
    "conv_role": """SELECT conv_id AS i, w * 3 + CASE role WHEN 'assistant' THEN 0 WHEN 'user' THEN 1 ELSE 2 END AS j, CAST(sum(CASE WHEN w = 0 THEN 1 ELSE length(text) END) * 100 AS BIGINT) AS v FROM conversations, range(2) AS t(w) GROUP BY 1, 2""",
    "page_shape": "SELECT page_id AS i, j, CAST(len(regexp_extract_all(lower(html), '<' || t || '[ >]')) * 100 AS BIGINT) AS v FROM pages, (VALUES "
    + ", ".join(f"({j}, '{t}')" for j, t in enumerate(tables.TAGS))
    + ") AS t(j, t) WHERE len(regexp_extract_all(lower(html), '<' || t || '[ >]')) > 0",
}.items():
    query(f"SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, v FROM ({_sql})", f"build_{_name}")(lambda spark, d, build=getattr(tables, _name): _cents(build(spark, d)))


@query("""SELECT c_nationkey::BIGINT AS i, s_nationkey::BIGINT AS j, CAST(round(sum(l_extendedprice * (1 - l_discount)) * 10) AS BIGINT) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey
JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2""")
def build_nation_trade(spark, d):
    return tables.nation_trade(spark, d).df.select("i", "j", whole(F.col("v"), 10).alias("v"))


@query("SELECT w, CAST(count(*) AS BIGINT) AS n FROM (SELECT unnest(list_filter(regexp_split_to_array(lower(text), '[^a-zß-ÿ]+'), lambda x: x <> '')) AS w FROM documents) GROUP BY 1 ORDER BY n DESC, w LIMIT 200")
def build_vocabulary(spark, d):
    """The 200 most frequent words, ties by the word: the columns of a document-term matrix that SQL can name."""
    return table(spark, d, "documents").select(tables.words("text").alias("w")).groupBy("w").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "w").limit(200)


@query("SELECT o_orderkey AS row_id, CAST(len(list_distinct([o_orderpriority, o_orderstatus])) AS BIGINT) AS ones FROM orders")
def build_order_onehot(spark, d):
    a = tables.order_onehot(spark, d)
    return a.df.select("row_id", F.aggregate("vec", F.lit(0.0), lambda s, x: s + x).cast("long").alias("ones"))


@query("SELECT CAST(p AS INTEGER) AS j, CAST(round(sum(power(l_quantity / 50, p)) * 1e3) AS BIGINT) AS total FROM lineitem, range(16) AS t(p) GROUP BY p")
def build_line_poly(spark, d):
    a = tables.line_poly(spark, d)
    return a.df.select(F.posexplode("vec").alias("j", "v")).groupBy("j").agg(whole(F.sum("v"), 1e3).alias("total"))


@query("SELECT user_id, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS k_sum FROM events GROUP BY 1")
def json_feature_matrix(spark, d):
    return table(spark, d, "events").select("user_id", F.from_json("props", "k long")["k"].alias("k")).groupBy("user_id").agg(F.sum("k").alias("k_sum"))


@query("""SELECT e.event_id, max(o.event_id) AS previous FROM events e JOIN events o ON o.user_id = e.user_id AND o.event_type = 'purchase' AND e.event_type = 'click' AND o.ts < e.ts
AND NOT EXISTS (SELECT 1 FROM events x WHERE x.user_id = e.user_id AND x.event_type = 'purchase' AND x.ts < e.ts AND x.ts > o.ts) GROUP BY 1""")
def asof_event_feature(spark, d):
    """The last purchase before each click of the same user: one sort per user, no pairs."""
    events = table(spark, d, "events").where(F.col("event_type").isin("click", "purchase"))
    mark = F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))
    by = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1)).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return events.withColumn("p", F.max(mark).over(by)).where("event_type = 'click' AND p IS NOT NULL").select("event_id", F.col("p.event_id").alias("previous"))


@query("SELECT CAST(week AS INTEGER) AS week, CAST(count(*) AS BIGINT) AS n FROM events, range(5) AS t(week) WHERE ts >= TIMESTAMP '2024-01-01' + to_days(CAST(week * 7 AS INTEGER)) AND ts < TIMESTAMP '2024-01-01' + to_days(CAST(week * 7 + 7 AS INTEGER)) GROUP BY 1")
def interval_event_window(spark, d):
    """Events in half-open intervals, by a join with a handful of broadcast intervals."""
    start = F.lit("2024-01-01").cast("timestamp_ntz")
    weeks = spark.range(5).select(F.col("id").cast("int").alias("week"), (start + F.make_interval(days=(F.col("id") * 7).cast("int"))).alias("a"), (start + F.make_interval(days=(F.col("id") * 7 + 7).cast("int"))).alias("b"))
    e = table(spark, d, "events").select(F.col("ts").cast("timestamp_ntz").alias("ts"))
    return e.join(F.broadcast(weeks), (F.col("ts") >= F.col("a")) & (F.col("ts") < F.col("b"))).groupBy("week").agg(F.count("*").alias("n"))


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def anti_join_customers(spark, d):
    return table(spark, d, "customer").join(table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti").select("c_custkey")


@query("SELECT doc_id, n_chars FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def semi_join_labelled(spark, d):
    return table(spark, d, "documents").select("doc_id", "n_chars").join(table(spark, d, "labels").select("doc_id"), "doc_id", "left_semi")


@query("SELECT coalesce(a.k, b.k) AS k, CAST(coalesce(a.n, 0) - coalesce(b.n, 0) AS BIGINT) AS difference FROM (SELECT l_partkey AS k, count(*) AS n FROM lineitem WHERE l_returnflag = 'R' GROUP BY 1) a FULL JOIN (SELECT l_partkey AS k, count(*) AS n FROM lineitem WHERE l_returnflag = 'A' GROUP BY 1) b ON a.k = b.k")
def full_join_difference(spark, d):
    """A - B of two sparse vectors, absent entries zero."""
    line = table(spark, d, "lineitem")
    side = lambda f, n: line.where(F.col("l_returnflag") == f).groupBy(F.col("l_partkey").alias("k")).agg(F.count("*").alias(n))
    return side("R", "a").join(side("A", "b"), "k", "full").select("k", (F.coalesce("a", F.lit(0)) - F.coalesce("b", F.lit(0))).cast("long").alias("difference"))


@query("SELECT o_orderpriority, o_orderstatus, CAST(round(sum(o_totalprice) * 100) AS BIGINT) AS spend, count(*) AS n FROM orders GROUP BY CUBE (o_orderpriority, o_orderstatus)")
def cube_of_spend(spark, d):
    return table(spark, d, "orders").cube("o_orderpriority", "o_orderstatus").agg(whole(exact_sum("o_totalprice"), 100).alias("spend"), F.count("*").alias("n"))


@query("SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS mo, count(*) AS n FROM orders GROUP BY ROLLUP (year(o_orderdate), month(o_orderdate))")
def rollup_dates(spark, d):
    return table(spark, d, "orders").select(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("mo")).rollup("y", "mo").agg(F.count("*").alias("n"))


@query("SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_type), ())")
def grouping_sets_parts(spark, d):
    table(spark, d, "part").createOrReplaceTempView("frames_part")
    return spark.sql("SELECT p_brand, p_type, count(*) AS n FROM frames_part GROUP BY GROUPING SETS ((p_brand), (p_type), ())")


@query("SELECT vec_id, label, CAST(rank() OVER (PARTITION BY label ORDER BY embedding[1] DESC, vec_id) AS INTEGER) AS place, CAST(ntile(4) OVER (PARTITION BY label ORDER BY embedding[1] DESC, vec_id) AS INTEGER) AS quarter FROM embeddings")
def window_rank_in_label(spark, d):
    by = Window.partitionBy("label").orderBy(F.col("embedding")[0].desc(), "vec_id")
    return table(spark, d, "embeddings").select("vec_id", "label", F.rank().over(by).alias("place"), F.ntile(4).over(by).alias("quarter"))


@query("SELECT event_id, CAST(round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) * 1000) AS BIGINT) AS recent, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events")
def window_running_value(spark, d):
    by = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, d, "events").select("event_id", whole(F.sum("value").over(by.rowsBetween(-4, 0)), 1000).alias("recent"), F.lag("event_id").over(by).alias("before"))


@query("(SELECT l_partkey AS k FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A') EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity > 49")
def set_ops_columns(spark, d):
    line = table(spark, d, "lineitem")
    keys = lambda c: line.where(c).select(F.col("l_partkey").alias("k"))
    return keys("l_returnflag = 'R'").intersect(keys("l_returnflag = 'A'")).subtract(keys("l_quantity > 49"))


@query("SELECT DISTINCT CAST(l_quantity AS BIGINT) AS q, CAST(round(l_discount * 100) AS BIGINT) AS c FROM lineitem")
def dedup_rows(spark, d):
    return table(spark, d, "lineitem").select(F.col("l_quantity").cast("long").alias("q"), whole(F.col("l_discount"), 100).alias("c")).dropDuplicates()


@query()
def topk_loadings(spark, d):
    """The three columns of largest loading of each of five components."""
    v = thin.thin_svd(tables.emb(spark, d)).truncate(5).v_df()
    by = Window.partitionBy("k").orderBy(F.abs("v").desc(), "j")
    return v.select("j", F.posexplode("vec").alias("k", "v")).withColumn("place", F.row_number().over(by)).where("place <= 3").select("k", "place", "j")


# Functions


@query(f"""WITH {_E}, l AS (SELECT e.*, label FROM e JOIN embeddings USING (vec_id)), g AS (SELECT a.label, a.j AS i, b.j AS j, sum(a.v * b.v) AS v FROM l a JOIN l b ON a.vec_id = b.vec_id GROUP BY 1, 2, 3)
SELECT label, CAST(round(sum(v * v) * 1000) AS BIGINT) AS s4 FROM g GROUP BY 1""")
def svd_by_label(spark, d):
    return fn.svd_by_group(table(spark, d, "embeddings"), "label", "embedding").groupBy("label").agg(whole(F.sum(F.pow("sigma", F.lit(4.0))), 1000).alias("s4"))


@query("SELECT CAST(round(sum(l_quantity * l_quantity + l_discount * l_discount * 10000)) AS BIGINT) AS s2 FROM lineitem")
def svd_udtf(spark, d):
    fn.register(spark)
    table(spark, d, "lineitem").select("l_quantity", (F.col("l_discount") * 100).alias("c")).createOrReplaceTempView("frames_two")
    return spark.sql("SELECT CAST(round(sum(sigma * sigma)) AS BIGINT) AS s2 FROM spectral_singular_values(TABLE(SELECT l_quantity, c FROM frames_two))")


@query(f"WITH {_E} SELECT label, CAST(round(sum(v * v) * 1000) AS BIGINT) AS trace FROM e JOIN embeddings USING (vec_id) GROUP BY 1")
def gram_udaf(spark, d):
    g = fn.gram_by_group(table(spark, d, "embeddings"), "label", "embedding").withColumnRenamed("gram", "g")
    at, diagonal = 0, []
    for i in range(64):
        diagonal.append(at)
        at += 64 - i
    return g.select("label", whole(sum((F.col("g")[k] for k in diagonal), F.lit(0.0)), 1000).alias("trace"))


@query(_NORMS.format("", ""))
def project_udf(spark, d):
    """Scores under an orthogonal V keep the length of every row."""
    v = thin.thin_svd(tables.emb(spark, d), "gram", 2).v_numpy()
    rows = table(spark, d, "embeddings").select(F.col("vec_id").alias("row_id"), fn.projector(spark, v)("embedding").alias("y"))
    return rows.select("row_id", whole(fn.vec_dot("y", "y"), 1e6).alias("norm2"))


# Streaming: the same rows as a stream, until nothing is left


def _stream(spark, d, files: int = 4) -> DataFrame:
    """The events as files in the order of time, read as a stream."""
    top = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    events = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    dealt = thin.durable(events.repartitionByRange(files, "ts").withColumn("part", F.spark_partition_id()))
    for k in range(files):  # one file after the other, so that the stream meets them in the order of time
        dealt.where(F.col("part") == k).drop("part").write.mode("append").parquet(f"{top}/in")
    out = streaming.event_stream(spark, f"{top}/in", events.schema)
    out.frames_top = top
    return out


def _ran(stream: DataFrame, source: DataFrame, name: str, mode: str) -> DataFrame:
    return streaming.run_to_table(stream, f"frames_{name}", mode, f"{source.frames_top}/{name}")


@query("SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n, CAST(round(sum(value) * 100) AS BIGINT) AS s0, CAST(round(sum(value * value)) AS BIGINT) AS s0_0 FROM events GROUP BY 1")
def stream_gram_daily(spark, d):
    s = _stream(spark, d)
    out = _ran(streaming.windowed(s, "ts", [F.col("value")], late=None), s, "daily", "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n", whole(F.col("s0"), 100).alias("s0"), whole(F.col("s0_0")).alias("s0_0"))


@query("""WITH m AS (SELECT user_id, ts, value, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT user_id, value, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM m)
SELECT user_id, count(DISTINCT s) AS sessions, count(*) AS n FROM s GROUP BY 1""")
def stream_session_moments(spark, d):
    s = _stream(spark, d)
    out = _ran(streaming.sessions(s, "ts", "user_id", [F.col("value")]), s, "sessions", "complete")
    return out.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))


@query("SELECT count(*) AS n, CAST(round(sum(1 + value * value)) AS BIGINT) AS s2 FROM events")
def stream_r_factor(spark, d):
    """A running R factor over micro-batches: its squared singular values sum to the squares of all rows."""
    s = _stream(spark, d)
    state = streaming.RunningR(2)
    rows = s.select(F.col("event_id").alias("row_id"), F.array(F.lit(1.0), F.col("value")).alias("vec"))
    q = rows.writeStream.foreachBatch(state).option("checkpointLocation", f"{s.frames_top}/r").trigger(availableNow=True).start()
    q.awaitTermination()
    return frame(spark, "n long, s2 long", [(table(spark, d, "events").count(), round(float((state.sigma**2).sum())))])


@query("SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_dedup(spark, d):
    """Every event sent twice, counted once."""
    s = _stream(spark, d)
    twice = s.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    out = _ran(streaming.deduplicated(twice, "ts", "event_id", "40 days"), s, "dedup", "append")
    return out.groupBy("event_type").agg(F.count("*").alias("n"))


@query("SELECT event_type, CAST(round(sum(v) * 100) AS BIGINT) AS total FROM (SELECT event_type, value * 2 + 1 AS v FROM events) GROUP BY 1")
def stream_scored(spark, d):
    """A stream scored with a saved factor."""
    s = _stream(spark, d)
    score = fn.projector(spark, np.array([[2.0], [1.0]]))
    out = _ran(s.select("event_type", score(F.array(F.col("value"), F.lit(1.0)))[0].alias("v")), s, "scored", "append")
    return out.groupBy("event_type").agg(whole(F.sum("v"), 100).alias("total"))


# Cost, invariance and sweeps


@query("SELECT CAST(p AS INTEGER) AS partitions, true AS same FROM (VALUES (1), (4), (16)) AS t(p)")
def partition_invariance(spark, d):
    """Accuracy and values don't depend on how rows are dealt out."""
    a = tables.emb(spark, d)
    base = thin.thin_svd(a).sigma
    rows = []
    for p in (1, 4, 16):
        r = thin.thin_svd(RowFrame(a.df.repartition(p), 64))
        ok = np.allclose(r.sigma, base, rtol=1e-12) and accuracy.gram_defect(thin.stored(r.U)) < 1e-12
        rows.append((p, bool(ok)))
    return frame(spark, "partitions int, same boolean", rows)


@query()
def cost_meter_report(spark, d):
    with CostMeter(spark, "gram_1 on line4") as m:
        thin.thin_svd(tables.line4(spark, d), "gram", 1)
    return m.report.df(spark)


@query()
def thin_accuracy_table(spark, d):
    """Residual and defects of the four thin methods and the stock call on a geometric spectrum; W1-W3 at a small size."""
    rows = []
    for kind, a in (("geometric", synth.geo_thin(spark, 2000, 64, 4)), ("staircase", synth.stair(spark, 2000, 64, 64, 4))):
        a = thin.stored(a)
        for name, (core, passes) in METHODS.items():
            with CostMeter(spark, name) as m:
                r = thin.thin_svd(a, core, passes, q_form="indirect")
                r.U = thin.stored(r.U)
            x = accuracy.report(a, r)
            rows.append((kind, name, x.rank, x.residual, x.u_defect, x.v_defect, m.report.cpu_s, m.report.elapsed_s))
        r = stock.stock_thin(a)
        r.U = thin.stored(r.U)
        x = accuracy.report(a, r)
        rows.append((kind, "stock", x.rank, x.residual, x.u_defect, x.v_defect, None, None))
    return frame(spark, "spectrum string, method string, rank int, residual double, u_defect double, v_defect double, cpu_s double, elapsed_s double", rows)


@query()
def low_rank_accuracy_table(spark, d):
    """W4-W8 at a small size: both cores and the stock call, l = 20 and 10, two iterations, both spectra."""
    rows = []
    for kind, make in (("geometric", synth.geometric), ("staircase", synth.staircase)):
        for l_ in (20, 10):
            a = thin.stored(tables.spend(spark, d, 1000, 200, make(l_), 4))
            for core in ("mixed_qr", "gram"):
                r = low_rank.low_rank_svd(a, l_, 2, core)
                r.U = thin.stored(r.U)
                x = accuracy.report(a, r)
                rows.append((kind, l_, core, x.rank, x.residual, x.u_defect, x.v_defect))
            r = stock.stock_low_rank(a, l_)
            r.U = thin.stored(r.U)
            x = accuracy.report(a, r)
            rows.append((kind, l_, "stock", x.rank, x.residual, x.u_defect, x.v_defect))
    return frame(spark, "spectrum string, l int, method string, rank int, residual double, u_defect double, v_defect double", rows)


@query()
def cost_scaling(spark, d):
    """Elapsed seconds of a thin SVD, its left vectors written, against the number of rows, with the exponent."""
    rows = []
    for m in (20_000, 80_000, 320_000):
        a = thin.stored(tables.spend(spark, d, m, 32, synth.geometric(32), 8))
        m = a.height()  # a small table has fewer rows
        for core in ("gram", "mixed_qr"):
            if core not in {r[0] for r in rows}:
                thin.stored(thin.thin_svd(a, core, 1).U)  # starts workers and loads code, which is not counted
            with CostMeter(spark) as c:
                thin.stored(thin.thin_svd(a, core, 1).U)
            rows.append((core, float(m), c.report.cpu_s, c.report.elapsed_s))
    found = frame(spark, "core string, m double, cpu_s double, elapsed_s double", rows)
    return found.groupBy("core").agg(F.regr_slope(F.log("cpu_s"), F.log("m")).alias("cpu_exponent"), F.regr_slope(F.log("elapsed_s"), F.log("m")).alias("elapsed_exponent"))


@query()
def ablation_table(spark, d):
    """Mixing kinds and rounds, forms of Q and trackers on a hard spectrum: rank and orthonormality.

    Rows with a tracker are low-rank SVDs (l = 40, or as much as few rows allow, two iterations) whose subspace it follows, so that the sketch reaches below the working precision.
    """
    a = thin.stored(tables.spend(spark, d, 1500, 48, synth.geometric(48), 4))
    rows = []
    for kind, rounds in (("fourier", 1), ("fourier", 2), ("fourier", "log"), ("gaussian", 2), ("none", 2)):
        for form in ("direct", "indirect"):
            for passes in (1, 2):
                r = thin.thin_svd(a, "mixed_qr", passes, mixing=kind, rounds=rounds, q_form=form)
                rows.append((kind, str(rounds), form, passes, r.rank, accuracy.gram_defect(thin.stored(r.U)), None))
    l_ = min(40, a.height() - 1)
    for tracker in ("svd", "q_only", "lu") if l_ > 0 else ():
        r = low_rank.low_rank_svd(a, l_, 2, "mixed_qr", tracker=tracker)
        rows.append(("fourier", "2", "indirect", 2, r.rank, accuracy.gram_defect(thin.stored(r.U)), tracker))
    return frame(spark, "mixing string, rounds string, q_form string, passes int, rank int, u_defect double, tracker string", rows)


def flagship(spark, d) -> DataFrame:
    """Singular values of the embeddings and the share of the squares that the first k hold."""
    r = thin.thin_svd(tables.emb(spark, d), "mixed_qr", 2)
    share = np.cumsum(r.sigma**2) / (r.sigma**2).sum()
    return frame(spark, "k int, sigma double, share double", [(k + 1, float(s), float(x)) for k, (s, x) in enumerate(zip(r.sigma, share, strict=True))])


from . import experiments, relational  # noqa: E402, F401  (they register more queries)
