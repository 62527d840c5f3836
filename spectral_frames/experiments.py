"""Registered experiments on generated matrices: what the known spectrum says each method keeps and leaves, over sizes, layouts and partitions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from . import serial
from .cost import CostMeter
from .matrix import RowFrame
from .operators import accuracy, low_rank, stock, thin
from .sources import synth, tables
from .workloads import _E, _SPEND_ENTRIES, _TWO, METHODS, _two, frame, query, whole

#: Working precisions that lie well inside a gap of the spectrum: ranks and residuals follow from it whatever the seed.
_CASES = [("mixed_qr", 10, 1e-10), ("gram", 10, 1e-11), ("gram", 20, 1e-11)]
_KEPT = """SELECT {0} core, l, CAST(count(*) FILTER (v >= cut) AS INTEGER) AS rank, CAST(round(-100 * log10(max(v) FILTER (v < cut))) AS BIGINT) AS residual, true AS orthonormal
FROM (SELECT core, l, cut, power(10, -20.0 * j / (l - 1)) AS v FROM (VALUES ('mixed_qr', 10, 1e-10), ('gram', 10, sqrt(1e-11)), ('gram', 20, sqrt(1e-11))) AS c(core, l, cut), LATERAL range(l) AS r(j)){1} GROUP BY ALL"""
_SCHEMA = "core string, l int, rank int, residual long, orthonormal boolean"


def _measured(a, core: str, l_: int, wp: float) -> tuple:
    """Rank, hundredths of digits of the residual, and whether both factors are orthonormal."""
    r = low_rank.low_rank_svd(a, l_, 2, core, wp)
    r.U = thin.stored(r.U)
    x = accuracy.report(a, r, iterations=6)  # the next value is at least ten times smaller
    return core, l_, x.rank, round(-100 * np.log10(x.residual)), bool(x.u_defect < 1e-12 and x.v_defect < 1e-12)


@query(_KEPT.format("", ""))
def low_rank_square_tiles(spark, d):
    """Square and by tiles, where a full SVD is out of reach for large sizes: l = 10 and 20, two iterations."""
    rows = []
    for core, l_, wp in _CASES:
        a = synth.cosine_tiles(spark, 700, 700, synth.geometric(l_), 256, 256, 4)
        a.df = thin.durable(a.df)
        rows.append(_measured(a, core, l_, wp))
    return frame(spark, _SCHEMA, rows)


@query(_KEPT.format("", ""))
def low_rank_square_entries(spark, d):
    """The same by entries, whose residual is measured without a dense row."""
    rows = []
    for core, l_, wp in _CASES:
        a = synth.cosine_tiles(spark, 160, 160, synth.geometric(l_), 64, 64, 2).to_entries()
        a.df = thin.durable(a.df)
        rows.append(_measured(a, core, l_, wp))
    return frame(spark, _SCHEMA, rows)


@query(_KEPT.format("m,", ", (VALUES (400), (1600), (6400)) AS s(m)"))
def low_rank_by_height(spark, d):
    """Ten and a hundred times the rows at a fixed width: rank and residual stay."""
    rows = []
    for m in (400, 1600, 6400):
        for core, l_, wp in _CASES:
            rows.append((m, *_measured(thin.stored(tables.spend(spark, d, m, 60, synth.geometric(l_), 4)), core, l_, wp)))
    return frame(spark, "m int, " + _SCHEMA, rows)


@query(_KEPT.format("partitions,", ", (VALUES (1), (4), (18)) AS s(partitions)"))
def low_rank_by_partitions(spark, d):
    """The number of tasks changes no accuracy."""
    rows = []
    for p in (1, 4, 18):
        for core, l_, wp in _CASES:
            rows.append((p, *_measured(thin.stored(tables.spend(spark, d, 900, 60, synth.geometric(l_), p)), core, l_, wp)))
    return frame(spark, "partitions int, " + _SCHEMA, rows)


_STAIRS = """SELECT {0} CAST(size AS INTEGER) AS size, CAST(row_number() OVER (PARTITION BY {0} size ORDER BY bits DESC) AS INTEGER) AS k, CAST(round(bits / 63.0 * 1e9) AS BIGINT) AS sigma
FROM (SELECT size, (SELECT sum(CASE WHEN (w >> (3 * b)) & 7 > 0 THEN 1 << b ELSE 0 END) FROM range(7) AS t(b)) AS bits
FROM (SELECT size, CAST(floor(CAST(CAST(j AS FLOAT) * CAST(262144 AS FLOAT) / CAST(size AS FLOAT) AS DOUBLE) + 0.5) AS BIGINT) AS w FROM (VALUES {1}) AS t(size), LATERAL range(size) AS r(j))){2} WHERE bits > 0"""


@query(_STAIRS.format("core, layout,", "(20)", ", (VALUES ('mixed_qr'), ('gram')) AS c(core), (VALUES ('rows'), ('tiles'), ('entries')) AS y(layout)"))
def low_rank_stair_sigma(spark, d):
    """Repeated singular values come back from a sketch as wide as there are values, in every layout."""
    tiles = synth.cosine_tiles(spark, 150, 120, synth.staircase(20), 64, 64, 2)
    tiles.df = thin.durable(tiles.df)
    rows = []
    for layout, a in (("tiles", tiles), ("entries", tiles.to_entries()), ("rows", thin.stored(tiles.to_rows()))):
        for core in ("mixed_qr", "gram"):
            s = low_rank.low_rank_svd(a, 20, 2, core).sigma
            rows += [(core, layout, 20, j + 1, round(x * 1e9)) for j, x in enumerate(s.tolist())]
    return frame(spark, "core string, layout string, size int, k int, sigma long", rows)


_METHODS = ", (VALUES ('mixed_qr_1'), ('mixed_qr_2'), ('gram_1'), ('gram_2')) AS c(method), (VALUES (600), (2400)) AS s(m)"


@query(_STAIRS.format("method, m,", "(40)", _METHODS))
def thin_stair_sigma(spark, d):
    """The four thin methods on the staircase spectrum, two heights."""
    rows = []
    for m in (600, 2400):
        a = thin.stored(synth.stair(spark, m, 40, 40, 4))
        for name, (core, passes) in METHODS.items():
            rows += [(name, m, 40, j + 1, round(x * 1e9)) for j, x in enumerate(thin.thin_svd(a, core, passes).sigma.tolist())]
    return frame(spark, "method string, m int, size int, k int, sigma long", rows)


@query(f"""SELECT method, m, CAST(j + 1 AS INTEGER) AS k, CAST(round(power(10, -20.0 * j / 9) * 1e12) AS BIGINT) AS sigma FROM range(10) AS r(j){_METHODS}
WHERE power(10, -20.0 * j / 9) >= CASE WHEN method LIKE 'gram%' THEN sqrt(1e-11) ELSE 1e-10 END""")
def thin_geo_sigma(spark, d):
    """The four thin methods on the geometric spectrum: each value down to the working precision, and none below."""
    rows = []
    for m in (600, 2400):
        a = thin.stored(synth.geo_low(spark, m, 10, 10, 4))
        for name, (core, passes) in METHODS.items():
            s = thin.thin_svd(a, core, passes, 1e-10 if core == "mixed_qr" else 1e-11).sigma
            rows += [(name, m, j + 1, round(x * 1e12)) for j, x in enumerate(s.tolist())]
    return frame(spark, "method string, m int, k int, sigma long", rows)


@query("""SELECT core, CAST(cut AS INTEGER) AS cut, CAST(count(*) FILTER (v >= wp) AS INTEGER) AS rank, CAST(round(-100 * log10(max(v) FILTER (v < wp))) AS BIGINT) AS residual
FROM (VALUES ('mixed_qr', 1, 3e-3), ('mixed_qr', 2, 3e-8), ('gram', 1, 3e-3)) AS w(core, cut, wp), (SELECT power(10, -20.0 * j / 4) AS v FROM range(5) AS r(j)) GROUP BY ALL""")
def residual_by_precision(spark, d):
    """The residual is the first singular value below the working precision (its square root, for Gram)."""
    a = thin.stored(synth.geo_low(spark, 500, 50, 5, 2))
    rows = []
    for core, cut, wp in (("mixed_qr", 1, 3e-3), ("mixed_qr", 2, 3e-8), ("gram", 1, 3e-3)):
        r = low_rank.low_rank_svd(a, 5, 2, core, wp if core == "mixed_qr" else wp**2)
        rows.append((core, cut, r.rank, round(-100 * np.log10(accuracy.spectral_residual(a, r, 6)))))
    return frame(spark, "core string, cut int, rank int, residual long", rows)


@query(_SPEND_ENTRIES.format(60, 30, "-1.0 * k"))
def low_rank_gram_full_rank_reconstruct(spark, d):
    a = tables.spend(spark, d, 60, 30, 10.0 ** -np.arange(4.0)).to_entries().to_tiles(16, 16)
    a.df = thin.durable(a.df)
    rows = low_rank.low_rank_svd(a, 8, 2, "gram").reconstruct()
    return rows.df.select(F.col("row_id").alias("i"), F.posexplode("vec").alias("j", "v")).select("i", "j", whole(F.col("v"), 1e9).alias("value"))


@query("SELECT method, u_bad, v_bad FROM (VALUES ('explicit', false, false), ('stock', true, false)) AS t(method, u_bad, v_bad)")
def stock_thin_defect(spark, d):
    """On a spectrum that falls below machine precision the stock call's left vectors are not orthonormal, its right ones are."""
    a = thin.stored(synth.geo_low(spark, 800, 64, 20, 4))
    rows = []
    for name, r in (("explicit", thin.thin_svd(a, "gram", 2)), ("stock", stock.stock_thin(a, 20))):
        u, v = accuracy.gram_defect(thin.stored(r.U)), accuracy.gram_defect(r.v_numpy())
        rows.append((name, bool(u > 0.5), bool(v > 1e-10)))
        assert name == "stock" or u < 1e-12
    return frame(spark, "method string, u_bad boolean, v_bad boolean", rows)


_SUMS = f"""WITH {_E}, g AS (SELECT a.j AS i, b.j AS j, sum(a.v * b.v) AS v FROM e a JOIN e b USING (vec_id) GROUP BY 1, 2)
SELECT method, CAST(round((SELECT sum(v * v) FROM e) * 1000) AS BIGINT) AS s2, CAST(round(sum(v * v) * 1000) AS BIGINT) AS s4 FROM g, (VALUES {{0}}) AS c(method) GROUP BY method"""


@query(_SUMS.format("('mixed_qr_1'), ('mixed_qr_2'), ('gram_1'), ('gram_2'), ('exact')"))
def serial_power_sums(spark, d):
    """The serial methods and the exact SVD on the driver, of the embeddings (checked to be small)."""
    a = tables.emb(spark, d)
    found = {"exact": stock.exact_local(a)[1]}
    x = a.collect()
    found |= {name: serial.thin_svd(x, core, passes)[1] for name, (core, passes) in METHODS.items()}
    return frame(spark, "method string, s2 long, s4 long", [(k, round((s**2).sum() * 1000), round((s**4).sum() * 1000)) for k, s in found.items()])


@query(_KEPT.format("", ""))
def serial_low_rank(spark, d):
    rows = []
    for core, l_, wp in _CASES:
        u, v = synth.cosine_rows(np.arange(300), 300, l_), synth.cosine_rows(np.arange(90), 90, l_)
        x = (u * synth.geometric(l_)) @ v.T
        p, s, q = serial.low_rank_svd(x, l_, 2, core, wp, seed=1)
        good = max(np.abs(p.T @ p - np.eye(len(s))).max(), np.abs(q.T @ q - np.eye(len(s))).max()) < 1e-12
        rows.append((core, l_, len(s), round(-100 * np.log10(np.linalg.norm(x - (p * s) @ q.T, 2))), bool(good)))
    return frame(spark, _SCHEMA, rows)


_M6_COV = """e AS (SELECT o_custkey AS i, (year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS j, sum(o_totalprice) AS v FROM orders GROUP BY 1, 2),
n AS (SELECT count(DISTINCT i)::DOUBLE AS n FROM e), t AS (SELECT j, sum(v) AS s FROM e GROUP BY 1), g AS (SELECT a.j AS i, b.j AS j, sum(a.v * b.v) AS v FROM e a JOIN e b USING (i) GROUP BY 1, 2),
c AS (SELECT (coalesce(g.v, 0) - x.s * y.s / n.n) / (n.n - 1) AS v FROM n, t x CROSS JOIN t y LEFT JOIN g ON g.i = x.j AND g.j = y.j)"""


@query(f"WITH {_M6_COV} SELECT CAST(round(sum(v * v) / 1e16) AS BIGINT) AS s2 FROM c")
def pca_power_sum(spark, d):
    """The squares of all explained variances sum to those of the covariance matrix."""
    from .operators import pca

    p = pca.pca(thin.stored(tables.cust_month(spark, d).to_rows()))
    return frame(spark, "s2 long", [(round(float((p.explained_variance**2).sum()) / 1e16),)])


@query("SELECT * FROM (" + _TWO + ") WHERE k = 1")
def truncated_sigma(spark, d):
    r = thin.thin_svd(_two(spark, d), "gram", 2).truncate(1)
    assert r.U.n == 1 and r.v_numpy().shape == (2, 1)
    return frame(spark, "k int, sigma long", [(1, round(float(r.sigma[0]) * 1000))])


@query("SELECT CAST(i AS INTEGER) AS i, CAST(j AS INTEGER) AS j, CAST(round(CASE WHEN i + j = 0 THEN sum(l_quantity * l_quantity) WHEN i + j = 1 THEN sum(l_quantity * l_discount * 100) ELSE sum(l_discount * l_discount * 10000) END) AS BIGINT) AS value FROM lineitem, range(2) AS a(i), range(2) AS b(j) GROUP BY i, j")
def svd_as_qr(spark, d):
    """Q = U and R = diag(sigma) V*: R*R is the Gram matrix."""
    _, r = thin.as_qr(thin.thin_svd(_two(spark, d), "mixed_qr", 2))
    g = r.T @ r
    return frame(spark, "i int, j int, value long", [(i, j, round(float(g[i, j]))) for i in range(2) for j in range(2)])


@query("SELECT core, CAST((sum(l_quantity * l_quantity) > 0)::INTEGER + (sum(l_tax * l_tax) > 0)::INTEGER AS INTEGER) AS rank FROM lineitem, (VALUES ('mixed_qr'), ('gram')) AS c(core) GROUP BY core")
def rank_at_precision_zero(spark, d):
    """Working precision 0 drops exact zeros only: here a column of zeros between two others."""
    a = tables.from_columns(tables.table(spark, d, "lineitem"), ["l_quantity", F.lit(0.0), "l_tax"])
    a = thin.stored(a)
    rows = [("mixed_qr", thin.thin_svd(a, "mixed_qr", 1, 0.0, "none", q_form="indirect").rank), ("gram", thin.thin_svd(a, "gram", 1, 0.0).rank)]
    return frame(spark, "core string, rank int", rows)


@query("SELECT CAST(k + 1 AS INTEGER) AS k, CAST(round(sqrt(sum(power(CASE WHEN k = 0 THEN v1 ELSE v2 END, 2))) * 1e6) AS BIGINT) AS sigma FROM (SELECT 3.0 AS v1, 0.0 AS v2 UNION ALL SELECT 0.0, 2.0), range(2) AS t(k) GROUP BY k")
def wide_input_is_transposed(spark, d):
    """Two rows of five columns: more columns than rows."""
    a = RowFrame(spark.sql("SELECT * FROM VALUES (7L, array(0D, 3D, 0D, 0D, 0D)), (9L, array(0D, 0D, 0D, 2D, 0D)) AS t(row_id, vec)"), 5)
    r = thin.thin_svd(a)
    return frame(spark, "k int, sigma long", [(k + 1, round(float(x) * 1e6)) for k, x in enumerate(r.sigma)])


@query()
def synthesis_cost(spark, d):
    """Seconds to make generated matrices, apart from what is then done with them."""
    rows = []
    for kind, make in (("geometric thin", lambda: synth.geo_thin(spark, 20_000, 64, 8)), ("geometric tiles", lambda: synth.cosine_tiles(spark, 2000, 2000, synth.geometric(20), 512, 512, 8)), ("staircase thin", lambda: synth.stair(spark, 20_000, 64, 64, 8))):
        with CostMeter(spark, kind) as c:
            thin.durable(make().df)
        rows.append((kind, c.report.cpu_s, c.report.reserved_s, c.report.elapsed_s))
    return frame(spark, "matrix string, cpu_s double, reserved_s double, elapsed_s double", rows)


@query()
def low_rank_cost_scaling(spark, d):
    """Processor seconds of a low-rank SVD against l m n, with the exponent."""
    rows = []
    for m, n, l_ in ((20_000, 64, 8), (60_000, 64, 16), (120_000, 128, 16)):
        a = thin.stored(tables.spend(spark, d, m, n, synth.geometric(l_), 8))
        m = a.height()  # a small table has fewer rows
        for core in ("mixed_qr", "gram"):
            with CostMeter(spark) as c:
                r = low_rank.low_rank_svd(a, l_, 1, core)
                thin.stored(r.U)
            rows.append((core, float(l_) * m * n, c.report.cpu_s, c.report.elapsed_s))
    found = frame(spark, "core string, lmn double, cpu_s double, elapsed_s double", rows)
    return found.groupBy("core").agg(F.regr_slope(F.log("cpu_s"), F.log("lmn")).alias("cpu_exponent"), F.regr_slope(F.log("elapsed_s"), F.log("lmn")).alias("elapsed_exponent"), F.max("cpu_s").alias("largest_cpu_s"))


@query()
def stock_cost_ratio(spark, d):
    """Processor seconds of the low-rank methods and the stock call on one matrix."""
    a = thin.stored(synth.geo_low(spark, 40_000, 128, 20, 8))
    rows = []
    for name in ("mixed_qr", "gram", "stock"):
        with CostMeter(spark, name) as c:
            r = stock.stock_low_rank(a, 20) if name == "stock" else low_rank.low_rank_svd(a, 20, 2, name)
            thin.stored(r.U)
        rows.append((name, c.report.cpu_s, c.report.reserved_s, c.report.elapsed_s))
    return frame(spark, "method string, cpu_s double, reserved_s double, elapsed_s double", rows)
