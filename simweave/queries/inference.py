"""Queries over the posterior mathematics and decision tables: grids of small integers."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from simweave.functions import beta as B
from simweave.functions.columns import c2r, dequantise_gaussian, quantise_gaussian, r2c
from simweave.functions.posterior import BetaPosterior, GridPosterior, ShiftedBetaPosterior, TruncatedPosterior
from simweave.oracles import sql as S
from simweave.operators.candidates import num_bands
from simweave.plans.decision import JoinParams, classical_hashes_needed, classical_variance, decision_table, min_matches, prune_probability, required_cap
from simweave.plans.planner import fit_beta_prior
from simweave.queries import query
from simweave.sources.tables import table
from simweave.workloads import collection

J, C = BetaPosterior(), TruncatedPosterior()
CELLS = [(n, m) for n in (32, 64, 100) for m in range(0, n + 1, 4)]
GRID = "(SELECT n, m FROM (VALUES (32), (64), (100)) g(n), range(0, n + 1, 4) r(m))"


#: Thresholds of the tables of decisions: 0.4 to 0.9, one for each discount that occurs in lineitem.
LEVELS = "(SELECT DISTINCT round(0.4 + 5 * l_discount, 2) AS t FROM lineitem WHERE l_discount BETWEEN 0 AND 0.1)"


def _levels(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem", "l_discount").where("l_discount between 0 and 0.1").select(F.round(0.4 + 5 * F.col("l_discount"), 2).alias("t")).distinct()


def _at_levels(spark: SparkSession, d: str, of: Callable[[float], list[tuple]], schema: str) -> DataFrame:
    """The rows of(t) for every threshold, made in Spark's tasks; doubles rounded to 6 places."""
    names = [c.split()[0] for c in schema.split(", ")]

    def make(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            if len(frame):
                yield pd.DataFrame([r for t in frame["t"] for r in of(float(t))], columns=names)

    frame = _levels(spark, d).mapInPandas(make, schema)
    return frame.select(*(F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in frame.dtypes))


def _frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """The rows, doubles rounded to 6 places."""
    frame = spark.createDataFrame(rows, schema)
    return frame.select(*(F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in frame.dtypes))


@query("p01_binomial", f"SELECT n, m, s, round({S.binomial('n', 'm', 's')}, 6) AS p FROM {GRID}, (VALUES (0.1::DOUBLE), (0.5), (0.9)) t(s)")
def p01(spark, d):
    return _frame(spark, [(n, m, s, B.binom_pmf(m, n, s)) for n, m in CELLS for s in (0.1, 0.5, 0.9)], "n long, m long, s double, p double")


@query(
    "p02_grid_posterior",
    f"""SELECT n, m, round({S.upper_tail('0.7', 'm', 'n')}, 2) AS p FROM {GRID} WHERE n < 100""",
)
def p02(spark, d):
    g = GridPosterior(lambda s: s * 0 + 1, 0.0, 1.0, 4000)
    return spark.createDataFrame([(n, m, round(g.prob_ge(0.7, m, n), 6)) for n, m in CELLS if n < 100], "n long, m long, p double").select("n", "m", F.round("p", 2).alias("p"))


@query("p03_reg_inc_beta_int", f"SELECT n AS a, m + 1 AS b, x, round((SELECT sum({S.binomial('(n + m)', 'i', 'x')}) FROM range(n, n + m + 1) q(i)), 6) AS v FROM {GRID}, (VALUES (0.2::DOUBLE), (0.5), (0.8)) t(x)")
def p03_int(spark, d):
    return _frame(spark, [(n, m + 1, x, B.reg_inc_beta(x, n, m + 1)) for n, m in CELLS for x in (0.2, 0.5, 0.8)], "a long, b long, x double, v double")


REAL = [(2.5, 3.5), (1.5, 7.25), (10.5, 4.5)]


@query(
    "p03_reg_inc_beta_real",
    f"""SELECT a, b, x, round(exp(lgamma(a + b) - lgamma(a) - lgamma(b)) * (SELECT sum(CASE WHEN i = 0 OR i = 20000 THEN 1 WHEN i % 2 = 1 THEN 4 ELSE 2 END
      * pow(i * x / 20000, a - 1) * pow(1 - i * x / 20000, b - 1)) FROM range(0, 20001) q(i)) * x / 20000 / 3, 4) AS v
    FROM (VALUES {', '.join(f'({a}::DOUBLE, {b}::DOUBLE)' for a, b in REAL)}) g(a, b), (VALUES (0.3::DOUBLE), (0.6)) t(x)""",
)
def p03_real(spark, d):
    return spark.createDataFrame([(a, b, x, B.reg_inc_beta(x, a, b)) for a, b in REAL for x in (0.3, 0.6)], "a double, b double, x double, v double").withColumn("v", F.round("v", 4))


@query("p04_beta_posterior", f"SELECT n, m, m + 2.0::DOUBLE AS alpha, n - m + 5.0::DOUBLE AS beta, round((m + 2.0) / (n + 7.0), 6)::DOUBLE AS mean FROM {GRID}")
def p04(spark, d):
    return _frame(spark, [(n, m, m + 2.0, n - m + 5.0, (m + 2.0) / (n + 7.0)) for n, m in CELLS], "n long, m long, alpha double, beta double, mean double")


@query("p05_prob_ge_jaccard", f"SELECT n, m, t, round({S.upper_tail('t', 'm', 'n')}, 6) AS p FROM {GRID}, (VALUES (0.3::DOUBLE), (0.7), (0.9)) x(t)")
def p05(spark, d):
    return _frame(spark, [(n, m, t, J.prob_ge(t, m, n)) for n, m in CELLS for t in (0.3, 0.7, 0.9)], "n long, m long, t double, p double")


@query("p06_mode_jaccard", f"SELECT n, m, round(m / n::DOUBLE, 6) AS flat, round((m + 2) / (n + 5)::DOUBLE, 6) AS fitted FROM {GRID}")
def p06(spark, d):
    fitted = BetaPosterior(3.0, 4.0)
    return _frame(spark, [(n, m, J.mode(m, n), fitted.mode(m, n)) for n, m in CELLS], "n long, m long, flat double, fitted double")


@query("p07_concentration_jaccard", f"SELECT n, m, round({S.upper_tail('(m / n::DOUBLE - 0.05)', 'm', 'n')} - {S.upper_tail('(m / n::DOUBLE + 0.05)', 'm', 'n')}, 6) AS p FROM {GRID}")
def p07(spark, d):
    return _frame(spark, [(n, m, J.concentration(0.05, m, n)) for n, m in CELLS], "n long, m long, p double")


@query("p08_angular_maps", "SELECT k, round(cos(pi() * (1 - k / 100.0::DOUBLE)), 6) AS c, round(1 - acos(k / 50.0::DOUBLE - 1) / pi(), 6) AS r FROM range(0, 101) t(k)")
def p08(spark, d):
    k = F.col("id") / 100.0
    return spark.range(101).select(F.col("id").alias("k"), F.round(r2c(k), 6).alias("c"), F.round(c2r(F.col("id") / 50.0 - 1), 6).alias("r"))


COSINE_CELLS = [(n, m) for n, m in CELLS if m >= n // 3]
COSINE_GRID = f"(SELECT n, m FROM {GRID} WHERE m >= n // 3)"


@query("p09_cosine_posterior", f"SELECT n, m, round({S.upper_tail('0.5', 'm', 'n')}, 6) AS mass FROM {COSINE_GRID}")
def p09(spark, d):
    from math import exp

    return _frame(spark, [(n, m, exp(C._log_mass(0.5, 1.0, m, n))) for n, m in COSINE_CELLS], "n long, m long, mass double")


@query("p10_prob_ge_cosine", f"SELECT n, m, t, round({S.upper_tail(S.c2r('t'), 'm', 'n')} / {S.upper_tail('0.5', 'm', 'n')}, 6) AS p FROM {COSINE_GRID}, (VALUES (0.5::DOUBLE), (0.7), (0.9)) x(t)")
def p10(spark, d):
    return _frame(spark, [(n, m, t, C.prob_ge(t, m, n)) for n, m in COSINE_CELLS for t in (0.5, 0.7, 0.9)], "n long, m long, t double, p double")


@query("p11_mode_cosine", f"SELECT n, m, round({S.estimate('cosine', 'n', 'm')}, 6) AS est FROM {GRID}")
def p11(spark, d):
    return _frame(spark, [(n, m, C.estimate(m, n)) for n, m in CELLS], "n long, m long, est double")


@query(
    "p12_concentration_cosine",
    f"""SELECT n, m, round(({S.upper_tail(S.c2r('greatest(e - 0.05, 0)'), 'm', 'n')} - {S.upper_tail(S.c2r('least(e + 0.05, 1)'), 'm', 'n')}) / {S.upper_tail('0.5', 'm', 'n')}, 6) AS p
    FROM (SELECT n, m, {S.estimate('cosine', 'n', 'm')} AS e FROM {COSINE_GRID})""",
)
def p12(spark, d):
    return _frame(spark, [(n, m, C.concentration(0.05, m, n)) for n, m in COSINE_CELLS], "n long, m long, p double")


@query(
    "p13_shifted_beta",
    """SELECT n, m, round(sum(CASE WHEN cos(pi() * (1 - r)) >= 0.7 THEN w ELSE 0 END) / sum(w), 5) AS p FROM (
      SELECT n, m, r, pow(2 * r - 1, 1) * pow(2 - 2 * r, 2) * exp(m * ln(r) + (n - m) * ln(1 - r) - m * ln(m / n::DOUBLE) - (n - m) * ln(1 - m / n::DOUBLE)) AS w
      FROM (VALUES (32, 20), (64, 45), (128, 100)) g(n, m), (SELECT 0.5 + (i + 0.5) * 0.5 / 4000 AS r FROM range(0, 4000) q(i))) GROUP BY n, m""",
)
def p13(spark, d):
    g = ShiftedBetaPosterior(2.0, 3.0)
    return spark.createDataFrame([(n, m, g.prob_ge(0.7, m, n)) for n, m in ((32, 20), (64, 45), (128, 100))], "n int, m int, p double").select("n", "m", F.round("p", 5).alias("p"))


@query("p14_flat_prior", f"SELECT n, m, round(m / n::DOUBLE, 6) AS est, round((m + 1) / (n + 2)::DOUBLE, 6) AS mean FROM {GRID}")
def p14(spark, d):
    return _frame(spark, [(n, m, J.estimate(m, n), (m + 1) / (n + 2)) for n, m in CELLS], "n long, m long, est double, mean double")


_PAIRS = S.truth("page_links", "jaccard", 0.0001)


@query("p15_fit_prior", f"SELECT round(m * (m * (1 - m) / v - 1), 4) AS alpha, round((1 - m) * (m * (1 - m) / v - 1), 4) AS beta FROM (SELECT avg(similarity) AS m, var_pop(similarity) AS v FROM ({_PAIRS}))")
def p15(spark, d):
    from simweave.operators.candidates import sharing_pairs

    sets = collection(spark, d, "page_links")
    pairs = sharing_pairs(sets.select("id", F.explode("features").alias("feature")))
    a, b = fit_beta_prior(pairs, sets, "jaccard", 1_000_000)
    return spark.createDataFrame([(a, b)], "alpha double, beta double").select(F.round("alpha", 4).alias("alpha"), F.round("beta", 4).alias("beta"))


PRIORS = {"flat": (1.0, 1.0), "fitted": (3.0, 6.0), "wrong": (8.0, 1.5)}


@query(
    "p16_prior_sensitivity",
    f"""SELECT n, prior, round((7 * n // 10 + a - 1) / (n + a + b - 2), 6) AS est, round(abs((7 * n // 10 + a - 1) / (n + a + b - 2) - (7 * n // 10) / n::DOUBLE), 6) AS gap
    FROM (VALUES (20), (100), (500), (2000)) g(n), (VALUES {', '.join(f"('{k}', {a}::DOUBLE, {b}::DOUBLE)" for k, (a, b) in PRIORS.items())}) p(prior, a, b)""",
)
def p16(spark, d):
    rows = []
    for n in (20, 100, 500, 2000):
        m = 7 * n // 10
        for k, (a, b) in PRIORS.items():
            e = BetaPosterior(a, b).mode(m, n)
            rows.append((n, k, e, abs(e - J.mode(m, n))))
    return _frame(spark, rows, "n int, prior string, est double, gap double")


def _min_sql(tail: str, low: str) -> str:
    return f"""SELECT t, n, min(m) AS fewest FROM (SELECT t, n, m, {tail} AS p FROM {LEVELS} x, (VALUES (32), (64), (96), (128)) g(n), range({low}, n + 1) r(m))
      WHERE p >= 0.03 GROUP BY t, n"""


def _min_rows(posterior, t: float) -> list[tuple]:
    return [(t, n, m) for n, m in zip((32, 64, 96, 128), min_matches(posterior, t, 0.03, 32, 128), strict=True)]


@query("d01_min_matches_jaccard", _min_sql(S.upper_tail("t", "m", "n"), "0"))
def d01_j(spark, d):
    return _at_levels(spark, d, lambda t: _min_rows(J, t), "t double, n int, fewest long")


@query("d01_min_matches_cosine", _min_sql(f"{S.upper_tail(S.c2r('t'), 'm', 'n')} / {S.upper_tail('0.5', 'm', 'n')}", "n // 3"))
def d01_c(spark, d):
    return _at_levels(spark, d, lambda t: _min_rows(C, t), "t double, n int, fewest long")


def _verdict_sql(p: str, conc: str, est: str, low: str) -> str:
    return f"""WITH g AS MATERIALIZED (SELECT n, m, e, {conc} AS c FROM (SELECT n, m, {est} AS e FROM (VALUES (32), (64), (96), (128)) g(n), range({low}, n + 1) r(m)))
      SELECT t, n, m, CASE WHEN c >= 0.97 THEN 'accept' ELSE 'continue' END AS verdict, round(e, 6) AS est, round(p, 6) AS prob, round(c, 6) AS conc FROM (
      SELECT t, n, m, e, c, {p} AS p FROM g, {LEVELS} x) WHERE p >= 0.03"""


def _verdict_rows(posterior, t: float) -> list[tuple]:
    return [(t, *r) for r in decision_table(posterior, JoinParams(t, cap=128)).rows()]


_VERDICTS = "t double, n int, m long, verdict string, est double, prob double, conc double"


@query(
    "d02_verdicts_jaccard",
    _verdict_sql(S.upper_tail("t", "m", "n"), f"{S.upper_tail('(e - 0.05)', 'm', 'n')} - {S.upper_tail('(e + 0.05)', 'm', 'n')}", "m / n::DOUBLE", "0"),
)
def d02_j(spark, d):
    return _at_levels(spark, d, lambda t: _verdict_rows(J, t), _VERDICTS)


@query(
    "d02_verdicts_cosine",
    _verdict_sql(
        f"{S.upper_tail(S.c2r('t'), 'm', 'n')} / {S.upper_tail('0.5', 'm', 'n')}",
        f"({S.upper_tail(S.c2r('greatest(e - 0.05, 0)'), 'm', 'n')} - {S.upper_tail(S.c2r('least(e + 0.05, 1)'), 'm', 'n')}) / {S.upper_tail('0.5', 'm', 'n')}",
        S.estimate("cosine", "n", "m"), "n // 3",
    ),
)
def d02_c(spark, d):
    return _at_levels(spark, d, lambda t: _verdict_rows(C, t), _VERDICTS)


@query(
    "d03_gaussian_codes",
    """SELECT k, c AS code, round((c + 0.5) / 4096 - 8, 6) AS back, abs((c + 0.5) / 4096 - 8 - g) <= 1.0 / 8192 + 1e-12 AS close
    FROM (SELECT k, g, least(greatest(floor((g + 8) * 4096), 0), 65535)::INT AS c FROM (SELECT event_id AS k, value / 75 - 1 AS g FROM events))""",
)
def d03(spark, d):
    """The codes of event values, scaled into the range of a gaussian."""
    coded = table(spark, d, "events", "event_id", "value").select(F.col("event_id").alias("k"), (F.col("value") / 75 - 1).alias("g"))
    coded = coded.withColumn("code", quantise_gaussian(F.col("g")))
    back = dequantise_gaussian(F.col("code"))
    return coded.select("k", "code", F.round(back, 6).alias("back"), (F.abs(back - F.col("g")) <= 1.0 / 8192 + 1e-12).alias("close"))


@query(
    "d04_required_cap_jaccard",
    f"""WITH c AS MATERIALIZED (SELECT n, m, {S.upper_tail('(m / n::DOUBLE - 0.05)', 'm', 'n')} - {S.upper_tail('(m / n::DOUBLE + 0.05)', 'm', 'n')} AS c FROM range(32, 641, 32) g(n), range(0, n + 1) r(m) WHERE m >= n * 0.2),
      o AS MATERIALIZED (SELECT t, n, m, {S.upper_tail('t', 'm', 'n')} AS p FROM {LEVELS} x, (SELECT n, m FROM c WHERE c < 0.97))
    SELECT t, (max(n) FILTER (p >= 0.03) + 32)::INT AS cap FROM o GROUP BY t""",
)
def d04_j(spark, d):
    return _at_levels(spark, d, lambda t: [(t, required_cap(J, JoinParams(t)))], "t double, cap int")


@query("d04_required_cap_cosine")
def d04_c(spark, d):
    return _at_levels(spark, d, lambda t: [(t, required_cap(C, JoinParams(t)))], "t double, cap int")


_WIDTHS = (("jaccard", 3), ("cosine", 8), ("cosine", 16))


@query(
    "c02_num_bands",
    f"""SELECT measure, t, w, ceil(ln(0.03) / ln(1 - pow(CASE WHEN measure = 'jaccard' THEN t ELSE {S.c2r('t')} END, w)))::INT AS bands
    FROM {LEVELS} x, (VALUES {', '.join(f"('{m}', {w})" for m, w in _WIDTHS)}) g(measure, w)""",
)
def c02(spark, d):
    return _at_levels(spark, d, lambda t: [(m, t, w, num_bands(t, w, 0.03, m)) for m, w in _WIDTHS], "measure string, t double, w int, bands int")


@query("a13_classical_variance", f"SELECT t AS s, n, round(t * (1 - t) / n, 8) AS v FROM {LEVELS} x, (VALUES (16), (64), (360)) b(n)")
def a13(spark, d):
    grid = _levels(spark, d).select(F.col("t").alias("s"), F.explode(F.array(*map(F.lit, (16, 64, 360)))).alias("n"))
    return grid.select("s", "n", F.round(classical_variance(F.col("s"), F.col("n")), 8).alias("v"))


def _prune_rows(t: float) -> list[tuple]:
    rows = []
    for extra in (0.0, 0.05):
        s = min(t + extra, 0.99)
        rows.append(("jaccard", t, s, prune_probability(s, min_matches(J, t, 0.03, 32, 384), 32)))
        rows.append(("cosine", t, s, prune_probability(C.match_threshold(s), min_matches(C, t, 0.03, 32, 512), 32)))
    return rows


@query("a04_prune_probability")
def a04(spark, d):
    return _at_levels(spark, d, _prune_rows, "measure string, t double, s double, lost double")


_NEEDED = """SELECT s, n, (SELECT sum(exp(lgamma(n + 1) - lgamma(m + 1) - lgamma(n - m + 1) + m * ln(s) + (n - m) * ln(1 - s)))
  FROM range(greatest(floor(n * (s - 0.05) + 1e-9), 0)::BIGINT, least(ceil(n * (s + 0.05) - 1e-9), n)::BIGINT + 1) q(m)) >= 0.95 AS ok
  FROM (VALUES (0.1::DOUBLE), (0.3), (0.5), (0.7), (0.9), (0.95)) g(s), range(1, 601) r(n)"""


@query("w11_hashes_needed", f"SELECT s, min(n) FILTER (ok AND n >= 11)::INT AS first_n, (coalesce(max(n) FILTER (NOT ok), 0) + 1)::INT AS stable_n FROM ({_NEEDED}) GROUP BY s")
def w11(spark, d):
    return spark.createDataFrame([(s, *classical_hashes_needed(s, 0.05, 0.05, most=600)) for s in (0.1, 0.3, 0.5, 0.7, 0.9, 0.95)], "s double, first_n int, stable_n int")


_INWARD = _NEEDED.replace("floor(n * (s - 0.05) + 1e-9)", "ceil(n * (s - 0.05) - 1e-9)").replace("ceil(n * (s + 0.05) - 1e-9)", "floor(n * (s + 0.05) + 1e-9)")


_AT_LEVELS = _INWARD.replace("(VALUES (0.1::DOUBLE), (0.3), (0.5), (0.7), (0.9), (0.95)) g(s)", f"(SELECT t AS s FROM {LEVELS}) g")


@query("b05_hashes_needed_inward", f"SELECT s, min(n) FILTER (ok AND n >= 11)::INT AS first_n, (coalesce(max(n) FILTER (NOT coalesce(ok, false)), 0) + 1)::INT AS stable_n FROM ({_AT_LEVELS}) GROUP BY s")
def b05(spark, d):
    return _at_levels(spark, d, lambda t: [(t, *classical_hashes_needed(t, 0.05, 0.05, "inward", 600))], "s double, first_n int, stable_n int")


@query(
    "w13_worked_example",
    f"""SELECT measure, round(log10(p), 4) AS log10_p, p < 0.03 AS pruned FROM (SELECT 'jaccard' AS measure, {S.upper_tail('0.8', '10', '100')} AS p
    UNION ALL SELECT 'cosine', {S.upper_tail(S.c2r('0.8'), '10', '100')} / {S.upper_tail('0.5', '10', '100')})""",
)
def w13(spark, d):
    from math import log10

    rows = [("jaccard", log10(J.prob_ge(0.8, 10, 100)), True), ("cosine", log10(C.prob_ge(0.8, 10, 100)), True)]
    return spark.createDataFrame(rows, "measure string, log10_p double, pruned boolean").select("measure", F.round("log10_p", 4).alias("log10_p"), "pruned")
