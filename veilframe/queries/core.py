"""Queries of the method itself, its variants, baselines, measures and attacks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.rng import key_text, uniform, uniform_sql
from ..functions.rng import normal_sql
from ..plans import attacks, audit, baselines, classify, datasets, geometry, metrics, search
from ..plans.held import hold, holding, settled
from ..plans.matrix import KEY, NumericMatrixSpec, as_matrix
from ..plans.moments import covariance_long, fit, mean_std, standardize
from ..plans.perturb import PerturbationModel, expand, fit_model, move, release, rescale, smp, smp_grouped
from . import printed, sqltext as Q

ATTRS = list(Q.COLS)
QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = f
        if oracle:
            ORACLES[name or f.__name__] = oracle
        return f

    return keep


def _li4(spark: SparkSession, d: str) -> tuple[DataFrame, NumericMatrixSpec]:
    df, spec = datasets.li4(spark, d)
    return as_matrix(df, spec), spec


def _rounded(df: DataFrame, *extra: str) -> DataFrame:
    return df.select(*(F.round(c, p).alias(c) for c, p in zip(Q.COLS, Q.PLACES, strict=True)), *extra)


def _model(spark: SparkSession, d: str, **how) -> tuple[DataFrame, PerturbationModel]:
    m, spec = _li4(spark, d)
    return m, fit_model(m, spec, **how)


# --- moments -------------------------------------------------------------------------------------------------

_STAR = "li9 AS (SELECT l_quantity, l_extendedprice, l_discount, l_tax, o_totalprice, p_size::DOUBLE AS p_size, p_retailprice, s_acctbal, c_acctbal FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey)"


@query("WITH " + _STAR + " " + " UNION ALL ".join(f"SELECT '{a}' AS attr, round(avg({a}), 7) AS mean, round(stddev_samp({a}), 6) AS sd FROM li9" for a in datasets.LI9))
def moments_li9(spark, d):
    return mean_std(datasets._star(spark, d), list(datasets.LI9)).select("attr", F.round("mean", 7).alias("mean"), F.round("sd", 6).alias("sd"))


@query("WITH " + _STAR + " " + " UNION ALL ".join(f"SELECT {i + 1} AS i, {j + 1} AS j, {'1::DOUBLE AS cov' if i == j else f'round(corr({datasets.LI9[min(i, j)]}, {datasets.LI9[max(i, j)]}), 8) AS cov FROM li9'}" for i in range(9) for j in range(9)))
def corr_li9(spark, d):
    m = fit(datasets._star(spark, d).select(*(F.col(a).cast("double").alias(a) for a in datasets.LI9)), datasets.LI9, method="gram")
    return spark.createDataFrame([(i + 1, j + 1, round(float(m.cov[i, j]), 8)) for i in range(9) for j in range(9)], "i int, j int, cov double")


@query(f"WITH {Q.li()}, {Q.mo()} SELECT {', '.join(f'round((x{i} - m{i}) / s{i}, 8) AS {c}' for i, c in enumerate(Q.COLS))}, cls FROM li, mo")
def zscore_li4(spark, d):
    m, _ = _li4(spark, d)
    return standardize(m, fit(m, ATTRS)).select(*(F.round(c, 8).alias(c) for c in ATTRS), "cls")


@query(f"WITH {Q.li()}, {Q.cov()} SELECT i + 1 AS i, j + 1 AS j, round(c, 9) AS cov FROM cov", "cov_li4")
def cov_long_li4(spark, d):
    m, _ = _li4(spark, d)
    return covariance_long(m, ATTRS).select("i", "j", F.round("cov", 9).alias("cov"))


# --- geometry ------------------------------------------------------------------------------------------------


_MEANS = ", ".join(f"({j + 1}, {p}, (SELECT avg(x{j}) FROM li))" for j, p in enumerate(Q.PLACES))


@query(f"WITH {Q.li()} SELECT axis::INT AS axis, j::INT AS j, round(CASE WHEN axis = j THEN -m ELSE m END, p) AS single, round(CASE WHEN axis = j THEN m ELSE -m END, p) AS complement FROM range(1, 5) a(axis), (VALUES {_MEANS}) b(j, p, m)")
def refl_signs(spark, d):
    """Means of the attributes of all records after each reflection."""
    m, _ = _li4(spark, d)
    of = lambda a, j, kind: F.round(F.avg(F.col(ATTRS[j]) * float(geometry.reflection(4, a, kind)[j])), Q.PLACES[j])
    cells = [(a, j) for a in range(1, 5) for j in range(4)]
    row = m.agg(*(of(a, j, kind).alias(f"{kind}_{a}_{j}") for a, j in cells for kind in ("single", "complement")))
    return row.select(F.inline(F.array(*(F.struct(F.lit(a).alias("axis"), F.lit(j + 1).alias("j"), F.col(f"single_{a}_{j}").alias("single"), F.col(f"complement_{a}_{j}").alias("complement")) for a, j in cells))))


for _n in (2, 3, 4):

    def _rot(spark, d, n=_n):
        """Each angle's rotation, and the covariances of the records' rotated attributes (i) with the attributes (j)."""
        m, _ = _li4(spark, d)
        df, cov = search.rotation_df(spark, n, geometry.angles()), covariance_long(m, ATTRS[:n]).select(F.col("i").alias("k"), F.col("j").alias("at"), "cov")
        turned = df.withColumnRenamed("j", "own").join(F.broadcast(cov), F.col("own") == F.col("k")).groupBy("theta_deg", "i", F.col("at").alias("j"))
        return turned.agg(F.round(F.max(F.when(F.col("own") == F.col("at"), F.col("r"))), 9).alias("r"), F.round(F.sum(F.col("r") * F.col("cov")), 8).alias("cov"))

    query(f"WITH RECURSIVE {Q.li()}, {Q.cov()}, {Q.rot(_n)} SELECT theta::INT AS theta_deg, (a.i + 1)::INT AS i, (b.j + 1)::INT AS j, round(any_value(m[a.i * {_n} + b.j + 1]), 9) AS r, round(sum(m[a.i * {_n} + cov.i + 1] * c), 8) AS cov FROM rot, range(0, {_n}) a(i), range(0, {_n}) b(j), cov WHERE cov.j = b.j AND cov.i < {_n} GROUP BY ALL", f"rot_matrix_n{_n}")(_rot)


@query(f"WITH RECURSIVE {Q.li()}, {Q.cov()}, {Q.rot(4)}, e AS (SELECT theta, i, j, list_sum(list_transform(range(0, 4), lambda k: m[i * 4 + k + 1] * m[j * 4 + k + 1])) AS p FROM rot, range(0, 4) a(i), range(0, 4) b(j)), o AS (SELECT theta, max(abs(p - CASE WHEN i = j THEN 1 ELSE 0 END)) < 1e-9 AS orthogonal FROM e GROUP BY theta), v AS (SELECT theta, a.i, sum(m[a.i * 4 + cov.i + 1] * m[a.i * 4 + cov.j + 1] * c) AS v FROM rot, range(0, 4) a(i), cov GROUP BY ALL), w AS (SELECT theta, round(min(v), 8) AS least, round(max(v), 8) AS greatest, abs(sum(v) - 4) < 1e-9 AS kept FROM v GROUP BY theta) SELECT theta::INT AS theta_deg, orthogonal, least, greatest, kept FROM o JOIN w USING (theta)")
def rot_orthogonal(spark, d):
    """Whether a rotation is orthogonal, and the variances of the records' rotated attributes: least, greatest, sum kept."""
    m, _ = _li4(spark, d)
    cov, out = fit(m, ATTRS).cov, []
    for a in geometry.angles():
        r = geometry.rotation(4, a)
        v = search.var_from_cov(cov, r)
        out.append((a, geometry.orthogonality_error(r) < 1e-9, round(float(v.min()), 8), round(float(v.max()), 8), bool(abs(v.sum() - 4) < 1e-9)))
    return spark.createDataFrame(out, "theta_deg int, orthogonal boolean, least double, greatest double, kept boolean")


# --- search --------------------------------------------------------------------------------------------------


def _grid(spark, d, form="exact", reflection="single"):
    m, _ = _li4(spark, d)
    return search.grid_cov_df(covariance_long(m, ATTRS), search.rotation_df(spark, 4, geometry.angles()), 4, form, reflection)


_GRID_OUT = " SELECT axis, theta_deg, round(phi, 8) AS phi FROM grid"
for _name, _how in (("phi_grid_cov_li4", {}), ("phi_printed_form", {"form": "printed"}), ("phi_grid_complement", {"reflection": "complement"})):
    query(Q.base(**_how) + _GRID_OUT, _name)(lambda spark, d, how=_how: _grid(spark, d, **how).select("axis", "theta_deg", F.round("phi", 8).alias("phi")))


@query(Q.base() + _GRID_OUT)
def phi_grid_driver_li4(spark, d):
    m, _ = _li4(spark, d)
    return search.grid_df(spark, search.grid_cov(fit(m, ATTRS).cov), geometry.angles()).select("axis", "theta_deg", F.round("phi", 8).alias("phi"))


@query(Q.base() + _GRID_OUT)
def phi_grid_scan_li4(spark, d):
    m, _ = _li4(spark, d)
    z = standardize(m, fit(m, ATTRS))
    return search.grid_df(spark, search.grid_scan(z, ATTRS, geometry.translation(4)), geometry.angles()).select("axis", "theta_deg", F.round("phi", 8).alias("phi"))


@query(Q.base() + " SELECT theta_deg, " + ", ".join(f"max(round(phi, 8)) FILTER (WHERE axis = {i}) AS axis_{i}" for i in range(1, 5)) + " FROM grid GROUP BY theta_deg")
def phi_curve_axis(spark, d):
    return search.curve_axis(_grid(spark, d).withColumn("phi", F.round("phi", 8)), 4)


@query(Q.base() + " SELECT theta_deg, min(round(phi, 8)) AS phi FROM grid GROUP BY theta_deg")
def phi_curve_global(spark, d):
    return search.curve_global(_grid(spark, d).withColumn("phi", F.round("phi", 8)))


for _name, _sel in (("select_maximin", "maximin"), ("select_global_max", "global_max"), ("select_best_axis", "maximin_best_axis")):
    query(Q.base(selection=_sel) + " SELECT theta_deg, axis, phi_opt FROM pick", _name)(lambda spark, d, sel=_sel: search.select_df(_grid(spark, d), sel))


@query(Q.base() + " SELECT v.theta::INT AS theta_deg, v.axis::INT AS axis, (v.i + 1)::INT AS i, round(v, 8) AS v, round(s, 8) AS s FROM v JOIN s USING (theta, axis, i)")
def var_and_cross_from_cov(spark, d):
    m, _ = _li4(spark, d)
    cov, out = fit(m, ATTRS).cov, []
    for axis, t in search.candidates(4, geometry.angles()):
        a = geometry.rotation(4, t) * geometry.reflection(4, axis)
        v, s = search.var_from_cov(cov, a), search.cross_from_cov(cov, a)
        out += [(int(t), axis, i + 1, round(float(v[i]), 8), round(float(s[i]), 8)) for i in range(4)]
    return spark.createDataFrame(out, "theta_deg int, axis int, i int, v double, s double")


_SEPARATED = " UNION ALL ".join(f"SELECT * FROM ({Q.base(selection=s)} SELECT '{s}' AS label, round(grid.phi, 8) AS phi, top AS phi_max, round(grid.phi, 8) >= top - 1e-9 AS separated FROM grid JOIN pick USING (theta_deg, axis), (SELECT round(max(phi), 8) AS top FROM grid))" for s in ("global_max", "maximin"))


@query(_SEPARATED)
def separation_check(spark, d):
    g, out = _grid(spark, d), []
    for selection in ("global_max", "maximin"):
        best = search.select_df(g, selection).select(F.col("theta_deg").alias("t"), F.col("axis").alias("a"))
        marked = g.join(F.broadcast(best)).select(F.lit(selection).alias("label"), F.round("phi", 8).alias("phi"), ((F.col("theta_deg") == F.col("t")) & (F.col("axis") == F.col("a"))).alias("chosen"))
        out.append(search.satisfies_separation(marked))
    return out[0].unionByName(out[1])


# --- release -------------------------------------------------------------------------------------------------

_YS = " SELECT " + ", ".join(f"round(y{i}, 8) AS {c}" for i, c in enumerate(Q.COLS)) + ", cls FROM moved"


@query(f"{Q.base()}, {Q.moved()}{_YS}")
def move_li4(spark, d):
    m, model = _model(spark, d)
    return move(m, model).select(*(F.round(c, 8).alias(c) for c in ATTRS), "cls")


@query(f"{Q.base()}, {Q.moved()}, {Q.expanded()}{_YS.replace('(y', '(e').replace('moved', 'expanded')}")
def expand_li4(spark, d):
    m, model = _model(spark, d)
    return expand(move(m, model), ATTRS, 0.3).select(*(F.round(c, 8).alias(c) for c in ATTRS), "cls")


@query(Q.released() + Q.values("r", "rel"))
def rescale_li4(spark, d):
    m, model = _model(spark, d)
    return _rounded(rescale(expand(move(m, model), ATTRS, 0.3), model), "cls")


def _release(spark, d, order="global", kind="keyed", **how):
    df, spec = datasets.li4(spark, d)
    return _rounded(smp(df, spec, order=order, kind=kind, **how), "cls")


for _name, _how, _sql in (
    ("smp_cov_li4", {}, {}),
    ("smp_scan_li4", {"search_by": "scan"}, {}),
    ("smp_sigma0", {"sigma": 0.0}, {"sigma": 0.0}),
    ("smp_sorted", {"order": "sorted"}, {}),
    ("smp_block", {"order": "block"}, {}),
    ("smp_complement", {"reflection": "complement"}, {"reflection": "complement"}),
    ("smp_global_max", {"selection": "global_max"}, {"selection": "global_max"}),
    ("smp_best_axis", {"selection": "maximin_best_axis"}, {"selection": "maximin_best_axis"}),
):
    query(Q.released(**_sql) + Q.values("r", "rel"), _name)(lambda spark, d, how=_how: _release(spark, d, **how))


@query()
def smp_fast_rng(spark, d):
    return _release(spark, d, kind="fast")


@query()
def smp_grouped_by_flag(spark, d):
    df, spec = datasets.li4(spark, d)
    return _rounded(smp_grouped(df, NumericMatrixSpec(spec.value_cols, spec.key_cols, "cls"), "cls"), "cls")


_SERIES = (0.1, 0.2, 0.3)
_SERIES_SQL = " UNION ALL ".join(f"SELECT * FROM ({Q.released(s, seed=f'smp-{k}')} SELECT {s}::DOUBLE AS sigma, count(*) AS rows, {', '.join(f'round(avg(r{i}), 5) AS mean_{i}, round(stddev_samp(r{i}), 5) AS sd_{i}' for i in range(4))} FROM rel)" for k, s in enumerate(_SERIES))


@query(_SERIES_SQL)
def release_series(spark, d):
    from ..plans.perturb import release_series as series

    df, spec = datasets.li4(spark, d)
    moments = [f(c, i) for i, c in enumerate(ATTRS) for f in (lambda c, i: F.round(F.avg(c), 5).alias(f"mean_{i}"), lambda c, i: F.round(F.stddev_samp(c), 5).alias(f"sd_{i}"))]
    out = [x.agg(F.lit(s).alias("sigma"), F.count(F.lit(1)).alias("rows"), *moments) for s, x in zip(_SERIES, series(df, spec, list(_SERIES), kind="keyed"), strict=True)]
    return out[0].unionByName(out[1]).unionByName(out[2])


# --- baselines -----------------------------------------------------------------------------------------------


@query()
def rp_li4(spark, d):
    m, spec = _li4(spark, d)
    return _rounded(baselines.rotation(m, spec), "cls")


@query()
def gp_li4(spark, d):
    m, spec = _li4(spark, d)
    return _rounded(baselines.geometric(m, spec), "cls")


@query()
def additive_li4(spark, d):
    m, spec = _li4(spark, d)
    return _rounded(baselines.additive(m, spec), "cls")


ORACLES["additive_li4"] = f"WITH {Q.li()}, {Q.mo()} SELECT " + ", ".join(f"round(x{i} + 0.3::DOUBLE * s{i} * {normal_sql('add', 'noise', 'key', i)}, {p}) AS {c}" for i, (c, p) in enumerate(zip(Q.COLS, Q.PLACES, strict=True))) + ", cls FROM li, mo"

_FLAGS = ("A", "N", "R")
_RR = f"""WITH {Q.li()}, o AS (SELECT key, cls, list_filter(['A', 'N', 'R'], lambda x: x <> cls) AS others FROM li)
SELECT key, CASE WHEN {uniform_sql('rr', 'keep', 'key')} < 0.7 THEN cls ELSE others[(floor({uniform_sql('rr', 'pick', 'key')} * 2) + 1)::INT] END AS cls FROM o"""


@query(_RR)
def randomized_response(spark, d):
    m, _ = _li4(spark, d)
    return baselines.randomized_response(m, "cls", F.col(KEY), list(_FLAGS)).select(F.col(KEY).alias("key"), "cls")


@query(f"WITH a AS ({_RR}), n AS (SELECT count(*) AS n FROM a) SELECT cls, round(count(*) / any_value(n), 8) AS observed, round((count(*) / any_value(n) - 0.15::DOUBLE) / 0.55::DOUBLE, 8) AS estimate FROM a, n GROUP BY cls")
def response_estimate(spark, d):
    got = baselines.response_estimate(randomized_response(spark, d), "cls", 3)
    return got.select("cls", F.round("observed", 8).alias("observed"), F.round("estimate", 8).alias("estimate"))


@query()
def laplace_value(spark, d):
    m, _ = _li4(spark, d)
    return baselines.laplace_value(m, "l_quantity", F.col(KEY), 1.0, 50.0, 1.0).select(F.col(KEY).alias("key"), "l_quantity")


@query()
def laplace_query(spark, d):
    m, _ = _li4(spark, d)
    by = m.groupBy("cls").agg(F.count(F.lit(1)).cast("double").alias("n"))
    return baselines.laplace_query(by, "n", F.col("cls"), 1.0, 1.0)


# --- measures ------------------------------------------------------------------------------------------------


def _pairs(spark, d, **how):
    df, spec = datasets.li4(spark, d)
    m = as_matrix(df, spec, repeated="number")
    model = fit_model(m, spec, **how)
    rel = release(m, model, "none")
    return m, rel, model


def _std(prefix_x="x", prefix_y="r", source="rel"):
    mom = ", ".join(f"avg({p}{i}) AS a{p}{i}, stddev_samp({p}{i}) AS d{p}{i}" for i in range(4) for p in (prefix_x, prefix_y))
    gaps = [f"stddev_samp(({prefix_y}{i} - a{prefix_y}{i}) / d{prefix_y}{i} - ({prefix_x}{i} - a{prefix_x}{i}) / d{prefix_x}{i})" for i in range(4)]
    return f", st AS (SELECT {mom} FROM {source}), g AS (SELECT {', '.join(f'{x} AS g{i}' for i, x in enumerate(gaps))} FROM {source}, st) SELECT round(least(g0, g1, g2, g3), 7) AS std_min, round((g0 + g1 + g2 + g3) / 4, 7) AS std_avg FROM g"


_RES = lambda df: df.select(F.round("std_min", 7).alias("std_min"), F.round("std_avg", 7).alias("std_avg"))


@query(Q.released(numbered=True) + " " + " UNION ALL ".join(f"SELECT '{c}' AS attr, round((SELECT var_samp((r{i} - x{i}) / s{i}) FROM rel, mo), 8) AS variance" for i, c in enumerate(Q.COLS)))
def diff_variance_li4(spark, d):
    m, rel, _ = _pairs(spark, d)
    mo = fit(m, ATTRS)
    return metrics.diff_variance(metrics.paired(standardize(m, mo), standardize(rel, mo), ATTRS), ATTRS).select("attr", F.round("variance", 8).alias("variance"))


@query(Q.released(sigma=0.0, numbered=True) + " SELECT round(least(" + ", ".join(f"var_samp((r{i} - x{i}) / s{i})" for i in range(4)) + "), 8) AS phi FROM rel, mo")
def phi_of_release(spark, d):
    m, rel, _ = _pairs(spark, d, sigma=0.0)
    mo = fit(m, ATTRS)
    return metrics.phi(metrics.paired(standardize(m, mo), standardize(rel, mo), ATTRS), ATTRS).select(F.round("phi", 8).alias("phi"))


@query(Q.released(numbered=True) + _std())
def naive_true(spark, d):
    m, rel, _ = _pairs(spark, d)
    return _RES(attacks.naive(m, rel, ATTRS))


_PLACED = f", px AS (SELECT row_number() OVER (ORDER BY {uniform_sql('place', 'first', 'key')}, key) AS k, {', '.join(f'x{i}' for i in range(4))} FROM rel), py AS (SELECT row_number() OVER (ORDER BY {uniform_sql('place', 'order', 'key')}, key) AS k, {', '.join(f'r{i}' for i in range(4))} FROM rel), placed AS (SELECT * FROM px JOIN py USING (k))"


@query(Q.released(numbered=True) + _PLACED + _std(source="placed"))
def naive_released(spark, d):
    m, rel, _ = _pairs(spark, d)
    return _RES(attacks.naive(m, rel, ATTRS, "released"))


for _name, _attack in (("known_io_li4", lambda m, r: attacks.known_io(m, r, ATTRS)), ("known_io_procrustes", lambda m, r: attacks.known_io(m, r, ATTRS, solver="procrustes")), ("ica_li4", lambda m, r: attacks.ica(m, r, ATTRS)), ("known_sample_li4", lambda m, r: attacks.known_sample(m, r, ATTRS))):

    def _run(spark, d, attack=_attack):
        m, rel, _ = _pairs(spark, d)
        return _RES(attack(m, rel))

    query(None, _name)(_run)


@query()
def complementary_li4(spark, d):
    df, spec = datasets.li4(spark, d)
    m = as_matrix(df, spec)
    rels = [release(m, fit_model(m, spec, sigma=s, seed=f"smp-{s}"), "none") for s in (0.2, 0.3, 0.4)]
    return _RES(attacks.complementary(m, rels, ATTRS))


@query()
def eigen_li4(spark, d):
    m, rel, _ = _pairs(spark, d)
    return spark.createDataFrame([(k, round(a, 7), round(b, 7)) for k, a, b in attacks.eigen(m, rel, ATTRS)], "k int, original double, released double")


_GAP = lambda p: "sqrt(" + " + ".join(f"pow(a.{p}{i} - b.{p}{i}, 2)" for i in range(4)) + ")"
_OWN_R = ", ".join(f"(r{i} - avg(r{i}) OVER ()) / stddev_samp(r{i}) OVER () AS w{i}" for i in range(4))


@query(Q.released(numbered=True) + f", z AS (SELECT key, {', '.join(f'(x{i} - m{i}) / s{i} AS z{i}' for i in range(4))}, {_OWN_R} FROM rel, mo), kn AS (SELECT * FROM z ORDER BY {uniform_sql('dist', 'known', 'key')}, key LIMIT 30), pr AS (SELECT a.key AS k1, b.key AS k2, {_GAP('z')} AS d FROM kn a JOIN kn b ON a.key < b.key), e AS (SELECT a.key AS k1, b.key AS other, {_GAP('w')} AS e FROM kn a JOIN z b ON a.key <> b.key), h AS (SELECT (pr.k2 = e.other) AS hit FROM pr JOIN e USING (k1) WHERE abs(d - e) < 0.05) SELECT (SELECT count(*) FROM pr) AS pairs, count(*) AS matches, coalesce(sum(hit::BIGINT), 0)::BIGINT AS true_matches FROM h")
def distance_li4(spark, d):
    """The numbered records and their release are each made once and held."""
    df, spec = datasets.li4(spark, d)
    with holding():
        m = hold(as_matrix(df, spec, repeated="number"))
        mo = fit(m, ATTRS)
        rel = hold(release(m, fit_model(m, spec, moments=mo), "none"))
        return settled(attacks.distance(m, rel, ATTRS, moments=mo))


@query()
def risk_levels(spark, d):
    m, rel, _ = _pairs(spark, d)
    rows = None
    for name, got in (("naive estimation", attacks.naive(m, rel, ATTRS, "released")), ("known input and output", attacks.known_io(m, rel, ATTRS, pairing="released")), ("known sample", attacks.known_sample(m, rel, ATTRS, pairing="released"))):
        part = got.select(F.lit(name).alias("attack"), "std_min")
        rows = part if rows is None else rows.unionByName(part)
    open_ = spark.createDataFrame([("distance inference", None), ("eigen-analysis", None)], "attack string, std_min double")
    return attacks.risk_table(rows.unionByName(open_))


_KS_CUT = metrics.ks_cutoff(4)


@query(Q.released(numbered=True) + f", z AS (SELECT key, [{', '.join(f'(x{i} - m{i}) / s{i}' for i in range(4))}] AS a, [{', '.join(f'(r{i} - m{i}) / s{i}' for i in range(4))}] AS b FROM rel, mo), k AS (SELECT key, list_max(list_transform(list_concat(a, b), lambda v: abs(len(list_filter(a, lambda p: p <= v)) - len(list_filter(b, lambda q: q <= v))))) AS k FROM z) SELECT key, k / 4.0::DOUBLE AS d, k >= 4 AS rejected FROM k")
def ks_tuples_li4(spark, d):
    m, rel, _ = _pairs(spark, d)
    return metrics.ks_tuples(metrics.paired(m, rel, ATTRS), fit(m, ATTRS))


@query(Q.released(numbered=True) + " " + " UNION ALL ".join(f"(WITH u AS (SELECT x{i} AS v, 1 AS a, 0 AS b FROM rel UNION ALL SELECT r{i}, 0, 1 FROM rel), c AS (SELECT v, sum(a) AS a, sum(b) AS b FROM u GROUP BY v), f AS (SELECT sum(a) OVER (ORDER BY v) / sum(a) OVER () - sum(b) OVER (ORDER BY v) / sum(b) OVER () AS g FROM c) SELECT '{c}' AS attr, round(max(abs(g)), 8) AS d, (SELECT count(*) FROM rel) AS n, (SELECT count(*) FROM rel) AS m FROM f)" for i, c in enumerate(Q.COLS)))
def ks_attributes_li4(spark, d):
    m, rel, _ = _pairs(spark, d)
    return metrics.ks_attributes(m, rel, ATTRS).select("attr", F.round("d", 8).alias("d"), "n", "m")


_H = lambda c, s: f"(SELECT log2(sum(k)) - sum(k * log2(k)) / sum(k) FROM (SELECT count(*) AS k FROM {s} GROUP BY {c}))"


@query("WITH " + _STAR + " " + " UNION ALL ".join(f"SELECT '{a}' AS attr, round({_H(a, 'li9')}, 8) AS h" for a in datasets.LI9))
def entropy_li9(spark, d):
    df = datasets._star(spark, d).select(*(F.col(a).cast("double").alias(a) for a in datasets.LI9))
    return metrics.entropy(df, list(datasets.LI9)).select("attr", F.round("h", 8).alias("h"))


@query(Q.released(numbered=True) + " " + " UNION ALL ".join(f"SELECT '{c}' AS attr, round({_H(f'x{i}', 'rel')}, 7) AS h_orig, round({_H(f'round(r{i}, 9)', 'rel')}, 7) AS h_pert, round({_H(f'round(r{i}, 9)', 'rel')} - {_H(f'x{i}', 'rel')}, 7) AS gain" for i, c in enumerate(Q.COLS)))
def entropy_gain_li4(spark, d):
    m, rel, _ = _pairs(spark, d)
    got = metrics.entropy_gain(m, rel.withColumns({a: F.round(a, 9) for a in ATTRS}), ATTRS)
    return got.select("attr", *(F.round(c, 7).alias(c) for c in ("h_orig", "h_pert", "gain")))


@query(Q.released(numbered=True) + " " + " UNION ALL ".join(f"SELECT '{c}' AS attr, round((SELECT avg(CASE WHEN r{i} BETWEEN lo AND hi THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) FROM rel, (SELECT min(x{i}) AS lo, max(x{i}) AS hi FROM rel)), 8) AS share" for i, c in enumerate(Q.COLS)))
def range_share(spark, d):
    m, rel, _ = _pairs(spark, d)
    return metrics.range_share(m, rel, ATTRS).select("attr", F.round("share", 8).alias("share"))


@query(Q.released(numbered=True) + " " + " UNION ALL ".join(f"SELECT '{c}' AS attr, round((avg(r{i}) - avg(x{i})) / stddev_samp(x{i}), 7) AS mean_shift, round(stddev_samp(r{i}) / stddev_samp(x{i}), 7) AS sd_ratio FROM rel" for i, c in enumerate(Q.COLS)))
def bias_report(spark, d):
    m, rel, _ = _pairs(spark, d)
    return metrics.bias_report(m, rel, ATTRS).select("attr", F.round("mean_shift", 7).alias("mean_shift"), F.round("sd_ratio", 7).alias("sd_ratio"))


_ISO = lambda p: "sqrt(" + " + ".join(f"pow(q.{p}{i} - o.{p}{i}, 2)" for i in range(4)) + ")"


@query(f"{Q.base(numbered=True)}, {Q.moved()}, z AS (SELECT key, {', '.join(f'(x{i} - m{i}) / s{i} AS a{i}, y{i} AS b{i}' for i in range(4))} FROM moved, mo), q AS (SELECT * FROM z ORDER BY {uniform_sql('pairs', 'iso', 'key')}, key LIMIT 64) SELECT count(*) AS pairs, max(abs({_ISO('a')} - {_ISO('b')})) < 1e-9 AS kept FROM q JOIN z o ON q.key <> o.key")
def isometry_pairs(spark, d):
    m, _, model = _pairs(spark, d)
    z = standardize(m, fit(m, ATTRS))
    return metrics.isometry_error(z, move(z, model, standardized=True), ATTRS).select("pairs", (F.col("max_error") < 1e-9).alias("kept"))


def _friedman_sql(rows: str, block: str) -> str:
    return f"""WITH t AS (SELECT * FROM {rows}), r AS (SELECT *, rank() OVER (PARTITION BY {block} ORDER BY v) + (count(*) OVER (PARTITION BY {block}, v) - 1) / 2.0::DOUBLE AS r, count(*) OVER (PARTITION BY {block}, v) AS ties FROM t),
s AS (SELECT method, avg(r) AS mean_rank, sum(r) AS s FROM r GROUP BY method), b AS (SELECT count(*) / 3 AS b, sum(ties * ties - 1)::DOUBLE AS g FROM r),
x AS (SELECT (12.0::DOUBLE * (SELECT sum(s * s) FROM s) / (b * 12) - 12 * b) / (1 - g / (b * 24)) AS chi2 FROM b)
SELECT method AS treatment, round(mean_rank, 6) AS mean_rank, round(chi2, 4) AS chi2, 2 AS dof, round(exp(-chi2 / 2), 9) AS p FROM s, x"""


def _friedman(df: DataFrame, block: list[str]) -> DataFrame:
    got = metrics.friedman(df, block, "method", "v")
    return got.select("treatment", F.round("mean_rank", 6).alias("mean_rank"), F.round("chi2", 4).alias("chi2"), "dof", F.round("p", 9).alias("p"))


def _cells(spark, d, blocks: dict[str, str], value: str) -> DataFrame:
    """v: an attribute's mean in the records of every block and return flag (method)."""
    rows = spark.read.parquet(f"{d}/lineitem.parquet").select(*(F.expr(x).alias(b) for b, x in blocks.items()), F.col("l_returnflag").alias("method"), F.col(value).alias("v"))
    return rows.groupBy(*blocks, "method").agg(F.round(F.avg("v"), 7).alias("v"))


for _name, _blocks, _value in (
    ("friedman_memory", {"line": "l_linenumber"}, "l_extendedprice"),
    ("friedman_accuracy", {"line": "l_linenumber", "status": "l_linestatus"}, "l_quantity"),
    ("friedman_resistance", {"line": "l_linenumber", "rest": "l_suppkey % 5"}, "l_discount"),
):
    _sql = f"(SELECT {', '.join(f'{x} AS {b}' for b, x in _blocks.items())}, l_returnflag AS method, round(avg({_value}), 7) AS v FROM lineitem GROUP BY ALL)"
    query(_friedman_sql(_sql, ", ".join(_blocks)), _name)(lambda spark, d, blocks=_blocks, value=_value: _friedman(_cells(spark, d, blocks, value), list(blocks)))


@query("SELECT l_returnflag, l_linestatus, round(quantile_cont(l_quantity, 0.25), 6) AS q1, round(quantile_cont(l_quantity, 0.5), 6) AS median, round(quantile_cont(l_quantity, 0.75), 6) AS q3 FROM lineitem GROUP BY ALL")
def box_stats_accuracy(spark, d):
    got = metrics.box_stats(spark.read.parquet(f"{d}/lineitem.parquet"), ["l_returnflag", "l_linestatus"], "l_quantity")
    return got.select("l_returnflag", "l_linestatus", *(F.round(c, 6).alias(c) for c in ("q1", "median", "q3")))


@query(f"WITH t AS (SELECT * FROM {printed.values_sql(printed.accuracy_rows(), 'dataset, classifier, method, pct')}) SELECT a.dataset, a.classifier, a.method, round(o.pct - a.pct, 6) AS loss FROM t a JOIN t o ON o.dataset = a.dataset AND o.classifier = a.classifier AND o.method = 'Original' WHERE a.method <> 'Original'")
def utility_loss(spark, d):
    return metrics.utility_loss(printed.accuracy(spark)).withColumn("loss", F.round("loss", 6))


# --- classification ------------------------------------------------------------------------------------------

_LETTERS = [f"share_{c}" for c in datasets.LETTERS]
_LSQL = "docs AS (SELECT doc_id::VARCHAR AS key, lang, " + ", ".join(f"(length(text) - length(replace(text, '{c}', ''))) / n_chars::DOUBLE AS share_{c}" for c in datasets.LETTERS) + f", floor({uniform_sql('fold', 'fold', 'doc_id::VARCHAR')} * 10)::INT AS fold FROM documents WHERE length(text) > 0)"
_NB = f"""WITH {_LSQL}, held AS (SELECT h::INT AS held FROM range(0, 10) r(h)),
tr AS (SELECT held, lang AS c, count(*) AS n, {', '.join(f'avg({a}) AS m_{a}, greatest(avg({a} * {a}) - avg({a}) * avg({a}), 1e-9) AS v_{a}' for a in _LETTERS)} FROM docs JOIN held ON fold <> held GROUP BY ALL),
w AS (SELECT *, sum(n) OVER (PARTITION BY held) AS total FROM tr),
sc AS (SELECT key, fold, lang, c, -2 * ln(n / total) + {' + '.join(f'ln(v_{a}) + pow({a} - m_{a}, 2) / v_{a}' for a in _LETTERS)} AS cost FROM docs JOIN w ON fold = held),
best AS (SELECT key, fold, lang, arg_min(c, cost) AS p FROM sc GROUP BY ALL)
SELECT fold, sum((lang = p)::BIGINT)::BIGINT AS correct, count(*) AS total FROM best GROUP BY fold"""


def _letters(spark, d):
    df, spec = datasets.doc_letters(spark, d)
    return as_matrix(df, spec), spec


@query(_NB)
def nb_accuracy_doc_letters(spark, d):
    return classify.cv_native(*_letters(spark, d), algorithm="nb")


_CEN = _NB.replace("w AS (SELECT *, sum(n) OVER (PARTITION BY held) AS total FROM tr)", "w AS (SELECT tr.*, " + ", ".join(f"d_{a}" for a in _LETTERS) + " FROM tr JOIN (SELECT held, " + ", ".join(f"var_samp({a}) AS d_{a}" for a in _LETTERS) + " FROM docs JOIN held ON fold <> held GROUP BY held) USING (held))")
_CEN = _CEN.replace("-2 * ln(n / total) + " + " + ".join(f"ln(v_{a}) + pow({a} - m_{a}, 2) / v_{a}" for a in _LETTERS), " + ".join(f"pow({a} - m_{a}, 2) / d_{a}" for a in _LETTERS))


@query(_CEN)
def centroid_accuracy_doc_letters(spark, d):
    return classify.cv_native(*_letters(spark, d), algorithm="centroid")


@query()
def knn_accuracy_doc_letters(spark, d):
    m, spec = _letters(spark, d)
    with holding():
        return settled(classify.cv_accuracy(hold(m), spec, "knn", folds=10))


# --- audits --------------------------------------------------------------------------------------------------


@query("SELECT min(c) AS k, count(*) AS classes FROM (SELECT count(*) AS c FROM lineitem GROUP BY l_returnflag, l_linestatus, l_linenumber)")
def k_anonymity(spark, d):
    return audit.k_anonymity(spark.read.parquet(f"{d}/lineitem.parquet"), ["l_returnflag", "l_linestatus", "l_linenumber"])


@query("SELECT min(c) AS l FROM (SELECT count(DISTINCT l_returnflag) AS c FROM lineitem GROUP BY l_linestatus, l_linenumber)")
def l_diversity(spark, d):
    return audit.l_diversity(spark.read.parquet(f"{d}/lineitem.parquet"), ["l_linestatus", "l_linenumber"], "l_returnflag")


@query("WITH c AS (SELECT l_linestatus, l_linenumber, l_returnflag, count(*) AS c FROM lineitem GROUP BY ALL), s AS (SELECT sum(c) AS n, max(c) AS top FROM c GROUP BY l_linestatus, l_linenumber) SELECT round(max(top / n), 9) AS alpha, min(n)::BIGINT AS k FROM s")
def alpha_k_anonymity(spark, d):
    return audit.alpha_k(spark.read.parquet(f"{d}/lineitem.parquet"), ["l_linestatus", "l_linenumber"], "l_returnflag").select(F.round("alpha", 9).alias("alpha"), "k")


@query("WITH w AS (SELECT l_returnflag AS f, count(*) / (SELECT count(*) FROM lineitem) AS p FROM lineitem GROUP BY 1), g AS (SELECT l_linestatus, l_linenumber, count(*) AS n FROM lineitem GROUP BY 1, 2), c AS (SELECT l_linestatus, l_linenumber, l_returnflag AS f, count(*) AS c FROM lineitem GROUP BY 1, 2, 3), x AS (SELECT g.l_linestatus, g.l_linenumber, sum(abs(coalesce(c, 0) / n - p)) / 2 AS t FROM g CROSS JOIN w LEFT JOIN c ON c.l_linestatus = g.l_linestatus AND c.l_linenumber = g.l_linenumber AND c.f = w.f GROUP BY ALL) SELECT round(max(t), 9) AS t FROM x")
def t_closeness(spark, d):
    return audit.t_closeness(spark.read.parquet(f"{d}/lineitem.parquet"), ["l_linestatus", "l_linenumber"], "l_returnflag").select(F.round("t", 9).alias("t"))


# --- data sets -----------------------------------------------------------------------------------------------

for _name, _f in datasets.DATASETS.items():

    def _profile(spark, d, f=_f):
        df, spec = f(spark, d)
        m = as_matrix(df, spec)
        mo = fit(m, spec.value_cols)
        c = search.select(search.grid_cov(mo.cov[np.ix_(mo.sd > 0, mo.sd > 0)]), geometry.angles())
        return spark.createDataFrame([(mo.rows, spec.n, c.theta, c.axis, round(c.phi_opt, 6))], "rows long, attributes int, theta_deg int, axis int, phi_opt double")

    query(None, f"ds_{_name}")(_profile)
