"""Measures, attacks, baselines, classifiers."""

import numpy as np
import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from veilframe.plans import attacks, baselines, classify, datasets, geometry, metrics, places, workloads
from veilframe.plans.matrix import KEY, NumericMatrixSpec, as_matrix
from veilframe.plans.moments import fit
from veilframe.plans.perturb import fit_model, release
from veilframe.queries import printed


@pytest.fixture(scope="module")
def li4(spark, sf_small):
    df, spec = datasets.li4(spark, sf_small)
    return as_matrix(df, spec).dropDuplicates([KEY]).persist(), spec, list(spec.value_cols)


# Mean ranks (RP, GP, SMP), statistic and p of the three printed comparisons.
@pytest.mark.parametrize(
    "table,block,value,want",
    [
        (printed.memory, ["dataset"], "v", ((1.86, 2.57, 1.57), 3.7143, 0.1561)),
        (printed.accuracy, ["dataset", "classifier"], "pct", ((1.41, 1.99, 2.60), 24.7914, 4.1364e-06)),
        (printed.resistance, ["dataset", "measure"], "v", ((1.65, 1.85, 2.50), 16.6108, 2.4718e-04)),
    ],
)
def test_rank_test_golden(spark, table, block, value, want):
    rows = table(spark).where("method <> 'Original'").withColumnRenamed(value, "val")
    got = {r.treatment: r for r in metrics.friedman(rows, block, "method", "val").collect()}
    assert [round(got[m].mean_rank, 2) for m in printed.METHODS] == pytest.approx(want[0], abs=0.011)
    assert round(got["SMP"].chi2, 4) == want[1] and got["SMP"].p == pytest.approx(want[2], rel=1e-3)
    assert metrics.chi2_tail(got["SMP"].chi2, 2) == pytest.approx(want[2], rel=1e-3)


def test_ks_cutoffs():
    # Least statistic, times n, that tells two samples of n apart.
    want = {4: 4, 5: 4, 7: 5, 8: 5, 9: 6, 11: 6, 12: 7, 17: 8, 28: 10, 64: 15}
    assert {n: metrics.ks_cutoff(n) for n in want} == want


def test_ks_tuples_ends(li4):
    matrix, _, attrs = li4
    m = fit(matrix, attrs)
    same = metrics.ks_tuples(metrics.paired(matrix, matrix, attrs), m)
    assert same.where("d <> 0 or rejected").count() == 0
    far = matrix.select(KEY, *(F.col(a) + 1e9 for a in attrs)).toDF(KEY, *attrs)
    apart = metrics.ks_tuples(metrics.paired(matrix, far, attrs), m)
    assert apart.where("d <> 1 or not rejected").count() == 0


def test_ks_attributes_by_numpy(li4):
    matrix, spec, attrs = li4
    other = release(matrix, fit_model(matrix, spec), "none")
    got = {r.attr: r.d for r in metrics.ks_attributes(matrix, other, attrs).collect()}
    for a in attrs:
        x, y = (np.sort([r[0] for r in df.select(a).collect()]) for df in (matrix, other))
        at = np.concatenate([x, y])
        want = np.abs(np.searchsorted(x, at, side="right") / len(x) - np.searchsorted(y, at, side="right") / len(y)).max()
        assert got[a] == pytest.approx(want, abs=1e-12)


def test_entropy(spark):
    df = spark.createDataFrame([(float(i), 1.0) for i in range(64)], "u double, c double")
    got = {r.attr: r.h for r in metrics.entropy(df, ["u", "c"]).collect()}
    assert got["u"] == pytest.approx(6) and got["c"] == pytest.approx(0)
    assert all(r.gain == 0 for r in metrics.entropy_gain(df, df.orderBy(F.desc("u")), ["u", "c"]).collect())


def test_isometry(li4):
    matrix, spec, attrs = li4
    from veilframe.plans.moments import standardize
    from veilframe.plans.perturb import move

    model = fit_model(matrix, spec)
    z = standardize(matrix, fit(matrix, attrs))
    r = metrics.isometry_error(z, move(z, model, standardized=True), attrs).first()
    assert r.pairs > 100 and r.max_error < 1e-9


def test_phi_of_the_release_is_the_guarantee(li4):
    matrix, spec, attrs = li4
    model = fit_model(matrix, spec, sigma=0.0)
    from veilframe.plans.moments import standardize

    m = fit(matrix, attrs)
    got = metrics.phi(metrics.paired(standardize(matrix, m), standardize(release(matrix, model, "none"), m), attrs), attrs).first()["phi"]
    assert got == pytest.approx(model.phi_opt, abs=1e-6)


def test_known_pairs_undo_a_plain_rotation(li4):
    matrix, spec, attrs = li4
    plain = release(matrix, fit_model(matrix, spec, sigma=0.0), "none")
    for solver in ("lstsq", "procrustes"):
        assert attacks.known_io(matrix, plain, attrs, solver=solver).first()["std_avg"] < 1e-3
    assert attacks.known_io(matrix, plain, attrs, pairing="released").first()["std_min"] > 1.3  # order hides the pairs


def test_independent_components_are_found(li4):
    """The line columns are independent and not normal: the ideal case for this attack."""
    matrix, spec, attrs = li4
    plain = release(matrix, fit_model(matrix, spec, sigma=0.0), "none")
    assert attacks.ica(matrix, plain, attrs).first()["std_avg"] < 0.25


def test_shuffled_naive_is_root_two(li4):
    matrix, spec, attrs = li4
    r = attacks.naive(matrix, release(matrix, fit_model(matrix, spec), "none"), attrs, "released").first()
    assert r.std_avg == pytest.approx(np.sqrt(2), abs=0.03)


def test_every_row_gets_one_place(li4):
    matrix, _, attrs = li4
    assert attacks.by_place(matrix, matrix, attrs).count() == matrix.count()


def test_component_matching():
    corr = np.array([[0.1, -0.9], [0.8, 0.2]])
    assert attacks.match_components(corr) == [(0, 1, -1.0), (1, 0, 1.0)]


def test_baselines(li4):
    matrix, spec, attrs = li4
    m = fit(matrix, attrs)
    q, score = baselines.best_orthogonal(matrix, m, 10, "x")
    assert geometry.orthogonality_error(q) < 1e-12
    assert baselines.best_orthogonal(matrix, m, 3, "x", "data")[1] == pytest.approx(baselines.best_orthogonal(matrix, m, 3, "x")[1], abs=1e-9)
    for df in (baselines.rotation(matrix, spec), baselines.geometric(matrix, spec), *(baselines.additive(matrix, spec, dist=k) for k in ("normal", "uniform", "laplace"))):
        assert df.count() == matrix.count() and df.columns == matrix.columns
    noisy = metrics.diff_variance(metrics.paired(matrix, baselines.additive(matrix, spec, 0.5, "laplace"), attrs), attrs)
    for r in noisy.collect():
        assert r.variance == pytest.approx((0.5 * m.sd[attrs.index(r.attr)]) ** 2, rel=0.1)


def test_randomized_response_estimate(li4):
    matrix, _, _ = li4
    answers = baselines.randomized_response(matrix, "cls", F.col(KEY), ["A", "N", "R"], 0.6)
    truth = {r["cls"]: r["count"] / matrix.count() for r in matrix.groupBy("cls").count().collect()}
    for r in baselines.response_estimate(answers, "cls", 3, 0.6).collect():
        assert r.estimate == pytest.approx(truth[r["cls"]], abs=0.04)


@pytest.mark.parametrize("algorithm", ["nb", "centroid"])
def test_native_folds_equal_fold_by_fold(spark, sf_mid, algorithm):
    df, spec = datasets.cust_spend(spark, sf_mid)
    m = as_matrix(df, spec)
    rows = classify.with_folds(m)
    one = {r.fold: (r.correct, r.total) for r in classify.cv_native(m, spec, algorithm=algorithm).collect()}
    assert sum(t for _, t in one.values()) == m.count()
    run = classify.gaussian_nb if algorithm == "nb" else classify.nearest_centroid
    got = run(rows.where("fold <> 4"), rows.where("fold = 4"), list(spec.value_cols), "cls")
    assert (got.where("cls = predicted").count(), got.count()) == one[4]


def test_classifiers_learn(spark, sf_mid):
    df, spec = datasets.doc_letters(spark, sf_mid)
    m = as_matrix(df, spec).persist()
    rows = classify.with_folds(m)
    for algorithm in ("knn", "tree", "svm", "mlp", "nb"):
        got = classify.predict(algorithm, rows.where("fold <> 0"), rows.where("fold = 0"), list(spec.value_cols), "cls")
        r = got.agg(F.avg((F.col("cls") == F.col("predicted")).cast("double")).alias("a"), F.count("*").alias("n")).first()
        assert r.n == rows.where("fold = 0").count() and r.a > 0.8, algorithm


def test_method_keeps_more_accuracy_than_random_rotation(spark, sf_mid):
    got = {(r.dataset, r.method): r.pct for r in workloads.accuracy_study(spark, sf_mid, ("cust_spend", "order_value"), ("nb",)).collect()}
    mean = lambda k: (got["cust_spend", k] + got["order_value", k]) / 2
    assert mean("SMP") > mean("RP")


def test_guarantee_rises_toward_the_middle(spark, sf_mid):
    got = {r.theta_deg: r for r in workloads.guarantee_dynamics(spark, sf_mid, degrees=(5, 35)).collect()}
    assert got[35].std_min > got[5].std_min and got[35].phi > got[5].phi


def test_noise_raises_the_least_deviation(spark, sf_mid):
    rows = sorted(map(tuple, workloads.sigma_sweep(spark, sf_mid, "cust_spend", (0.0, 0.5, 1.0)).collect()))
    assert rows[0][1] < rows[1][1] < rows[2][1]


def test_risk_levels(spark):
    df = spark.createDataFrame([("a", 0.7), ("b", 0.3), ("c", 0.0), ("d", None)], "attack string, std_min double")
    assert [r.level for r in attacks.risk_table(df).orderBy("attack").collect()] == ["low", "moderate", "high", "inconclusive"]
    spec = NumericMatrixSpec(("x",))
    assert spec.n == 1


@pytest.mark.parametrize("per_slot", [50, 1_000_000])
def test_classes_of_equal_size(spark, monkeypatch, per_slot):
    """Two-level places give the classes of one ordered pass, with ties, nulls and rows left over."""
    monkeypatch.setattr(places, "PER_SLOT", per_slot)
    df = spark.range(503).select("id", F.when(F.col("id") % 11 == 0, None).otherwise(F.col("id") * 7919 % 83).cast("double").alias("v"))
    got = datasets._ntile(df, 7, F.col("v"), ("id",)).select("id", "cls")
    want = df.select("id", F.ntile(7).over(Window.orderBy("v", "id")).alias("cls"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_ks_with_an_outlier_and_many_slots(spark, monkeypatch):
    monkeypatch.setattr(places, "PER_SLOT", 20)
    rng = np.random.default_rng(3)
    x, y = np.append(rng.normal(size=400), 1e12), rng.normal(0.3, 1, 300).round(1)
    df = lambda v: spark.createDataFrame([(float(a),) for a in v] + [(None,)], "a double")
    got = metrics.ks_attributes(df(x), df(y), ["a"]).first()
    at = np.concatenate([x, y])
    want = np.abs(np.searchsorted(np.sort(x), at, side="right") / len(x) - np.searchsorted(np.sort(y), at, side="right") / len(y)).max()
    assert got.d == pytest.approx(want, abs=1e-12) and (got.n, got.m) == (401, 300)


def test_repeated_keys(spark):
    df = spark.createDataFrame([(1, 5.0), (1, 3.0), (2, 4.0), (1, 3.0)], "id int, x double")
    spec = NumericMatrixSpec(("x",), ("id",))
    own = as_matrix(df, spec, repeated="number")
    assert sorted((r[KEY], r.x) for r in own.collect()) == [("1", 3.0), ("1#2", 3.0), ("1#3", 5.0), ("2", 4.0)]
    assert metrics.paired(own, own, ["x"]).count() == 4
    with pytest.raises(Exception, match="a key repeats"):
        as_matrix(df, spec, repeated="error").collect()


def test_distances_by_brute_force(li4):
    matrix, spec, attrs = li4
    plain = release(matrix, fit_model(matrix, spec, sigma=0.3), "none")
    got = attacks.distance(matrix, plain, attrs, known=8, eps=0.2).first()
    scaled = []
    for df in (matrix, plain):
        m = fit(df, attrs)
        scaled.append({r[KEY]: (np.array([r[a] for a in attrs]) - m.mean) / m.sd for r in df.collect()})
    x, y = scaled
    draws = matrix.select(KEY, attacks.uniform("dist", "known", F.col(KEY)).alias("u")).collect()
    known = sorted(r[KEY] for r in sorted(draws, key=lambda r: (r.u, r[KEY]))[:8])
    hits = [(b, k) for i, a in enumerate(known) for b in known[i + 1 :] for k in y if k != a and abs(np.linalg.norm(x[a] - x[b]) - np.linalg.norm(y[a] - y[k])) < 0.2]
    assert (got.pairs, got.matches, got.true_matches) == (28, len(hits), sum(b == k for b, k in hits))


def test_every_method_meets_both_pairings(spark, sf_small):
    study = workloads.resistance_study(spark, sf_small, ("cust_spend",), ("ni",)).persist()
    assert {(r.method, r.pairing) for r in study.collect()} == {(m, p) for m in workloads.METHODS for p in ("true", "released")}
    ranks = workloads.resistance_ranks(study)
    assert {(r.treatment, r.pairing) for r in ranks.collect()} == {(m, p) for m in workloads.METHODS for p in ("true", "released")}


@pytest.mark.parametrize("k", [1, 3])
def test_neighbours_block_by_block(monkeypatch, k):
    """Blocks of training rows give the neighbours of one matrix of all distances, none of which is held."""
    rng = np.random.default_rng(2)
    q, x = rng.normal(size=(40, 3)), rng.normal(size=(500, 3)).round(1)
    d = (x * x).sum(axis=1) - 2 * q @ x.T
    want = np.sort(np.take_along_axis(d, np.argsort(d, axis=1, kind="stable")[:, :k], axis=1), axis=1)
    for rows in (2, 64, 1000):
        monkeypatch.setattr(classify, "ROWS_AT_ONCE", rows)
        at = classify.nearest(q, x, (x * x).sum(axis=1), k)
        assert np.allclose(np.sort(np.take_along_axis(d, at, axis=1), axis=1), want) and at.shape == (40, k)


def test_held_tables_are_dropped_and_records_keep_to_themselves(spark):
    """beside() gives every record once, also where keys repeat, and what a study holds goes with it."""
    from veilframe.plans.held import hold, holding

    df = spark.createDataFrame([(i // 2, float(i), float(i * i % 7)) for i in range(40)], "id int, x double, y double")
    spec = NumericMatrixSpec(("x", "y"), ("id",))
    matrix = as_matrix(df, spec)
    assert hold(matrix) is matrix
    with holding():
        pairs = workloads.beside(matrix, spec, fit(matrix, spec.value_cols), "SMP")
        assert pairs.storageLevel.useDisk and pairs.count() == 40
        assert sorted(r.x_x for r in pairs.collect()) == [float(i) for i in range(40)]
    assert not pairs.storageLevel.useDisk


def test_small_tables_stay_spread_over_slots(spark):
    """Places of a table of under a million rows are not found in one task."""
    from veilframe.plans.held import gathered, holding

    assert places.slots_for(900_000) > 50 and places.slots_for(100) == 1
    with holding():
        assert gathered(spark.range(0, 40, 1, 8), 40).rdd.getNumPartitions() == 1


def test_resistance_study_equals_attacks_on_pairs(spark, sf_small):
    """Versions beside their records and moments found once give what pairing each by itself gives."""
    study = {(r.attack, r.pairing): (r.std_min, r.std_avg) for r in workloads.resistance_study(spark, sf_small, ("cust_spend",), ("ni", "io"), methods=("SMP",)).collect()}
    matrix, spec, m = workloads.load(spark, sf_small, "cust_spend")
    attrs = list(spec.value_cols)
    rows = workloads.version(matrix, spec, m, "SMP")
    for pairing in ("true", "released"):
        for kind, run in (("ni", attacks.naive), ("io", attacks.known_io)):
            assert study[kind, pairing] == pytest.approx(tuple(run(matrix, rows, attrs, pairing=pairing).first()), rel=1e-9)


@pytest.mark.parametrize("k", [1, 3])
def test_neighbours_by_blocks_need_no_driver(spark, monkeypatch, k):
    """Blocks of rows against parts of queries find what all distances give, repeated keys and null labels included,
    and no training row is gathered by the driver."""
    for name, size in (("BLOCK", 90), ("PART", 30), ("ASKED_AT_ONCE", 16), ("BOX", 8)):
        monkeypatch.setattr(classify, name, size)
    monkeypatch.setattr(type(spark.range(1)), "toArrow", lambda *_: pytest.fail("rows are gathered by the driver"))
    rng = np.random.default_rng(4)
    rows = [(f"k{i // 2}", float(a), float(b), 7.0, None if i % 9 == 0 else int(a > 0) + int(b > 0)) for i, (a, b) in enumerate(rng.normal(size=(600, 2)))]
    df = spark.createDataFrame([(*r, i) for i, r in enumerate(rows)], f"{KEY} string, a double, b double, c double, cls int, i int")
    got = classify.knn(df.where("i < 480"), df.where("i >= 480"), ["a", "b", "c"], "cls", k)
    x = np.array([r[1:3] for r in rows])
    x = x / x[:480].std(axis=0, ddof=1)
    want = []
    for i in range(480, 600):
        near = np.argsort(((x[:480] - x[i]) ** 2).sum(axis=1), kind="stable")[:k]
        labels = [str(rows[j][4]) for j in near]
        want.append((rows[i][0], str(rows[i][4]), min(labels, key=lambda y: (-labels.count(y), y))))
    assert sorted((r[0], str(r.cls), str(r.predicted)) for r in got.collect()) == sorted(want)


def test_nearest_neighbour_is_asked_for_in_every_fold(spark, sf_small):
    """The query has all ten folds and every document, with the counts of all distances (equal ones: smaller key)."""
    from veilframe.queries import core

    got = [tuple(r) for r in core.QUERIES["knn_accuracy_doc_letters"](spark, sf_small).collect()]
    df, spec = datasets.doc_letters(spark, sf_small)
    rows = sorted(classify.with_folds(as_matrix(df, spec)).select(KEY, "cls", "fold", *spec.value_cols).collect())
    x, y, fold = np.array([r[3:] for r in rows]), np.array([r[1] for r in rows]), np.array([r[2] for r in rows])
    want = []
    for k in range(10):
        sd = x[fold != k].std(axis=0, ddof=1)
        d = ((x[fold == k][:, None, :] / sd - x[fold != k][None] / sd) ** 2).sum(axis=2)
        want.append((k, int((y[fold != k][d.argmin(axis=1)] == y[fold == k]).sum()), int((fold == k).sum())))
    assert got == want and sum(t for _, _, t in got) == len(rows)


def test_nearest_neighbours_of_all_folds_by_blocks(spark, monkeypatch):
    """Blocks of points against parts of them find what all distances give: equal rows, repeated keys, null labels,
    constants, attributes without spread outside a fold, and folds without records included."""
    for name, size in (("PACK", 90), ("TASKS", 5), ("LEAST_PART", 20), ("ASKED_AT_ONCE", 16), ("QUERIES_AT_ONCE", 7), ("BOX", 8)):
        monkeypatch.setattr(classify, name, size)
    rng = np.random.default_rng(5)
    values = np.round(rng.normal(size=(500, 2)) * 8) / 8
    values[rng.random(500) < 0.2] = 0.0
    rows = [(f"k{i // 2}", float(a), float(b), 0.1, 0.0, None if i % 9 == 0 else int(rng.integers(3))) for i, (a, b) in enumerate(values)]
    rows[7] = (*rows[7][:4], 5.0, rows[7][5])
    schema = f"{KEY} string, a double, b double, c double, d double, cls int"
    spec = NumericMatrixSpec(("a", "b", "c", "d"), (KEY,), "cls")
    for some, folds in ((rows, 4), (rows[:6], 10), (rows[:1], 2), ([], 2)):
        df = spark.createDataFrame(some, schema)
        fold = {r[0]: r.fold for r in classify.with_folds(df, folds).collect()}
        got = [tuple(r) for r in classify.cv_accuracy(df, spec, "knn", folds).collect()]
        want = []
        for k in range(folds):
            train, test = sorted((r for r in some if fold[r[0]] != k), key=lambda r: (r[0], str(r[5]))), [r for r in some if fold[r[0]] == k]
            x = np.array([r[1:5] for r in train]).reshape(-1, 4)
            spread = np.ptp(x, axis=0) > 0 if len(train) > 1 else np.zeros(4, dtype=bool)
            weights = np.divide(1, x.var(axis=0, ddof=1), out=np.zeros(4), where=spread) if spread.any() else np.zeros(4)
            hits = 0
            for r in test:
                if train:
                    d = ((x - np.array(r[1:5])) ** 2 * weights).sum(axis=1)
                    hits += r[5] is not None and train[int(d.argmin())][5] == r[5]
            want.append((k, hits, len(test)))
        assert got == want, (len(some), folds)
