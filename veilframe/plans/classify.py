"""Accuracy by k-fold cross-validation of five classifiers (and two with plain SQL twins)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rng import uniform
from .held import hold
from .matrix import KEY, NumericMatrixSpec

ALGORITHMS = ("mlp", "knn", "svm", "nb", "tree", "centroid")


def with_folds(df: DataFrame, folds: int = 10, seed: str = "fold") -> DataFrame:
    return df.withColumn("fold", F.floor(uniform(seed, "fold", F.col(KEY)) * folds).cast("int"))


def nearest_centroid(train: DataFrame, test: DataFrame, attrs: list[str], label: str) -> DataFrame:
    """key, label, predicted. Attributes over the training deviation; ties to the smaller label."""
    sd = train.agg(*(F.stddev_samp(a).alias(f"s_{a}") for a in attrs))
    centre = train.groupBy(F.col(label).alias("__c")).agg(*(F.avg(a).alias(f"c_{a}") for a in attrs)).join(F.broadcast(sd))
    d = sum((F.pow((F.col(a) - F.col(f"c_{a}")) / F.col(f"s_{a}"), 2) for a in attrs), F.lit(0.0))
    return test.join(F.broadcast(centre)).groupBy(KEY, label).agg(F.min(F.struct(d.alias("d"), F.col("__c").alias("c")))["c"].alias("predicted"))


def gaussian_nb(train: DataFrame, test: DataFrame, attrs: list[str], label: str) -> DataFrame:
    """key, label, predicted, from each class's means, variances and share; ties to the smaller label."""
    n = train.agg(F.count(F.lit(1)).alias("__n"))
    by = train.groupBy(F.col(label).alias("__c")).agg(F.count(F.lit(1)).alias("__k"), *(F.avg(a).alias(f"m_{a}") for a in attrs), *(F.greatest(F.var_pop(a), F.lit(1e-9)).alias(f"v_{a}") for a in attrs)).join(F.broadcast(n))
    cost = -2 * F.log(F.col("__k") / F.col("__n")) + sum((F.log(f"v_{a}") + F.pow(F.col(a) - F.col(f"m_{a}"), 2) / F.col(f"v_{a}") for a in attrs), F.lit(0.0))
    return test.join(F.broadcast(by)).groupBy(KEY, label).agg(F.min(F.struct(cost.alias("d"), F.col("__c").alias("c")))["c"].alias("predicted"))


#: Queries and training rows whose distances a task holds at a time.
QUERIES_AT_ONCE, ROWS_AT_ONCE = 256, 4096


def nearest(q: np.ndarray, x: np.ndarray, own: np.ndarray, k: int) -> np.ndarray:
    """Places in x of each query's k nearest rows, training rows block by block; for k = 1 the first of equals.

    own: the rows' squared lengths. A query's own length changes no order and is left out."""
    best, at = np.full((len(q), 0), np.inf), np.zeros((len(q), 0), dtype=np.int64)
    for a in range(0, len(x), ROWS_AT_ONCE):
        d = (-2 * q) @ x[a : a + ROWS_AT_ONCE].T
        d += own[a : a + ROWS_AT_ONCE]
        if k == 1:
            near = d.argmin(axis=1)[:, None]
        else:
            near = np.argpartition(d, min(k, d.shape[1]) - 1, axis=1)[:, :k]
        best, at = np.concatenate([best, np.take_along_axis(d, near, axis=1)], axis=1), np.concatenate([at, near + a], axis=1)
        if best.shape[1] > k:
            keep = best.argmin(axis=1)[:, None] if k == 1 else np.argpartition(best, k - 1, axis=1)[:, :k]
            best, at = np.take_along_axis(best, keep, axis=1), np.take_along_axis(at, keep, axis=1)
    return at


#: Training rows of a block, queries of a part (a task compares one with the other), queries that a task searches for
#: at a time, and training rows of a box.
BLOCK, PART, ASKED_AT_ONCE, BOX = 262_144, 32_768, 16_384, 1024
#: For all folds at once: points packed into a block or part at most, parts that are aimed at, and points of a part at least.
PACK, TASKS, LEAST_PART = 131_072, 24, 8192


def boxes(x: np.ndarray, size: int) -> list[np.ndarray]:
    """The rows of x in boxes of up to `size` (more only of equal rows), halved along the widest side."""
    todo, out = [np.arange(len(x))], []
    while todo:
        at = todo.pop()
        if len(at) <= size or not (wide := np.ptp(x[at], axis=0)).any():
            out.append(at)
            continue
        half = len(at) // 2
        at = at[np.argpartition(x[at, wide.argmax()], half)]
        todo += [at[:half], at[half:]]
    return out


def searched(q: np.ndarray, x: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Squared distances to and places in x of each query's k nearest rows (all, where x has fewer), nearest first.

    Exact: a box of rows is left out for a query only where it lies farther than the k-th row found before."""
    k, centre = min(k, len(x)), x.mean(axis=0)
    turn = np.linalg.eigh((x - centre).T @ (x - centre))[1]  # boxes along the main axes are smaller; distances stay
    x, q = (x - centre) @ turn, (q - centre) @ turn
    held = boxes(x, BOX)
    rows = [np.ascontiguousarray(x[at]) for at in held]
    own = [(r * r).sum(axis=1) for r in rows]
    low, high = np.array([r.min(axis=0) for r in rows]), np.array([r.max(axis=0) for r in rows])
    best, found = np.full((len(q), k), np.inf), np.zeros((len(q), k), dtype=np.int64)
    for a in range(0, len(q), ASKED_AT_ONCE):
        some = q[a : a + ASKED_AT_ONCE]
        gap = np.column_stack([(np.maximum(np.maximum(lo - some, some - hi), 0) ** 2).sum(axis=1) for lo, hi in zip(low, high, strict=True)])
        order, live = gap.argsort(axis=1), np.arange(len(some))
        for turn_of in range(len(held)):
            box = order[live, turn_of]
            near_enough = gap[live, box] * (1 - 1e-9) <= best[a + live, -1]
            live, box = live[near_enough], box[near_enough]
            if not len(live):
                break
            by_box = np.argsort(box, kind="stable")
            ends = np.flatnonzero(np.diff(box[by_box])) + 1
            for group in np.split(by_box, ends):
                b = box[group[0]]
                for c in range(0, len(group), QUERIES_AT_ONCE):
                    who = live[group[c : c + QUERIES_AT_ONCE]]
                    near = nearest(some[who], rows[b], own[b], min(k, len(rows[b])))
                    d = np.concatenate([best[a + who], ((some[who][:, None, :] - rows[b][near]) ** 2).sum(axis=2)], axis=1)
                    at = np.concatenate([found[a + who], held[b][near]], axis=1)
                    keep = d.argsort(axis=1, kind="stable")[:, :k]
                    best[a + who], found[a + who] = np.take_along_axis(d, keep, axis=1), np.take_along_axis(at, keep, axis=1)
    return best, found


def knn(train: DataFrame, test: DataFrame, attrs: list[str], label: str, k: int = 1) -> DataFrame:
    """Exact k nearest neighbours on attributes over the training deviation.

    Every block of training rows meets every part of the queries in a task of its own, and the nearest rows of the
    blocks are merged by query, so neither side has to fit the driver or one task. Equal distances: smaller key, then
    smaller label; equal votes: smaller label."""
    whole = train.agg(F.count(F.lit(1)), *(f(a) for f in (F.avg, F.stddev_samp) for a in attrs)).first()
    n, asked = whole[0], test.count()
    mean, scale = np.array([x or 0.0 for x in whole[1 : len(attrs) + 1]]), np.array([1 / s if s else 0.0 for s in whole[len(attrs) + 1 :]])
    blocks, parts = n // BLOCK + 1, asked // PART + 1
    dealt = lambda *c, of: F.pmod(F.xxhash64(*c), F.lit(of)).cast("int")
    each = lambda of: F.explode(F.sequence(F.lit(0), F.lit(of - 1)))
    named = F.coalesce(F.col(label).cast("string"), F.lit("None"))
    own = Window.partitionBy(KEY).orderBy(label, *attrs)  # records of one key stay apart
    kind = test.schema[label].dataType.simpleString()
    queries = test.select(KEY, label, *attrs).withColumn("__nr", F.row_number().over(own))
    spread = lambda df: df.repartition(3 * blocks * parts, "__block", "__part")
    left = spread(train.select(F.col(KEY).alias("__of"), named.alias("__y"), *(F.col(a).alias(f"__x_{a}") for a in attrs), dealt(KEY, *attrs, of=blocks).alias("__block")).withColumn("__part", each(parts)))
    right = spread(queries.withColumn("__part", dealt(KEY, "__nr", of=parts)).withColumn("__block", each(blocks)))

    def work(rows: pa.Table, wanted: pa.Table) -> pa.Table:
        def values(t: pa.Table, before: str = "") -> np.ndarray:
            return (np.column_stack([t.column(before + a).to_numpy() for a in attrs]) - mean) * scale

        if not rows.num_rows or not wanted.num_rows:
            return pa.table([pa.array([], t) for t in (pa.string(), pa.int32(), pa.float64(), pa.string(), pa.string())], names=["key", "nr", "d", "of", "y"])
        rows = rows.sort_by("__of")
        best, found = searched(values(wanted), values(rows, "__x_"), k)
        who = pa.array(np.repeat(np.arange(len(best)), best.shape[1]))
        hit = pa.array(found.ravel())
        return pa.table([wanted.column(KEY).take(who), wanted.column("__nr").take(who).cast(pa.int32()), pa.array(best.ravel()), rows.column("__of").take(hit), rows.column("__y").take(hit)], names=["key", "nr", "d", "of", "y"])

    by = lambda df: df.groupBy("__block", "__part")
    hits = by(left).cogroup(by(right)).applyInArrow(work, "key string, nr int, d double, of string, y string").groupBy("key", "nr")
    if k == 1:
        said = hits.agg(F.min(F.struct("d", "of", "y"))["y"].alias("predicted"))
    else:
        voters = F.transform(F.slice(F.sort_array(F.collect_list(F.struct("d", "of", "y"))), 1, k), lambda v: v["y"])
        votes = F.transform(F.array_distinct("v"), lambda y: F.struct((-F.size(F.filter("v", lambda o: o == y))).alias("n"), y.alias("y")))
        said = hits.agg(voters.alias("v")).select("key", "nr", F.array_min(votes)["y"].alias("predicted"))
    got = queries.join(said, (F.col(KEY) == F.col("key")) & (F.col("__nr") == F.col("nr")), "left")
    return got.select(KEY, label, F.col("predicted").try_cast(kind).alias("predicted"))


def _ml(algorithm: str, train: DataFrame, test: DataFrame, attrs: list[str], label: str) -> DataFrame:
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import DecisionTreeClassifier, LinearSVC, MultilayerPerceptronClassifier, NaiveBayes, OneVsRest
    from pyspark.ml.feature import StandardScaler, StringIndexer, VectorAssembler

    prep = Pipeline(stages=[StringIndexer(inputCol="__label", outputCol="__y", handleInvalid="keep", stringOrderType="alphabetAsc"), VectorAssembler(inputCols=attrs, outputCol="__raw"), StandardScaler(inputCol="__raw", outputCol="__x", withMean=True)])
    text = lambda df: df.withColumn("__label", F.col(label).cast("string"))
    ready = prep.fit(text(train))
    classes = len(ready.stages[0].labels)
    how = {"featuresCol": "__x", "labelCol": "__y"}
    kind = {
        "mlp": lambda: MultilayerPerceptronClassifier(layers=[len(attrs), max(2, (len(attrs) + classes) // 2), classes], maxIter=100, seed=7, **how),
        "svm": lambda: OneVsRest(classifier=LinearSVC(maxIter=30, regParam=0.001), **how),
        "nb": lambda: NaiveBayes(modelType="gaussian", **how),
        "tree": lambda: DecisionTreeClassifier(impurity="entropy", maxDepth=12, seed=7, **how),
    }[algorithm]()
    model = kind.fit(ready.transform(text(train)))
    names = F.array(*(F.lit(x) for x in ready.stages[0].labels))
    out = model.transform(ready.transform(text(test)))
    return out.select(KEY, label, F.get(names, F.col("prediction").cast("int")).cast(test.schema[label].dataType).alias("predicted"))


def predict(algorithm: str, train: DataFrame, test: DataFrame, attrs: list[str], label: str) -> DataFrame:
    if algorithm == "knn":
        return knn(train, test, attrs, label)
    if algorithm == "centroid":
        return nearest_centroid(train, test, attrs, label)
    return _ml(algorithm, train, test, attrs, label)


def nearest_apart(q: np.ndarray, of_q: np.ndarray, x: np.ndarray, of_x: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Squared distance to and place in x of each query's nearest row of another fold; inf and -1 where there is none.

    weights: by fold, of the attributes' squared differences. Exact: a box of rows is left out for a query only where
    it lies farther than the row found before, and what matrix products cannot tell apart is compared by differences.
    Of equally near rows the first of x."""
    best, found = np.full(len(q), np.inf), np.full(len(q), -1)
    if not len(q) or not len(x):
        return best, found
    unit = np.where(weights > 0, weights, np.inf).min(axis=0)
    unit[np.isinf(unit)] = 0  # an attribute that no fold counts
    centre, more = x.mean(axis=0), np.divide(weights, unit, out=np.ones_like(weights), where=unit > 0)
    xc, qc = (x - centre) * np.sqrt(unit), (q - centre) * np.sqrt(unit)
    turn = np.linalg.eigh(xc.T @ xc)[1]  # boxes along the main axes are smaller
    turned, asked = xc @ turn, qc @ turn
    held = [np.sort(at) for at in boxes(turned, BOX)]
    rounding = 1e-12 * max(np.abs(turned).max(), np.abs(asked).max())
    low, high = np.array([turned[at].min(axis=0) for at in held]) - rounding, np.array([turned[at].max(axis=0) for at in held]) + rounding
    own, length = more @ (xc * xc).T, (qc * qc * more[of_q]).sum(axis=1)
    room = 1e-13 * (length + own.max(axis=1)[of_q])
    own[of_x, np.arange(len(x))] = np.inf  # a query never meets its own fold
    rows, owns = [np.ascontiguousarray(xc[at].T) for at in held], [np.ascontiguousarray(own[:, at]) for at in held]
    del xc, turned, own  # as large as x each
    least_more = more.min(axis=1) * (1 - 1e-9)
    for a in range(0, len(q), ASKED_AT_ONCE):
        some, fold, best_here, found_here = (v[a : a + ASKED_AT_ONCE] for v in (q, of_q, best, found))
        gap = np.empty((len(some), len(held)))
        for b, (lo, hi) in enumerate(zip(low, high, strict=True)):
            out = np.maximum(np.maximum(lo - asked[a : a + ASKED_AT_ONCE], asked[a : a + ASKED_AT_ONCE] - hi), 0)
            gap[:, b] = np.einsum("ij,ij->i", out, out)
        gap *= least_more[fold][:, None]
        order, live, ask = gap.argsort(axis=1), np.arange(len(some)), -2 * qc[a : a + ASKED_AT_ONCE] * more[fold]
        for turn_of in range(len(held)):
            box = order[live, turn_of]
            near_enough = gap[live, box] <= best_here[live]
            live, box = live[near_enough], box[near_enough]
            if not len(live):
                break
            by_box = np.argsort(box, kind="stable")
            for group in np.split(by_box, np.flatnonzero(np.diff(box[by_box])) + 1):
                b = box[group[0]]
                for c in range(0, len(group), QUERIES_AT_ONCE):
                    who = live[group[c : c + QUERIES_AT_ONCE]]
                    d = ask[who] @ rows[b]
                    d += owns[b][fold[who]]
                    least = d.min(axis=1)
                    slack = room[a + who]
                    hope = np.flatnonzero(np.isfinite(least) & (least + length[a + who] <= best_here[who] + slack))
                    if not len(hope):
                        continue
                    i, j = np.nonzero(d[hope] <= (least + slack)[hope, None])
                    who, at = who[hope[i]], held[b][j]
                    d = ((x[at] - some[who]) ** 2 * weights[fold[who]]).sum(axis=1)
                    first = np.lexsort((at, d, who))
                    first = first[np.diff(who[first], prepend=-1) > 0]
                    who, at, d = who[first], at[first], d[first]
                    nearer = (d < best_here[who]) | (d == best_here[who]) & (at < found_here[who])
                    best_here[who[nearer]], found_here[who[nearer]] = d[nearer], at[nearer]
    return best, found


def cv_nearest(matrix: DataFrame, spec: NumericMatrixSpec, folds: int = 10) -> DataFrame:
    """fold, correct, total of the nearest neighbour for all folds in one plan.

    Every record is asked for among the records of all other folds, on attributes over those folds' deviation. Records
    of one fold and label with equal attributes are one point with a count and the smallest key. Every block of points
    meets every part of them in a task of its own; either is packed into one row and read where it is held, so that
    no copy of the points is shuffled for it, only a hit for each point and block. Equal distances: smaller key, then
    smaller label."""
    rows, attrs, label = with_folds(matrix, folds), list(spec.value_cols), spec.class_col
    value = {a: F.col(a).cast("double") for a in attrs}
    sums = rows.groupBy("fold").agg(F.count(F.lit(1)), *(f(v) for f in (F.avg, F.var_pop, F.min, F.max) for v in value.values())).collect()
    of = np.array([r[0] for r in sums], dtype=int)
    count = np.array([r[1] for r in sums], dtype=float)
    avg, var, low, high = np.array([r[2:] for r in sums], dtype=float).reshape(len(sums), 4, len(attrs)).transpose(1, 0, 2)
    weights = np.zeros((folds, len(attrs)))
    for k in range(folds):
        some = of != k
        if (n := count[some].sum()) > 1:
            squares = count[some] @ (var[some] + (avg[some] - count[some] @ avg[some] / n) ** 2)
            varies = (low[some].min(axis=0) < high[some].max(axis=0)) & (squares > 0)
            weights[k] = np.divide(n - 1, squares, out=np.zeros(len(attrs)), where=varies)

    named = F.coalesce(F.col(label).cast("string"), F.lit("None"))
    points = hold(rows.groupBy("fold", named.alias("y"), F.col(label).isNotNull().alias("known"), *(v.alias(f"x_{i}") for i, v in enumerate(value.values()))).agg(F.count(F.lit(1)).alias("n"), F.min(KEY).alias("of")))
    n, xs = points.count(), [f"x_{i}" for i in range(len(attrs))]
    blocks, parts = n // PACK + 1, n // min(max(n // TASKS, LEAST_PART), PACK) + 1
    order = [(c, "ascending") for c in ("of", "y", "known", "fold", *xs)]

    def packed(name: str, count: int) -> DataFrame:
        def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            if held := [b for b in batches if b.num_rows]:
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, held[0].schema) as out:
                    out.write_table(pa.Table.from_batches(held).sort_by(order))
                yield pa.record_batch([pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=[name])

        at = F.pmod(F.xxhash64(F.lit(name), "fold", "y", "known", *xs), F.lit(count)).cast("int")
        return hold(points.withColumn("at", at).repartitionById(count, "at").mapInArrow(pack, f"{name} binary"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        values = lambda t: np.column_stack([t.column(c).to_numpy() for c in xs])
        for batch in batches:
            for pair in zip(*batch.columns, strict=True):
                rows, wanted = (pa.ipc.open_stream(p.as_buffer()).read_all() for p in pair)
                best, found = nearest_apart(values(wanted), wanted.column("fold").to_numpy(), values(rows), rows.column("fold").to_numpy(), weights)
                hit = pa.array(found, mask=found < 0)
                hits = [*(wanted.column(c) for c in me[:-1]), pa.array(np.arange(len(best)), pa.int32()), pa.array(best), rows.column("of").take(hit), rows.column("y").take(hit)]
                yield from pa.table(hits, names=[*me, "d", "of", "said"]).to_batches()

    me = ["at", "fold", "y", "known", "n", "nr"]  # nr: a point's place in its part
    pairs = packed("block", blocks).hint("shuffle_replicate_nl").crossJoin(packed("part", parts))
    hits = pairs.mapInArrow(work, "at int, fold int, y string, known boolean, n long, nr int, d double, of string, said string")
    said = hits.groupBy(*me).agg(F.min(F.struct("d", "of", "said"))["said"].alias("said"))
    got = said.groupBy("fold").agg(F.sum(F.when(F.col("known") & (F.col("said") == F.col("y")), F.col("n"))).alias("correct"), F.sum("n").alias("total"))
    every = rows.sparkSession.range(folds).select(F.col("id").cast("int").alias("fold"))
    return every.join(F.broadcast(got), "fold", "left").select("fold", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("correct", "total"))).orderBy("fold")


def cv_accuracy(matrix: DataFrame, spec: NumericMatrixSpec, algorithm: str, folds: int = 10, run: int | None = None) -> DataFrame:
    """fold, correct, total. run: only so many of the folds (all by default)."""
    if algorithm == "knn" and run is None:
        return cv_nearest(matrix, spec, folds)
    rows, attrs, label = with_folds(matrix, folds), list(spec.value_cols), spec.class_col
    out = None
    for k in range(folds if run is None else run):
        got = predict(algorithm, rows.where(F.col("fold") != k), rows.where(F.col("fold") == k), attrs, label).agg(F.lit(k).alias("fold"), F.coalesce(F.sum((F.col(label).cast("string") == F.col("predicted").cast("string")).cast("long")), F.lit(0)).alias("correct"), F.count(F.lit(1)).alias("total"))
        out = got if out is None else out.unionByName(got)
    return out


def cv_native(matrix: DataFrame, spec: NumericMatrixSpec, folds: int = 10, algorithm: str = "nb") -> DataFrame:
    """fold, correct, total of Gaussian naive Bayes or nearest centroid for all folds in one plan.

    A fold's training moments are the sums of the other folds', so the records are aggregated once."""
    rows, attrs, label = with_folds(matrix, folds), list(spec.value_cols), spec.class_col
    part = rows.groupBy("fold", F.col(label).alias("__c")).agg(F.count(F.lit(1)).alias("n"), *(F.sum(a).alias(f"s_{a}") for a in attrs), *(F.sum(F.col(a) * F.col(a)).alias(f"q_{a}") for a in attrs))
    held = rows.sparkSession.range(folds).select(F.col("id").cast("int").alias("held"))
    train = part.join(F.broadcast(held), F.col("fold") != F.col("held")).groupBy("held", "__c").agg(*(F.sum(c).alias(c) for c in part.columns if c not in ("fold", "__c")))
    w = Window.partitionBy("held")
    mean = lambda a: F.col(f"s_{a}") / F.col("n")
    if algorithm == "nb":
        var = lambda a: F.greatest(F.col(f"q_{a}") / F.col("n") - mean(a) * mean(a), F.lit(1e-9))
        model = train.select("held", "__c", (-2 * F.log(F.col("n") / F.sum("n").over(w))).alias("base"), *(mean(a).alias(f"m_{a}") for a in attrs), *(var(a).alias(f"v_{a}") for a in attrs))
        cost = F.col("base") + sum((F.log(f"v_{a}") + F.pow(F.col(a) - F.col(f"m_{a}"), 2) / F.col(f"v_{a}") for a in attrs), F.lit(0.0))
    else:
        whole = lambda a: (F.sum(f"q_{a}").over(w) - F.pow(F.sum(f"s_{a}").over(w), 2) / F.sum("n").over(w)) / (F.sum("n").over(w) - 1)
        model = train.select("held", "__c", *(mean(a).alias(f"m_{a}") for a in attrs), *(whole(a).alias(f"v_{a}") for a in attrs))
        cost = sum((F.pow(F.col(a) - F.col(f"m_{a}"), 2) / F.col(f"v_{a}") for a in attrs), F.lit(0.0))
    best = rows.join(F.broadcast(model), F.col("fold") == F.col("held")).groupBy(KEY, "fold", label).agg(F.min(F.struct(cost.alias("d"), F.col("__c").alias("c")))["c"].alias("predicted"))
    return best.groupBy("fold").agg(F.sum((F.col(label) == F.col("predicted")).cast("long")).alias("correct"), F.count(F.lit(1)).alias("total"))
