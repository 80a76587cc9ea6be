"""Time, memory and scaling measurements of the methods."""

from __future__ import annotations

import math
import resource
import threading
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, datasets
from .held import hold, holding
from .matrix import NumericMatrixSpec, as_matrix
from .moments import fit
from .perturb import fit_model, release


def timed(run: Callable[[], DataFrame]) -> float:
    """Seconds of building a table and writing it nowhere."""
    began = time.time()
    run().write.format("noop").mode("overwrite").save()
    return time.time() - began


def methods(matrix: DataFrame, spec: NumericMatrixSpec, kind: str = "fast", literal: bool = False) -> dict[str, Callable[[], DataFrame]]:
    """SMP by covariance, SMP by scan, and the two baselines (literal: candidates scored on the records)."""
    scoring = "data" if literal else "cov"
    return {
        "SMP-cov": lambda: release(matrix, fit_model(matrix, spec), "block", kind),
        "SMP-scan": lambda: release(matrix, fit_model(matrix, spec, search_by="scan"), "block", kind),
        "RP": lambda: baselines.rotation(matrix, spec, scoring=scoring),
        "GP": lambda: baselines.geometric(matrix, spec, scoring=scoring, kind=kind),
    }


def time_sweep(spark: SparkSession, folder: str, dataset: str = "li9", shares: tuple[float, ...] = (0.25, 0.5, 1.0), widths: tuple[int, ...] = (), names: tuple[str, ...] = ("SMP-cov",)) -> list[tuple[str, int, int, float]]:
    """(method, rows, attributes, seconds) with rising rows, then with rising attributes."""
    from ..functions.rng import uniform
    from .matrix import KEY

    out = []
    with holding():
        df, spec = datasets.DATASETS[dataset](spark, folder)
        whole = hold(as_matrix(df, spec))
        for share, width in [*((s, spec.n) for s in shares), *((1.0, w) for w in widths)]:
            part = spec.only(list(spec.value_cols[:width]))
            matrix = whole.select(KEY, *part.value_cols, *spec.kept).where(uniform("bench", "rows", F.col(KEY)) < share).persist()
            rows = matrix.count()
            out += [(name, rows, width, timed(methods(matrix, part)[name])) for name in names]
            matrix.unpersist()
    return out


def slope(points: list[tuple[float, float]]) -> float:
    """Exponent of growth: least squares on logarithms."""
    xs, ys = [math.log(x) for x, _ in points], [math.log(y) for _, y in points]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys, strict=True)) / sum((x - mx) ** 2 for x in xs)


def speedup(basic_seconds: float, optimized_seconds: float) -> float:
    return basic_seconds / optimized_seconds


def scalability(spark: SparkSession, folder: str, rows: int, limit_s: float = 3600, name: str = "SMP-cov") -> dict:
    """One method over 28 attributes and about so many records (replicas, then a keyed sample), cancelled after limit_s seconds."""
    from ..functions.rng import uniform
    from .matrix import KEY

    base = datasets.li28(spark, folder)[0].count()
    times = max(1, math.ceil(rows / base))
    df, spec = datasets.li28(spark, folder, times)
    matrix = as_matrix(df, spec).where(uniform("scale", "rows", F.col(KEY), 0, "fast") < min(1.0, rows / (base * times)))
    tag = f"scalability-{rows}"
    spark.addTag(tag)
    stop = threading.Timer(limit_s, lambda: spark.interruptTag(tag))
    stop.start()
    try:
        return {"method": name, "rows": rows, "attributes": spec.n, "seconds": round(timed(methods(matrix, spec)[name]), 2)}
    except Exception as e:
        if stop.is_alive():
            raise
        return {"method": name, "rows": rows, "attributes": spec.n, "seconds": None, "stopped": str(e)[:80]}
    finally:
        stop.cancel()
        spark.removeTag(tag)


def peak_memory(spark: SparkSession, run: Callable[[], DataFrame]) -> dict:
    """KB at the highest: heap of the JVM by its memory pools (reset first), and this process and its children."""
    beans = spark._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans()
    for bean in beans:
        bean.resetPeakUsage()
    seconds = timed(run)
    heap = sum(b.getPeakUsage().getUsed() for b in beans if b.getType().toString() == "Heap memory")
    return {"seconds": seconds, "heap_kb": heap // 1024, "driver_kb": resource.getrusage(resource.RUSAGE_SELF).ru_maxrss, "children_kb": resource.getrusage(resource.RUSAGE_CHILDREN).ru_maxrss}


def moments_only(matrix: DataFrame, spec: NumericMatrixSpec) -> float:
    began = time.time()
    fit(matrix, spec.value_cols)
    return time.time() - began
