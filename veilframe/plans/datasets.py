"""The experiment's data sets, built from the given tables: key, numeric attributes in order, and a class."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import read_table, replicate
from .held import gathered, hold
from .matrix import NumericMatrixSpec
from .places import inner_cuts, ranked, slot_of, slots_for

LINE_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
LI4 = ("l_quantity", "l_extendedprice", "l_discount", "l_tax")
LI9 = (*LI4, "o_totalprice", "p_size", "p_retailprice", "s_acctbal", "c_acctbal")
# Letters whose shares make doc_letters, and the letter classes of doc_layout.
LETTERS = "acdehiklnoqrstuw"
PUNCTUATION, VOWELS, ACCENTED = ".,;:!?", "aeiou", "éèàçêñäöüßóíáú"


def _ntile(df: DataFrame, buckets: int, value: Column, keys: tuple[str, ...]) -> DataFrame:
    """Classes of equal size by a value and then the key, the first classes one larger where rows are left over."""
    rows = hold(df.withColumn("__v", value.cast("double")))
    n = rows.count()
    rows = gathered(rows, n)
    shares = inner_cuts(slots_for(n))
    cuts = rows.agg(F.percentile_approx("__v", shares, 10 * len(shares))).first()[0] if shares else []
    placed = ranked(rows.withColumn("__slot", slot_of(F.col("__v"), cuts)), "__slot", ["__v", *keys], "__place")
    size, over = divmod(n, buckets)
    at = F.col("__place") - 1
    small = F.lit(over) + F.floor((at - over * (size + 1)) / F.lit(max(size, 1)))
    cls = F.when(at < over * (size + 1), F.floor(at / F.lit(size + 1))).otherwise(small) + 1
    return gathered(placed.withColumn("cls", cls.cast("int")).drop("__v", "__slot", "__place"), n)


def _doubles(df: DataFrame, spec: NumericMatrixSpec) -> DataFrame:
    return df.select(*spec.key_cols, *(F.col(c).cast("double").alias(c) for c in spec.value_cols), *spec.kept)


def li4(spark: SparkSession, d: str) -> tuple[DataFrame, NumericMatrixSpec]:
    spec = NumericMatrixSpec(LI4, LINE_KEY, "cls")
    return _doubles(read_table(spark, d, "lineitem").withColumnRenamed("l_returnflag", "cls"), spec), spec


def _star(spark: SparkSession, d: str) -> DataFrame:
    li = read_table(spark, d, "lineitem")
    orders = read_table(spark, d, "orders").join(read_table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    return li.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(read_table(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey")).join(read_table(spark, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))


def _revenue() -> Column:
    return F.col("l_extendedprice") * (1 - F.col("l_discount"))


def li9(spark: SparkSession, d: str) -> tuple[DataFrame, NumericMatrixSpec]:
    spec = NumericMatrixSpec(LI9, LINE_KEY, "cls")
    return _doubles(_ntile(_star(spark, d).select(*LINE_KEY, *LI9), 7, _revenue(), LINE_KEY), spec), spec


def cust_spend(spark: SparkSession, d: str) -> tuple[DataFrame, NumericMatrixSpec]:
    lines = read_table(spark, d, "lineitem").join(read_table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    flag = lambda f: F.coalesce(F.sum(F.when(F.col("l_returnflag") == f, F.col("l_extendedprice"))), F.lit(0.0)).alias(f"spend_{f.lower()}")
    by = lines.groupBy("o_custkey").agg(F.countDistinct("o_orderkey").alias("n_orders"), flag("A"), flag("N"), flag("R"), F.avg("l_discount").alias("avg_discount"), F.sum("l_quantity").alias("sum_quantity"), F.sum("l_extendedprice").alias("__total"))
    rows = read_table(spark, d, "customer").join(by, F.col("c_custkey") == F.col("o_custkey"), "left")
    cols = ("c_acctbal", "n_orders", "spend_a", "spend_n", "spend_r", "avg_discount", "sum_quantity")
    rows = rows.fillna(0, subset=[*cols, "__total"])
    spec = NumericMatrixSpec(cols, ("c_custkey",), "cls")
    return _doubles(_ntile(rows, 2, 100 * F.col("c_acctbal") + F.col("__total"), ("c_custkey",)), spec), spec


def part_profile(spark: SparkSession, d: str) -> tuple[DataFrame, NumericMatrixSpec]:
    by = read_table(spark, d, "lineitem").groupBy("l_partkey").agg(F.count(F.lit(1)).alias("n_lines"), F.avg("l_quantity").alias("avg_quantity"), F.sum("l_quantity").alias("sum_quantity"), F.avg("l_extendedprice").alias("avg_price"), F.avg("l_discount").alias("avg_discount"), F.avg("l_tax").alias("avg_tax"), F.min("l_extendedprice").alias("min_price"), F.max("l_extendedprice").alias("max_price"), F.countDistinct("l_suppkey").alias("n_suppliers"), F.avg(_revenue()).alias("__rev"))
    rows = read_table(spark, d, "part").join(by, F.col("p_partkey") == F.col("l_partkey"))
    spec = NumericMatrixSpec(("p_size", "p_retailprice", "n_lines", "avg_quantity", "sum_quantity", "avg_price", "avg_discount", "avg_tax", "min_price", "max_price", "n_suppliers"), ("p_partkey",), "cls")
    return _doubles(_ntile(rows, 7, F.col("__rev"), ("p_partkey",)), spec), spec


def counted(docs: DataFrame, classes: dict[str, str]) -> DataFrame:
    """doc_id, lang, n_chars, length (in characters) and, for every class, how many characters of the text are in it.

    Counted on the bytes of Arrow batches: SQL's translate() looks every character up, once for each class."""
    rows = docs.select("doc_id", "lang", "n_chars", F.length("text").alias("length"), F.col("text").cast("string").alias("text"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            text = batch.column(4).cast(pa.large_string())
            bounds = np.frombuffer(text.buffers()[1], np.int64, len(text) + 1 + text.offset)[text.offset :]
            data = np.frombuffer(text.buffers()[2] or b"", np.uint8)[bounds[0] : bounds[-1]]
            counts = []
            for characters in classes.values():
                n = np.zeros(len(text), dtype=np.int32)
                for c in sorted(set(characters)):
                    code = c.encode()
                    at = np.flatnonzero(data == code[0])
                    for k in range(1, len(code)):  # a whole character never spans two texts
                        at = at[data[at + k] == code[k]]
                    n += np.diff(np.searchsorted(at, bounds - bounds[0])).astype(np.int32)
                counts.append(pa.array(n, mask=np.asarray(text.is_null(), dtype=bool)))
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], *counts], names=["doc_id", "lang", "n_chars", "length", *classes])

    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema.fields[:4])
    return rows.mapInArrow(work, kinds + "".join(f", {c} int" for c in classes))


def _layout(docs: DataFrame) -> DataFrame:
    n = F.col("length")
    classes = {"spaces": " ", "line_feeds": "\n", "uppers": "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "digits": "0123456789", "marks": PUNCTUATION, "vowels": VOWELS, "accents": ACCENTED}
    return counted(docs, classes).withColumns({"word_chars": n / (1 + F.col("spaces")), "vowel_share": F.col("vowels") / n, "accent_share": F.col("accents") / n, "upper_share": F.col("uppers") / n})


LAYOUT = ("n_chars", "spaces", "line_feeds", "uppers", "digits", "marks", "word_chars", "vowel_share", "accent_share", "upper_share")


def doc_layout(spark: SparkSession, d: str) -> tuple[DataFrame, NumericMatrixSpec]:
    spec = NumericMatrixSpec(LAYOUT, ("doc_id",), "cls")
    return _doubles(_layout(read_table(spark, d, "documents").where("length(text) > 0")).withColumnRenamed("lang", "cls"), spec), spec


def doc_quality(spark: SparkSession, d: str) -> tuple[DataFrame, NumericMatrixSpec]:
    spec = NumericMatrixSpec(LAYOUT, ("doc_id",), "cls")
    rows = _layout(read_table(spark, d, "documents").where("length(text) > 0")).join(read_table(spark, d, "labels"), "doc_id")
    return _doubles(rows.withColumnRenamed("quality", "cls"), spec), spec


def doc_letters(spark: SparkSession, d: str) -> tuple[DataFrame, NumericMatrixSpec]:
    rows = read_table(spark, d, "documents").where("length(text) > 0")
    rows = counted(rows, {f"n_{c}": c for c in LETTERS}).withColumns({f"share_{c}": F.col(f"n_{c}") / F.col("n_chars") for c in LETTERS}).withColumnRenamed("lang", "cls")
    spec = NumericMatrixSpec(tuple(f"share_{c}" for c in LETTERS), ("doc_id",), "cls")
    return _doubles(rows, spec), spec


def order_value(spark: SparkSession, d: str) -> tuple[DataFrame, NumericMatrixSpec]:
    by = read_table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n_lines"), F.sum("l_quantity").alias("sum_quantity"), F.avg("l_extendedprice").alias("avg_price"), F.avg("l_discount").alias("avg_discount"), F.avg("l_tax").alias("avg_tax"), F.min("l_quantity").alias("min_quantity"), F.max("l_extendedprice").alias("max_price"))
    rows = read_table(spark, d, "orders").join(by, F.col("o_orderkey") == F.col("l_orderkey")).withColumns({"order_month": F.month("o_orderdate"), "order_weekday": F.dayofweek("o_orderdate") - 1})
    spec = NumericMatrixSpec(("o_totalprice", "n_lines", "sum_quantity", "avg_price", "avg_discount", "avg_tax", "min_quantity", "max_price", "order_month", "order_weekday"), ("o_orderkey",), "cls")
    return _doubles(_ntile(rows, 2, F.col("o_totalprice") / 500000 + F.col("sum_quantity") / 300 - 5 * F.col("avg_discount"), ("o_orderkey",)), spec), spec


def event_load(spark: SparkSession, d: str) -> tuple[DataFrame, NumericMatrixSpec]:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    seconds = F.unix_micros(F.col("ts").cast("timestamp")) / 1e6
    rows = read_table(spark, d, "events").withColumns({"event_hour": F.hour("ts"), "event_weekday": F.dayofweek("ts") - 1, "k": F.get_json_object("props", "$.k").cast("double"), "previous_value": F.lag("value").over(w), "moving_mean": F.avg("value").over(w.rowsBetween(-5, -1)), "running_number": F.row_number().over(w), "gap_seconds": seconds - F.lag(seconds).over(w)})
    rows = rows.where("previous_value is not null").withColumn("cls", (F.col("value") > F.col("moving_mean")).cast("int"))
    spec = NumericMatrixSpec(("value", "event_hour", "event_weekday", "k", "previous_value", "moving_mean", "running_number", "gap_seconds"), ("event_id",), "cls")
    return _doubles(rows, spec), spec


def li28(spark: SparkSession, d: str, times: int = 1) -> tuple[DataFrame, NumericMatrixSpec]:
    rows = _star(spark, d)
    per_order = read_table(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("__ok")).agg(F.sum("l_quantity").alias("order_quantity"), F.count(F.lit(1)).alias("order_lines"))
    rows = rows.join(per_order, F.col("l_orderkey") == F.col("__ok"))
    dates = {f"{n}_{k}": f(c) for n, c in (("ship", "l_shipdate"), ("order", "o_orderdate")) for k, f in (("year", F.year), ("month", F.month), ("day", F.dayofmonth), ("weekday", lambda x: F.dayofweek(x) - 1))}
    rows = rows.withColumns({**dates, "ship_yearday": F.dayofyear("l_shipdate"), "ship_delay": F.datediff("l_shipdate", "o_orderdate"), "unit_price": F.col("l_extendedprice") / F.col("l_quantity"), "tax_amount": F.col("l_extendedprice") * F.col("l_tax"), "discount_amount": F.col("l_extendedprice") * F.col("l_discount"), "part_mod": F.col("l_partkey") % 97})
    cols = (*LI9, "ship_year", "ship_month", "ship_day", "ship_weekday", "ship_yearday", "order_year", "order_month", "order_day", "order_weekday", "ship_delay", "l_linenumber", "unit_price", "tax_amount", "discount_amount", "order_quantity", "order_lines", "s_nationkey", "c_nationkey", "part_mod")
    mid = rows.agg(F.percentile_approx(_revenue(), 0.5, 10_000).alias("__mid"))
    rows = rows.join(F.broadcast(mid)).withColumn("cls", (_revenue() > F.col("__mid")).cast("int"))
    key = LINE_KEY
    if times > 1:
        rows, key = replicate(rows, times), (*LINE_KEY, "replica")
    spec = NumericMatrixSpec(cols, key, "cls")
    line = F.col("l_linenumber")
    return rows.select(*(F.col(k) if k != "l_linenumber" else line.alias("__line") for k in key), *(F.col(c).cast("double").alias(c) for c in cols), "cls"), NumericMatrixSpec(cols, tuple("__line" if k == "l_linenumber" else k for k in key), "cls")


def emb64(spark: SparkSession, d: str) -> tuple[DataFrame, NumericMatrixSpec]:
    cols = tuple(f"e{i}" for i in range(1, 65))
    rows = read_table(spark, d, "embeddings").select("vec_id", F.col("label").alias("cls"), *(F.element_at("embedding", i + 1).alias(c) for i, c in enumerate(cols)))
    spec = NumericMatrixSpec(cols, ("vec_id",), "cls")
    return _doubles(rows, spec), spec


DATASETS: dict[str, Callable] = {f.__name__: f for f in (li4, li9, cust_spend, part_profile, doc_layout, doc_letters, order_value, event_load, li28, emb64, doc_quality)}
#: Stand-ins of the seven data sets that the accuracy, attack and entropy studies use.
STUDIED = ("doc_letters", "doc_layout", "li9", "cust_spend", "part_profile", "order_value", "event_load")
