"""Mixing sources to target weights by hierarchical budgeting.

A tree of domain, language and source has a whole-number weight for every node, its share among its siblings.
A token budget flows from the root. A node's supply is `epochs` times the tokens below it; among siblings the
budget goes by weight, a sibling whose supply is short gets its supply, and what it lacks goes to its siblings
by weight. Only when a whole subtree is short does its parent's level make it up, so siblings come before
ancestors. Whole numbers throughout, so that every engine gets the same budgets.

Each leaf takes its documents in a seeded order that differs from epoch to epoch, and of those the longest
prefix whose tokens stay within its budget. Order numbers are 32-bit heads of MD5 digests. Prefix sums are
two-level: tokens by (leaf, epoch, slice of the order), then document by document in the one slice in which
the budget ends, which holds a 1/slices part of the leaf.

Null domains, languages or sources are nodes of their own, named `none`. A null text has no tokens. Documents
without tokens come along in the epochs that their leaf takes. Rows that agree in doc_id, text, language and source
stand side by side in the order and each counts; rows are told apart by 128 bits. An empty table gives no rows. Of
further columns, mixed() keeps all, whatever their names.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table, written

LEVELS = ("domain", "lang", "source")


def token_count(text: Column) -> Column:
    """Runs of anything but 0x20 and 0x09 to 0x0D."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def domain_of(source: Column) -> Column:
    """The default: a stand-in domain of a source named by a number, its last digit's parity."""
    return F.when(source.isNull(), "none").when(source.rlike("[02468]$"), "even").when(source.rlike("[13579]$"), "odd").otherwise("other")


def _share(kids: DataFrame, parent: list[str], name: str) -> DataFrame:
    """Adds `budget` to kids (supply, weight, parent's `given`), level by level water filling in closed form.

    Siblings in order of supply to weight: the first k that get their whole supply are those for which the
    rest's level, (given - their supply) / (rest's weight), passes their own ratio."""
    big = "decimal(38,0)"
    by = Window.partitionBy(*parent) if parent else Window.partitionBy(F.lit(0))
    # a ratio of whole numbers as an exact sorting key: quotient, then remainder over weight
    order = by.orderBy("__ratio", name)
    upto = order.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = kids.withColumn("__ratio", F.col("supply").cast("double") / F.col("weight"))
    rows = rows.withColumns({"__full": F.sum(F.col("supply").cast(big)).over(upto), "__w": F.sum(F.col("weight").cast(big)).over(by) - F.sum(F.col("weight").cast(big)).over(upto) + F.col("weight").cast(big)})
    # this node is short if its supply is at most its share of what those before it leave
    left = F.col("given").cast(big) - (F.col("__full") - F.col("supply").cast(big))
    rows = rows.withColumn("__short", (F.col("supply").cast(big) * F.col("__w")).cast(big) <= (left * F.col("weight").cast(big)).cast(big))
    rows = rows.withColumn("__short", F.min(F.col("__short").cast("int")).over(upto) == 1)  # the first that is not ends the run
    rest_w = F.coalesce(F.sum(F.when(~F.col("__short"), F.col("weight").cast(big))).over(by), F.lit(0).cast(big))
    rest = F.col("given").cast(big) - F.coalesce(F.sum(F.when(F.col("__short"), F.col("supply").cast(big))).over(by), F.lit(0).cast(big))
    rows = rows.withColumns({"__restw": rest_w, "__rest": rest})
    run = F.sum(F.when(~F.col("__short"), F.col("weight").cast(big)).otherwise(F.lit(0).cast(big))).over(upto)
    rows = rows.withColumn("__run", run)
    rows = rows.withColumn("__before", F.col("__run") - F.col("weight").cast(big))
    cut = lambda run: F.expr(f"(__rest * {run}) div nullif(__restw, 0)")
    budget = F.when(F.col("__short"), F.col("supply")).otherwise(cut("__run") - cut("__before"))
    return rows.withColumn("budget", budget.cast("long")).drop("__ratio", "__full", "__w", "__short", "__restw", "__rest", "__run", "__before")


def leaf_budgets(leaves: DataFrame, budget: Column, epochs: int = 2) -> DataFrame:
    """domain, lang, source, tokens, budget. leaves: LEVELS, tokens (long), weight_domain, weight_lang, weight_source."""
    leaves = leaves.withColumn("supply", F.col("tokens") * epochs)
    whole = leaves.agg(F.sum("supply").alias("all")).select(F.least(budget, F.coalesce("all", F.lit(0))).cast("long").alias("given"))
    top = leaves.groupBy("domain").agg(F.sum("supply").alias("supply"), F.max("weight_domain").alias("weight")).crossJoin(F.broadcast(whole))
    top = _share(top, [], "domain").select("domain", F.col("budget").alias("given"))
    mid = leaves.groupBy("domain", "lang").agg(F.sum("supply").alias("supply"), F.max("weight_lang").alias("weight")).join(top, "domain")
    mid = _share(mid, ["domain"], "lang").select("domain", "lang", F.col("budget").alias("given"))
    low = leaves.withColumnRenamed("weight_source", "weight").join(mid, ["domain", "lang"])
    return _share(low, ["domain", "lang"], "source").select(*LEVELS, "tokens", "budget")


def _row() -> list[Column]:
    """128 bits that tell rows of different doc_id, text, language or source apart."""
    return [F.xxhash64("doc_id", "text", "lang", "source").alias("__row"), F.xxhash64(F.lit("row"), "source", "lang", "text", "doc_id").alias("__row2")]


def _with_leaf(docs: DataFrame, domain: Callable[[Column], Column]) -> DataFrame:
    none = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("none"))
    return docs.select(F.col("doc_id").alias("__id"), *_row(), F.coalesce(domain(F.col("source").cast("string")), F.lit("none")).alias("domain"), none("lang").alias("lang"), none("source").alias("source"), token_count(F.col("text").cast("string")).alias("tokens"))


def tempered(leaves: DataFrame, power: float = 0.5) -> DataFrame:
    """Weights of the production query: a node weighs a power of its tokens, in whole numbers, at least 1."""
    of = F.sqrt if power == 0.5 else lambda x: F.pow(x, F.lit(power))
    root = lambda *by: F.greatest(F.floor(of(F.sum("tokens").over(Window.partitionBy(*by)))), F.lit(1)).cast("long")
    return leaves.withColumns({"weight_domain": root("domain"), "weight_lang": root("domain", "lang"), "weight_source": root("domain", "lang", "source")})


def draws(docs: DataFrame, seed: str = "mix", epochs: int = 2, part: tuple[int, int] = (1, 1), slices: int = 4096, weigh=tempered, domain: Callable[[Column], Column] = domain_of) -> DataFrame:
    """(__id, __row, __row2, tokens, LEVELS, copies): how often each row is drawn; rows drawn never are left out.

    The whole budget is part[0]/part[1] of all tokens. domain: the domain of a source; a table with a domain column
    of its own takes `lambda source: F.col("domain")`."""
    rows = written(_with_leaf(docs, domain), "leaves")
    keys = list(LEVELS)
    sums = rows.groupBy(*keys).agg(F.sum("tokens").alias("tokens"))
    total = sums.agg(F.coalesce(F.sum("tokens"), F.lit(0)).alias("t")).first()["t"]
    plan = leaf_budgets(weigh(sums), F.lit(total * part[0] // part[1]).cast("long"), epochs)
    plan = plan.withColumns({"full": F.when(F.col("tokens") > 0, F.least(F.floor(F.col("budget") / F.col("tokens")), F.lit(epochs))).otherwise(F.lit(1)).cast("long")})
    plan = written(plan.withColumn("rest", F.col("budget") - F.col("full") * F.col("tokens")).select(*keys, "full", "rest"), "plan")
    small = plan.count() <= 100_000  # about 100 bytes a leaf
    plan_ = F.broadcast(plan) if small else plan
    place = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), F.col("full").cast("string"), F.coalesce(F.col("__id").cast("string"), F.lit("none")))), 1, 8), 16, 10).cast("long")
    drawn = rows.join(plan_, keys).withColumn("place", place).withColumn("slice", F.floor(F.col("place") / ((1 << 32) // slices)).cast("int"))
    by_slice = drawn.groupBy(*keys, "slice").agg(F.sum("tokens").alias("in_slice"), F.max("rest").alias("rest"))
    upto = Window.partitionBy(*keys).orderBy("slice").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    edge = by_slice.withColumn("after", F.sum("in_slice").over(upto)).where("after > rest").groupBy(*keys).agg(F.min(F.struct("slice", (F.col("after") - F.col("in_slice")).alias("before"))).alias("edge"))
    edge = edge.select(*keys, F.col("edge.slice").alias("edge"), F.col("edge.before").alias("before"))
    marked = drawn.join(F.broadcast(edge) if small else edge, keys, "left")
    inside = marked.where("rest > 0 and (edge is null or slice < edge)").select("__id", "__row", "__row2", "tokens", *keys, (F.col("full") + 1).alias("copies"))
    run = Window.partitionBy(*keys).orderBy("place", F.col("__id").asc_nulls_first(), "__row", "__row2").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    last = marked.where("rest > 0 and slice = edge").withColumn("upto", F.col("before") + F.sum("tokens").over(run))
    last = last.select("__id", "__row", "__row2", "tokens", *keys, (F.col("full") + (F.col("upto") <= F.col("rest")).cast("long")).alias("copies"))
    outside = marked.where("rest = 0 or slice > edge").select("__id", "__row", "__row2", "tokens", *keys, F.col("full").alias("copies"))
    return inside.unionByName(last).unionByName(outside).where("copies > 0")


def mixed(docs: DataFrame, **how) -> DataFrame:
    """docs as drawn: a row for each copy, in the columns of docs.

    Of equal rows at the end of a budget some are drawn once more than the rest; which of them does not matter, as
    long as their number is right, so those alone are numbered."""
    picked = draws(docs, **how).groupBy("__row", "__row2").agg(F.min("copies").alias("__least"), F.max("copies").alias("__most"), F.count(F.lit(1)).alias("__drawn"), F.sum("copies").alias("__all"))
    own = docs.select(*(F.col(f"`{c}`") for c in docs.columns), *_row())
    rows = own.join(picked.withColumnsRenamed({"__row": "__r1", "__row2": "__r2"}), (F.col("__row") == F.col("__r1")) & (F.col("__row2") == F.col("__r2")))
    # equal rows that are never drawn are missing from the picked, and then the least is none
    split = own.groupBy("__row", "__row2").agg(F.count(F.lit(1)).alias("__n")).where("__n > 1").select(F.col("__row").alias("__r3"), F.col("__row2").alias("__r4"), "__n")
    rows = rows.join(split, (F.col("__row") == F.col("__r3")) & (F.col("__row2") == F.col("__r4")), "left")
    even = (F.col("__least") == F.col("__most")) & (F.col("__drawn") == F.coalesce("__n", F.lit(1)))
    n = F.coalesce("__n", F.lit(1))
    nr = F.row_number().over(Window.partitionBy("__row", "__row2").orderBy(F.lit(0)))
    uneven = rows.where(~even).withColumn("__copies", F.floor(F.col("__all") / n) + (nr <= F.col("__all") % n).cast("long"))
    out = rows.where(even).withColumn("__copies", F.col("__least")).unionByName(uneven).where("__copies > 0")
    return out.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__copies").cast("int")))).select(*(F.col(f"`{c}`") for c in docs.columns))


def op2_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = draws(table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source"))
    return got.select(F.col("__id").alias("doc_id"), *LEVELS, "tokens", "copies")


def _share_sql(out: str, rows: str, parent: str, name: str) -> str:
    by = f"PARTITION BY {parent}" if parent else ""
    return f"""
{out}_a AS (SELECT *, sum(supply) OVER w AS upto, sum(weight) OVER w AS wupto, sum(weight) OVER ({by}) AS wall FROM {rows} WINDOW w AS ({by} ORDER BY supply::DOUBLE / weight, {name} ROWS UNBOUNDED PRECEDING)),
{out}_b AS (SELECT *, bool_and(supply * (wall - wupto + weight) <= (given - upto + supply) * weight) OVER ({by} ORDER BY supply::DOUBLE / weight, {name} ROWS UNBOUNDED PRECEDING) AS short FROM {out}_a),
{out}_c AS (SELECT *, given - coalesce(sum(supply) FILTER (WHERE short) OVER ({by}), 0) AS rest, wall - coalesce(sum(weight) FILTER (WHERE short) OVER ({by}), 0) AS restw,
  wupto - coalesce(sum(weight) FILTER (WHERE short) OVER ({by}), 0) AS run FROM {out}_b),
{out} AS (SELECT *, CASE WHEN short THEN supply ELSE (rest * run) // restw - (rest * (run - weight)) // restw END AS budget FROM {out}_c)"""


ORACLE_MIX = f"""
WITH rows AS (
  SELECT doc_id, CASE WHEN source IS NULL THEN 'none' WHEN regexp_matches(source, '[02468]$') THEN 'even' WHEN regexp_matches(source, '[13579]$') THEN 'odd' ELSE 'other' END AS domain,
         coalesce(lang, 'none') AS lang, coalesce(source, 'none') AS source, coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0) AS tokens FROM documents
), leaf AS (SELECT domain, lang, source, sum(tokens) AS tokens, 2 * sum(tokens) AS supply FROM rows GROUP BY ALL),
l1 AS (SELECT domain, sum(supply) AS supply, greatest(floor(sqrt(sum(tokens))), 1)::HUGEINT AS weight, (SELECT sum(tokens) FROM leaf) AS given FROM leaf GROUP BY domain),
{_share_sql("b1", "l1", "", "domain")},
l2 AS (SELECT domain, lang, any_value(b1.budget) AS given, sum(leaf.supply) AS supply, greatest(floor(sqrt(sum(leaf.tokens))), 1)::HUGEINT AS weight FROM leaf JOIN b1 USING (domain) GROUP BY domain, lang),
{_share_sql("b2", "l2", "domain", "lang")},
l3 AS (SELECT leaf.domain, leaf.lang, source, leaf.tokens, leaf.supply, b2.budget AS given, greatest(floor(sqrt(leaf.tokens)), 1)::HUGEINT AS weight FROM leaf JOIN b2 USING (domain, lang)),
{_share_sql("b3", "l3", "domain, lang", "source")},
plan AS (SELECT domain, lang, source, CASE WHEN tokens > 0 THEN least(budget // tokens, 2) ELSE 1 END AS taken, tokens AS all_tokens, budget FROM b3),
placed AS (SELECT rows.*, taken, budget - taken * all_tokens AS rest, substr(md5('mix:' || taken::VARCHAR || ':' || coalesce(doc_id::VARCHAR, 'none')), 1, 8) AS place FROM rows JOIN plan USING (domain, lang, source)),
summed AS (SELECT *, sum(tokens) OVER (PARTITION BY domain, lang, source ORDER BY place, doc_id ROWS UNBOUNDED PRECEDING) AS upto FROM placed)
SELECT doc_id, domain, lang, source, tokens, (taken + CASE WHEN rest > 0 AND upto <= rest THEN 1 ELSE 0 END)::BIGINT AS copies FROM summed WHERE taken > 0 OR (rest > 0 AND upto <= rest)
"""

QUERIES = {"op2_mixing": op2_mixing}
ORACLES = {"op2_mixing": ORACLE_MIX}
