"""Line dedup by overlapping three-line windows, in DataFrame functions only.

Every run of three consecutive lines of a document is hashed to 128 bits. A window that occurs more than once
anywhere, same document included, keeps its first occurrence (smallest doc_id, then position); the lines of
all later occurrences are covered, overlapping covers merge, and the covered lines go. Windows are judged on
the input, not on what is left. Lines are compared as they are; windows of nothing but white space are left
alone, and so are documents of fewer than three lines.

Rows that agree in doc_id and text are one document and keep the same result; rows are told apart by 128 bits of
the two. A null text has no lines and stays null; a null doc_id comes first in order. An empty table gives no rows.
Other columns stay as they are, but for n_lines and n_removed, which are replaced.

A document's text is split once to find windows and once to write what is left; all work on a document is in
proportion to its lines.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, written

SPAN = 3


def _row() -> list[Column]:
    """128 bits that tell rows of different doc_id or text apart."""
    return [F.xxhash64("doc_id", "text").alias("__row"), F.xxhash64(F.lit(SPAN), "text", "doc_id").alias("__row2")]


def line_windows(docs: DataFrame) -> DataFrame:
    """(__row, __row2, __id, __at, __h1, __h2): every window with more than white space, by its first line's place and hash."""
    lines = F.split(F.col("text").cast("string"), "\n")
    n = F.size(lines) - (SPAN - 1)
    # the lines shifted against one another: a window's hash needs no look into the whole array
    threes = F.arrays_zip(*(F.slice(lines, i + 1, n).alias(f"l{i}") for i in range(SPAN)))

    def hashed(x: Column) -> Column:
        parts = [x[f"l{i}"] for i in range(SPAN)]
        blank = F.concat(*parts).rlike(r"^\s*$")
        return F.struct(F.xxhash64(*parts).alias("h1"), F.when(~blank, F.xxhash64(F.lit(SPAN), *reversed(parts))).alias("h2"))

    rows = docs.select(*_row(), F.col("doc_id").alias("__id"), F.when(F.size(lines) >= SPAN, F.transform(threes, hashed)).alias("__w"))
    windows = rows.select("__row", "__row2", "__id", F.posexplode("__w").alias("__at", "__h"))
    return windows.select("__row", "__row2", "__id", "__at", F.col("__h.h1").alias("__h1"), F.col("__h.h2").alias("__h2")).where("__h2 is not null")


def covered_lines(docs: DataFrame) -> DataFrame:
    """(__row, __row2, __covered): for each document with lines to remove, their positions in order."""
    windows = written(line_windows(docs), "windows")
    place = F.struct("__id", "__row", "__row2", "__at")
    firsts = windows.groupBy("__h1", "__h2").agg(F.count(F.lit(1)).alias("__n"), F.min(place).alias("__first")).where("__n > 1").drop("__n")
    later = windows.join(firsts, ["__h1", "__h2"]).where(~(place.eqNullSafe(F.col("__first"))))
    places = later.groupBy("__row", "__row2").agg(F.collect_set("__at").alias("__ats"))
    return places.select("__row", "__row2", F.array_sort(F.array_distinct(F.flatten(F.transform("__ats", lambda a: F.sequence(a, a + SPAN - 1))))).alias("__covered"))


def dedup_lines(docs: DataFrame) -> DataFrame:
    """docs with the covered lines taken out of text, and columns n_lines and n_removed."""
    cover = covered_lines(docs).withColumnsRenamed({"__row": "__r1", "__row2": "__r2"})
    own = [c for c in docs.columns if c not in ("n_lines", "n_removed")]
    # lines are split before the join, so that the lambda below looks into an array that is there already
    rest = docs.select(*(F.col(f"`{c}`") for c in own if c != "text"), *_row(), F.split(F.col("text").cast("string"), "\n").alias("__lines"))
    rest = rest.join(cover, (F.col("__row") == F.col("__r1")) & (F.col("__row2") == F.col("__r2")), "left")
    left = F.array_except(F.sequence(F.lit(0), F.size("__lines") - 1), F.col("__covered"))
    kept = F.when(F.col("__covered").isNull(), F.col("__lines")).otherwise(F.transform(left, lambda i: F.element_at("__lines", i + 1)))
    n, gone = F.when(F.col("__lines").isNull(), F.lit(0)).otherwise(F.size("__lines")), F.when(F.col("__covered").isNull(), F.lit(0)).otherwise(F.size("__covered"))
    text = F.array_join(kept, "\n").cast(docs.schema["text"].dataType)
    return rest.select(*(text.alias("text") if c == "text" else F.col(f"`{c}`") for c in own), n.cast("long").alias("n_lines"), gone.cast("long").alias("n_removed"))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))


ORACLE_LINES = """
WITH cut AS (SELECT doc_id, text, string_split(text, chr(10)) AS lines FROM documents),
windows AS (
  SELECT doc_id, text, unnest(range(0, len(lines) - 2)) AS pos, lines FROM cut WHERE len(lines) >= 3
), keyed AS (
  SELECT doc_id, text, pos, lines[pos + 1] || chr(10) || lines[pos + 2] || chr(10) || lines[pos + 3] AS w FROM windows
), ranked AS (
  SELECT doc_id, pos, row_number() OVER (PARTITION BY w ORDER BY doc_id, pos) AS k FROM keyed WHERE regexp_replace(w, '[ \\t\\n\\x0B\\f\\r]+', '', 'g') <> ''
), covered AS (SELECT DISTINCT doc_id, unnest([pos, pos + 1, pos + 2]) AS pos FROM ranked WHERE k > 1),
gone AS (SELECT doc_id, list(pos) AS ats, count(*) AS n FROM covered GROUP BY doc_id)
SELECT doc_id, CASE WHEN n IS NULL THEN text ELSE array_to_string(list_filter(lines, lambda x, i: NOT list_contains(ats, i - 1)), chr(10)) END AS text,
       coalesce(len(lines), 0)::BIGINT AS n_lines, coalesce(n, 0)::BIGINT AS n_removed
FROM cut LEFT JOIN gone USING (doc_id)
"""

QUERIES = {"op10_line_dedup": op10_line_dedup}
ORACLES = {"op10_line_dedup": ORACLE_LINES}
