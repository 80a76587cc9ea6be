"""Places of rows in an order of all rows, found in two levels: slots of the order, then places inside a slot.

A slot has at most about PER_SLOT rows, so the number of slots follows the table's size and no task orders a whole table.
Tables of fewer rows are dealt over up to SPREAD slots of SMALL_SLOT rows or more, so their rows stay spread over tasks.
The slots' sizes, one number each, are what is summed in one task and sent to all."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

PER_SLOT = 1_000_000
SPREAD, SMALL_SLOT = 256, 16_384


def slots_for(rows: int, least: int = 1) -> int:
    return max(least, rows // PER_SLOT + 1, min(SPREAD, rows // SMALL_SLOT + 1))


def inner_cuts(slots: int) -> list[float]:
    """Shares at which slots of equal size meet."""
    return [k / slots for k in range(1, slots)]


def slot_of(value: Column, cuts: list[float]) -> Column:
    """How many of the ascending cuts lie below a value; 0 for null. Equal values share a slot."""
    if not cuts:
        return F.lit(0)
    at = np.asarray(cuts, dtype=float)

    @F.pandas_udf("int")
    def find(v: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(at, v.to_numpy(dtype=float), side="left").astype(np.int32))

    return F.when(value.isNull(), 0).otherwise(find(value))


def ranked(rows: DataFrame, slot: str, order: list[str], name: str) -> DataFrame:
    """rows with their place (from 1) in the order by slot, then by the columns of `order`."""
    sizes = rows.groupBy(F.col(slot).alias("__s")).agg(F.count(F.lit(1)).alias("__c"))
    before = sizes.select("__s", F.coalesce(F.sum("__c").over(Window.orderBy("__s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__before"))
    inside = F.row_number().over(Window.partitionBy(slot).orderBy(*order))
    return rows.join(F.broadcast(before), F.col(slot) == F.col("__s")).withColumn(name, F.col("__before") + inside).drop("__s", "__before")
