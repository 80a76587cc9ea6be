"""Tables that a study works on several times: held on disk by the executors while it runs, then dropped."""

from __future__ import annotations

import contextlib
import contextvars
from collections.abc import Iterator

from pyspark import StorageLevel
from pyspark.sql import DataFrame

_held: contextvars.ContextVar[list[DataFrame] | None] = contextvars.ContextVar("held", default=None)


@contextlib.contextmanager
def holding() -> Iterator[None]:
    """What hold() is given meanwhile is computed once; at the end it is dropped, so results must be settled by then."""
    mine: list[DataFrame] = []
    token = _held.set(mine)
    try:
        yield
    finally:
        _held.reset(token)
        for df in reversed(mine):
            df.unpersist()


#: Rows that a task of a held table has at least: many small partitions cost more in tasks than their rows.
ROWS_A_TASK = 65_536


def gathered(df: DataFrame, rows: int) -> DataFrame:
    """df in no more partitions than its rows need; partitions are put together where they are. Outside of holding() as it is."""
    return df if _held.get() is None else df.coalesce(rows // ROWS_A_TASK + 1)


def hold(df: DataFrame) -> DataFrame:
    """df, stored on first use; outside of holding() as it is."""
    mine = _held.get()
    if mine is None:
        return df
    mine.append(df.persist(StorageLevel.DISK_ONLY))
    return df


def settled(small: DataFrame) -> DataFrame:
    """The rows of a table of measured values, computed now."""
    return small.sparkSession.createDataFrame(small.collect(), small.schema)
