"""Distinct values of numeric columns with their counts on two sides, moved as packed arrays.

A task sorts up to FLUSH rows of a column at a time and cuts the distinct values, with their counts, into slots; what
is shuffled is one row of packed numbers for each slot and flush instead of one for each value, and a frequent value
is one entry of a flush, however often it occurs. A slot's arrays are merged by one task. Every value is counted."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .places import inner_cuts, slots_for

FLUSH = 1_000_000
#: Rows over which the slots' ends are sought among one row in SPARSE; the ends only balance slots, they change no result.
MANY, SPARSE = 2_000_000, 64
_SUMS = "attr int, slot int, n long, m long, n_log double, m_log double, low double, high double"


def slot_ends(sides: list[DataFrame], attrs: list[str], rows: int) -> list[list[float]]:
    """Ascending ends of slots of about equal size, for each attribute."""
    either = sides[0].select(*attrs)
    for other in sides[1:]:
        either = either.unionByName(other.select(*attrs))
    if rows > MANY:
        either = either.where(F.pmod(F.xxhash64(*attrs), F.lit(SPARSE)) == 0)
    shares = inner_cuts(slots_for(rows, 16))
    row = either.agg(*(F.percentile_approx(F.col(a).cast("double"), shares, max(1000, 10 * len(shares))).alias(f"c{i}") for i, a in enumerate(attrs))).first()
    return [sorted(set(row[f"c{i}"] or [])) for i in range(len(attrs))]


def _packed(df: DataFrame, attrs: list[str], ends: list[list[float]], side: int) -> DataFrame:
    """attr, slot, side, the distinct values of a flush ascending, their counts, and how many nulls there were."""

    def flush(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []
        for i in range(len(attrs)):
            whole = pa.chunked_array([b.column(i) for b in held])
            v, c = np.unique(whole.drop_null().to_numpy() + 0.0, return_counts=True)
            if whole.null_count:
                out.append((i, -1, side, b"", b"", whole.null_count))
            at = [0, *np.searchsorted(v, ends[i], side="right").tolist(), len(v)]
            out += [(i, k, side, v[a:b].tobytes(), c[a:b].astype(np.int64).tobytes(), 0) for k, (a, b) in enumerate(zip(at, at[1:], strict=False)) if b > a]
        kinds = (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*out, strict=True), kinds, strict=True)], names=["attr", "slot", "side", "v", "c", "nulls"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(batch)
            if sum(b.num_rows for b in held) >= FLUSH:
                yield from flush(held)
                held = []
        if held:
            yield from flush(held)

    return df.select(*(F.col(a).cast("double").alias(a) for a in attrs)).mapInArrow(work, "attr int, slot int, side int, v binary, c binary, nulls long")


def slot_sums(sides: list[DataFrame], attrs: list[str]) -> list:
    """For each attribute and slot: the rows n and m of the one or two sides, the sums of count times log2 count, and
    the least and greatest running difference a / n - b / m inside the slot (n, m: the sides' rows without nulls).
    Slot -1 has the nulls."""
    present = [s.agg(F.count(F.lit(1)), *(F.count(a) for a in attrs)).first() for s in sides]
    ends = slot_ends(sides, attrs, sum(r[0] for r in present))
    totals = [[max(1, present[min(k, len(sides) - 1)][i + 1]) for k in (0, 1)] for i in range(len(attrs))]
    packed = _packed(sides[0], attrs, ends, 0)
    for other in sides[1:]:
        packed = packed.unionByName(_packed(other, attrs, ends, 1))

    def merge(f: pd.DataFrame) -> pd.DataFrame:
        attr, slot = int(f["attr"].iloc[0]), int(f["slot"].iloc[0])
        v = np.concatenate([np.frombuffer(x, np.float64) for x in f["v"]])
        c = np.concatenate([np.frombuffer(x, np.int64) for x in f["c"]])
        side = np.repeat(f["side"].to_numpy(), [len(x) // 8 for x in f["v"]])
        if slot < 0:
            count = [np.array([f["nulls"][f["side"] == k].sum()]) for k in (0, 1)]
            gap = np.zeros(1)
        else:
            order = np.argsort(v, kind="stable")
            v = v[order]
            first = np.flatnonzero(np.concatenate([[True], (v[1:] != v[:-1]) & ~(np.isnan(v[1:]) & np.isnan(v[:-1]))]))
            count = [np.add.reduceat(np.where(side == k, c, 0)[order], first) for k in (0, 1)]
            gap = np.cumsum(count[0]) / totals[attr][0] - np.cumsum(count[1]) / totals[attr][1]
        logs = [float((x * np.log2(np.maximum(x, 1))).sum()) for x in count]
        return pd.DataFrame([(attr, slot, int(count[0].sum()), int(count[1].sum()), *logs, float(gap.min()), float(gap.max()))], columns=["attr", "slot", "n", "m", "n_log", "m_log", "low", "high"])

    return packed.groupBy("attr", "slot").applyInPandas(merge, _SUMS).orderBy("attr", "slot").collect()


def entropies(sides: list[DataFrame], attrs: list[str]) -> list[tuple]:
    """(attr, bits of entropy of each side) over distinct values, null being one."""
    rows, out = slot_sums(sides, attrs), []
    for i, a in enumerate(attrs):
        of = [r for r in rows if r["attr"] == i]
        sums = [(sum(r[k] for r in of), sum(r[f"{k}_log"] for r in of)) for k in ("n", "m")[: len(sides)]]
        if all(n for n, _ in sums):
            out.append((a, *(float(np.log2(n) - s / n) for n, s in sums)))
    return out


def greatest_gaps(orig: DataFrame, other: DataFrame, attrs: list[str]) -> list[tuple]:
    """(attr, d, n, m): the two-sample statistic, nulls left out."""
    rows, out = slot_sums([orig, other], attrs), []
    for i, a in enumerate(attrs):
        of = [r for r in rows if r["attr"] == i and r["slot"] >= 0]
        n, m = sum(r["n"] for r in of), sum(r["m"] for r in of)
        d, before_n, before_m = 0.0, 0, 0
        for r in of:
            base = before_n / max(n, 1) - before_m / max(m, 1)
            d = max(d, abs(base + r["low"]), abs(base + r["high"]))
            before_n, before_m = before_n + r["n"], before_m + r["m"]
        if n and m:
            out.append((a, float(d), n, m))
    return out
