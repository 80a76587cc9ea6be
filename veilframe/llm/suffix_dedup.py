"""Suffix-array dedup: every byte covered by a string of `span` bytes that also starts anywhere else goes.

The suffixes that matter are chosen by content. Of the GRAM-byte strings in each window of `span` bytes the
one of smallest hash is the window's anchor, so equal windows have equal anchors at equal offsets. The
windows of one anchor occurrence form a run; run and anchor make a segment of text. Equal segments are one leaf of
their anchor's suffix tree with its number of occurrences, found by a 128-bit hash with partial sums before the
shuffle, so copies of any number cost one leaf; a leaf met more than once is a repeat as a whole. Anchors of several
leaves, the edges of repeated text, go to the enhanced suffix array of their anchor, one representative a leaf:
suffixes from the anchor on are sorted, and a stack scan of their common prefix lengths visits every common-prefix
interval, inner ones first. An interval's children are merged, smaller into larger, in the order of what stands to
the left of their anchors, so each member meets its new neighbours there just once: their common left context gives
the group's left part, and a group whose left contexts differ beyond it, and whose right contexts differ beyond the
interval, is a maximal repeat of all its members. The merging makes some k log k neighbours for k leaves, however
deep the intervals nest; bytes to remove need these alone.

repeat_groups() gives the maximal repeats themselves with all their occurrences. They reach as far as their anchor's
run, so a longer repeat comes as a chain of overlapping groups, one an anchor.

An anchor with over `most` distinct segments (a passage that very many texts share with different
surroundings) is never gathered: its windows are counted by 128-bit hashes in a distributed aggregation, which
gives the same bytes to remove, and groups of one window each.

Matches never cross documents; a null text is empty. Rows that agree in doc_id and text are occurrences of
their own, so both lose their bytes. Texts shorter than `span` bytes keep all. Very long texts are read in
overlapping pieces; cuts of runs at the pieces' ends do not change results. An empty table gives no rows. Columns
other than doc_id and text, whatever their names, are not read.
"""

from __future__ import annotations

import bisect
import functools
import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import byte_slices, table, text_bytes, written

GRAM, PIECE = 32, 1 << 20


class Rolling:
    """Polynomial hashes of any stretch of a byte array, from prefix sums modulo 2 ** 64."""

    def __init__(self, seed: int, most: int):
        rng = np.random.default_rng(seed)
        self.value = rng.integers(0, 1 << 64, 256, dtype=np.uint64)
        base = int(rng.integers(1 << 62, 1 << 63)) * 2 + 1 & (1 << 64) - 1
        self.power = self._powers(base, most)
        self.inverse = self._powers(pow(base, -1, 1 << 64), most)

    @staticmethod
    def _powers(base: int, most: int) -> np.ndarray:
        out = np.full(most, base, dtype=np.uint64)
        out[0] = 1
        return np.multiply.accumulate(out)

    def sums(self, data: np.ndarray) -> np.ndarray:
        out = np.zeros(len(data) + 1, dtype=np.uint64)
        np.cumsum(self.value[data] * self.power[: len(data)], out=out[1:])
        return out

    def of(self, sums: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((sums[end] - sums[start]) * self.inverse[start])


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(32))


@functools.cache
def rollings() -> tuple[Rolling, Rolling]:
    return Rolling(11, PIECE + 4096), Rolling(12, PIECE + 4096)


def sliding_least(x: np.ndarray, width: int) -> np.ndarray:
    """Least of every `width` neighbours, in two passes over blocks of that width."""
    n = len(x) - width + 1
    padded = np.full(-(-len(x) // width) * width, np.iinfo(x.dtype).max, dtype=x.dtype)
    padded[: len(x)] = x
    blocks = padded.reshape(-1, width)
    upto = np.minimum.accumulate(blocks, axis=1).ravel()
    after = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(after[:n], upto[width - 1 : width - 1 + n])


def runs_of(data: np.ndarray, at: np.ndarray, span: int) -> tuple[np.ndarray, ...]:
    """(text, anchor hash, two segment hashes, anchor, first and last window start) of every run; places in data."""
    none = (np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.uint64), *[np.zeros(0, np.int64)] * 3)
    if len(data) < span or int(np.diff(at).max(initial=0)) < span:
        return none
    one, two = rollings()
    sums = one.sums(data)
    grams = len(data) - GRAM + 1
    hashes = mix((sums[GRAM:] - sums[:grams]) * one.inverse[:grams])
    low = np.uint64((1 << 24) - 1)
    least = sliding_least((hashes & ~low) | np.arange(grams, dtype=np.uint64), span - GRAM + 1)
    starts = np.arange(len(least))
    ends = np.repeat(at[1:], np.diff(at))[: len(least)]
    starts = starts[starts + span <= ends]
    anchor = (least[starts] & low).astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], anchor[1:] != anchor[:-1]]))
    last = np.concatenate([first[1:] - 1, [len(starts) - 1]])
    s0, s1, p = starts[first], starts[last], anchor[first]
    text = np.searchsorted(at, s0, side="right") - 1
    size = (s1 - s0).astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)
    return text, hashes[p], one.of(sums, s0, s1 + span) ^ size, two.of(two.sums(data), s0, s1 + span) ^ size, p, s0, s1


RUNS = "doc_id long, row long, anchor long, seg1 long, seg2 long, p long, s0 long, s1 long"


def _keyed(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("doc_id", text).alias("row"), text.alias("text"))


def anchor_runs(docs: DataFrame, span: int = 400) -> DataFrame:
    """RUNS of every text. row: a hash of doc_id and text; places are in bytes of the text."""

    def pieces(data: np.ndarray, at: np.ndarray) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """(first row, place of the piece in its row, bytes, offsets)."""
        for a, b in byte_slices(at, PIECE):
            if at[b] - at[a] <= PIECE:
                yield a, 0, data[at[a] : at[b]], at[a : b + 1] - at[a]
            else:
                for cut in range(0, int(at[b] - at[a]), PIECE):
                    part = data[at[a] + cut : min(at[b], at[a] + cut + PIECE + span - 1)]
                    yield a, cut, part, np.array([0, len(part)])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, rows = batch.column(0), batch.column(1)
            data, at = text_bytes(batch.column(2))
            for a, cut, part, offsets in pieces(data, at):
                text, anchor, seg1, seg2, p, s0, s1 = runs_of(part, offsets, span)
                if len(text):
                    which = pa.array(text + a)
                    base = offsets[text] - cut
                    made = [anchor.view(np.int64), seg1.view(np.int64), seg2.view(np.int64), p - base, s0 - base, s1 - base]
                    yield pa.RecordBatch.from_arrays([ids.take(which), rows.take(which), *map(pa.array, made)], names=[x.split()[0] for x in RUNS.split(", ")])

    return _keyed(docs).mapInArrow(work, RUNS)


def common(a: bytes, b: bytes) -> int:
    """Length of the common prefix."""
    n = min(len(a), len(b))
    differ = int.from_bytes(a[:n], "big") ^ int.from_bytes(b[:n], "big")
    return n - (differ.bit_length() + 7) // 8


def intervals(shared: list[int]) -> Iterator[tuple[int, int, int]]:
    """Every common-prefix interval (length, first, last) of sorted strings, inner ones first, by one stack scan.

    shared[i] is the length of the common prefix of strings i and i + 1."""
    stack: list[tuple[int, int]] = []
    for i, length in enumerate([*shared, -1]):
        first = i
        while stack and length < stack[-1][0]:
            whole, first = stack.pop()
            yield whole, first, i
        if length >= 0 and (not stack or length > stack[-1][0]):
            stack.append((length, first))


class _Ordered:
    """Members in the order of their left contexts."""

    def __init__(self, lefts: list[bytes], rank: list[int], m: int):
        self.lefts, self.rank, self.members, self.ranks = lefts, rank, [m], [rank[m]]

    def add(self, m: int) -> list[int]:
        """Puts a member in; the members it now stands between."""
        at = bisect.bisect(self.ranks, self.rank[m])
        beside = self.members[max(0, at - 1) : at + 1]
        self.ranks.insert(at, self.rank[m])
        self.members.insert(at, m)
        return beside


def merges(lefts: list[bytes], rights: list[bytes]) -> Iterator[tuple[int, _Ordered, list[tuple[int, int]]]]:
    """Every common-prefix interval of the sorted rights, inner ones first: its length, its members in the order of
    their lefts, and the pairs of its different children that came to stand side by side in that order."""
    order = sorted(range(len(rights)), key=rights.__getitem__)
    rank = [0] * len(lefts)
    for k, m in enumerate(sorted(range(len(lefts)), key=lefts.__getitem__)):
        rank[m] = k
    whole: dict[int, tuple[int, _Ordered]] = {}  # first place of an interval -> its last place and members
    for right, first, last in intervals([common(rights[x], rights[y]) for x, y in zip(order, order[1:], strict=False)]):
        at, kept, pairs = first, None, []
        while at <= last:
            end, child = whole.pop(at, None) or (at, _Ordered(lefts, rank, order[at]))
            at = end + 1
            if kept is None:
                kept = child
                continue
            if len(child.members) > len(kept.members):
                kept, child = child, kept
            own = set(child.members)
            pairs += [(m, other) for m in child.members for other in kept.add(m) if other not in own]
        whole[first] = last, kept
        yield right, kept, pairs


def maximal_repeats(lefts: list[bytes], rights: list[bytes], least: int) -> Iterator[tuple[int, int, list[int]]]:
    """Maximal repeats of at least so many bytes through one anchor: (left part, right part, all members).

    lefts run backward from the anchor, rights forward. Members of different children of an interval differ after
    its right part; a run of the left order around two of them, as far as `left` bytes are common, is diverse to the
    left if `left` is the least of its neighbours' common parts."""
    for right, group, pairs in merges(lefts, rights):
        if all(common(lefts[x], lefts[y]) + right < least for x, y in pairs):
            continue
        seen: set[tuple[int, int]] = set()
        members, n = group.members, len(group.members)
        near = [common(lefts[x], lefts[y]) for x, y in zip(members, members[1:], strict=False)]
        for x, y in pairs:
            a, b = sorted((bisect.bisect_left(group.ranks, group.rank[x]), bisect.bisect_left(group.ranks, group.rank[y])))
            left = min(near[a:b])  # others may have come between
            while left + right >= least:
                while a and near[a - 1] >= left:
                    a -= 1
                while b < n - 1 and near[b] >= left:
                    b += 1
                if (left, a) in seen:
                    break
                seen.add((left, a))
                yield left, right, members[a : b + 1]
                left = max([*near[max(0, a - 1) : a], *near[b : b + 1]], default=-least - right)


def repeated_windows(lefts: list[bytes], rights: list[bytes], span: int) -> dict[int, tuple[int, int]]:
    """For each member with a window that another member has, the least and greatest left part of such windows.

    A member's best partner, to either side, stands beside it at some merge, so neighbours are enough."""
    out: dict[int, tuple[int, int]] = {}
    reach = max(map(len, lefts), default=0)
    for right, _, pairs in merges(lefts, rights):
        if right + reach < span:
            continue
        for pair in pairs:
            left = common(lefts[pair[0]], lefts[pair[1]])
            if left + right >= span:
                for m in pair:
                    low, high = out.get(m, (span, -1))
                    out[m] = min(low, max(0, span - right)), max(high, left)
    return out


FOUND = "anchor long, seg1 long, seg2 long, low long, high long"
PARTS = "anchor long, seg1 long, seg2 long, n long, d long, back long, segment binary"


def _texts_of(needed: DataFrame, docs: DataFrame) -> DataFrame:
    """PARTS: the segments' bytes, cut out of the representatives' texts. back: bytes before the anchor."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in PARTS.split(", ")]
        for batch in batches:
            data, at = text_bytes(batch.column(0))
            lists = batch.column(1)
            counts = np.asarray(lists.value_lengths().fill_null(0))
            flat = lists.flatten()
            fields = {flat.type.field(i).name: flat.field(i) for i in range(flat.type.num_fields)}
            start = np.repeat(at[:-1], counts) + fields["s0"].to_numpy(zero_copy_only=False)
            end = np.repeat(at[:-1], counts) + fields["s1"].to_numpy(zero_copy_only=False)
            for a in range(0, len(flat), 4000):
                b = min(len(flat), a + 4000)
                made = [data[s:e].tobytes() for s, e in zip(start[a:b], end[a:b], strict=True)]
                yield pa.RecordBatch.from_arrays([*(fields[n].slice(a, b - a) for n in names[:6]), pa.array(made, pa.binary())], names=names)

    keyed = _keyed(docs)
    lists = needed.groupBy("row", "doc_id").agg(F.collect_list(F.struct("anchor", "seg1", "seg2", "n", "d", "back", "s0", "s1")).alias("parts")).select(F.col("row").alias("__row"), F.col("doc_id").alias("__id"), "parts")
    joined = keyed.join(lists, (F.col("row") == F.col("__row")) & F.col("doc_id").eqNullSafe(F.col("__id")))
    return joined.select("text", "parts").mapInArrow(work, PARTS)  # repeated rows give equal parts, which are one key later


def _by_anchor(parts: DataFrame, one: Callable[[list[tuple[int, int]], list[bytes], list[bytes], list[int]], Iterator[tuple]], kinds: str) -> DataFrame:
    """one(keys, lefts, rights, occurrences) gives rows of longs for each anchor, whose leaves come together in one task."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in kinds.split(", ")]
        out: list[tuple] = []
        leaves: dict[tuple, tuple] = {}
        anchor = None

        def finish() -> None:
            if leaves:
                rows = list(leaves.values())
                lefts, rights = [r[1][: r[0]][::-1] for r in rows], [r[1][r[0] :] for r in rows]
                out.extend((anchor, *row) for row in one(list(leaves), lefts, rights, [r[2] for r in rows]))

        def flush() -> pa.RecordBatch:
            done = pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], pa.int64()) for i in range(len(names))], names=names)
            out.clear()
            return done

        for batch in batches:
            columns = [batch.column(i).to_pylist() for i in range(6)]
            for a, seg1, seg2, n, back, segment in zip(*columns, strict=True):
                if a != anchor:
                    finish()
                    leaves, anchor = {}, a
                leaves[seg1, seg2] = (back, segment, n)
                if len(out) > 5000:
                    yield flush()
        finish()
        yield flush()

    rows = parts.select("anchor", "seg1", "seg2", "n", "back", "segment").repartition("anchor").sortWithinPartitions("anchor")
    return rows.mapInArrow(work, kinds)


def _in_groups(parts: DataFrame, span: int) -> DataFrame:
    """FOUND for the anchors of few segments."""

    def one(keys: list[tuple[int, int]], lefts: list[bytes], rights: list[bytes], n: list[int]) -> Iterator[tuple]:
        for m, (low, high) in repeated_windows(lefts, rights, span).items():
            if n[m] == 1:  # those found more often are covered as a whole
                yield *keys[m], len(lefts[m]) - high, len(lefts[m]) - low

    return _by_anchor(parts, one, FOUND)


MEMBERS = "anchor long, nr long, seg1 long, seg2 long, low long, length long"


def _groups(parts: DataFrame, span: int) -> DataFrame:
    """MEMBERS of the maximal repeats of each anchor of few segments: low is where the repeat begins in the segment."""

    def one(keys: list[tuple[int, int]], lefts: list[bytes], rights: list[bytes], n: list[int]) -> Iterator[tuple]:
        nr, whole = 0, {m for m, k in enumerate(n) if k > 1}
        for left, right, group in maximal_repeats(lefts, rights, span):
            whole -= {m for m in group if left == len(lefts[m]) and right == len(rights[m])}
            for m in group:
                yield nr, *keys[m], len(lefts[m]) - left, left + right
            nr += 1
        for m in sorted(whole):  # a leaf that no larger group holds as a whole
            yield nr, *keys[m], 0, len(lefts[m]) + len(rights[m])
            nr += 1

    return _by_anchor(parts, one, MEMBERS)


def _open_windows(parts: DataFrame, span: int) -> DataFrame:
    """The windows that occur twice or more of the anchors of many segments: counts of window hashes, summed before
    the shuffle."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one, two = rollings()
        for batch in batches:
            segments = batch.column(3).to_pylist()
            for a in range(0, len(segments), 500):
                firsts, seconds, counts = [], [], []
                for s in segments[a : a + 500]:
                    data = np.frombuffer(s, np.uint8)
                    start = np.arange(len(data) - span + 1)
                    firsts.append(one.of(one.sums(data), start, start + span))
                    seconds.append(two.of(two.sums(data), start, start + span))
                    counts.append(len(start))
                part, which = batch.slice(a, len(counts)), pa.array(np.repeat(np.arange(len(counts)), counts))
                places = np.concatenate([np.arange(c) for c in counts])
                yield pa.RecordBatch.from_arrays([*(part.column(i).take(which) for i in range(3)), pa.array(np.concatenate(firsts).view(np.int64)), pa.array(np.concatenate(seconds).view(np.int64)), pa.array(places)], names=["anchor", "seg1", "seg2", "w1", "w2", "place"])

    windows = parts.select("anchor", "seg1", "seg2", "segment").mapInArrow(work, "anchor long, seg1 long, seg2 long, w1 long, w2 long, place long")
    twice = windows.groupBy("anchor", "w1", "w2").agg(F.count(F.lit(1)).alias("c")).where("c > 1").drop("c")
    return windows.join(twice, ["anchor", "w1", "w2"])


def _in_the_open(parts: DataFrame, span: int) -> DataFrame:
    """FOUND for the anchors of many segments."""
    return _open_windows(parts, span).groupBy("anchor", "seg1", "seg2").agg(F.min("place").alias("low"), F.max("place").alias("high"))


def _leaves(docs: DataFrame, span: int, all_of_several: bool = False) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Runs; segments with their number n and a representative; PARTS of the anchors of several segments.

    Anchors whose segments are all repeated have nothing to compare for coverage: they come with all_of_several only."""
    if not 2 * GRAM <= span <= 4000:
        raise ValueError("span must be 64 to 4000 bytes")
    runs = written(anchor_runs(docs, span), "runs")
    first = F.min(F.struct("row", "doc_id", "p", "s0", "s1")).alias("first")
    segments = written(runs.groupBy("anchor", "seg1", "seg2").agg(F.count(F.lit(1)).alias("n"), first), "segments")
    mixed = segments.groupBy("anchor").agg(F.count(F.lit(1)).alias("d"), F.min("n").alias("rarest")).where("d > 1" if all_of_several else "d > 1 and rarest = 1").drop("rarest")
    needed = segments.join(mixed, "anchor").select("anchor", "seg1", "seg2", "n", "d", "first.row", "first.doc_id", (F.col("first.p") - F.col("first.s0")).alias("back"), "first.s0", (F.col("first.s1") + span).alias("s1"))
    return runs, segments, written(_texts_of(needed, docs), "parts")


def covered(docs: DataFrame, span: int = 400, most: int = 20_000) -> DataFrame:
    """(row, doc_id, cover): for each text with bytes to remove, stretches (start, end) that may overlap."""
    runs, segments, parts = _leaves(docs, span)
    found = _in_groups(parts.where(F.col("d") <= most), span).unionByName(_in_the_open(parts.where(F.col("d") > most), span))
    whole = segments.where("n > 1").select("anchor", "seg1", "seg2", F.lit(0).cast("long").alias("low"), (F.col("first.s1") - F.col("first.s0")).alias("high"))
    known = whole.unionByName(found)
    stretches = runs.select("doc_id", "row", "anchor", "seg1", "seg2", "s0").join(known, ["anchor", "seg1", "seg2"])
    return stretches.groupBy("row", "doc_id").agg(F.collect_list(F.struct((F.col("s0") + F.col("low")).alias("start"), (F.col("s0") + F.col("high") + span).alias("end"))).alias("cover"))


def repeat_groups(docs: DataFrame, span: int = 400, most: int = 20_000) -> DataFrame:
    """The maximal repeats of at least `span` bytes with all their occurrences: anchor and nr (together the group's
    name), length in bytes, doc_id, start (byte of the text)."""
    runs, segments, parts = _leaves(docs, span, True)
    groups = _groups(parts.where(F.col("d") <= most), span)
    alone = segments.join(segments.groupBy("anchor").agg(F.count(F.lit(1)).alias("d")).where("d = 1"), "anchor").where("n > 1")
    alone = alone.select("anchor", F.lit(0).cast("long").alias("nr"), "seg1", "seg2", F.lit(0).cast("long").alias("low"), (F.col("first.s1") - F.col("first.s0") + span).alias("length"))
    windows = _open_windows(parts.where(F.col("d") > most), span).select("anchor", F.xxhash64("w1", "w2").alias("nr"), "seg1", "seg2", F.col("place").alias("low"), F.lit(span).cast("long").alias("length"))
    found = groups.unionByName(alone).unionByName(windows)
    return runs.join(found, ["anchor", "seg1", "seg2"]).select("anchor", "nr", "length", "doc_id", (F.col("s0") + F.col("low")).alias("start"))


KEPT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def remaining(docs: DataFrame, span: int = 400, most: int = 20_000, with_bytes: bool = False) -> DataFrame:
    """KEPT for every row, and with with_bytes a binary column kept: the bytes left (which may cut a letter)."""
    names = [x.split()[0] for x in KEPT.split(", ")] + ["kept"] * with_bytes

    def cut(raw: bytes, starts: np.ndarray, ends: np.ndarray) -> tuple[bytes, int]:
        order = np.argsort(starts, kind="stable")
        starts, reach = starts[order], np.maximum.accumulate(ends[order])
        new = np.concatenate([[True], starts[1:] > reach[:-1]])  # touching stretches are one
        begin, end = starts[new], reach[np.concatenate([np.flatnonzero(new)[1:] - 1, [len(reach) - 1]])]
        edges = [0, *(x for pair in zip(begin.tolist(), end.tolist(), strict=True) for x in pair), len(raw)]
        return b"".join(raw[edges[i] : edges[i + 1]] for i in range(0, len(edges), 2)), len(begin)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = text_bytes(batch.column(1))
            lists = batch.column(2)
            counts = np.asarray(lists.value_lengths().fill_null(0))
            to = np.concatenate([[0], np.cumsum(counts)])
            flat = lists.flatten()
            starts, ends = (flat.field(i).to_numpy(zero_copy_only=False) for i in range(2))
            rows = []
            for i in range(len(batch)):
                raw, spans = data[at[i] : at[i + 1]].tobytes(), 0
                kept = raw
                if counts[i]:
                    kept, spans = cut(raw, starts[to[i] : to[i + 1]], ends[to[i] : to[i + 1]])
                rows.append((len(raw), len(raw) - len(kept), spans, hashlib.sha256(kept).hexdigest(), kept))
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()][: 4 + with_bytes]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds))], names=names)

    cover = covered(docs, span, most).select(F.col("row").alias("__row"), F.col("doc_id").alias("__id"), "cover")
    rows = _keyed(docs).join(cover, (F.col("row") == F.col("__row")) & F.col("doc_id").eqNullSafe(F.col("__id")), "left")
    return rows.select("doc_id", "text", "cover").mapInArrow(work, KEPT + ", kept binary" * with_bytes)


def op4_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remaining(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable] = {"op4_suffix_array_dedup": op4_suffix_array_dedup}
ORACLES: dict[str, str] = {}
