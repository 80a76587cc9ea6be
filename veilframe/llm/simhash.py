"""SimHash near-dedup with Golay-code fuzzy hashing.

A text's fingerprint has a bit for each of 64 positions that is set in over half of its shingles' hashes.
The distinct fingerprints are cut into three segments of 22, 21 and 21 bits; each, padded to 23 bits, is
decoded by the perfect binary Golay code to the index of its codeword, and again with each bit flipped. A
segment thus has one to six indices, and two segments that differ in one bit share the index of either with
the list of the other. Of at most three differing bits either some segment holds none, and then one of the other
two holds at most one: a key of the first segment's own bits and the second's index (33 or 34 bits) brings the
link together. Or each segment holds one: a key of all three indices (36 bits) does. The Hamming distance then
decides exactly. A fingerprint has some 80 keys; at over 33 bits, candidates stay in proportion to the distinct
fingerprints up to some 10^9 of them.

Equal fingerprints are one node from the start, so copies are never paired. Components are found on edge
tables (see common.components), never on the driver. A null or wordless text has fingerprint zero and links
like any other. Repeated rows share a node. A null doc_id is never a component's name unless it has no other.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import byte_slices, components, drop_written, table, text_bytes, written

SEGMENTS = (22, 21, 21)
# Fixed value: generator polynomial of the (23, 12) Golay code.
GENERATOR = 0xC75


class Golay:
    """Decoding of 23-bit words: every word is within three bits of exactly one codeword."""

    def __init__(self) -> None:
        self.of_bit = np.array([self._rest(1 << i) for i in range(23)], dtype=np.int64)
        self.of_byte = np.zeros((3, 256), dtype=np.int64)
        for k in range(3):
            for v in range(256):
                self.of_byte[k, v] = self._rest((v << (8 * k)) & 0x7FFFFF)
        self.error = np.zeros(2048, dtype=np.int64)
        for weight in range(4):
            for places in itertools.combinations(range(23), weight):
                self.error[np.bitwise_xor.reduce(self.of_bit[list(places)]) if places else 0] = sum(1 << p for p in places)

    @staticmethod
    def _rest(word: int) -> int:
        for i in range(22, 10, -1):
            if word >> i & 1:
                word ^= GENERATOR << (i - 11)
        return word

    def syndrome(self, words: np.ndarray) -> np.ndarray:
        return self.of_byte[0, words & 255] ^ self.of_byte[1, words >> 8 & 255] ^ self.of_byte[2, words >> 16]

    def index(self, words: np.ndarray) -> np.ndarray:
        """Index (12 bits) of the nearest codeword."""
        return (words ^ self.error[self.syndrome(words)]) >> 11

    def indices(self, words: np.ndarray, bits: int) -> np.ndarray:
        """A row of indices for each word: its own first, then those after one flipped bit; -1 where repeated."""
        s = self.syndrome(words)
        flips = np.concatenate([[0], 1 << np.arange(bits)])
        of = np.concatenate([[0], self.of_bit[:bits]])
        all_ = ((words[:, None] ^ flips) ^ self.error[s[:, None] ^ of]) >> 11
        order = np.argsort(all_, axis=1, kind="stable")
        ranked = np.take_along_axis(all_, order, axis=1)
        again = np.zeros_like(ranked, dtype=bool)
        again[:, 1:] = ranked[:, 1:] == ranked[:, :-1]
        out = all_.copy()
        np.put_along_axis(out, order, np.where(again, -1, ranked), axis=1)
        return out


def segments_of(fps: np.ndarray) -> list[np.ndarray]:
    out, at = [], 0
    for bits in SEGMENTS:
        out.append((fps >> np.uint64(at) & np.uint64((1 << bits) - 1)).astype(np.int64))
        at += bits
    return out


def fuzzy_keys(fps: np.ndarray, golay: Golay, side: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, key) of every fingerprint for one side; two fingerprints at most three bits apart meet on opposite sides.

    A key of kinds 0 to 5 has one segment's bits and another's index; one of kind 6 three indices, of which
    side 0 lists the last and side 1 the first two."""
    parts = segments_of(fps)
    lists = [golay.indices(s, bits) for s, bits in zip(parts, SEGMENTS, strict=True)]
    rows, keys = [], []
    for kind, (i, j) in enumerate(itertools.permutations(range(len(SEGMENTS)), 2)):
        of = lists[j] if side else lists[j][:, :1]
        r, c = np.nonzero(of >= 0)
        rows.append(r)
        keys.append(kind << 40 | parts[i][r] << 12 | of[r, c])
    first, second, third = (lists[k][:, :1] if (k < 2) == (side == 0) else lists[k] for k in range(3))
    r, c = np.nonzero(first >= 0)
    r2, c2 = np.nonzero(second[r] >= 0)
    r, pair = r[r2], first[r[r2], c[r2]] << 12 | second[r[r2], c2]
    r3, c3 = np.nonzero(third[r] >= 0)
    rows.append(r[r3])
    keys.append(6 << 40 | pair[r3] << 12 | third[r[r3], c3])
    return np.concatenate(rows), np.concatenate(keys)


def fingerprint(text: bytes, words: int = 3) -> int:
    """Of UTF-8 text, lower-cased in A-Z, over shingles of so many words (fewer: the whole sequence)."""
    parts = text.lower().split()  # bytes split at 0x20 and 0x09 to 0x0D, and only there
    if not parts:
        return 0
    joined = b" ".join(parts)
    n = len(parts) - words + 1
    if n <= 1:
        return xxhash.xxh64_intdigest(joined, 42)
    starts = np.zeros(len(parts) + 1, dtype=np.int64)
    np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1, out=starts[1:])
    of, at = xxhash.xxh64_intdigest, starts.tolist()
    counts = np.zeros(64, dtype=np.int64)
    for a in range(0, n, 65536):
        b = min(n, a + 65536)
        h = np.fromiter((of(joined[s : e - 1], 42) for s, e in zip(at[a:b], at[a + words : b + words], strict=True)), np.uint64, b - a)
        counts += np.unpackbits(h.astype(">u8").view(np.uint8)).reshape(-1, 64).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > n).tobytes(), "big")


def fingerprints(docs: DataFrame, words: int = 3) -> DataFrame:
    """(doc_id, fp): fp as a signed long with the fingerprint's bits."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = text_bytes(batch.column(1))
            fps = np.array([fingerprint(data[a:b].tobytes(), words) for a, b in zip(at[:-1], at[1:], strict=True)], dtype=np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(work, "doc_id long, fp long")


def links(distinct: DataFrame, most: int = 3) -> DataFrame:
    """Edges (a, b) between distinct fingerprints (column fp) at most three bits apart, each once or a few times."""
    if not 0 <= most <= 3:
        raise ValueError("the keys are only sure up to three errors")

    def keyed(side: int, name: str) -> DataFrame:
        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            golay = Golay()
            for batch in batches:
                fps = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
                for a in range(0, len(fps), 20_000):
                    part = fps[a : a + 20_000]
                    rows, keys = fuzzy_keys(part, golay, side)
                    yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(part[rows].view(np.int64))], names=["key", name])

        return distinct.select("fp").mapInArrow(work, f"key long, {name} long")

    return keyed(0, "a").join(keyed(1, "b").hint("merge"), "key").where((F.col("a") != F.col("b")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= most)).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def near_groups(docs: DataFrame, words: int = 3, most: int = 3) -> DataFrame:
    """doc_id, fp, component_id for every row."""
    base = written(fingerprints(docs, words), "fingerprints")
    distinct = written(base.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct")
    roots = components(links(distinct, most), "simhash")
    rooted = distinct.join(roots.hint("merge"), F.col("fp") == F.col("node"), "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    named = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    names = rooted.join(named.hint("merge"), "root").select(F.col("fp").alias("__fp"), "component_id")
    return base.join(names.hint("merge"), F.col("fp") == F.col("__fp")).select("doc_id", "fp", "component_id")


# --- near copies by fingerprints and by similarity of word shingles ---------------------------------------------
#
# The pipeline links texts by their SimHash fingerprints as above, and then those that more bits tell apart by their
# sets of shingles. These links are exact: two texts are linked if the Jaccard similarity of their sets of shingles reaches the threshold.
# Candidates share a shingle among the first n - ceil(similarity * n) + 1 of their n, in one order for all texts;
# no pair at the threshold can avoid that. Shingles that a sample shows to be common come last in the order, which
# keeps buckets small and changes no result. Of the candidates, FILTER_BITS bits and then, for what passes, WIDE_BITS
# bits drop pairs that lie MARGIN deviations past the threshold; all others are decided by their whole sets.
#
# A first round compares each bucket's rows with its leader, drawn by key so that buckets of the same texts have
# different ones. A second round compares the rows of a bucket that are not yet in one component: in buckets of at
# most SMALL_BUCKET rows by a join, in larger ones block by block, the rows outside the leader's component against
# all, where only rows with a likely partner fetch their sets and only links between components leave a task. So every pair of a bucket is either compared or joined
# already, and no bucket has to fit a task.

FILTER_BITS, WIDE_BITS, MARGIN = 128, 1024, 5
#: A shingle is common if at least one in COMMON texts of the sample (one text in SAMPLE) and SEEN of them have it.
COMMON, SAMPLE, SEEN = 2000, 16, 8
SMALL_BUCKET, BLOCK = 32, 256
_ONES = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).astype(np.float64)
_SPREAD = np.random.default_rng(8).integers(1 << 62, 1 << 63, WIDE_BITS // 64, dtype=np.uint64) | np.uint64(1)


def _majority(rows: np.ndarray) -> np.ndarray:
    """Of n rows of bytes, the bytes of the bits that over half the rows set."""
    n, width = rows.shape
    counts = np.bincount((rows + np.arange(width) * 256).ravel(), minlength=width * 256).reshape(width, 256) @ _ONES
    return np.packbits(2 * counts > n, axis=1).ravel()


def shingle_set(text: bytes, words: int = 5) -> np.ndarray:
    """Distinct hashes, ascending, of the shingles of a text's lower-cased words (fewer words: the whole sequence)."""
    parts = text.lower().split()
    joined = b" ".join(parts)
    if len(parts) <= words:
        return np.array([xxhash.xxh3_64_intdigest(joined)], dtype=np.uint64)
    at = np.concatenate([[0], np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1)]).tolist()
    return np.unique(np.fromiter((xxhash.xxh3_64_intdigest(joined[a : b - 1]) for a, b in zip(at[: len(parts) - words + 1], at[words:], strict=True)), np.uint64))


def signature(items: np.ndarray, bits: int = FILTER_BITS) -> np.ndarray:
    """So many bits of a shingle set, as signed longs."""
    spread = items[:, None] * _SPREAD[: bits // 64]
    return _majority((spread ^ (spread >> np.uint64(31))).view(np.uint8).reshape(len(items), -1)).view(np.int64)


def prefix_of(items: np.ndarray, similarity: float, common: np.ndarray) -> np.ndarray:
    """The first shingles in the order (common or not, hash): sets of that similarity share one of theirs."""
    late = np.isin(items, common, assume_unique=True)
    ordered = np.concatenate([items[~late], items[late]])
    return ordered[: len(items) - math.ceil(similarity * len(items) - 1e-9) + 1]


def text_name() -> Column:
    """Equal texts have equal names, and a null text that of the empty one."""
    return F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit("")))


def named(docs: DataFrame) -> DataFrame:
    """doc_id, name, text."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_name().alias("name"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))


def _sets(texts: DataFrame, words: int, wide: bool = False) -> DataFrame:
    """name and items, the whole shingle set, from name and text; if asked for, wide: its WIDE_BITS bits."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = text_bytes(batch.column(1))
            for a, b in byte_slices(at, 4 << 20):
                sets = [shingle_set(data[x:y].tobytes(), words) for x, y in zip(at[a:b], at[a + 1 : b + 1], strict=True)]
                more = [_lists([signature(x, WIDE_BITS) for x in sets])] * wide
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), _lists(sets), *more], names=["name", "items", "wide"][: 2 + wide])

    return texts.select("name", "text").mapInArrow(work, "name long, items array<long>" + ", wide array<long>" * wide)


def _lists(arrays: list[np.ndarray]) -> pa.Array:
    offsets = np.concatenate([[0], np.cumsum([len(x) for x in arrays])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(arrays).view(np.int64)))


def common_shingles(texts: DataFrame, words: int) -> np.ndarray:
    """Shingles that come late in the order: at most COMMON times a text's mean number of them, whatever the table's size."""
    sample = texts.where(F.pmod("name", F.lit(SAMPLE)) == 0)
    n = sample.select("name").distinct().count()
    if n < SEEN:
        return np.zeros(0, np.uint64)
    counted = _sets(sample.dropDuplicates(["name"]), words).select(F.explode("items").alias("item")).groupBy("item").count()
    found = counted.where(F.col("count") >= max(SEEN, n // COMMON)).select("item").toArrow().column(0).to_numpy()
    return np.sort(found.view(np.uint64))


def sketches(texts: DataFrame, words: int, similarity: float, common: np.ndarray) -> DataFrame:
    """doc_id, name, fp (the SimHash fingerprint), size of the shingle set, its bits b0 and b1, and its prefix."""
    b = [f"b{i}" for i in range(FILTER_BITS // 64)]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = text_bytes(batch.column(2))
            fps, sizes, bits, prefixes = [], [], [], []
            for x, y in zip(at[:-1], at[1:], strict=True):
                text = data[x:y].tobytes()
                items = shingle_set(text, words)
                fps.append(fingerprint(text))
                sizes.append(len(items))
                bits.append(signature(items))
                prefixes.append(prefix_of(items, similarity, common))
            if sizes:
                bits = np.stack(bits)
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.array(fps, dtype=np.uint64).view(np.int64)), pa.array(sizes, pa.int32()), *(pa.array(bits[:, i].copy()) for i in range(len(b))), _lists(prefixes)], names=["doc_id", "name", "fp", "size", *b, "prefix"])

    return texts.select("doc_id", "name", "text").mapInArrow(work, "doc_id long, name long, fp long, size int, " + ", ".join(f"{x} long" for x in b) + ", prefix array<long>")


BITS = [f"b{i}" for i in range(FILTER_BITS // 64)]


def most_differing(similarity: float, bits: int = FILTER_BITS) -> int:
    """Of so many bits, those that sets of that similarity differ in at most, MARGIN deviations past what is expected."""
    angle = math.acos(2 * similarity / (1 + similarity)) / math.pi
    return math.ceil(bits * angle + MARGIN * math.sqrt(bits * angle * (1 - angle)))


def can_be_similar(similarity: float) -> Column:
    """Of two rows x and y, by their sizes and bits."""
    sizes = F.least("x.size", "y.size") >= F.lit(similarity) * F.greatest("x.size", "y.size") - 1e-9
    differing = sum((F.bit_count(F.col(f"x.{b}").bitwiseXOR(F.col(f"y.{b}"))) for b in BITS), F.lit(0))
    return sizes & (differing <= most_differing(similarity))


def shared_buckets(distinct: DataFrame) -> DataFrame:
    """key, name, size, bits, n and leads (whether the row is its bucket's leader) of the buckets of several rows."""
    keyed = distinct.select(F.explode("prefix").alias("key"), "name", "size", *BITS)
    draw = F.xxhash64("name", "key")
    heads = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min(draw).alias("__lead")).where("n > 1")
    return keyed.join(heads, "key").withColumn("leads", draw == F.col("__lead")).drop("__lead")


def leader_pairs(buckets: DataFrame, similarity: float) -> DataFrame:
    """Edges (a, b), a < b, of every row with its buckets' leaders, if these can be similar."""
    pairs = buckets.where("not leads").alias("x").join(buckets.where("leads").alias("y"), F.col("x.key") == F.col("y.key"))
    return pairs.where(can_be_similar(similarity)).select(F.least("x.name", "y.name").alias("a"), F.greatest("x.name", "y.name").alias("b")).distinct()


def mixed_buckets(buckets: DataFrame, roots: DataFrame) -> DataFrame:
    """The rows of buckets that lie in several components, with root and the leader's root."""
    rows = buckets.join(roots, F.col("name") == F.col("node"), "left").withColumn("root", F.coalesce("root", "name")).drop("node")
    mixed = rows.groupBy("key").agg(F.min("root").alias("__low"), F.max("root").alias("__high"), F.max(F.when(F.col("leads"), F.col("root"))).alias("lead_root")).where("__low <> __high").drop("__low", "__high")
    return rows.join(mixed, "key")


def component_pairs(mixed: DataFrame, similarity: float) -> DataFrame:
    """Edges (a, b) of all pairs in small buckets that are in different components and can be similar."""
    small = mixed.where(F.col("n") <= SMALL_BUCKET)
    pairs = small.alias("x").join(small.alias("y"), (F.col("x.key") == F.col("y.key")) & (F.col("x.root") < F.col("y.root")) & can_be_similar(similarity))
    return pairs.select(F.least("x.name", "y.name").alias("a"), F.greatest("x.name", "y.name").alias("b")).distinct()


def block_rows(mixed: DataFrame) -> DataFrame:
    """The rows of large buckets, once for each pair of blocks that they take part in: key, asker and other block.

    Askers are the rows outside the leader's component; a row of the leader's component need not meet its own."""
    large = mixed.where(F.col("n") > SMALL_BUCKET).withColumn("asks", F.col("root") != F.col("lead_root"))
    sizes = large.groupBy("key").agg(F.ceil(F.sum(F.col("asks").cast("int")) / BLOCK).cast("int").alias("askers"), F.ceil(F.max("n") / BLOCK).cast("int").alias("others"))
    of = large.groupBy(F.col("name").alias("__name")).agg(F.collect_list("key").alias("keys"))  # no longer than a text's prefix
    rows = large.join(sizes, "key").join(of, F.col("name") == F.col("__name")).withColumn("draw", F.xxhash64("name", F.lit("block")))
    own = ["key", "name", "size", *BITS, "root", "keys"]
    first = rows.where("asks").select(*own, F.lit(True).alias("asks"), F.pmod("draw", "askers").cast("int").alias("asker"), F.explode(F.sequence(F.lit(0), F.col("others") - 1)).alias("other"))
    second = rows.select(*own, F.lit(False).alias("asks"), F.explode(F.sequence(F.lit(0), F.col("askers") - 1)).alias("asker"), F.pmod("draw", "others").cast("int").alias("other"))
    return first.unionByName(second)


def block_links(asks: np.ndarray, names: np.ndarray, roots: np.ndarray, sizes: np.ndarray, bits: np.ndarray, items: list[np.ndarray], similarity: float, most_wide: int, chunk: int = 64) -> list[tuple[int, int]]:
    """Links between components among the rows of a pair of blocks: exact similarity, and one link for components
    that several would join."""
    root_of: dict[int, int] = {}

    def top(r: int) -> int:
        while r in root_of:
            r = root_of[r]
        return r

    out: list[tuple[int, int]] = []
    others = np.flatnonzero(~asks)
    for i in np.flatnonzero(asks).tolist():
        fine = (np.minimum(sizes[others], sizes[i]) >= similarity * np.maximum(sizes[others], sizes[i]) - 1e-9) & (np.bitwise_count(bits[others] ^ bits[i]).sum(axis=1, dtype=np.int64) <= most_wide)
        left, mine = others[fine & (roots[others] != roots[i])], items[i]
        for a in range(0, len(left), chunk):
            part = [j for j in left[a : a + chunk].tolist() if top(int(roots[j])) != top(int(roots[i]))]
            if not part:
                continue
            flat = np.concatenate([items[j] for j in part])
            at = np.searchsorted(mine, flat)
            hit = mine[np.minimum(at, len(mine) - 1)] == flat
            shared = np.add.reduceat(hit, np.concatenate([[0], np.cumsum([len(items[j]) for j in part[:-1]], dtype=np.int64)]), dtype=np.int64)
            for j, n in zip(part, shared.tolist(), strict=True):
                x, y = top(int(roots[i])), top(int(roots[j]))
                if x != y and n >= similarity * (len(mine) + len(items[j]) - n) - 1e-9:
                    root_of[max(x, y)] = min(x, y)
                    out.append((int(names[i]), int(names[j])))
    return out


BLOCK_KEY = ["key", "asker", "other"]


def _by_block(rows: DataFrame, one: Callable[[pa.Table], pa.RecordBatch], kinds: str) -> DataFrame:
    """one() on the rows of every pair of blocks, of which a task holds one at a time."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        last = None
        for batch in batches:
            ids = np.stack([batch.column(c).to_numpy() for c in BLOCK_KEY], axis=1)
            cuts = [0, *(np.flatnonzero((ids[1:] != ids[:-1]).any(axis=1)) + 1).tolist(), len(ids)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                if a == b:
                    continue
                if held and tuple(ids[a]) != last:
                    yield one(pa.Table.from_batches(held))
                    held = []
                held.append(batch.slice(a, b - a))
                last = tuple(ids[a])
        if held:
            yield one(pa.Table.from_batches(held))

    return rows.repartition(*BLOCK_KEY).sortWithinPartitions(*BLOCK_KEY).mapInArrow(work, kinds)


def rows_with_partners(rows: DataFrame, similarity: float, sets: DataFrame | None = None) -> DataFrame:
    """Those block_rows that can be similar to a row across, of another component: by FILTER_BITS, or with sets by
    WIDE_BITS. Texts' sets are read for these only. Rows that meet in several large buckets do so in the first."""
    wide = sets is not None
    most, names = most_differing(similarity, WIDE_BITS if wide else FILTER_BITS), [*BLOCK_KEY, "name", "size", *BITS, "root", "asks"]

    def one(t: pa.Table) -> pa.RecordBatch:
        asks, sizes, roots = (t.column(c).to_numpy() for c in ("asks", "size", "root"))
        bits = np.stack([t.column(b).to_numpy() for b in BITS], axis=1) if not wide else t.column("wide").combine_chunks().flatten().to_numpy().reshape(t.num_rows, -1)
        i, j = np.flatnonzero(asks), np.flatnonzero(~asks)
        near = (np.minimum(sizes[i][:, None], sizes[j]) >= similarity * np.maximum(sizes[i][:, None], sizes[j]) - 1e-9) & (roots[i][:, None] != roots[j])
        differing = np.zeros(near.shape, dtype=np.int32)
        for k in range(bits.shape[1]):
            differing += np.bitwise_count(bits[i, k].view(np.uint64)[:, None] ^ bits[j, k].view(np.uint64))
        near &= differing <= most
        if not wide and near.any():
            lists, own = t.column("keys").combine_chunks(), t.column("key")[0].as_py()
            keys, of = lists.flatten().to_numpy(), np.repeat(np.arange(t.num_rows), lists.value_lengths().to_numpy())
            names_, code = np.unique(keys[keys < own], return_inverse=True)
            has = np.zeros((t.num_rows, len(names_)), dtype=np.float32)
            has[of[keys < own], code] = 1
            both = has[i].any(axis=0) & has[j].any(axis=0)
            near &= has[i][:, both] @ has[j][:, both].T == 0
        kept = t.select(names).take(pa.array(np.concatenate([i[near.any(axis=1)], j[near.any(axis=0)]])))
        return pa.RecordBatch.from_arrays([c.combine_chunks() for c in kept.columns], names=names)

    kinds = "key long, asker int, other int, name long, size int, " + ", ".join(f"{b} long" for b in BITS) + ", root long, asks boolean"
    return _by_block(rows if sets is None else rows.join(sets.select(F.col("name").alias("__name"), "wide"), F.col("name") == F.col("__name")).drop("__name"), one, kinds)


def block_edges(rows: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """Edges (a, b) of texts of that similarity, from block_rows and the texts' sets."""
    most_wide = most_differing(similarity)

    def one(t: pa.Table) -> pa.RecordBatch:
        column = lambda c: t.column(c).to_numpy()
        items = [x.values.to_numpy().view(np.uint64) for x in t.column("items")]
        bits = np.stack([column(b) for b in BITS], axis=1).view(np.uint64)
        links = np.array(block_links(column("asks"), column("name"), column("root"), column("size"), bits, items, similarity, most_wide), dtype=np.int64).reshape(-1, 2)
        links.sort(axis=1)
        return pa.RecordBatch.from_arrays([pa.array(links[:, 0].copy()), pa.array(links[:, 1].copy())], names=["a", "b"])

    both = rows.join(sets.select(F.col("name").alias("__name"), "items"), F.col("name") == F.col("__name")).drop("__name")
    return _by_block(both, one, "a long, b long").distinct()


def sets_of(names: DataFrame, texts: DataFrame, distinct: DataFrame, words: int) -> DataFrame:
    """name, items and wide bits of the named texts, each from one row that has it."""
    of = distinct.select("name", "least").join(names, "name").select(F.col("name").alias("__name"), "least")
    wanted = texts.join(of, (F.col("name") == F.col("__name")) & F.col("doc_id").eqNullSafe(F.col("least")), "left_semi").dropDuplicates(["name"])
    return _sets(wanted, words, True)


def similar(edges: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """Those edges whose whole shingle sets have that Jaccard similarity or more."""
    beside = lambda rows, c: rows.join(sets.select(F.col("name").alias("a"), F.col(c).alias("x")), "a").join(sets.select(F.col("name").alias("b"), F.col(c).alias("y")), "b")
    differing = sum((F.bit_count(F.col("x")[i].bitwiseXOR(F.col("y")[i])) for i in range(WIDE_BITS // 64)), F.lit(0))
    near = written(beside(edges, "wide").where(differing <= most_differing(similarity, WIDE_BITS)).select("a", "b"), "near")
    shared = beside(near, "items").select("a", "b", F.size(F.array_intersect("x", "y")).alias("n"), (F.size("x") + F.size("y")).alias("sum"))
    return shared.where(F.col("n") >= F.lit(similarity) * (F.col("sum") - F.col("n")) - 1e-9).select("a", "b")


def _ends(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("a").alias("name")).union(edges.select("b")).distinct()


def fingerprint_edges(distinct: DataFrame, most: int) -> DataFrame:
    """Edges (a, b), a < b, of names by their SimHash fingerprints: a name and the first of its fingerprint, and the
    firsts of fingerprints at most so many bits apart."""
    heads = written(distinct.groupBy("fp").agg(F.min("name").alias("head")), "heads")
    equal = distinct.select("name", "fp").join(heads.hint("merge"), "fp").where("name <> head").select("name", "head")
    of = lambda end: heads.select(F.col("fp").alias(end), F.col("head").alias(f"{end}_head")).hint("merge")
    near = links(heads, most).distinct().join(of("a"), "a").join(of("b"), "b").select("a_head", "b_head")
    return equal.union(near).select(F.least("name", "head").alias("a"), F.greatest("name", "head").alias("b"))


def similar_groups(docs: DataFrame, words: int = 5, similarity: float = 0.8, bits: int | None = None) -> DataFrame:
    """doc_id, name, component_id, group: groups of texts linked by at least that similarity of their sets of word shingles.

    bits: texts whose SimHash fingerprints differ in at most so many bits are linked first; the rounds on shingle sets
    then compare only what the fingerprints have not joined.
    component_id is the smallest doc_id of a group and null if all are null; group tells all groups apart."""
    texts = named(docs)
    base = written(sketches(texts, words, similarity, common_shingles(texts, words)), "sketches")
    distinct = written(base.groupBy("name").agg(F.min("doc_id").alias("least"), *(F.first(c).alias(c) for c in ("fp", "size", *BITS, "prefix"))), "names")
    by_bits = None if bits is None else written(fingerprint_edges(distinct, bits), "fingerprint-links")
    buckets = written(shared_buckets(distinct), "buckets")
    edges = written(leader_pairs(buckets, similarity), "candidates")
    sets = written(sets_of(_ends(edges), texts, distinct, words), "sets")
    found = written(similar(edges, sets, similarity), "similar")
    if by_bits is not None:
        found = found.union(by_bits)
    roots = components(found, "similar")
    mixed = written(mixed_buckets(buckets, roots), "mixed")
    drop_written(buckets)
    edges, rows = written(component_pairs(mixed, similarity), "candidates"), written(rows_with_partners(block_rows(mixed), similarity), "blocks")
    names = _ends(edges).union(rows.select("name")).distinct()
    drop_written(sets)
    sets = written(sets_of(names, texts, distinct, words), "sets")
    rows = written(rows_with_partners(rows, similarity, sets), "blocks")
    more = written(similar(edges, sets, similarity).union(block_edges(rows, sets, similarity)), "similar")
    if more.limit(1).count():
        roots = components(found.union(more), "similar")
    rooted = distinct.select("name", "least").join(roots, F.col("name") == F.col("node"), "left").select("name", "least", F.coalesce("root", "name").alias("root"))
    chosen = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    names = rooted.join(chosen, "root").select(F.col("name").alias("__name"), "component_id", F.col("root").alias("group"))
    return base.select("doc_id", "name").join(names, F.col("name") == F.col("__name")).select("doc_id", "name", "component_id", "group")


def keep_one(docs: DataFrame, words: int = 5, similarity: float = 0.8, bits: int | None = 3) -> DataFrame:
    """docs with one document of each group of similar_groups, by fingerprints and shingle sets: the one of smallest id, null ids last; of repeated
    rows, one. Rows are told apart by id and text, so one id may stand for several texts."""
    groups = written(similar_groups(docs, words, similarity, bits), "groups")
    first = F.struct(F.col("doc_id").isNull().alias("late"), F.col("doc_id").alias("id"), F.col("name").alias("of"))
    kept = groups.groupBy("group").agg(F.min(first).alias("kept")).select(F.col("group").alias("__in"), "kept")
    gone = groups.join(kept, F.col("group") == F.col("__in")).where(~(F.col("doc_id").eqNullSafe(F.col("kept.id")) & (F.col("name") == F.col("kept.of"))))
    gone = gone.select(F.col("doc_id").alias("__gone"), F.col("name").alias("__of")).distinct()
    own = docs.withColumns({"__id": F.col("doc_id").cast("long"), "__name": text_name()})
    left = own.join(gone, F.col("__id").eqNullSafe(F.col("__gone")) & (F.col("__name") == F.col("__of")), "left_anti")
    if groups.groupBy("doc_id", "name").count().where("count > 1").limit(1).count():
        left = left.dropDuplicates(["__id", "__name"])
    return left.drop("__id", "__name")


def op8_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    groups = near_groups(table(spark, sf_dir, "documents"))
    return groups.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


QUERIES = {"op8_simhash_near_dedup": op8_simhash_near_dedup}
ORACLES: dict[str, str] = {}
