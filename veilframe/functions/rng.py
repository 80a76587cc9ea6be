"""Keyed pseudo-random columns: equal on every partitioning, retry and engine.

kind "keyed" takes 48 bits of an MD5 digest (other engines can reproduce it), "fast" the same of XXH64 (for
large releases), "native" Spark's own generator (depends on partitioning). The seed is its owner's secret.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TOP = float(1 << 48)
KINDS = ("keyed", "fast", "native")


def uniform(seed: str, stream: str, key: Column, j: int = 0, kind: str = "keyed") -> Column:
    """A number in (0, 1) for the key (a string column)."""
    if kind == "native":
        return F.rand(int(hashlib.md5(f"{seed}:{stream}:{j}".encode()).hexdigest()[:8], 16))
    if kind == "fast":
        whole = F.shiftrightunsigned(F.xxhash64(F.lit(f"{seed}:{stream}:{j}"), key), 16)
    else:
        whole = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), F.lit(stream), key, F.lit(str(j)))), 1, 12), 16, 10).cast("long")
    return (whole + 0.5) / TOP


def normal(seed: str, stream: str, key: Column, j: int = 0, kind: str = "keyed") -> Column:
    """A standard normal number, from two uniform ones."""
    if kind == "native":
        return F.randn(int(hashlib.md5(f"{seed}:{stream}:{j}".encode()).hexdigest()[:8], 16))
    u1, u2 = uniform(seed, stream + "a", key, j, kind), uniform(seed, stream + "b", key, j, kind)
    return F.sqrt(-2.0 * F.log(u1)) * F.cos(F.lit(2 * math.pi) * u2)


def key_text(keys: tuple[str, ...] | list[str]) -> Column:
    return F.concat_ws(":", *(F.col(k).cast("string") for k in keys))


def uniform_of(seed: str, stream: str, key: str, j: int = 0) -> float:
    """The driver's twin of uniform(kind="keyed")."""
    return (int(hashlib.md5(f"{seed}:{stream}:{key}:{j}".encode()).hexdigest()[:12], 16) + 0.5) / TOP


def normal_of(seed: str, stream: str, key: str, j: int = 0) -> float:
    return math.sqrt(-2 * math.log(uniform_of(seed, stream + "a", key, j))) * math.cos(2 * math.pi * uniform_of(seed, stream + "b", key, j))


def gaussian_matrix(seed: str, stream: str, rows: int, columns: int) -> np.ndarray:
    return np.array([[normal_of(seed, stream, f"{i}", j) for j in range(columns)] for i in range(rows)])


_TURNS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
_ADDED = np.array([int(abs(math.sin(i + 1)) * 2**32) for i in range(64)], dtype=np.uint32)
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
#: The longest message of one MD5 block.
ONE_BLOCK = 55


def md5_top(words: np.ndarray) -> np.ndarray:
    """The first 48 bits of the MD5 digests of one-block messages, given as (16, n) little-endian words."""
    n = words.shape[1]
    a, b, c, d = (np.full(n, x, np.uint32) for x in _START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        if i < 16:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
            at = i
        elif i < 32:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
            at = (5 * i + 1) % 16
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            f ^= d
            at = (3 * i + 5) % 16
        else:
            np.invert(d, out=f)
            f |= b
            f ^= c
            at = 7 * i % 16
        f += a
        f += _ADDED[i]
        f += words[at]
        turn = _TURNS[i // 16][i % 4]
        np.right_shift(f, np.uint32(32 - turn), out=t)
        f <<= np.uint32(turn)
        f |= t
        f += b
        a, b, c, d, f = d, f, b, c, a
    a, b = a + np.uint32(_START[0]), b + np.uint32(_START[1])
    return a.byteswap().astype(np.uint64) << np.uint64(16) | (b.byteswap() >> np.uint32(16)).astype(np.uint64)


def keyed_normals(keys: pa.Array, seed: str, stream: str, count: int) -> Iterator[np.ndarray]:
    """The column twin of normal(kind="keyed") for j = 0, 1, ...: all keys of a batch at a time."""
    keys = keys.cast(pa.large_string())
    n = len(keys)
    bounds = np.frombuffer(keys.buffers()[1], np.int64, n + 1 + keys.offset)[keys.offset :]
    data = np.frombuffer(keys.buffers()[2] or b"", np.uint8)[bounds[0] : bounds[-1]]
    size = np.diff(bounds)
    head = f"{seed}:{stream}".encode()  # then the letter of the draw, a colon, the key, a colon and j
    before = len(head) + 2
    longest = ONE_BLOCK - before - 1 - len(str(max(count - 1, 0)))
    hard = np.flatnonzero((size > longest) | (np.asarray(keys.is_null(), dtype=bool)))
    hard_keys = [keys[i].as_py() for i in hard.tolist()]
    fits = np.ones(n, dtype=bool)
    fits[hard] = False
    block = np.zeros((n, 64), np.uint8)
    flat = block.reshape(-1)
    if longest >= 0:
        block[:, : len(head)] = np.frombuffer(head, np.uint8)
        block[:, before - 1] = ord(":")
        inside = np.arange(len(data)) - np.repeat(bounds[:-1] - bounds[0], size)
        kept = np.repeat(fits, size)
        flat[(np.repeat(np.arange(n) * 64 + before, size) + inside)[kept]] = data[kept]
    end = np.where(fits, np.arange(n) * 64 + before + size, 0)[fits]  # of the colon after the key

    for j in range(count):
        tail = f":{j}".encode()
        u = np.empty((2, n), np.uint64)
        if len(end):
            for k, c in enumerate(tail):
                flat[end + k] = c
            flat[end + len(tail)] = 0x80
            bits = 8 * (before + size + len(tail))
            block[:, 56], block[:, 57] = bits & 255, bits >> 8 & 255
            block[:, len(head)] = ord("a")
            words = np.empty((16, 2 * n), np.uint32)
            words[:, :n] = block.view("<u4").T
            block[:, len(head)] = ord("b")
            words[:, n:] = block.view("<u4").T
            u = md5_top(words).reshape(2, n)
        for i, key in zip(hard.tolist(), hard_keys, strict=True):
            for k, letter in enumerate("ab"):
                text = ":".join([seed, stream + letter, *([] if key is None else [key]), str(j)])
                u[k, i] = int(hashlib.md5(text.encode()).hexdigest()[:12], 16)
        u1, u2 = (u + 0.5) / TOP
        yield np.sqrt(-2.0 * np.log(u1)) * np.cos(2 * math.pi * u2)


def with_keyed_normals(df: DataFrame, key: str, attrs: list[str], seed: str, stream: str, add) -> DataFrame:
    """attrs become add(values, draws), with the normal draws of kind "keyed" on Arrow batches; nulls stay."""
    where, at = [df.columns.index(a) for a in attrs], df.columns.index(key)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = list(batch.columns)
            for i, z in zip(where, keyed_normals(columns[at], seed, stream, len(where)), strict=True):
                none = np.asarray(columns[i].is_null()) if columns[i].null_count else None
                columns[i] = pa.array(add(columns[i].to_numpy(zero_copy_only=False), z), mask=none)
            yield pa.RecordBatch.from_arrays(columns, names=batch.schema.names)

    return df.mapInArrow(work, df.schema)


def uniform_sql(seed: str, stream: str, key: str, j: object = 0) -> str:
    """DuckDB text of uniform(kind="keyed"); key is an SQL expression, j a number or an expression."""
    return f"((('0x' || substr(md5('{seed}:{stream}:' || {key} || ':' || {j}), 1, 12))::BIGINT + 0.5::DOUBLE) / 281474976710656::DOUBLE)"


def normal_sql(seed: str, stream: str, key: str, j: object = 0) -> str:
    return f"(sqrt(-2::DOUBLE * ln({uniform_sql(seed, stream + 'a', key, j)})) * cos(2 * pi() * {uniform_sql(seed, stream + 'b', key, j)}))"
