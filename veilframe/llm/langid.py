"""Language identification by prediction by partial matching over bytes.

For every language the contexts of up to `order` bytes that its training texts hold form a tree, stored once
for all languages: a node is a context, its children extend the context by one byte to the left. A node
gives every next byte a frozen code length in bits: if the byte followed the context c times of n, with d
distinct followers, minus log2(c / (n + d)); else the escape, minus log2(d / (n + d)), plus the length that
the context shorter by its oldest byte gives. Below the empty context all 256 bytes are equal. A text's
score under a language is the sum over all its bytes, each read in its longest context that the tree has;
the shortest code names the language, and the score is the posterior of that language under equal priors.

The model learns from a bounded sample (about `per_lang` texts a language, fewer if they would pass `most_sample`
bytes in all), drawn by hash among texts of at most `most_bytes`; a language with longer texts only learns from its
shortest ones. No language is left out, however many there are: `max_nodes`, and `most_model` bytes of tables, bound
the tree instead, rarer deep contexts going first. All statistics are tables that are looked up, so scoring is a few
gathers a byte. Bytes that no training text holds share one column.

A null text, or one without a letter, is `und` with score 0. A null lang is never learned. With nothing to
learn from, everything is `und`. Ties go to the smaller name. Repeated rows get equal rows. Columns other than
doc_id, text and lang, whatever their names, are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import byte_slices, table, text_bytes


@dataclass
class Model:
    langs: list[str]
    order: int
    code: np.ndarray  # byte -> symbol; the last symbol stands for all bytes not seen
    child: np.ndarray  # (nodes, symbols): node of the context with one more byte, or 0
    bits: np.ndarray  # (nodes, symbols, languages): code lengths


def _followers(streams: list[np.ndarray], depth: int, symbols: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each language the keys (context of `depth` symbols, then the next symbol) of its texts, with counts."""
    out = []
    for s in streams:  # texts are parted by -1
        key, fine = np.zeros(len(s), dtype=np.int64), np.ones(len(s), dtype=bool)
        for back in range(depth, -1, -1):
            at = np.concatenate([np.full(min(back, len(s)), -1), s[: max(0, len(s) - back)]])
            fine &= at >= 0
            key = key * symbols + np.maximum(at, 0)
        out.append(np.unique(key[fine], return_counts=True))
    return out


def train(samples: dict[str, list[bytes]], order: int = 3, max_nodes: int = 40_000, most_model: int = 256 << 20) -> Model:
    """most_model: bytes of the tables, which go to every task."""
    langs = sorted(samples)
    seen = np.zeros(256, dtype=bool)
    for texts in samples.values():
        for t in texts:
            seen[np.frombuffer(t, np.uint8)] = True
    code = np.full(256, int(seen.sum()), dtype=np.int32)
    code[seen] = np.arange(int(seen.sum()))
    symbols = int(seen.sum()) + 1
    max_nodes = max(1, min(max_nodes, most_model // (4 * symbols * (len(langs) + 1))))
    streams = [np.concatenate([x for t in samples[lang] for x in (code[np.frombuffer(t, np.uint8)], [-1])] or [np.array([-1])]) for lang in langs]

    def lengths(parent: np.ndarray, found: list[tuple[np.ndarray, np.ndarray]], contexts: np.ndarray) -> np.ndarray:
        rows = parent.copy()
        for k, (keys, counts) in enumerate(found):
            where = np.searchsorted(contexts, keys // symbols)
            inside = (where < len(contexts)) & (contexts[np.minimum(where, len(contexts) - 1)] == keys // symbols)
            node, symbol, c = where[inside], keys[inside] % symbols, counts[inside]
            n = np.bincount(node, c, len(contexts))
            d = np.bincount(node, minlength=len(contexts))
            has = n > 0
            rows[has, :, k] -= np.log2(d[has] / (n[has] + d[has]))[:, None]
            rows[node, symbol, k] = -np.log2(c / (n[node] + d[node]))
        return rows

    found = _followers(streams, 0, symbols)
    bits = [lengths(np.full((1, symbols, len(langs)), 8.0), found, np.zeros(1, dtype=np.int64))]
    child = [np.zeros((1, symbols), dtype=np.int32)]
    contexts, first, total = np.zeros(1, dtype=np.int64), 0, 1
    for depth in range(1, order + 1):
        found = _followers(streams, depth, symbols)
        names, where = np.unique(np.concatenate([k // symbols for k, _ in found]), return_inverse=True)
        weight = np.bincount(where, np.concatenate([c for _, c in found]), len(names))
        parent = np.searchsorted(contexts, names % symbols ** (depth - 1))
        kept = (parent < len(contexts)) & (contexts[np.minimum(parent, len(contexts) - 1)] == names % symbols ** (depth - 1))
        room = max_nodes - total
        if kept.sum() > room:
            ranked = np.flatnonzero(kept)[np.argsort(-weight[kept], kind="stable")]
            kept[ranked[room:]] = False
        names, parent = names[kept], parent[kept]
        if not len(names):
            break
        child[-1][parent, names // symbols ** (depth - 1)] = total + np.arange(len(names))
        bits.append(lengths(bits[-1][parent], found, names))
        child.append(np.zeros((len(names), symbols), dtype=np.int32))
        contexts, first, total = names, total, total + len(names)
    return Model(langs, order, code, np.concatenate(child), np.concatenate(bits).astype(np.float32))


def code_lengths(model: Model, data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """(texts, languages): bits that every text takes under every language. at: the texts' offsets in data."""
    out = np.zeros((len(at) - 1, len(model.langs)))
    step = 1 << 18
    for a in range(0, len(data), step):
        b = min(len(data), a + step)
        low = max(0, a - model.order)
        s = model.code[data[low:b]]
        place = np.arange(a, b)
        text = np.searchsorted(at, place, side="right") - 1
        into = place - at[text]  # bytes of the text before this one
        node, open_ = np.zeros(b - a, dtype=np.int32), np.ones(b - a, dtype=bool)
        for back in range(1, model.order + 1):
            before = np.zeros(b - a, dtype=np.int32)
            fits = place - back >= low
            before[fits] = s[place[fits] - back - low]
            next_ = model.child[node, before]
            open_ &= (into >= back) & (next_ > 0)
            node = np.where(open_, next_, node)
        bits = model.bits[node, s[a - low :]]
        starts = np.flatnonzero(np.concatenate([[True], text[1:] != text[:-1]]))
        out[text[starts]] += np.add.reduceat(bits, starts, axis=0, dtype=np.float64)
    return out


def training_rows(docs: DataFrame, may_learn: Column, per_lang: int = 250, most_bytes: int = 8_000, most_sample: int = 256 << 20) -> dict[str, list[bytes]]:
    """Texts by language, about per_lang each (four standard deviations above at most)."""
    size = F.octet_length(F.col("text").cast("string"))
    fit = docs.where(may_learn & F.col("lang").isNotNull() & (size > 0)).select("doc_id", F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"), size.alias("size"))
    counts = {r["lang"]: r for r in fit.groupBy("lang").agg(F.count(F.when(F.col("size") <= most_bytes, 1)).alias("n"), F.min("size").alias("least")).collect()}
    if not counts:
        return {}
    per_lang = max(4, min(per_lang, most_sample // (most_bytes * len(counts))))
    spark = docs.sparkSession
    plan = spark.createDataFrame([(k, float(min(1.0, per_lang / r["n"])) if r["n"] else 1.0, int(max(most_bytes, r["least"]))) for k, r in counts.items()], "__lang string, share double, upto long")
    draw = F.pmod(F.xxhash64(F.col("doc_id"), F.lit("learn")), F.lit(1 << 30)) / F.lit(float(1 << 30))
    drawn = fit.join(F.broadcast(plan), F.col("lang") == F.col("__lang")).where((F.col("size") <= F.col("upto")) & (draw < F.col("share")))
    # repeated rows have one draw: a text counts once
    rows = drawn.select("doc_id", "lang", "text").dropDuplicates().limit(2 * per_lang * len(counts)).collect()
    out: dict[str, list[bytes]] = {}
    for r in sorted(rows, key=lambda r: (r["lang"], r["doc_id"] is None, r["doc_id"] or 0, r["text"])):
        out.setdefault(r["lang"], []).append(r["text"].encode("utf-8", "surrogatepass"))
    return out


PREDICTED = "doc_id long, held_out boolean, lang_pred string, score double, bits_per_byte double"


def identify(docs: DataFrame, model: Model | None, held_out: Column) -> DataFrame:
    """doc_id, held_out, lang_pred, score, bits_per_byte, from the text alone."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            lettered = batch.column(3).to_numpy(zero_copy_only=False).astype(bool)
            data, at = text_bytes(batch.column(2))
            pred, score, rate = np.full(len(lettered), "und", dtype=object), np.zeros(len(lettered)), np.zeros(len(lettered))
            for a, b in byte_slices(at, 4 << 20) if m is not None else ():
                bits = code_lengths(m, data[at[a] : at[b]], at[a : b + 1] - at[a])
                best = bits.argmin(axis=1)
                least = bits.min(axis=1)
                post = 1 / np.exp2(np.clip(least[:, None] - bits, -1000, 0)).sum(axis=1)
                ok = lettered[a:b]
                pred[a:b][ok] = np.array(m.langs, dtype=object)[best[ok]]
                score[a:b][ok] = post[ok]
                rate[a:b][ok] = least[ok] / np.diff(at[a : b + 1])[ok]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(pred, pa.string()), pa.array(score), pa.array(rate)], names=[x.split()[0] for x in PREDICTED.split(", ")])

    text = F.col("text").cast("string")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(held_out, F.lit(False)).alias("held_out"), text.alias("text"), F.coalesce(text.rlike(r"\p{L}"), F.lit(False)).alias("lettered"))
    return rows.mapInArrow(work, PREDICTED)


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    held_out = F.crc32(F.col("doc_id").cast("string")) % 3 == 1
    samples = training_rows(docs, ~F.coalesce(held_out, F.lit(False)))
    return identify(docs, train(samples) if samples else None, held_out)


QUERIES = {"op1_language_id": op1_language_id}
ORACLES: dict[str, str] = {}
