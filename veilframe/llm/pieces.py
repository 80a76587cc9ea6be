"""SentencePiece encoding and decoding with the n best segmentations.

The pieces of a public model span a lattice over a text. Forward Viterbi gives every position the best score
of what lies before it; that is the exact rest cost of an A* search from the end backward, which therefore
meets complete segmentations best first. Pieces of a BPE model carry merge ranks, not probabilities; they are
read as a Zipf law over the ranks (rank r: probability in proportion to 1 / (r + 2)).

No piece goes on after a letter with a space, so a text's lattice falls apart before every run of spaces;
each part is searched once and remembered, and the n best of the whole are combined from the parts' lists.
(A model that has such a piece is refused.) Characters outside all pieces become byte pieces, so decoding
gives the text back exactly, a literal U+2581 included.

All segmentations, the best as well, come from the search. Since its rest costs are exact, every agenda entry stands
for a complete segmentation of just that score, so the agenda needs no more entries than segmentations are still
wanted; beside the text a search holds one number a character, however long a run without spaces is.

A null text has null ids; an empty text has none. Repeated rows get equal rows; other columns, whatever their names,
are not read.
"""

from __future__ import annotations

import bisect
import hashlib
import heapq
import math
import re
from array import array
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
#: Log probabilities are whole multiples of 1 / SCALE, so that sums are exact and ties are ties.
SCALE = 1 << 20
REMEMBERED = 350_000
#: Parts of more letters are searched each time.
LONG = 200


@dataclass
class Pieces:
    score: dict[str, tuple[int, int]]  # piece with plain spaces -> log probability in units of 1 / SCALE, id
    byte_ids: list[int]  # of the 256 byte pieces
    byte_score: int
    text_of: list[bytes]  # by id
    longest: int


def load(path: str = MODEL) -> Pieces:
    """Reads a model's pieces on the driver."""
    import sentencepiece

    m = sentencepiece.SentencePieceProcessor(model_file=path)
    ids = range(m.get_piece_size())
    byte_ids, normal, text_of = [0] * 256, [], [b""] * len(ids)
    for i in ids:
        if m.is_byte(i):
            value = int(m.id_to_piece(i)[3:5], 16)
            byte_ids[value], text_of[i] = i, bytes([value])
        elif not (m.is_control(i) or m.is_unknown(i) or m.is_unused(i)):
            normal.append(i)
    weights = 1 / (np.arange(len(normal) + 256) + 2)
    logs = np.rint(np.log(weights / weights.sum()) * SCALE).astype(int)
    score = {}
    for rank, i in enumerate(sorted(normal, key=lambda i: (-m.get_score(i), i))):
        piece = m.id_to_piece(i).replace("▁", " ")
        if re.search("[^ ] ", piece):
            raise ValueError(f"piece {i} goes on with a space after a letter")
        score[piece], text_of[i] = (int(logs[rank]), i), piece.encode("utf-8")
    return Pieces(score, byte_ids, int(logs[-1]), text_of, max(map(len, score)))


def best_before(pieces: Pieces, part: str) -> array:
    """The forward pass: the best score of what lies before every position."""
    n, find, longest = len(part), pieces.score.get, pieces.longest
    best = array("q", [-(1 << 62)]) * (n + 1)
    best[0] = 0
    for start, letter in enumerate(part):
        base, single = best[start], False
        for end in range(start + 1, min(n, start + longest) + 1):
            got = find(part[start:end])
            if got is not None:
                single |= end == start + 1
                if base + got[0] > best[end]:
                    best[end] = base + got[0]
        if not single:
            cost = pieces.byte_score * len(letter.encode("utf-8", "surrogatepass"))
            if base + cost > best[start + 1]:
                best[start + 1] = base + cost
    return best


def edges_into(pieces: Pieces, part: str, at: int) -> list[tuple[int, int, tuple[int, ...]]]:
    """(start, score, ids) of every way into a position."""
    out, find = [], pieces.score.get
    for start in range(at - 1, max(0, at - pieces.longest) - 1, -1):
        got = find(part[start:at])
        if got is not None:
            out.append((start, got[0], (got[1],)))
        elif start == at - 1:
            raw = part[start].encode("utf-8", "surrogatepass")
            out.append((start, pieces.byte_score * len(raw), tuple(pieces.byte_ids[b] for b in raw)))
    return out


def search(best: array | list[int], into: Callable[[int], list[tuple[int, int, tuple[int, ...]]]], n: int, ahead: int = 0) -> tuple[list[tuple[int, tuple[int, ...]]], list[int]]:
    """The n best ways through a lattice as (score, ids), best first, from its end backward; and the scores of up to
    `ahead` more, which the agenda's next entries are sure to lead to.

    best: the best score of what lies before every position. Of equal agenda entries the older one goes first."""
    # (minus the whole's score, age, position, score behind, ids behind), at most as many as are still wanted
    agenda, made, out, insort = [(-best[-1], 0, len(best) - 1, 0, None)], 0, [], bisect.insort
    while agenda and len(out) < n:
        _, _, at, behind, tail = agenda.pop(0)
        if not at:
            ids: list[int] = []
            while tail is not None:
                ids += tail[0]
                tail = tail[1]
            out.append((behind, tuple(ids)))
            continue
        room = n + ahead - len(out)
        for start, score, ids_ in into(at):
            score += behind
            rank = -best[start] - score
            if len(agenda) < room:
                made += 1
                insort(agenda, (rank, made, start, score, (ids_, tail)))
            elif rank < agenda[-1][0]:
                made += 1
                agenda.pop()
                insort(agenda, (rank, made, start, score, (ids_, tail)))
    return out, [-entry[0] for entry in agenda[:ahead]]


def n_best(pieces: Pieces, part: str, n: int) -> list[tuple[int, tuple[int, ...]]]:
    """The n best segmentations of a part as (score, ids), best first."""
    return search(best_before(pieces, part), lambda at: edges_into(pieces, part, at), n)[0]


class Encoder:
    """Encodes texts part by part, remembering parts. Keeps at most two generations of REMEMBERED of them."""

    def __init__(self, pieces: Pieces, n: int = 1):
        import ahocorasick

        self.pieces, self.n, self.ahead = pieces, n, int(n > 1)  # of most parts the best and the next one's score are enough
        covered = {c for piece in pieces.score for c in piece}
        if not covered <= pieces.score.keys():
            raise ValueError("a letter of a piece is no piece itself")
        letters = "".join(sorted(covered - {" "})).translate({ord(c): "\\" + c for c in "\\]^-[&~|"})
        # no piece has a letter outside `covered`, so such a letter is a part of its own
        self.parts = re.compile(f" *[{letters}]+| +|[^ {letters}]", re.DOTALL)
        self.matcher = ahocorasick.Automaton()
        for piece, (score, i) in pieces.score.items():
            self.matcher.add_word(piece, (len(piece), score, (i,)))
        self.matcher.make_automaton()
        self.joined = {piece[i : i + 2] for piece in pieces.score for i in range(len(piece) - 1)}
        self.known: dict[str, tuple[int, bytes, float]] = {}
        self.before: dict[str, tuple[int, bytes, float]] = {}
        self.words: dict[str, tuple[int, bytes, float]] = {}
        self.words_before: dict[str, tuple[int, bytes, float]] = {}
        self.lists: dict[str, list[tuple[int, tuple[int, ...]]]] = {}

    def _solve(self, part: str) -> tuple[int, bytes, float] | None:
        """The search on a part whose forward pass is one run of the matcher; None with a letter outside all pieces."""
        n = len(part)
        if n > LONG:  # edges are found again when they are wanted
            best = array("q", [0]) + array("q", [-(1 << 62)]) * n
            for last, (size, score, _) in self.matcher.iter(part):
                score += best[last + 1 - size]
                if score > best[last + 1]:
                    best[last + 1] = score
            return None if best[n] < -(1 << 61) else self._packed(search(best, lambda at: edges_into(self.pieces, part, at), 1, self.ahead))
        # search(best, into, 1, 1) with its agenda written out: rest costs are exact, so the first descent never turns
        # back, and of what it leaves behind only the best score, of a second way into some position, is wanted
        low = -(1 << 62)
        best, next_, by = [0] + [low] * n, [low] * (n + 1), [()] * (n + 1)
        for last, (size, score, ids) in self.matcher.iter(part):
            last += 1
            score += best[last - size]
            if score > best[last]:
                next_[last], best[last], by[last] = best[last], score, (size, ids[0])
            elif score > next_[last]:
                next_[last] = score
        if best[n] < -(1 << 61):
            return None
        found, gap, at = [], 1 << 62, n
        while at:
            size, i = by[at]
            found.append(i)
            if best[at] - next_[at] < gap:
                gap = best[at] - next_[at]
            at -= size
        found.reverse()
        return best[n], array("i", found).tobytes(), gap if gap < 1 << 60 else math.inf

    @staticmethod
    def _packed(found: tuple[list[tuple[int, tuple[int, ...]]], list[int]]) -> tuple[int, bytes, float]:
        [(score, ids)], after = found
        return score, array("i", ids).tobytes(), score - after[0] if after else math.inf

    def part(self, part: str) -> tuple[int, bytes, float]:
        """(best score, best ids as bytes, gap to the second best)."""
        if (made := self.before.get(part)) is None and (made := self._solve(part)) is None:
            made = self._packed(search(best_before(self.pieces, part), lambda at: edges_into(self.pieces, part, at), 1, self.ahead))  # a letter outside all pieces
        if len(part) > LONG:
            return made
        if len(self.known) >= REMEMBERED:  # frequent parts come back from the generation before
            self.before = dict(self.known)
            self.known.clear()
        self.known[part] = made
        return made

    def word(self, word: str) -> tuple[int, bytes, float]:
        """part() of a space and a word, which may hold letters outside all pieces and so fall into several parts."""
        if (made := self.words_before.get(word)) is None:
            made = None
            if 1 < len(word) <= 100 and word[-2:] not in self.joined:  # no piece spans the last two letters: a mark after a word
                head, tail = self.words.get(word[:-1]) or self.word(word[:-1]), self.known.get(word[-1]) or self.part(word[-1])
                made = head[0] + tail[0], head[1] + tail[1], min(head[2], tail[2])
            else:
                made = self._solve(" " + word)
            if made is None:
                all_ = [self.known.get(p) or self.part(p) for p in self.parts.findall(" " + word)]
                made = sum(p[0] for p in all_), b"".join(p[1] for p in all_), min(p[2] for p in all_)
        if len(word) > LONG:
            return made
        if len(self.words) >= REMEMBERED:
            self.words_before = dict(self.words)
            self.words.clear()
        self.words[word] = made
        return made

    def choices(self, part: str) -> list[tuple[int, tuple[int, ...]]]:
        """The n best segmentations of a part."""
        if len(self.lists) >= REMEMBERED // 20:
            self.lists.clear()
        found = self.lists.get(part)
        if found is None:
            found = self.lists[part] = n_best(self.pieces, part, self.n)
        return found

    def _parts_of(self, text: str) -> tuple[Callable[[int], str], list[tuple[int, bytes, float]]]:
        """Names (by place) and solutions of a text's parts: its words, if single spaces part them."""
        padded = " " + text
        if "  " not in padded:
            known, words = self.words, text.split(" ")
            return lambda i: " " + words[i], [known.get(w) or self.word(w) for w in words]
        names, known = self.parts.findall(padded), self.known
        return names.__getitem__, [known.get(p) or self.part(p) for p in names]

    def encode(self, text: str) -> tuple[np.ndarray, list[float], list[list[Edit]]]:
        """Best ids; the scores of the n best; and each of these as edits of the best ids."""
        if not text:
            return np.zeros(0, np.int32), [0.0], [[]]
        names, parts = self._parts_of(text)
        scores, found, gaps = zip(*parts, strict=True)
        ids, total = np.frombuffer(b"".join(found), np.int32), sum(scores)
        if self.n == 1:
            return ids, [total / SCALE], [[]]
        # a combination among the n best leaves the best choice only in the n - 1 parts of smallest gap
        gaps = np.array(gaps, dtype=np.float64)
        most = np.partition(gaps, self.n - 2)[self.n - 2] if len(gaps) >= self.n else math.inf
        near = np.flatnonzero((gaps <= most) & (gaps < math.inf))
        ranked = sorted((gaps[i], i) for i in near.tolist())[: self.n - 1]
        combos: list[tuple[int, list[Edit]]] = [(0, [])]
        for _, i in ranked:
            own, at, size = (scores[i], tuple(array("i", found[i]))), sum(map(len, found[:i])) // 4, len(found[i]) // 4
            choices = [own, *(c for c in self.choices(names(i)) if c != own)]  # of ties, ids may hold another one
            combos = heapq.nsmallest(self.n, ((loss + (choices[0][0] - c[0]), [*how, (at, size, list(c[1]))] if k else how) for loss, how in combos for k, c in enumerate(choices)), key=lambda x: x[0])
        return ids, [(total - loss) / SCALE for loss, _ in combos], [sorted(how) for _, how in combos]


#: (place in the best ids, how many of them go, the ids that come).
Edit = tuple[int, int, list[int]]
EDITS = "array<array<struct<at:int,dropped:int,ids:array<int>>>>"


def edited(ids: np.ndarray | list[int], edits: list[Edit]) -> list[int]:
    """The segmentation that edits of the best ids stand for."""
    out, last = [], 0
    for at, dropped, new in sorted(map(tuple, edits)):
        out += [*ids[last:at], *new]
        last = at + dropped
    return [int(i) for i in [*out, *ids[last:]]]


def _encoder(pieces: Pieces, n: int) -> Encoder:
    """The encoder of this process, kept with the pieces from task to task."""
    made = pieces.__dict__.setdefault("encoders", {})
    if n not in made:
        made[n] = Encoder(pieces, n)
    return made[n]


def decoded_bytes(pieces: Pieces, ids: np.ndarray | list[int]) -> bytes:
    raw = b"".join(map(pieces.text_of.__getitem__, ids.tolist() if isinstance(ids, np.ndarray) else ids))
    return raw[1:] if raw[:1] == b" " else raw


def decode(pieces: Pieces, ids: np.ndarray | list[int]) -> str:
    return decoded_bytes(pieces, ids).decode("utf-8", "surrogatepass")


def encoded(df: DataFrame, pieces: Pieces, text: str = "text", keys: tuple[str, ...] = ("doc_id",), n: int = 1) -> DataFrame:
    """keys, ids array<int> of the best segmentation, n_pieces, scores array<double> of the n best, the n best
    as EDITS of ids (see edited()), decoded_sha256."""
    shared = df.sparkSession.sparkContext.broadcast(pieces)
    kinds = [df.schema[k].dataType.simpleString() for k in keys]
    out = ", ".join([*(f"`{k}` {t}" for k, t in zip(keys, kinds, strict=True)), f"ids array<int>, n_pieces long, scores array<double>, segmentations {EDITS}, decoded_sha256 string"])
    of_edits = pa.list_(pa.list_(pa.struct([("at", pa.int32()), ("dropped", pa.int32()), ("ids", pa.list_(pa.int32()))])))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(shared.value, n)
        for batch in batches:
            size = max(1, min(500, 500 * len(batch) * 4096 // max(1, batch.nbytes)))
            for a in range(0, len(batch), size):
                part = batch.slice(a, size)
                ids, scores, edits, digests = [], [], [], []
                for t in part.column(len(keys)).to_pylist():
                    if t is None:
                        ids.append(None), scores.append(None), edits.append(None), digests.append(None)
                        continue
                    got, s, how = encoder.encode(t)
                    ids.append(got), scores.append(s)
                    edits.append([[{"at": at, "dropped": d, "ids": new} for at, d, new in h] for h in how])
                    digests.append(hashlib.sha256(decoded_bytes(encoder.pieces, got)).hexdigest())
                sizes = np.array([0 if x is None else len(x) for x in ids])
                values = pa.array(np.concatenate([x for x in ids if x is not None] or [np.zeros(0, np.int32)]), pa.int32())
                offsets = pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32())
                mask = pa.array([x is None for x in ids])
                lists = pa.ListArray.from_arrays(offsets, values, mask=mask)
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(keys))), lists, pa.array(sizes, pa.int64()), pa.array(scores, pa.list_(pa.float64())), pa.array(edits, of_edits), pa.array(digests, pa.string())], names=[*keys, "ids", "n_pieces", "scores", "segmentations", "decoded_sha256"])

    return df.select(*keys, F.col(text).cast("string").alias("__text")).mapInArrow(work, out)


def decoded(df: DataFrame, pieces: Pieces, ids: str = "ids", keys: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """keys and text, from a column of ids."""
    shared = df.sparkSession.sparkContext.broadcast(pieces)
    kinds = [df.schema[k].dataType.simpleString() for k in keys]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [None if x is None else decode(shared.value, x) for x in batch.column(len(keys)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(keys))), pa.array(texts, pa.string())], names=[*keys, "text"])

    return df.select(*keys, F.col(ids).alias("__ids")).mapInArrow(work, ", ".join([*(f"`{k}` {t}" for k, t in zip(keys, kinds, strict=True)), "text string"]))


def op5_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids of the best segmentation of every whole text, the four best with their scores, and the decoded text's digest."""
    return encoded(table(spark, sf_dir, "documents").withColumn("doc_id", F.col("doc_id").cast("long")), load(), n=4)


QUERIES = {"op5_sentencepiece": op5_sentencepiece}
ORACLES: dict[str, str] = {}
