import hashlib
import random

import numpy as np
import pytest

from veilframe.llm import suffix_dedup as D


def brute(texts, span=400):
    where = {}
    raws = [(t or "").encode() for t in texts]
    for k, raw in enumerate(raws):
        for i in range(len(raw) - span + 1):
            where.setdefault(raw[i : i + span], []).append((k, i))
    gone = [bytearray(len(r)) for r in raws]
    for places in where.values():
        if len(places) > 1:
            for k, i in places:
                gone[k][i : i + span] = b"\1" * span
    out = []
    for raw, g in zip(raws, gone):
        kept = bytes(c for c, x in zip(raw, g) if not x)
        spans = sum(1 for i in range(len(g)) if g[i] and (i == 0 or not g[i - 1]))
        out.append((len(raw), len(raw) - len(kept), spans, hashlib.sha256(kept).hexdigest()))
    return out


def corpus(seed, n=60):
    r = random.Random(seed)
    words = ["".join(r.choices("abcdefgh é", k=r.randint(2, 9))) for _ in range(400)]
    say = lambda k: " ".join(r.choices(words, k=k))
    passages = [say(k) for k in (60, 70, 75, 90, 200)]
    texts = []
    for _ in range(n):
        t = say(r.randint(1, 200))
        if r.random() < 0.6:
            t += r.choice(["", " ", "x"]) + r.choice(passages) + say(r.randint(0, 60))
        if r.random() < 0.2:
            p = r.choice(passages)
            t += p[r.randint(0, 40) :] + say(3)
        texts.append(t)
        if r.random() < 0.2:
            w = t.split(" ")
            w[r.randrange(len(w))] = "edit"
            texts.append(" ".join(w))
    texts += [texts[0], texts[0], None, "", "a" * 399, "a" * 400, "ab" * 450, "z" * 1200, "short"]
    return texts


def got(spark, texts, **how):
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, row string").repartition(3)
    rows = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in D.remaining(df, **how).collect()}
    return [rows[i] for i in range(len(texts))]


@pytest.mark.parametrize("most", [20_000, 1])
def test_against_every_window(spark, most):
    texts = corpus(1)
    assert got(spark, texts, most=most) == brute(texts)


def test_pieces_of_long_texts(spark, monkeypatch):
    texts = corpus(2, 20)
    texts += ["".join(t or "" for t in texts[:12]), "qq" + "".join(t or "" for t in texts[5:15])]
    want = brute(texts)
    ids, df = range(len(texts)), spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    monkeypatch.setattr(D, "PIECE", 1500)  # pickled by reference, so cut on the driver
    one = []
    for t in texts:
        raw = np.frombuffer((t or "").encode(), np.uint8)
        n = 0
        for cut in range(0, len(raw), 1500):
            part = raw[cut : cut + 1500 + 399]
            n += int(sum(D.runs_of(part, np.array([0, len(part)]), 400)[6] - D.runs_of(part, np.array([0, len(part)]), 400)[5] + 1))
        one.append(n)
    assert one == [max(0, len((t or "").encode()) - 399) for t in texts]
    assert got(spark, texts) == want and len(ids) == df.count()


def test_documents(spark, sf_small):
    rows = spark.read.parquet(f"{sf_small}/documents.parquet").select("doc_id", "text").orderBy("doc_id").collect()
    mine = {r.doc_id: tuple(r)[1:] for r in D.op4_suffix_array_dedup(spark, sf_small).collect()}
    assert [mine[r.doc_id] for r in rows] == brute([r.text for r in rows])


def test_maximal_repeats_by_brute_force():
    r = random.Random(4)
    for _ in range(200):
        n = r.randint(2, 7)
        lefts = [bytes(r.choices(b"ab", k=r.randint(0, 6))) for _ in range(n)]
        rights = [bytes(r.choices(b"ab", k=r.randint(1, 6))) for _ in range(n)]
        want = set()
        for i in range(n):
            for j in range(i):
                le, ri = D.common(lefts[i], lefts[j]), D.common(rights[i], rights[j])
                if le + ri >= 4:
                    want.add((le, ri, tuple(k for k in range(n) if D.common(lefts[k], lefts[i]) >= le and D.common(rights[k], rights[i]) >= ri)))
        assert {(a, b, tuple(sorted(g))) for a, b, g in D.maximal_repeats(lefts, rights, 4)} == want


def test_windows_of_members_by_brute_force():
    r = random.Random(5)
    for _ in range(300):
        n, span = r.randint(2, 9), r.randint(2, 6)
        lefts = [bytes(r.choices(b"ab", k=r.randint(0, 6))) for _ in range(n)]
        rights = [bytes(r.choices(b"ab", k=r.randint(1, 6))) for _ in range(n)]
        want = {}
        for m in range(n):
            xs = [x for x in range(span) for o in range(n) if o != m and D.common(lefts[m], lefts[o]) >= x and D.common(rights[m], rights[o]) >= span - x]
            xs += [x for o in range(n) if o != m for x in range(span, 7) if D.common(lefts[m], lefts[o]) >= x]
            if xs:
                want[m] = min(xs), max(xs)
        assert D.repeated_windows(lefts, rights, span) == want


def test_nested_intervals_stay_linear():
    """A comb of ever deeper intervals, each with one member more: its neighbours grow as the members do."""
    rights = [b"a" * k + b"b" for k in range(3000)]
    lefts = [b"x" * 10] * 3000
    assert sum(len(p) for _, _, p in D.merges(lefts, rights)) < 3000 * 13


def test_groups_are_maximal_repeats_with_all_occurrences(spark):
    texts = corpus(6, 25)
    raws = [(t or "").encode() for t in texts]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    groups = {}
    for r in D.repeat_groups(df).collect():
        groups.setdefault((r.anchor, r.nr, r.length), []).append((r.doc_id, r.start))
    where = {}
    for k, raw in enumerate(raws):
        for i in range(len(raw) - 399):
            where.setdefault(raw[i : i + 400], set()).add((k, i))
    repeated = {p for places in where.values() if len(places) > 1 for p in places}
    told = set()
    for (_, _, length), places in groups.items():
        strings = {raws[k][i : i + length] for k, i in places}
        assert len(strings) == 1 and len(places) > 1 and len(set(places)) == len(places)
        string = strings.pop()
        everywhere = {(k, i + d) for k, i in where[string[:400]] for d in [0] if raws[k][i : i + length] == string}
        assert set(places) == everywhere  # all occurrences, not just neighbours
        told |= {(k, i + d) for k, i in places for d in range(length - 399)}
    assert told == repeated


def test_sf_mid_documents(spark, sf_mid):
    rows = spark.read.parquet(f"{sf_mid}/documents.parquet").select("doc_id", "text").orderBy("doc_id").collect()
    mine = {r.doc_id: tuple(r)[1:] for r in D.op4_suffix_array_dedup(spark, sf_mid).collect()}
    assert [mine[r.doc_id] for r in rows] == brute([r.text for r in rows])


def test_empty(spark):
    df = spark.createDataFrame([(1, "a")], "doc_id long, text string")
    assert D.remaining(df.where("doc_id > 3")).count() == 0
    r = D.remaining(spark.createDataFrame([(None, "k" * 500), (None, "k" * 500)], "doc_id long, text string"), with_bytes=True).collect()
    assert [(x.n_removed, bytes(x.kept)) for x in r] == [(500, b"")] * 2
