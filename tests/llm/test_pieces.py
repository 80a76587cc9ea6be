import hashlib
import itertools
import math

import pytest

from veilframe.llm import pieces as P


@pytest.fixture(scope="module")
def model():
    return P.load()


def brute(model, part):
    out = []
    n = len(part)
    for cuts in itertools.product([0, 1], repeat=n - 1):
        at = [0, *(i + 1 for i, c in enumerate(cuts) if c), n]
        score, ids = 0, []
        for a, b in zip(at, at[1:]):
            got = model.score.get(part[a:b])
            if got:
                score, ids = score + got[0], [*ids, got[1]]
            elif b == a + 1:
                raw = part[a:b].encode()
                score, ids = score + model.byte_score * len(raw), [*ids, *(model.byte_ids[x] for x in raw)]
            else:
                break
        else:
            out.append((score, tuple(ids)))
    return sorted(out, key=lambda x: -x[0])


@pytest.mark.parametrize("part", [" the", " thening", "  able", " 日本語é", "▁x", " ", "aaaaaa", " inter"])
def test_n_best_match_all_segmentations(model, part):
    want, got = brute(model, part), P.n_best(model, part, 6)
    assert len(got) == min(6, len(want))
    assert [round(s, 9) for s, _ in got] == [round(s, 9) for s, _ in want[:6]]
    assert len({i for _, i in got}) == len(got)
    scores = dict((i, s) for s, i in want)
    assert all(math.isclose(scores[i], s) for s, i in got)


def test_n_best_of_a_text_match_all_segmentations(model):
    text = "the inn an"
    want = [s for s, _ in brute(model, " " + text)[:5]]
    e = P.Encoder(model, 5)
    ids, scores, how = e.encode(text)
    assert [round(s * P.SCALE) for s in scores] == want
    assert P.edited(ids, how[0]) == ids.tolist()
    assert len({tuple(P.edited(ids, h)) for h in how}) == 5
    assert all(P.decode(model, P.edited(ids, h)) == text for h in how)


@pytest.mark.parametrize("text", ["", " ", "a", " a  b\n c\td ", "▁ literal ▁", "日本 \U0001f600\x00é", "x" * 40_000, "a b " * 500, "\n\n"])
def test_round_trip(model, text):
    ids, _, _ = P.Encoder(model).encode(text)
    assert P.decode(model, ids) == text
    import sentencepiece

    theirs = sentencepiece.SentencePieceProcessor(model_file=P.MODEL)
    if "▁" not in text and "\x00" not in text:
        assert theirs.decode(ids.tolist()) == text


def test_the_first_descent_is_the_search(model):
    import random

    rng, e = random.Random(3), P.Encoder(model, 4)
    for _ in range(400):
        part = " " + "".join(rng.choice("theinasro,.1") for _ in range(rng.randrange(1, 14)))
        [(score, ids)], after = P.search(P.best_before(model, part), lambda at: P.edges_into(model, part, at), 1, 1)
        got = e._solve(part)
        assert got[0] == score and got[2] == (score - after[0] if after else math.inf)
        assert sum(dict((i, s) for s, i in model.score.values())[int(i)] for i in P.np.frombuffer(got[1], "i4")) == score


def score_of(model, ids):
    by_id = {i: s for s, i in model.score.values()}
    return sum(by_id.get(i, model.byte_score) for i in ids) / P.SCALE


def test_a_long_run_is_never_cut(model):
    """The best segmentation of a run by a plain dynamic program over the whole of it."""
    for text in ("ab" * 30_000, "thein" * 8_000 + "g"):
        part = " " + text
        best = [0.0] + [-math.inf] * len(part)
        for end in range(1, len(part) + 1):
            best[end] = max(best[a] + model.score[part[a:end]][0] for a in range(max(0, end - model.longest), end) if part[a:end] in model.score)
        ids, scores, how = P.Encoder(model, 4).encode(text)
        assert round(scores[0] * P.SCALE) == best[-1] and scores == sorted(scores, reverse=True)
        assert len({tuple(P.edited(ids, h)) for h in how}) == 4
        assert all(P.decode(model, P.edited(ids, h)) == text for h in how)


def test_columns(spark, sf_small, model):
    docs = spark.read.parquet(f"{sf_small}/documents.parquet")
    texts = dict(docs.select("doc_id", "text").collect())
    got = P.op5_sentencepiece(spark, sf_small).collect()
    assert len(got) == len(texts)
    for r in got:
        assert r.decoded_sha256 == hashlib.sha256(texts[r.doc_id].encode()).hexdigest()
        assert r.n_pieces == len(r.ids) and list(r.scores) == sorted(r.scores, reverse=True)
        all_ = [P.edited(r.ids, h) for h in r.segmentations]
        assert all_[0] == r.ids and len(set(map(tuple, all_))) == len(r.scores)
        for ids, score in zip(all_, r.scores):
            assert P.decode(model, ids) == texts[r.doc_id] and (not ids or math.isclose(score_of(model, ids), score, rel_tol=1e-9))
    back = P.decoded(P.encoded(docs, model), model)
    assert {r.doc_id: r.text for r in back.collect()} == texts


def test_edges(spark, model):
    df = spark.createDataFrame([(1, None, "x"), (2, "", "x"), (None, "a", "x"), (2, "", "x")], "doc_id long, text string, ids string")
    got = P.encoded(df, model, n=3).collect()
    assert sorted((r.doc_id or 0, r.ids if r.ids is None else len(r.ids)) for r in got) [0][1] >= 1
    assert [r.ids for r in got if r.doc_id == 1] == [None] and [r.ids for r in got if r.doc_id == 2] == [[], []]
    assert P.encoded(df.where("doc_id > 5"), model).count() == 0
