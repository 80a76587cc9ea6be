import math

import numpy as np

from veilframe.llm import langid as L


def slow_bits(texts, text, order, unseen):
    """Code length of a text, context by context, straight from the definition."""
    counts = {}
    for t in texts:
        for i in range(len(t)):
            for k in range(min(i, order) + 1):
                at = counts.setdefault(t[i - k : i], {})
                at[t[i]] = at.get(t[i], 0) + 1

    def length(ctx, s):
        at = counts.get(ctx)
        if at is None:
            return length(ctx[1:], s) if ctx else 8.0
        n, d = sum(at.values()), len(at)
        if s in at:
            return -math.log2(at[s] / (n + d))
        return -math.log2(d / (n + d)) + (length(ctx[1:], s) if ctx else 8.0)

    return sum(length(text[max(0, i - order) : i], text[i]) for i in range(len(text)))


def test_code_lengths_match_the_definition():
    samples = {"en": [b"the cat sat on the mat", b"on the other hand"], "de": [b"die katze sitzt", "über den Fluß".encode()]}
    m = L.train(samples, order=3)
    texts = [b"the katze", b"", b"zzz \xff\xfe the", "Fluß".encode(), b"t"]
    data = np.frombuffer(b"".join(texts), np.uint8)
    at = np.cumsum([0, *map(len, texts)])
    got = L.code_lengths(m, data, at)
    for i, t in enumerate(texts):
        for k, lang in enumerate(m.langs):
            assert math.isclose(got[i, k], slow_bits(samples[lang], t, 3, None), abs_tol=1e-3), (t, lang)


def test_probabilities_never_exceed_one():
    m = L.train({"a": [b"abracadabra" * 5], "b": [b"banana bandana" * 3]}, order=3)
    seen = int((m.code < m.code.max()).sum())
    total = np.exp2(-m.bits[:, :seen].astype(float)).sum(axis=1) + (256 - seen) * np.exp2(-m.bits[:, -1].astype(float))
    assert (total <= 1 + 1e-5).all()


def test_slices_do_not_change_lengths(monkeypatch):
    rng = np.random.default_rng(1)
    texts = [bytes(rng.integers(97, 105, n).astype(np.uint8)) for n in (5, 0, 300_000, 7)]
    m = L.train({"x": texts[:1], "y": [texts[2][:400]]}, order=3)
    at = np.cumsum([0, *map(len, texts)])
    whole = L.code_lengths(m, np.frombuffer(b"".join(texts), np.uint8), at)
    for i, t in enumerate(texts):
        one = L.code_lengths(m, np.frombuffer(t, np.uint8), np.array([0, len(t)]))
        assert np.allclose(whole[i], one[0])


def test_held_out_accuracy(spark, sf_mid):
    from pyspark.sql import functions as F

    got = L.op1_language_id(spark, sf_mid).join(spark.read.parquet(f"{sf_mid}/documents.parquet").select("doc_id", "lang"), "doc_id")
    r = got.where("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double")).alias("a"), F.count("*").alias("n")).first()
    assert r["n"] > 250 and r["a"] > 0.97


def test_edges(spark):
    rows = [(1, None, "en"), (2, "", "en"), (3, "12 3 ...", "en"), (4, "the cat", "en"), (5, "le chat", "fr"), (None, "abc", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    never, every = L.F.lit(False), L.F.lit(True)
    got = {r.doc_id: r for r in L.identify(df, L.train(L.training_rows(df, every)), never).collect()}
    assert [got[i].lang_pred for i in (1, 2, 3, 4, 5)] == ["und", "und", "und", "en", "fr"] and len(got) == 6
    assert {r.lang_pred for r in L.identify(df, None, never).collect()} == {"und"}
    assert L.training_rows(df.where("doc_id > 9"), every) == {}


def test_no_language_is_left_out(spark):
    rows = [(k, f"lang{k % 90}", f"wort{k % 90} " * (3 if k % 90 else 2000)) for k in range(270)]
    df = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    got = L.training_rows(df, L.F.lit(True))
    assert set(got) == {f"lang{k}" for k in range(90)} and len(got["lang0"]) == 3  # longer than most_bytes, yet learned
    m = L.train(got, most_model=1 << 20)
    assert m.bits.nbytes + m.child.nbytes <= 1 << 20 and len(m.langs) == 90
    text = b"wort17 wort17"
    assert m.langs[int(L.code_lengths(m, np.frombuffer(text, np.uint8), np.array([0, len(text)])).argmin())] == "lang17"
