import re

import numpy as np

from veilframe.llm import quality as Q

WORD = re.compile("[^\x20\x09-\x0d]+")


def brute(text):
    text = text or ""
    words = WORD.findall(text)
    lines, seen, dup = text.split("\n"), set(), 0
    for line in lines:
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    at = {}
    for i in range(len(words) - 2):
        at.setdefault(tuple(words[i : i + 3]), []).append(i)
    covered = {i + k for v in at.values() if len(v) > 1 for i in v for k in range(3)}
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), dup, len(covered)


def test_stats_of_odd_texts():
    for t in [None, "", " ", "a", "a b c", "x x x x x", "é ü \x85 a\x1cb\n\n \nq\nq\n", "a b c d a b c", "l\nl\nl \nl\n\n", "#|<>&" * 30, "日本 語 " * 9]:
        assert Q.text_stats((t or "").encode()) == brute(t), t


def test_stats_of_documents(spark, sf_small):
    docs = spark.read.parquet(f"{sf_small}/documents.parquet")
    texts = dict(docs.select("doc_id", "text").collect())
    for r in Q.judged(docs).collect():
        n, chars, symbols, dup, rep = brute(texts[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (n, chars, symbols, dup, rep)
        assert r.base_failed == (n < 50 or 100 * rep > 50 * n)
        assert not (r.base_failed and r.kept)


def test_estimates_ignore_far_rows(spark):
    rng = np.random.default_rng(1)
    clean = rng.normal(size=(3000, 5)) * np.array([2.0, 1.0, 0.4, 1.0, 0.3]) + 7
    bad = rng.normal(size=(600, 5)) + np.array([40, 7, 7, 30, 7])
    rows = [("en", "s", *map(float, r)) for r in np.vstack([clean, bad])]
    df = spark.createDataFrame(rows, "lang string, source string, " + ", ".join(f"{v} double" for v in Q.VECTOR))
    model = {r["__level"]: r for r in Q.mcd_models(df).collect()}["pair"]
    assert np.allclose(model["mean"], 7, atol=0.25)
    scatter = np.linalg.inv(np.array(model["inverse"]).reshape(5, 5))
    assert np.allclose(np.sqrt(np.diag(scatter)), [2.0, 1.0, 0.4, 1.0, 0.3], rtol=0.25)


def test_steps_match_plain_concentration(spark):
    """The binned step picks the h closest rows up to one bin, so its estimate is that of a plain step."""
    rng = np.random.default_rng(5)
    x = rng.normal(size=(2000, 5)) * 3
    df = spark.createDataFrame([("a", "b", *map(float, r)) for r in x], "lang string, source string, " + ", ".join(f"{v} double" for v in Q.VECTOR))
    model = {r["__level"]: r for r in Q.mcd_models(df, 0.75).collect()}["all"]
    mean, scatter = np.median(x, axis=0), np.diag(np.full(5, 9.0))
    for _ in range(12):
        d = np.einsum("ij,jk,ik->i", x - mean, np.linalg.inv(scatter), x - mean)
        near = x[np.argsort(d)[:1500]]
        mean, scatter = near.mean(axis=0), np.cov(near.T, ddof=0) * Q.consistency(0.75, 5)
    assert np.allclose(model["mean"], mean, atol=0.15)
    assert np.allclose(np.diag(np.linalg.inv(np.array(model["inverse"]).reshape(5, 5))), np.diag(scatter), rtol=0.1)


def plain_mcd(x, share, tries, rng):
    """Least log determinant, mean, scatter and unit over random starts of six rows each, with exact h."""
    n, p = x.shape
    h = int(np.ceil(share * n))
    off = x - np.median(x, axis=0)
    unit = np.array([np.sqrt((c[c != 0] ** 2).mean()) if (c != 0).any() else 1.0 for c in off.T])
    ridge, best = np.diag((Q.RIDGE * unit) ** 2), None
    for _ in range(tries):
        some = x[rng.choice(n, p + 1, replace=False)]
        mean, scatter = some.mean(axis=0), np.cov(some.T, ddof=0)
        for _ in range(40):
            gap = x - mean
            near = x[np.argsort((gap @ np.linalg.inv(scatter + ridge) * gap).sum(axis=1), kind="stable")[:h]]
            before, mean, scatter = mean, near.mean(axis=0), np.cov(near.T, ddof=0) * Q.consistency(h / n, p)
            if np.allclose(before, mean, atol=1e-12):
                break
        logdet = np.linalg.slogdet((scatter + ridge) / np.outer(unit, unit))[1]
        if best is None or logdet < best[0]:
            best = logdet, mean, scatter, unit
    return best


def test_verdicts_on_documents_match_a_search_from_random_starts(spark, sf_mid):
    docs = spark.read.parquet(f"{sf_mid}/documents.parquet")
    judged = Q.judged(docs).withColumns(Q.vector_columns()).toPandas()
    fine = judged[~judged.base_failed].reset_index(drop=True)
    x, rng, least = fine[list(Q.VECTOR)].to_numpy(), np.random.default_rng(3), 10 * len(Q.VECTOR)
    sizes = {"pair": fine.groupby(["lang", "source"]).size(), "lang": fine.groupby("lang").size()}
    chosen = [("pair", a, b) if sizes["pair"][a, b] >= least else ("lang", a, None) if sizes["lang"][a] >= least else ("all", None, None) for a, b in zip(fine.lang, fine.source, strict=True)]
    models = {(r["__level"], r["__lang"], r["__source"]): r for r in Q.mcd_models(spark.createDataFrame(fine[["lang", "source", *Q.VECTOR]])).collect()}
    kept = np.zeros(len(fine), dtype=bool)
    for group in set(chosen):
        level, lang, source = group
        rows = x[((fine.lang == lang) | (level == "all")) & ((fine.source == source) | (level != "pair"))]
        logdet, mean, scatter, unit = plain_mcd(rows, 0.75, 30, rng)
        assert models[group]["logdet"] <= logdet + 0.35, group  # up to one bin more rows than h
        own = np.array([c == group for c in chosen])
        gap = x[own] - mean
        kept[own] = (gap @ np.linalg.inv(Q.final_scatter(scatter, unit)[0]) * gap).sum(axis=1) <= Q.CHI2_CUT
    assert (kept == fine.kept.to_numpy()).mean() >= 0.985
    assert 0.85 <= fine.kept.mean() < 1


def test_edges(spark):
    schema = "doc_id long, text string, lang string, source string, n_words string"
    rows = [(1, None, None, None, "x"), (None, "a " * 60, "en", "s", "x"), (2, "", "en", None, None), (2, "", "en", None, None)]
    df = spark.createDataFrame(rows, schema)
    got = Q.judged(df).collect()
    assert len(got) == 4 and not any(r.kept for r in got if r.doc_id)
    assert Q.judged(df.where("doc_id > 9")).count() == 0
    assert Q.keep_good(df).columns == df.columns
