import hashlib
from collections import Counter, defaultdict
from fractions import Fraction

from pyspark.sql import functions as F

from veilframe.llm import mixing as M


def fill(given, kids):
    """Plain water filling with exact fractions: {name: (supply, weight)} -> shares before rounding."""
    out, open_, left = {}, dict(kids), Fraction(given)
    while open_:
        w = sum(x[1] for x in open_.values())
        short = {k: x for k, x in open_.items() if x[0] <= left * x[1] / w}
        if not short:
            out |= {k: left * x[1] / w for k, x in open_.items()}
            break
        for k, x in short.items():
            out[k] = Fraction(x[0])
            left -= x[0]
            del open_[k]
    return out


def leaves(spark, rows):
    return spark.createDataFrame(rows, "domain string, lang string, source string, tokens long, weight_domain long, weight_lang long, weight_source long")


def test_budgets_match_exact_water_filling(spark):
    rows = [("a", "en", "s1", 100, 3, 2, 5), ("a", "en", "s2", 5, 3, 2, 5), ("a", "fr", "s1", 7, 3, 9, 1), ("b", "en", "s3", 1000, 1, 1, 1), ("b", "en", "s4", 1, 1, 1, 9), ("c", "de", "s5", 0, 4, 1, 1)]
    for budget in (0, 1, 37, 150, 500, 2000, 9999):
        got = {(r.domain, r.lang, r.source): r.budget for r in M.leaf_budgets(leaves(spark, rows), F.lit(budget).cast("long"), 2).collect()}
        supply = defaultdict(int)
        for d, g, s, t, *_ in rows:
            for k in ((), (d,), (d, g), (d, g, s)):
                supply[k] += 2 * t
        top = fill(min(budget, supply[()]), {r[0]: (supply[r[:1]], r[4]) for r in rows})
        assert sum(got.values()) == min(budget, supply[()])
        for d, share in top.items():
            mine = sum(v for k, v in got.items() if k[0] == d)
            assert abs(mine - share) < 1 and mine <= supply[(d,)]
            mid = fill(mine, {r[1]: (supply[r[:2]], r[5]) for r in rows if r[0] == d})
            for g, part in mid.items():
                inner = sum(v for k, v in got.items() if k[:2] == (d, g))
                assert abs(inner - part) < 1
                low = fill(inner, {r[2]: (supply[r[:3]], r[6]) for r in rows if r[:2] == (d, g)})
                assert all(abs(got[d, g, s] - x) < 1 for s, x in low.items())


def test_shortage_goes_to_siblings_first(spark):
    rows = [("a", "en", "s1", 10, 1, 1, 1), ("a", "en", "s2", 1000, 1, 1, 1), ("b", "en", "s3", 1000, 1, 1, 1)]
    got = {r.source: r.budget for r in M.leaf_budgets(leaves(spark, rows), F.lit(200).cast("long"), 1).collect()}
    assert got == {"s1": 10, "s2": 90, "s3": 100}


def test_draws_are_prefixes(spark, sf_mid):
    docs = spark.read.parquet(f"{sf_mid}/documents.parquet")
    got = {r["__id"]: r for r in M.draws(docs, slices=7).collect()}
    other = {r["__id"]: r.copies for r in M.draws(docs.repartition(5), slices=4096).collect()}
    assert {k: r.copies for k, r in got.items()} == other
    by = defaultdict(list)
    for r in docs.select("doc_id", "lang", "source", M.token_count(F.col("text")).alias("t")).collect():
        by[r.lang, r.source].append((r.doc_id, r.t))
    for rows in by.values():
        copies = {i: got[i].copies if i in got else 0 for i, _ in rows}
        full = min(copies.values())
        assert max(copies.values()) <= full + 1
        order = sorted(rows, key=lambda r: (hashlib.md5(f"mix:{full}:{r[0]}".encode()).hexdigest()[:8], r[0]))
        more = [copies[i] - full for i, _ in order]
        assert more == sorted(more, reverse=True)  # a prefix of the seeded order


def test_mixed_rows_and_edges(spark):
    rows = [(1, "a b c", "en", "src1", 5), (2, None, "en", "src1", 0), (3, "", None, None, 0), (None, "x y", "fr", "src2", 3), (1, "a b c", "en", "src1", 5)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, tokens int")
    out = M.mixed(df, part=(1, 1), epochs=1)
    assert out.columns == df.columns
    assert Counter(r.doc_id for r in out.collect()) == Counter([1, 1, 2, 3, None])
    assert M.mixed(df.where("doc_id > 9")).count() == 0


def test_equal_rows_keep_the_budget_and_domains_are_a_parameter(spark):
    rows = [(1, "a b", "en", "src1", "d1")] * 7 + [(k, "x y", "en", "src1", "d2") for k in range(2, 9)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, domain string")
    for num in range(0, 15):
        out = M.mixed(df, part=(num, 14), epochs=1, domain=lambda source: F.col("domain")).collect()
        assert abs(2 * len(out) - 2 * num) <= 2 and 2 * len(out) <= 28 * num // 14  # at most one document a leaf is left over
        assert sum(r.doc_id == 1 for r in out) == num // 2
    twice = M.mixed(df, part=(1, 2), epochs=1).collect()
    assert len(twice) == 7
