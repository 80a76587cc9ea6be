"""Every stage against its operator's own brute force, on the input that it gets."""

import hashlib
import os

import duckdb
import pytest

import __spark_entry__ as entry
import corpus_pipeline as P
from test_native import brute_lines
from veilframe.llm import quality, simhash
from veilframe.llm.common import written


def test_stages(spark, sf_small):
    docs = spark.read.parquet(f"{sf_small}/documents.parquet")
    names = docs.columns
    for k, (name, stage) in enumerate(P.STAGES):
        out = written(stage(spark, docs, sf_small), "test")
        before, after = docs.collect(), out.collect()
        texts = {r.doc_id: r.text for r in before}
        if k < 4:
            assert out.columns == names, name
        if k == 0:
            assert {r.doc_id for r in after} == {r.doc_id for r in quality.judged(docs).where("kept").collect()}
            assert all(r.text == texts[r.doc_id] for r in after)
        if k == 1:
            rows = sorted((r.doc_id, r.text) for r in before)
            want = {i: t for (i, old), t in zip(rows, brute_lines(rows)) if t or t == old}
            assert {r.doc_id: r.text for r in after} == want and all(r.n_chars == len(r.text) for r in after if r.text != texts[r.doc_id])
        if k == 2:
            groups = simhash.similar_groups(docs).collect()
            assert {r.doc_id for r in after} <= {r.component_id for r in groups}
            assert len({r.text for r in after}) == len(after)  # no exact copies left
        if k == 3:
            assert {r.doc_id for r in after} <= set(texts) and all(r.text == texts[r.doc_id] for r in after)
        if k == 4:
            assert all(r.decoded_sha256 == hashlib.sha256(texts[r.doc_id].encode()).hexdigest() for r in after)
        docs = out


def test_odd_tables(spark):
    df = spark.createDataFrame([(1, None, None, None, None), (None, "", "en", "s", 0), (2, "w " * 60, None, "src1", 1), (2, "w " * 60, None, "src1", 1), (3, " ".join(f"w{i}" for i in range(80)), "en", "src2", 5)], "doc_id long, text string, lang string, source string, n_chars long")
    for d in (df, df.where("doc_id > 99")):
        for _, stage in P.STAGES:
            d = written(stage(spark, d, ""), "odd")
        d.count()


@pytest.mark.parametrize("name", [k for k in entry.oracle_sql() if k.startswith("op")])
def test_oracles(spark, sf_small, name):
    con = duckdb.connect()
    for t in os.listdir(sf_small):
        con.execute(f"CREATE VIEW {t.split('.')[0]} AS SELECT * FROM read_parquet('{sf_small}/{t}')")
    df = entry.queries()[name](spark, sf_small)
    names = sorted(df.columns)
    show = lambda rows: sorted((tuple(map(str, r)) for r in rows), key=str)
    assert show(df.select(*names).collect()) == show(con.execute(f"SELECT {', '.join(names)} FROM ({entry.oracle_sql()[name]})").fetchall())
