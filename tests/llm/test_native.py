"""URL filters and line dedup against brute force, and their plans."""

import re

from veilframe.llm import line_dedup as D
from veilframe.llm import url_filter as U


def verdict(url, listed):
    if url is None or "://" not in url:
        host = path = ""
        canon = None
    else:
        rest = url.split("://", 1)[1]
        host = "".join(c.lower() if "A" <= c <= "Z" else c for c in re.match(r"[^/?#]*", rest)[0])
        path = re.match(r"[^/?#]*([^?#]*)", rest)[1]
        q = re.match(r"[^?#]*\?([^#]*)", rest)
        fields = sorted(x for x in (q[1].split("&") if q else []) if x and not x.startswith("utm_"))
        canon = host + path.rstrip("/") + ("?" + "&".join(fields) if fields else "") if host else None
    fits = [r for r in U.RULES if (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)]
    rule = max(fits, key=lambda r: len(r.name), default=None)
    return host, path, rule.name if rule else None, rule.verdict if rule else ("block" if canon and canon in listed else "allow"), canon


def test_urls(spark):
    urls = ["http://A.Example.net/en/x", "http://example.net/fr", "http://net/", "http://net", "https://x.org/fr/1", "http://x.org/de", "http://www.example.com/de/", None, "", "no scheme", "://", "http://u@h.com:80/p?q=1#f", "http://h.com?b=2&utm_x=1&a=1", "http://h.com/?a=1&b=2", "ftp://É.com/É", "http://a.com/x://b.net/", "http://badnet/en/", "http://h.com//"] * 2
    pages = spark.createDataFrame([(i, u, "c") for i, u in enumerate(urls)], "page_id long, url string, host string")
    listed = spark.createDataFrame([("http://h.com/?a=1&b=2",), (None,), ("http://h.com/p?q=1",), ("http://H.com/?b=2&a=1",)], "url string")
    keys = {verdict(u, ())[4] for (u,) in listed.collect()} - {None}
    for limit in (64 << 20, 0):
        got = {r.page_id: tuple(r)[1:6] for r in U.url_verdicts(pages, listed, broadcast_bytes=limit).collect()}
        assert got == {i: verdict(u, keys) for i, u in enumerate(urls)}
    none = U.url_verdicts(pages, listed.where("url = 'x'"))
    assert none.count() == len(urls) and none.where("maybe_listed").count() == 0
    assert U.url_verdicts(pages.where("page_id > 99"), listed).count() == 0


def test_filter_passes_all_listed_and_few_others(spark):
    pages = spark.range(20000).selectExpr("id as page_id", "concat('http://h', id, '.com/') as url")
    out = U.url_verdicts(pages, pages.where("page_id % 10 = 0"))
    assert out.where("page_id % 10 = 0 and not maybe_listed").count() == 0
    assert out.where("page_id % 10 <> 0 and maybe_listed").count() < 300
    assert out.where("(verdict = 'block') <> (page_id % 10 = 0)").count() == 0


def brute_lines(rows):
    seen, gone = set(), [set() for _ in rows]
    for k in sorted(range(len(rows)), key=lambda k: (rows[k][0] is not None, rows[k][0] or 0)):
        lines = (rows[k][1] or "").split("\n")
        for i in range(len(lines) - 2):
            w = "\n".join(lines[i : i + 3])
            if w.strip():
                if w in seen:
                    gone[k] |= {i, i + 1, i + 2}
                seen.add(w)
    return [None if t is None else "\n".join(x for i, x in enumerate(t.split("\n")) if i not in gone[k]) for k, (_, t) in enumerate(rows)]


def test_lines(spark):
    texts = ["a\nb\nc\nd", "x\na\nb\nc\ny", "a\nb\nc\nd\ne", "b\nc\nd", "q\nq\nq\nq\nq", None, "", "one", "\n\n\n\n", "\n\n\n\n", "a\nb", "z\n\n\nz\n\n\nz"]
    rows = list(enumerate(texts))
    df = spark.createDataFrame([(i, t, 3) for i, t in rows], "doc_id long, text string, n_removed int").repartition(3)
    got = {r.doc_id: r.text for r in D.dedup_lines(df).collect()}
    assert [got[i] for i in range(len(texts))] == brute_lines(rows)
    twice = D.dedup_lines(df.union(df))
    assert {(r.doc_id, r.text) for r in twice.collect()} == {(i, t) for i, t in got.items()}  # repeated rows are one document
    assert D.dedup_lines(df.where("doc_id > 99")).count() == 0


def test_documents(spark, sf_small):
    rows = [tuple(r) for r in spark.read.parquet(f"{sf_small}/documents.parquet").select("doc_id", "text").orderBy("doc_id").collect()]
    got = {r.doc_id: r.text for r in D.op10_line_dedup(spark, sf_small).collect()}
    assert [got[i] for i, _ in rows] == brute_lines(rows)


def test_no_python_in_the_plans(spark, sf_small):
    for df in (D.op10_line_dedup(spark, sf_small), U.op6_url_filters(spark, sf_small)):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert not re.search("Python|Pandas|Arrow", plan)
