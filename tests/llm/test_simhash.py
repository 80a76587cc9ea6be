import numpy as np
import pytest

from veilframe.llm import common
from veilframe.llm import simhash as S


def brute(rows, words=3):
    fps = [S.fingerprint((t or "").encode(), words) for _, t in rows]
    ids, at = [r[0] for r in rows], list(range(len(rows)))

    def find(x):
        while at[x] != x:
            x = at[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 3:
                a, b = find(i), find(j)
                at[max(a, b)] = min(a, b)
    least = {}
    for i in range(len(rows)):
        r = find(i)
        least[r] = min(least.get(r, ids[i]), ids[i])
    return sorted((ids[i], f"{fps[i]:016x}", least[find(i)]) for i in range(len(rows)))


def test_golay_is_perfect():
    g = S.Golay()
    assert len(set(g.error.tolist())) == 2048
    rng = np.random.default_rng(1)
    x = rng.integers(0, 1 << 23, 500)
    code = x ^ g.error[g.syndrome(x)]
    assert (g.syndrome(code) == 0).all() and all((int(a) ^ int(b)).bit_count() <= 3 for a, b in zip(x, code))
    lists = g.indices(x, 23)
    assert set((lists >= 0).sum(axis=1).tolist()) <= {1, 6}


def test_three_errors_share_a_key():
    g, rng = S.Golay(), np.random.default_rng(2)
    x = rng.integers(0, 1 << 63, 300, dtype=np.uint64)
    y = x.copy()
    for _ in range(3):
        y ^= np.uint64(1) << rng.integers(0, 64, 300).astype(np.uint64)
    a, b = (set(zip(*(v.tolist() for v in S.fuzzy_keys(z, g, side)))) for side, z in enumerate((x, y)))
    assert {r for r, _ in a & b} == set(range(300))
    strangers = set(zip(*(v.tolist() for v in S.fuzzy_keys(rng.integers(0, 1 << 63, 300, dtype=np.uint64), g, 1))))
    assert len(a & strangers) == 0  # keys are over 33 bits wide


def test_groups_match_brute_force(spark):
    rng = np.random.default_rng(3)
    words = [f"w{i}" for i in range(300)]
    rows = []
    for i in range(120):
        base = [words[k] for k in rng.integers(0, 300, 200)]
        rows.append((len(rows), " ".join(base)))
        if i % 3 == 0:
            base[50] = "changed"
            rows.append((len(rows), " ".join(base)))
    rows += [(900, None), (901, ""), (902, " \n "), (903, rows[0][1]), (904, "one two"), (905, "ONE two")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("fp", S.F.lit("clash"))
    got = S.near_groups(df).collect()
    assert sorted((r.doc_id, f"{r.fp & (1 << 64) - 1:016x}", r.component_id) for r in got) == brute(rows)


def test_real_documents_match_brute_force(spark, sf_small):
    rows = [tuple(r) for r in spark.read.parquet(f"{sf_small}/documents.parquet").select("doc_id", "text").collect()]
    got = S.op8_simhash_near_dedup(spark, sf_small).collect()
    assert sorted(map(tuple, got)) == brute(rows)


def test_keep_one_and_empty(spark):
    df = spark.createDataFrame([(1, "a b c d e f"), (2, "a b c d e f"), (2, "a b c d e f"), (3, "z")], "doc_id long, text string")
    assert sorted(r.doc_id for r in S.keep_one(df).collect()) == [1, 3]
    assert S.near_groups(df.where("doc_id > 9")).count() == 0


def jaccard(a, b, k=5):
    sets = [set(zip(*[t.lower().split()[i:] for i in range(k)])) for t in (a, b)]
    return len(sets[0] & sets[1]) / max(1, len(sets[0] | sets[1]))


def test_two_errors_share_an_index():
    g, rng = S.Golay(), np.random.default_rng(6)
    x = rng.integers(0, 1 << 23, 400)
    y = x ^ (1 << rng.integers(0, 23, 400)) ^ (1 << rng.integers(0, 23, 400))
    assert all(set(a[a >= 0]) & set(b[b >= 0]) for a, b in zip(g.indices(x, 23), g.indices(y, 23)))


def test_near_copies_are_found_and_others_left(spark):
    rng = np.random.default_rng(9)
    words = [f"w{i}" for i in range(2000)]
    rows, near = [], []
    for i in range(150):
        base = [words[k] for k in (rng.zipf(1.3, 300) % 2000)]
        rows.append((len(rows), " ".join(base)))
        if i % 2 == 0:
            for at in rng.choice(300, 3, replace=False):
                base[at] = f"new{i}{at}"
            near.append((len(rows) - 1, len(rows)))
            rows.append((len(rows), " ".join(base)))
    assert min(jaccard(rows[a][1], rows[b][1]) for a, b in near) > 0.85
    got = {r.doc_id: r.component_id for r in S.similar_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert sum(got[b] == a for a, b in near) >= 0.93 * len(near)
    twins = {x for p in near for x in p}
    assert all(got[i] == i for i, _ in rows if i not in twins)


def test_near_copies_of_documents(spark, sf_small):
    docs = spark.read.parquet(f"{sf_small}/documents.parquet").select("doc_id", "text")
    text = dict(docs.collect())
    got = {}
    for r in S.similar_groups(docs).collect():
        got.setdefault(r.component_id, []).append(r.doc_id)
    for ids in got.values():
        for i in ids[1:]:
            assert max(jaccard(text[i], text[j]) for j in ids if j != i) > 0.6 or text[i].lower().split() == text[ids[0]].lower().split()


def test_limit(spark):
    with pytest.raises(ValueError):
        S.links(spark.createDataFrame([(1,)], "fp long"), 4)


def similar_components(texts, least=0.8):
    """Components of all pairs by brute force: for each text the smallest index that it reaches."""
    sets, at = [set(S.shingle_set(t.encode()).tolist()) for t in texts], list(range(len(texts)))

    def find(x):
        while at[x] != x:
            x = at[x]
        return x

    for i in range(len(texts)):
        for j in range(i):
            n = len(sets[i] & sets[j])
            if n >= least * (len(sets[i]) + len(sets[j]) - n) - 1e-9:
                a, b = find(i), find(j)
                at[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(texts))]


def crowded(n, seed, edits, length=120):
    """Texts with random edits of one base: similarities on both sides of the threshold, all in the same buckets."""
    rng = np.random.default_rng(seed)
    base, out = [f"w{k}" for k in rng.integers(0, 500, length)], []
    for i in range(n):
        text = list(base)
        for at in rng.choice(length, int(rng.integers(1, edits)), replace=False):
            text[at] = f"new{i}x{at}" if rng.random() < 0.5 else f"alt{at}"
        out.append(" ".join(text))
    return out


def test_dense_buckets_match_brute_force(spark):
    texts = [t for k in range(6) for t in crowded(40, k, 9)]
    got = {r.doc_id: r.component_id for r in S.similar_groups(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [got[i] for i in range(len(texts))] == similar_components(texts)


def test_real_near_copies_match_brute_force(spark, sf_small):
    rows = sorted(tuple(r) for r in spark.read.parquet(f"{sf_small}/documents.parquet").select("doc_id", "text").collect())
    got = {r.doc_id: r.component_id for r in S.similar_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [got[i] for i, _ in rows] == [rows[k][0] for k in similar_components([t or "" for _, t in rows])]


def test_blocks_compare_all_components():
    rng = np.random.default_rng(4)
    base = rng.permutation(10_000).astype(np.uint64)
    for seed in range(5):
        rng = np.random.default_rng(seed)
        items = [np.sort(np.concatenate([rng.choice(base[:60], 45, replace=False), rng.choice(base[100:], 3, replace=False)])) for _ in range(60)]
        roots = rng.integers(0, 20, 60)
        asks = np.concatenate([roots != 0, np.zeros(60, bool)])  # every row once among all, those outside component 0 as askers too
        rows = np.concatenate([np.arange(60), np.arange(60)])
        rows, asks = rows[asks | (np.arange(120) >= 60)], asks[asks | (np.arange(120) >= 60)]
        got = S.block_links(asks, rows, roots[rows], np.full(len(rows), 48), np.zeros((len(rows), 2), np.uint64), [items[r] for r in rows], 0.6, 128, chunk=7)

        def groups(pairs):
            at = list(range(20))

            def find(x):
                while at[x] != x:
                    x = at[x]
                return x

            for i, j in pairs:
                a, b = find(roots[i]), find(roots[j])
                at[max(a, b)] = min(a, b)
            return [find(x) for x in range(20)]

        alike = lambda i, j: len(np.intersect1d(items[i], items[j])) >= 0.6 * len(np.union1d(items[i], items[j])) - 1e-9
        assert all(alike(i, j) for i, j in got)
        assert groups(got) == groups([(i, j) for i in range(60) for j in range(i) if alike(i, j)])


def test_groups_do_not_depend_on_batch_size(spark):
    texts = crowded(400, 7, 12)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = []
    for size in ("10000", "64"):
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", size)
        try:
            got.append(sorted((r.doc_id, r.component_id) for r in S.similar_groups(docs).collect()))
        finally:
            spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert got[0] == got[1] and [c for _, c in got[0]] == similar_components(texts)


def test_large_buckets_match_brute_force(spark, monkeypatch):
    monkeypatch.setattr(S, "SMALL_BUCKET", 4)
    monkeypatch.setattr(S, "BLOCK", 16)
    texts = [t for k in range(2) for t in crowded(150, k, 12)]
    got = {r.doc_id: r.component_id for r in S.similar_groups(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [got[i] for i in range(len(texts))] == similar_components(texts)


def test_links_are_exact_at_the_threshold(spark):
    base = [f"w{k}" for k in range(104)]  # 100 shingles
    texts = [" ".join(base)]
    for at in ((10, 50), (10, 50, 90)):  # each edit inside takes five shingles of either text
        edited = list(base)
        for k in at:
            edited[k] = f"new{k}{len(at)}"
        texts.append(" ".join(edited))
    sims = [jaccard(texts[0], t) for t in texts[1:]]
    assert sims[0] > 0.8 > sims[1]
    got = [r.component_id for r in S.similar_groups(spark.createDataFrame([(0, texts[0]), (1, texts[1]), (2, texts[0] + " z"), (3, texts[2])], "doc_id long, text string")).orderBy("doc_id").collect()]
    assert got == [0, 0, 0, 3]


def test_rows_without_ids_and_with_shared_ids_stay(spark):
    text = lambda k: " ".join(f"w{k}x{i}" for i in range(60))
    rows = [(None, text(0)), (None, text(1)), (None, text(1) + " z"), (5, text(2)), (5, text(3)), (5, text(3)), (6, text(4)), (7, text(4)), (7, text(5))]
    got = [tuple(r) for r in S.keep_one(spark.createDataFrame(rows, "doc_id long, text string")).collect()]
    texts = sorted(t.removesuffix(" z") for _, t in got)
    assert texts == sorted(text(k) for k in range(6)) and (6, text(4)) in got and (7, text(5)) in got


def test_no_side_of_a_join_is_gathered_on_the_driver(spark, monkeypatch):
    """Neither the links, nor any round of the components, nor the groups' own plan broadcasts a table."""
    plans, write = [], common.written

    def noted(df, name):
        plans.append(df._jdf.queryExecution().executedPlan().toString())
        return write(df, name)

    monkeypatch.setattr(common, "written", noted)
    monkeypatch.setattr(S, "written", noted)
    rows = [(i, " ".join(f"w{i // 3}x{j}" for j in range(2000)) + f" {i}") for i in range(60)]
    got = S.near_groups(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted((r.doc_id, r.component_id) for r in got.collect()) == [(i, c) for i, _, c in brute(rows)]
    plans.append(got._jdf.queryExecution().executedPlan().toString())
    assert sum("Join" in p for p in plans) >= 4 and not any("Broadcast" in p for p in plans)


def test_the_kept_ones_differ_in_fingerprint(spark, sf_small):
    same = " ".join(["one phrase that this page says again and over"] * 200)
    other = [f"{same} {' '.join(f'{k}{i}' for i in range(40))}" for k in "xy"]
    assert jaccard(*other) < 0.5 and (S.fingerprint(other[0].encode()) ^ S.fingerprint(other[1].encode())).bit_count() <= 3
    df = spark.createDataFrame([(1, other[0]), (2, other[1]), (3, "z " * 9), (4, " ".join(f"w{i}" for i in range(99)))], "doc_id long, text string")
    assert sorted(r.doc_id for r in S.keep_one(df).collect()) == [1, 3, 4]
    docs = spark.read.parquet(f"{sf_small}/documents.parquet").select("doc_id", "text")
    fps = [S.fingerprint((r.text or "").encode()) for r in S.keep_one(docs).collect()]
    assert min((a ^ b).bit_count() for i, a in enumerate(fps) for b in fps[:i]) > 3
