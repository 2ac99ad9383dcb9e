"""Near-duplicate documents and vectors against quadratic versions, with the odd rows."""

from __future__ import annotations

import random

import numpy as np
import pytest

from tests.llm import brute
from tracelake.llm import components, minhash, textvec, vectors


def _documents():
    rng = random.Random(4)
    words = [f"w{k}" for k in range(60)] + ["É", "ÀB", "Wort"]
    base = [rng.choice(words) for _ in range(120)]
    out = []
    for i in range(60):  # near copies of one text, with more and more changes
        own = list(base)
        for _ in range(i // 6):
            own[rng.randrange(len(own))] = rng.choice(words)
        out.append((i, " ".join(own)))
    out += [(100 + i, " ".join(rng.choice(words) for _ in range(rng.randrange(1, 40)))) for i in range(40)]
    out += [(200, None), (201, ""), (202, " \t\n\x0b\x0c\r"), (203, "one two"), (204, "ONE\ttwo"), (205, "one two three"), (206, "éA b c d e"), (207, "Éa b c d e"), (208, "éa B c d e")]
    out += [(300 + i, "same text here and there") for i in range(30)]
    out += [(400, " ".join(str(k) for k in range(30_000))), (401, " ".join(str(k) for k in range(2000, 30_000)))]
    return out


def test_near_duplicates_are_the_brute_force_ones(spark):
    rows = _documents()
    df = spark.createDataFrame([(t, i, 1, "x") for i, t in rows], "text string, doc_id long, rep int, component string").repartition(5)
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash.near_duplicates(df).collect()}
    assert got == brute.near_duplicates(rows)
    kept = minhash.one_of_each(df)
    assert kept.columns == df.columns
    assert {r.doc_id for r in kept.collect()} == {i for i, v in got.items() if v[2]}


def test_near_copies_from_80_percent(spark):
    text = [f"w{k}" for k in range(100)]
    near = [*text[:30], "x", *text[31:70], "y", *text[71:]]  # 86 of 106 shingles
    rows = [*_documents()[:60], (900, " ".join(text)), (901, " ".join(near))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash.near_duplicates(df, 80).collect()}
    assert got == brute.near_duplicates(rows, 80) and not got[901][2]
    assert {r.doc_id for r in minhash.one_of_each(df, 80).collect()} == {i for i, v in got.items() if v[2]}
    assert {r.doc_id for r in minhash.one_of_each(df).collect()} >= {900, 901}
    assert (minhash.band_rows(85), minhash.band_rows(80)) == (5, 4)


@pytest.mark.parametrize("few", [0, 10**9])
def test_star_rounds_find_the_same(spark, monkeypatch, few):
    monkeypatch.setattr(minhash, "FEW_PAIRS", few)
    rounds = []
    star = minhash._star_round
    monkeypatch.setattr(minhash, "_star_round", lambda *a: rounds.append(a[-1]) or star(*a))
    rng = random.Random(8)
    base = [f"w{rng.randrange(400)}" for _ in range(150)]
    rows = _documents()[:100]
    for i in range(400):  # a chain of drifting copies, so that no one centre links them all
        if i % 20 == 0:
            base[rng.randrange(150)] = "new"
        own = list(base)
        own[rng.randrange(150)] = f"x{i}"
        rows.append((1000 + i, " ".join(own)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash.near_duplicates(df).collect()}
    assert got == brute.near_duplicates(rows)
    assert bool(rounds) == (few == 0)


def test_large_group_of_near_copies_costs_few_comparisons(spark, monkeypatch):
    rng = random.Random(7)
    base = [f"w{k}" for k in range(200)]
    rows = []
    for i in range(1500):
        own = list(base)
        own[rng.randrange(200)] = f"x{i}"
        rows.append((i, " ".join(own)))
    left = []
    pairs = minhash._pairs_left
    monkeypatch.setattr(minhash, "_pairs_left", lambda m: left.append(pairs(m)) or left[-1])
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    assert {r.component_id for r in minhash.near_duplicates(df).collect()} == {0}
    assert left[0][0] > 1_000_000 and left[-1][0] < 16 * 25 * 1500 / 10


def test_one_of_each_keeps_texts_that_share_an_id(spark):
    a, b, c = "a b c d e f g", "h i j k l m n o", "p q r s t u v"
    rows = [(3, a), (9, a), (9, b), (3, c), (3, c), (3, c.upper()), (None, a), (7, None), (7, ""), (7, "")]
    df = spark.createDataFrame([(t, i, 1, k) for k, (i, t) in enumerate(rows)], "text string, doc_id long, t_hash int, held int")
    kept = minhash.one_of_each(df)
    assert kept.columns == df.columns
    got = sorted((-1 if r.doc_id is None else r.doc_id, r.text or "") for r in kept.collect())
    assert [g for g in got if g[1] not in (c, c.upper())] == [(-1, a), (3, a), (7, ""), (7, ""), (7, ""), (9, b)]
    assert len([g for g in got if g[1] in (c, c.upper())]) == 1
    assert minhash.one_of_each(df.limit(0)).count() == 0


def test_blocks_of_a_large_bucket(spark, monkeypatch):
    monkeypatch.setattr(minhash, "BLOCK", 8)
    monkeypatch.setattr(minhash, "FEW_PAIRS", 10**9)
    rows = _documents()[:100]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash.near_duplicates(df).collect()}
    assert got == brute.near_duplicates(rows)


def test_rows_without_id_and_repeated_rows(spark):
    text = "a b c d e f g"
    df = spark.createDataFrame([(None, text), (5, text), (5, text), (7, text)], "doc_id long, text string")
    got = sorted(((r.doc_id is None, r.doc_id), r.component_id, r.kept) for r in minhash.near_duplicates(df).collect())
    assert got == [((False, 5), 5, True), ((False, 5), 5, True), ((False, 7), 5, False), ((True, None), None, True)]
    assert minhash.near_duplicates(df.limit(0)).count() == 0


def test_signature_slots_agree_as_often_as_sets_do():
    rng = np.random.default_rng(1)
    x = np.sort(rng.integers(0, 2**63, 1000, dtype=np.uint64))
    a, b = x[:900], x[100:]
    s = minhash.min_max([a, b])
    assert abs((s[0] == s[1]).mean() - 0.8) < 0.12


def test_words_are_cut_and_lowered_as_said():
    import pyarrow as pa

    texts = ["A b\tC\n\nd\x0be\x0cf\rg", None, "", "É é", "x"]
    data, offsets = textvec.raw(pa.array(texts))
    sets = textvec.shingle_sets(data, offsets)
    assert [len(s) for s in sets] == [len(brute.shingles(t)) for t in texts]


def test_components(spark):
    rng = random.Random(2)
    links = [(rng.randrange(80), rng.randrange(80)) for _ in range(50)] + [(k, k + 1) for k in range(100, 160)] + [(200, k) for k in range(201, 260)] + [(3, 3)]
    got = {r.node: r.component for r in components.components(spark.createDataFrame(links, "a long, b long")).collect()}
    want = brute.roots({x for p in links for x in p}, links)
    assert all(got.get(n, n) == w for n, w in want.items())


def _vectors():
    rng = np.random.default_rng(3)
    base = rng.standard_normal((30, 16))
    rows = []
    for k in range(300):
        v = base[k % 30] + 0.25 * rng.standard_normal(16) * (k % 7) / 6
        rows.append((k, v.astype(np.float32).tolist(), int(k % 2)))
    rows += [(1000 + k, base[0].astype(np.float32).tolist(), 0) for k in range(40)]
    rows += [(2000, None, 0), (2001, [0.0] * 16, 0), (2002, [float("nan")] + [1.0] * 15, 0), (2003, [None] + [1.0] * 15, 0), (2004, base[0].tolist(), None), (2005, [float("inf")] + [1.0] * 15, 1)]
    rows += [(2006, [1.0, 2.0], 0), (2007, [2.0, 4.0], 0), (2008, [], 1)]
    return rows


def _good(v, label):
    return v is not None and label is not None and len(v) > 0 and all(x is not None and np.isfinite(x) for x in v) and any(v)


@pytest.mark.parametrize("cell", [4096, 20])
def test_vector_links_are_the_brute_force_ones(spark, monkeypatch, cell):
    monkeypatch.setattr(vectors, "CELL", cell)
    monkeypatch.setattr(vectors, "BLOCK", 2048 if cell > 100 else 16)
    rows = _vectors()
    links = []
    for a, v, x in rows:
        for b, w, y in rows:
            if a < b and x == y and _good(v, x) and _good(w, y) and len(v) == len(w):
                p, q = np.array(v, dtype=float), np.array(w, dtype=float)
                if p @ q / np.sqrt(p @ p) / np.sqrt(q @ q) >= 0.93:
                    links.append((a, b))
    top = brute.roots([r[0] for r in rows], links)
    many = {r[0]: 0 for r in rows}
    for a, b in links:
        many[a] += 1
        many[b] += 1
    df = spark.createDataFrame([(i, v, x, 1, 2) for i, v, x in rows], "vec_id long, embedding array<float>, label int, cell int, rep int").repartition(3)
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in vectors.near_duplicates(df).collect()}
    assert got == {i: (many[i], top[i], top[i] == i) for i in many}
    assert vectors.near_duplicates(df.limit(0)).count() == 0


def test_cover_tree_levels_cover_and_nest():
    x = vectors.unit(np.random.default_rng(1).standard_normal((200, 5)))
    tree = vectors.CoverTree(x, 0.1)
    for (own, _, _), (below, parent, _) in zip(tree.levels, tree.levels[1:]):
        assert set(own) <= set(below) and parent.max() < len(own)
    own, _, reach = tree.levels[-1]
    d = np.sqrt(((x - x[own][tree.home]) ** 2).sum(axis=1))
    assert (d <= reach[tree.home] + 1e-12).all()


def test_neighbours(spark):
    rng = np.random.default_rng(8)
    x = rng.standard_normal((900, 12)).astype(np.float32)
    x[100:140] = x[100]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(5000, None), (5001, [0.0] * 12), (5100, [float("nan")] * 12)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got: dict = {}
    for r in vectors.nearest(df, df.where("vec_id % 100 = 0"), 10).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    hit = 0
    for q in range(0, 900, 100):
        d = np.sqrt(((x.astype(float) - x[q].astype(float)) ** 2).sum(axis=1))
        d[q] = np.inf
        want = np.lexsort((np.arange(900), d))[:10].tolist()
        own = got[q]
        assert [r[0] for r in own] == list(range(1, 11))
        assert all(a[2] <= b[2] for a, b in zip(own, own[1:]))
        assert all(abs(s - d[v]) < 1e-12 for _, v, s in own)
        hit += len(set(want) & {v for _, v, _ in own})
    assert hit / 90 >= 0.9
    assert [v for _, v, _ in got[100]] == list(range(101, 111))  # ties go to the smaller id
    few = vectors.nearest(df.where("vec_id < 4"), df.where("vec_id = 0"), 10).collect()
    assert len(few) == 3
    assert vectors.nearest(df.limit(0), df.limit(0)).count() == 0


def test_a_chance_agreement_of_slot_bytes_loses_no_pair():
    rng = np.random.default_rng(3)
    one = rng.integers(0, 256, minhash.SKETCH, dtype=np.uint8)
    two = one.copy()
    two[2 * minhash.PERMUTATIONS :] += 1  # all slot bytes agree, no band key but the third does
    third = 2 * minhash.PERMUTATIONS + 4 * 2
    two[third : third + 4] = one[third : third + 4]
    i, j = np.array([0]), np.array([1])
    met = [bool(minhash._close(np.stack([one, two]), band, i, j)[0]) for band in range(5)]
    assert met == [True, True, True, False, False]


def test_pairs_at_the_threshold_are_all_found(spark):
    rng = random.Random(8)
    rows = []
    for k in range(400):  # lone pairs, most of them just above the threshold
        words = [f"v{k}x{rng.randrange(10**6)}" for _ in range(124)]
        other = list(words)
        other[rng.randrange(20, 100)], other[rng.randrange(4)] = "y", "z"
        rows += [(2 * k, " ".join(words)), (2 * k + 1, " ".join(other))]
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == brute.near_duplicates(rows)
    assert sum(not v[2] for v in got.values()) == 400


def test_queries_pass_by_the_index_in_many_batches(spark, monkeypatch):
    rng = np.random.default_rng(12)
    x = rng.standard_normal((300, 8))
    monkeypatch.setattr(vectors, "NEAR_CELL", 100)
    monkeypatch.setattr(vectors, "SEGMENT", 60)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        df = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "vec_id long, embedding array<double>")
        got = {}
        for r in vectors.nearest(df, df.where("vec_id % 2 = 0"), 3).collect():
            got.setdefault(r.query_id, []).append((r.rank, r.vec_id))
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    right = 0
    for q in range(0, 300, 2):
        d = ((x - x[q]) ** 2).sum(axis=1)
        d[q] = np.inf
        right += len(set(np.argsort(d)[:3].tolist()) & {v for _, v in got[q]})
    assert set(got) == set(range(0, 300, 2)) and right >= 0.9 * 450


def test_cells_are_pruned_and_cost_no_neighbour(spark, monkeypatch):
    rng = np.random.default_rng(5)
    base = rng.standard_normal((12, 24)) * 8
    x = base[rng.integers(0, 12, 1500)] + rng.standard_normal((1500, 24))
    df = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "vec_id long, embedding array<double>").repartition(3)
    got = []
    for cell, parts in ((10**9, "4"), (100, "4"), (100, "7")):
        monkeypatch.setattr(vectors, "NEAR_CELL", cell)
        spark.conf.set("spark.sql.shuffle.partitions", parts)
        got.append(sorted(map(tuple, vectors.nearest(df, df.where("vec_id % 10 = 0"), 5).collect())))
    spark.conf.set("spark.sql.shuffle.partitions", "4")
    assert got[1] == got[2]
    d = np.sqrt(((x[::10, None] - x[None]) ** 2).sum(axis=2))
    d[np.arange(150), np.arange(0, 1500, 10)] = np.inf
    want = {(10 * q, int(v)) for q in range(150) for v in np.argsort(d[q], kind="stable")[:5]}
    for rows in got:
        assert len({(r[0], r[2]) for r in rows} & want) >= 0.95 * len(want)
