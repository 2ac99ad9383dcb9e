"""Archives, packing, mixing, and the pipeline."""

from __future__ import annotations

import base64
import hashlib
import random
import zlib
from collections import Counter
from pathlib import Path

import public_tokenizers
import pytest

import corpus_pipeline
from tracelake.llm import common, mixing, packing, pii, tokens, warc

VOCABULARY = public_tokenizers.path("byte_bpe_50k.json")


def test_archive_round_trip(spark):
    rng = random.Random(1)
    rows = [(k, f"http://h/{k}?q=é x", "<p>" + "".join(rng.choice("abc é") for _ in range(rng.randrange(300))) + "</p>") for k in range(300)]
    rows += [(1000 + k, "u", "same") for k in range(50)] + [(2000, None, None), (2001, "u\r\nX: y", ""), (2002, "u", "z" * 300_000), (None, "u", "same"), (5, "u", "second row of page 5"), (5, "u", "second row of page 5")]
    df = spark.createDataFrame([(*r, "clash") for r in rows], "page_id long, url string, html string, sha string").repartition(4)
    folder = common.new_folder(spark, "warc-test")
    manifest = warc.write(df, folder, file_bytes=2000, shard_bytes=20_000)
    listed = manifest.collect()
    assert len({r.shard for r in listed}) > 2 and len(listed) > len({r.shard for r in listed})
    assert sum(r.records for r in listed) == len(rows)
    got = warc.read(spark, folder).collect()
    top: dict = {}
    for p, _, h in rows:
        b = (h or "").encode()
        top[b] = max(top.get(b, -1), -1 if p is None else p)
    want = Counter()
    for p, _, h in rows:
        b = (h or "").encode()
        again = p != top[b]
        want[(p, len(b), base64.b32encode(hashlib.sha1(b).digest()).decode(), "revisit" if again else "response", top[b] if again else None, None if again else b)] += 1
    assert Counter((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to, None if r.payload is None else bytes(r.payload)) for r in got) == want
    other = common.new_folder(spark, "warc-test")
    again = warc.write(df.repartition(7), other, file_bytes=2000, shard_bytes=20_000).collect()
    assert sorted((r.name, r.sha1, r.bytes) for r in again) == sorted((r.name, r.sha1, r.bytes) for r in listed)
    for r in listed:
        assert hashlib.sha1(Path(folder.removeprefix("file://"), r.name).read_bytes()).hexdigest() == r.sha1
    Path(folder.removeprefix("file://"), listed[0].name).write_bytes(b"broken")
    with pytest.raises(Exception, match="manifest says"):
        warc.read(spark, folder).count()


def test_empty_archive(spark):
    folder = common.new_folder(spark, "warc-test")
    assert warc.write(spark.createDataFrame([], "page_id long, url string, html string"), folder).count() == 0
    assert warc.read(spark, folder).count() == 0


@pytest.mark.parametrize("added", [True, False])
def test_ids_are_the_tokenizer_s(added):
    from tokenizers import Tokenizer

    reference = Tokenizer.from_file(VOCABULARY)
    reference.encode_special_tokens = not added
    rng = random.Random(3)
    bits = ["'s", "'t", "'re", "'ve", "'ll", "'d", "'", "''", " ", "  ", "\n", "\t", "a", "B", "é", "ß", "1", "²", "!", "...", "_", " the", "中", "😀", "'L", "'sx", "\x00", "\x1f", "\x85", "　", "٣", "<|endoftext|>", "<|", "|>"]
    texts = ["a <|endoftext|> b", "<|endoftext|>", "<|endoftext|><|endoftext|>x", "<|endoftext<|endoftext|>", ""]
    texts += ["".join(rng.choice(bits) for _ in range(rng.randrange(30))) for _ in range(4000)] + ["x" * 50_000, " " * 1000, ""]
    pieces = tokens.Pieces(VOCABULARY, added)
    ids, at = pieces.encode(texts)
    want = [e.ids for e in reference.encode_batch(texts, add_special_tokens=False)]
    assert [ids[a:b].tolist() for a, b in zip(at, at[1:])] == want
    assert added == (want[0] == [64, 220, 50256, 275])
    for t, w in zip(texts[:300], want):
        assert pieces.encode([t])[0].tolist() == w


def test_packing(spark):
    rng = random.Random(2)
    rows = [(k, " ".join(rng.choice(["alpha", "beta", "gamma,", "x9"]) for _ in range(rng.choice((1, 5, 50, 400, 3000))))) for k in range(200)]
    rows += [(500, None), (501, ""), (502, "same"), (502, "same"), (None, "no id")]
    df = spark.createDataFrame([(t, i, 1) for i, t in rows], "text string, doc_id long, sequence_id int").repartition(3)
    got = packing.packed(df, VOCABULARY, keep_ids=True).collect()
    ids, at = tokens.Pieces(VOCABULARY).encode([t or "" for _, t in rows])
    want = Counter((i, *ids[a:b].tolist(), 0) for (i, _), a, b in zip(rows, at, at[1:]))
    found: dict = {}
    for r in got:
        assert 1 <= r.length <= 2048 and len(r.ids) == r.length
        assert zlib.crc32(b"".join(x.to_bytes(4, "little") for x in r.ids)) == r.ids_crc32
        assert r.piece == 0 or r.length == 2048
        found.setdefault(r.doc_id, []).append(r)
    for i, own in found.items():
        if i != 502:
            own.sort(key=lambda r: r.piece)
            assert [r.start for r in own] == [sum(x.length for x in own[:k]) for k in range(len(own))]
            assert want[(i, *[x for r in own for x in r.ids])] == 1
    bins: dict = {}
    for r in got:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    total = sum(r.length for r in got)
    for places in bins.values():
        places.sort()
        assert [o for o, _ in places] == [sum(n for _, n in places[:k]) for k in range(len(places))] and sum(n for _, n in places) <= 2048
    assert len(bins) <= -(-total // 2048) + 1
    assert packing.packed(df.limit(0), VOCABULARY).count() == 0


def test_local_search_empties_bins_that_best_fit_leaves():
    bins = [[6, 3], [5, 4], [7], [3]]
    out = packing.local_search(bins, 10)
    assert sorted(x for b in out for x in b) == [3, 3, 4, 5, 6, 7] and len(out) == 3 and all(sum(b) <= 10 for b in out)
    rng = random.Random(1)
    for _ in range(50):
        h = Counter(rng.randrange(1, 60) for _ in range(rng.randrange(1, 80)))
        made = packing.plan(h, 60)
        assert sum((Counter({k: c * n for k, c in Counter(p).items()}) for p, n in made), Counter()) == h
        assert all(sum(p) <= 60 for p, _ in made)
        before = packing.best_fit(h, 60)
        assert sum(n for _, n in made) <= sum(n for _, n in before)


@pytest.mark.parametrize("n", [60, 6000, 6_000_000])
def test_local_search_reaches_all_bins_of_a_pattern(n):
    made = packing.plan({800: n, 648: n, 600: n}, 2048)
    assert sum(times for _, times in made) == n and all(sum(p) <= 2048 for p, _ in made)
    assert sum((Counter({k: c * t for k, c in Counter(p).items()}) for p, t in made), Counter()) == {800: n, 648: n, 600: n}


def test_local_search_takes_two_of_many_short_ones():
    made = packing.local_search([[1] * 450 + [20, 20], [41], [451]], 491)
    assert [sum(b) for b in made] == [491, 491] and sum(map(len, made)) == 454


def _targets(sizes, weights=(3, 1, 2), budget=1.5, cap=2.0):
    names = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [None] * (None in sizes)
    w = {s: weights[k % 3] for k, s in enumerate(names)}
    left, out, free = budget * sum(sizes.values()), {}, set(names)
    while free:
        share = left / sum(w[s] for s in free)
        full = {s for s in free if share * w[s] >= cap * sizes[s]}
        if not full:
            return out | {s: share * w[s] for s in free}
        for s in full:
            out[s] = cap * sizes[s]
        left -= sum(out[s] for s in full)
        free -= full
    return out


def test_mixing(spark):
    rng = random.Random(9)
    rows = [(k, " ".join("w" for _ in range(rng.randrange(60))), rng.choice(["b", "a", "a", "a", "Z", "é", None])) for k in range(1500)]
    rows += [(9000, None, "b"), (9001, "", "b"), (9002, "x y", "tiny"), (9003, "x y", None), (9003, "x y", None), (None, "a b c", "a"), (9004, None, "void")]
    df = spark.createDataFrame([(i, t, s, 3) for i, t, s in rows], "doc_id long, text string, source string, size int").repartition(4)
    got = mixing.taken(df).collect()
    assert len(got) == len(rows)
    sizes: dict = {}
    for _, t, s in rows:
        sizes[s] = sizes.get(s, 0) + len((t or "").split())
    want = _targets(sizes)
    per: dict = {}
    source = {i: s for i, _, s in rows}
    for r in got:
        s = source[r.doc_id]
        assert r.source_size == sizes[s] and abs(r.target - want[s]) < 1e-6 and r.taken in (0, r.size, 2 * r.size)
        per[s] = per.get(s, 0) + r.taken
    for s in sizes:
        assert abs(per[s] - want[s]) <= 61
    total = sum(per.values())
    assert 1.5 * sum(sizes.values()) - 120 <= total <= 1.5 * sum(sizes.values())
    again = mixing.taken(df.repartition(9)).collect()
    assert sorted(map(tuple, again), key=str) == sorted(map(tuple, got), key=str)
    assert mixing.taken(df.limit(0)).count() == 0
    mixed = mixing.mixed(df)
    assert mixed.columns == df.columns
    many = Counter(r.doc_id for r in mixed.collect())
    assert all(many[r.doc_id] == r.taken // r.size for r in got if r.size and r.doc_id not in (9003,))


def test_the_mix_follows_the_fair_queue(spark):
    """The order of virtual finish times, worked off one document at a time."""
    rng = random.Random(12)
    rows = [(k, "w " * rng.randrange(40), rng.choice(["a", "a", "b", "c", None])) for k in range(400)] + [(900, "w " * 7, "a")] * 40
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    keys = {(r.doc_id, r.size): r.h for r in df.selectExpr("doc_id", "cast(size(filter(split(text, ' '), x -> x <> '')) as bigint) as size").selectExpr("*", "xxhash64(17, doc_id, size) as h").collect()}
    sizes = Counter()
    for _, t, s in rows:
        sizes[s] += len(t.split())
    target = _targets(sizes)
    queue = []
    for source in sizes:
        own = sorted((keys[i, len(t.split())] % 2**64, i, len(t.split())) for i, t, s in rows if s == source)
        done = 0
        for h, i, n in own:
            done += n
            for epoch in range(2):
                finish = (done + epoch * sizes[source]) / target[source]
                queue.append((finish, source or "\U0010ffff", h - 2**64 * (h >= 2**63), i, n, epoch))
    want, spent, budget = Counter(), 0, 1.5 * sum(sizes.values())
    over = False
    for finish, _, _, i, n, _ in sorted(queue):
        over = over or spent + n > budget
        if not over:
            spent += n
            want[i] += n
    got = Counter()
    for r in mixing.taken(df).collect():
        got[r.doc_id] += r.taken
    assert {i: n for i, n in got.items() if n} == {i: n for i, n in want.items() if n}


def test_rows_that_repeat_are_mixed_as_often_as_decided(spark):
    rows = [(1, "a b c", "s", k % 3) for k in range(40)] + [(2, "a b c", "s", 7)] * 41 + [(3, "x y", "t", 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, words int")
    for budget in (0.35, 0.5, 0.77, 1.13, 1.5):
        decided = Counter()
        for r in mixing.mix(df, budget=budget).collect():
            decided[r.doc_id] += r.copies
        made = mixing.mixed(df, budget=budget)
        assert made.columns == df.columns
        got = Counter(r.doc_id for r in made.collect())
        assert got == Counter({i: n for i, n in decided.items() if n})


def test_an_empty_corpus_mixes_to_nothing(spark):
    df = spark.createDataFrame([(1, None, "a"), (2, "", None)], "doc_id long, text string, source string")
    assert [(r.size, r.target, r.taken) for r in mixing.taken(df).collect()] == [(0, 0.0, 0), (0, 0.0, 0)]


def test_pipeline(spark, data):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language", "near_duplicates", "personal_data", "mixture", "sequences"]
    docs = spark.read.parquet(f"{data}/documents.parquet")
    before = docs
    for name, stage in corpus_pipeline.STAGES:
        after = common.written(stage(spark, before, data), "stage")
        if name != "sequences":
            assert after.columns == docs.columns
        if name == "language":
            assert after.count() > 0.97 * before.count()
        if name == "near_duplicates":
            from tests.llm import brute

            top = brute.near_duplicates([(r.doc_id, r.text) for r in before.collect()])
            assert {r.doc_id for r in after.collect()} == {i for i, v in top.items() if v[2]}
        if name == "personal_data":
            assert after.count() == before.count()
            assert sum(r.n_email + r.n_ip + r.n_card + r.n_phone for r in pii.report(after).collect()) == 0
        if name == "mixture":
            assert max(Counter(r.doc_id for r in after.collect()).values()) <= 2
        before = after
    assert before.columns == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]


def test_slices_do_not_change_the_mix_or_the_packing(spark, monkeypatch):
    from tracelake.llm import common

    rng = random.Random(6)
    df = spark.createDataFrame([(k, " ".join("w" * rng.randrange(1, 40)), rng.choice(["a", "b", None])) for k in range(300)], "doc_id long, text string, source string")
    sizes = df.selectExpr("doc_id", "0 as piece", "length(text) as length")
    got = []
    for bits in (6, 1, 11):
        monkeypatch.setattr(common, "slice_bits", lambda rows, bits=bits: bits)
        got.append((sorted(map(tuple, mixing.taken(df).collect())), sorted(map(tuple, packing.pack(sizes, 128).collect()))))
    assert got[0] == got[1] == got[2]


def test_number_of_slices_follows_the_rows():
    from tracelake.llm import common

    assert common.slice_bits(0) == common.slice_bits(1000) == 6
    assert 10**11 / 2 ** common.slice_bits(10**11) <= 10**6
