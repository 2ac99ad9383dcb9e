"""Licences, language, personal data, quotations."""

from __future__ import annotations

import hashlib
import random
import re
from pathlib import Path

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from tracelake.llm import langid, licences, pii, quotes


def test_licences(spark):
    mit = dict(licences.KNOWN)["MIT"]
    text = next(t for k, t in licences.KNOWN if t.startswith("MIT License"))
    rows = [
        (1, text), (2, "Copyright (c) 2020 Somebody\n" + text.upper().replace("LICENSE", "LICENCE")), (3, text + " and more"), (4, None), (5, ""), (6, "..."), (7, "All Rights Reserved"),
        (8, re.sub(r"\s+", "\n  ", text)), (9, "x " * 50_000), (9, "x " * 50_000),
    ]
    df = spark.createDataFrame([(i, t, "clash") for i, t in rows], "doc_id long, text string, digest string")
    got = {r.doc_id: r.licence for r in licences.scan(df).collect()}
    assert got == {1: "MIT", 2: "MIT", 3: None, 4: None, 5: None, 6: None, 7: "proprietary", 8: "MIT", 9: None}
    assert mit and licences.scan(df).count() == 10 and licences.scan(df.limit(0)).count() == 0


def test_whole_texts_of_long_licences(spark):
    folder = Path("/usr/share/common-licenses")
    names = {"Apache-2.0": "Apache-2.0", "GPL-2": "GPL-2.0", "GPL-3": "GPL-3.0", "LGPL-2.1": "LGPL-2.1", "MPL-2.0": "MPL-2.0", "CC0-1.0": "CC0-1.0"}
    held = {k: (folder / k).read_text() for k in names if (folder / k).is_file()}
    if not held:
        pytest.skip("no licence texts on this machine")
    rows = [(i, text) for i, text in enumerate(held.values())] + [(100 + i, re.sub(r"\s+", " ", text).upper()) for i, text in enumerate(held.values())]
    rows += [(200 + i, text[:-200]) for i, text in enumerate(held.values())]
    got = {r.doc_id: r.licence for r in licences.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i, k in enumerate(held):
        assert got[i] == names[k] and got[200 + i] is None
        # On one line, all of it goes with a copyright notice that it holds.
        assert got[100 + i] in (names[k], None)
    con = duckdb.connect()
    con.execute("CREATE TABLE documents (doc_id BIGINT, text VARCHAR)")
    con.executemany("INSERT INTO documents VALUES (?, ?)", rows)
    assert {r[0]: r[2] for r in con.execute(f"SELECT doc_id, canonical_digest, licence FROM ({licences.oracle_sql()})").fetchall()} == got


_SYLLABLES = {"xx": ["ka", "to", "mi"], "yy": ["schr", "öf", "elt"], "zz": ["что", "да", "не"]}


def _speech(rng, lang, n=30):
    return " ".join("".join(rng.choice(_SYLLABLES[lang]) for _ in range(3)) for _ in range(n))


def test_language(spark):
    rng = random.Random(6)
    rows = [(i, _speech(rng, lang), lang, "s") for i, lang in enumerate(["xx", "yy", "zz"] * 80)]
    rows += [(1000, None, "xx", "s"), (1001, "", None, "s"), (1002, "12 - !", "xx", None), (1003, _speech(rng, "zz", 9000), None, "s"), (None, _speech(rng, "yy"), None, None)]
    df = spark.createDataFrame([(*r, 0.5) for r in rows], "doc_id long, text string, lang string, source string, score double")
    got = {r.doc_id: r for r in langid.identify(df).collect()}
    assert len(got) == len(rows)
    import zlib

    for i, text, lang, _ in rows:
        r = got[i]
        assert r.held_out == (i is not None and zlib.crc32(str(i).encode()) % 3 == 1)
        assert 0 <= r.score <= 1
        if not re.search(r"[^\W\d_]", text or ""):
            assert r.lang_pred == "und"
        elif lang:
            assert r.lang_pred == lang and r.score > 0.5
    assert got[1003].lang_pred == "zz" and got[None].lang_pred == "yy"
    assert langid.accepted(df).columns == df.columns
    assert {r.doc_id for r in df.join(langid.accepted(df).select("doc_id"), "doc_id", "left_anti").collect()} == {1000, 1001, 1002, None}
    assert langid.identify(df.limit(0)).count() == 0
    nothing = langid.identify(df.withColumn("lang", F.lit(None).cast("string"))).collect()
    assert {r.lang_pred for r in nothing} == {"und"}


def test_every_language_is_learned_or_refused(spark, monkeypatch):
    rng = random.Random(3)
    rows = [(i, _speech(rng, "xx", 5), f"l{i % 7}") for i in range(70)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    assert langid.train(df).languages == [f"l{k}" for k in range(7)]
    monkeypatch.setattr(langid, "MOST_WEIGHTS", 5 * langid.DIMENSIONS)
    with pytest.raises(ValueError, match="more than 5 different"):
        langid.train(df)


def test_prediction_doesn_t_depend_on_the_batch():
    texts = ["abc def", "", "ghi", "ÄÖ ü"]
    whole, at, letters = langid.features(texts)
    for k, t in enumerate(texts):
        own, _, n = langid.features([t])
        assert own.tolist() == whole[at[k] : at[k + 1]].tolist() and n[0] == letters[k]


def test_ftrl_is_sparse_and_calibration_helps():
    rng = np.random.default_rng(2)
    rows = [(np.array([k % 2, 5 + k % 40]), np.ones(2)) for k in range(400)]
    w = langid.ftrl(rows, [k % 2 for k in range(400)], 2, l1=2.0)
    assert w[0, 0] > 0 > w[0, 1] and np.count_nonzero(w[5:45]) < 40
    logits = rng.standard_normal((500, 3)) * 9
    labels = np.array([rng.choice(3, p=langid.softmax(x / 9)) for x in logits])
    assert 4 < langid.calibrate(logits, labels) < 20


_PATTERNS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def _valid(kind, m):
    d = re.sub("[^0-9]", "", m)
    if kind == "email":
        return True
    if kind == "ip":
        return all(int(x) <= 255 for x in m.split("."))
    if kind == "phone":
        return 9 <= len(d) <= 15
    luhn = sum(x if k % 2 == 0 else (2 * x - 9 if x > 4 else 2 * x) for k, x in enumerate(map(int, reversed(d))))
    return 13 <= len(d) <= 19 and luhn % 10 == 0


def _spans(text):
    return [f"{k}:{m.start()}:{m.end()}" for k, p in _PATTERNS.items() for m in re.finditer(p, text or "") if _valid(k, m.group())]


def test_pattern_spans(spark):
    rng = random.Random(5)
    bits = ["a", "b@", "@", "c.d", "x@y.z", ".", "1", "12", "255", "256", "0001", "+", "-", " ", "(", ")", "4111 1111 1111 1111", "5500005555555559", "é", "😀", "\n", "_", "+1 (988) 555-2485", "1.2.3.4", "10.0.0.1.", "\x01", "\x02", "u.01@mail.example.com"]
    rows = [(i, "".join(rng.choice(bits) for _ in range(rng.randrange(25)))) for i in range(1500)]
    rows += [(9001, None), (9002, ""), (9003, "9" * 20000), (9004, "1 " * 20000), (9005, "a" * 50000), (9006, "1." * 20000), (9007, "+" + "1-" * 20000), (9008, "x@y.z"), (9008, "x@y.z")]
    df = spark.createDataFrame([(i, t, "s", 1) for i, t in rows], "doc_id long, text string, spans string, h int").repartition(4)
    got = {r.doc_id: r for r in pii.report(df).collect()}
    for i, t in rows:
        want = _spans(t)
        base = [s for s in got[i].spans.split(",") if s and s.split(":")[0] in _PATTERNS]
        assert base == want, t
        assert got[i].base_sha256 == hashlib.sha256(",".join(want).encode()).hexdigest()
        assert [got[i][f"n_{k}"] for k in _PATTERNS] == [sum(s.startswith(k) for s in want) for k in _PATTERNS]
    clean = pii.sanitised(df)
    assert clean.columns == df.columns and clean.count() == len(rows)
    assert pii.report(df.limit(0)).count() == 0


def _replaced(text, spans):
    """The spans replaced one by one, the plain way."""
    labels = {"removed": "", "generalised": "[TERM]"} | {k: f"[{k.upper()}]" for k in _PATTERNS}
    out, at = "", 0
    for begin, end, kind in sorted(((b, e, k) for k, b, e in spans), key=lambda s: (s[0], -s[1], s[2])):
        if begin >= at:
            out += text[at:begin] + labels[kind]
        at = max(at, end)
    return out + text[at:]


def test_texts_are_replaced_at_their_spans(spark):
    rng = random.Random(15)
    bits = ["é", "😀", "\n", "word ", "x@y.zz", " ", "+1 (988) 555-2485", "1.2.3.4", "4111 1111 1111 1111", "Quetzal", "a" * 300, "1.2.3.4@host.org"]
    rows = [(i, "".join(rng.choice(bits) for _ in range(rng.randrange(200)))) for i in range(150)]
    rows += [(1000, ("x@y.zz 1.2.3.4 é " * 40) * 300), (1001, None), (1002, "x@y.zz"), (1003, "x@y.zz" * 5)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = pii.annotate(df).collect()
    for r in got:
        if r.text is not None:
            spans = [(s.kind, s.start, s.end) for s in r.spans]
            assert all(r.text[s.start : s.end] == s.value for s in r.spans)
            assert r.clean_text == _replaced(r.text, spans)
            assert [f"{k}:{b}:{e}" for k, b, e in spans if k in _PATTERNS] == _spans(r.text)
        else:
            assert r.clean_text is None and r.spans == []


def test_many_addresses_in_one_text_take_time_in_proportion(spark):
    import time

    took = []
    for n in (10, 5_000, 50_000):  # the first warms up
        df = spark.createDataFrame([(1, " ".join(f"user{k}@mail{k % 977}.example.com and" for k in range(n))), (2, "nothing")], "doc_id long, text string")
        began = time.perf_counter()
        r = {r.doc_id: r for r in pii.annotate(df, "found", "clean").collect()}
        assert len(r[1].found) == n and not r[2].found and "@" not in r[1].clean
        took.append(time.perf_counter() - began)
    assert took[2] < 3 * took[1] + 10  # ten times as many; when each cost the text anew, a hundred


def _disclosed(rows):
    """What the statistics say, by dictionaries: per text the terms that are removed, and generalised."""
    import math
    from collections import Counter

    texts = Counter(t for _, t in rows if t is not None)
    total, distinct = sum(texts.values()), len(texts)
    found = {t: {(k, t[m.start() : m.end()].lower()) for k, p in _PATTERNS.items() for m in re.finditer(p, t) if _valid(k, m.group())} for t in texts}
    words = {t: {w.lower() for w in re.findall(r"[^\W\d_]+", t) if len(w) >= 3} for t in texts}
    entity, term, both = Counter(), Counter(), Counter()
    e_texts, b_texts, among = Counter(), Counter(), Counter()
    for t, n in texts.items():
        for w in words[t]:
            term[w] += n
        for e in found[t]:
            entity[e] += n
            e_texts[e] += 1
            for w in words[t]:
                both[e, w] += n
                b_texts[e, w] += 1
    out: dict = {}
    for (e, w), n in both.items():
        content = math.log(total / entity[e])
        share = math.log(n * total / (entity[e] * term[w])) / content if content > 0 else None
        k, m = b_texts[e, w], e_texts[e]
        rate = min((term[w] - n + k) / distinct, 1.0)
        part = k / m
        chance = k * (math.log(part) - math.log(rate)) + ((m - k) * (math.log(1 - part) - math.log(1 - rate)) if k < m and rate < 1 else 0.0)
        if share is not None and share >= pii.GENERALISE_AT and part > rate and chance >= -math.log(pii.ALPHA):
            for t in texts:
                if e in found[t] and w in words[t]:
                    out.setdefault(t, {})
                    out[t][w] = max(out[t].get(w, 0), share)
    return out


def test_disclosing_terms_are_those_of_the_statistics(spark):
    rng = random.Random(21)
    names = [f"{a}{b}" for a in ("ada", "bob", "cyn", "dan", "eve", "fay") for b in ("ford", "wick", "stone", "ley", "mere")]
    rows = []
    for i in range(400):
        name, mailed = rng.choice(names), rng.random() < 0.3
        words = [rng.choice(["please", "contact", "about", "case", "éclair", "someone"]) for _ in range(8)]
        if rng.random() < (0.8 if mailed else 0.04):
            words[rng.randrange(8)] = name.title()
        text = " ".join(words)
        if mailed:
            text += f" to {name}x@corp.org" + (f" or {rng.choice(names)}@mail.net, 10.0.0.{rng.randrange(90)}" if rng.random() < 0.4 else "")
        rows.append((i, text))
        if rng.random() < 0.1:
            rows += [(1000 + i, text)] * 3
    want = _disclosed(rows)
    assert sum(map(len, want.values())) > 20
    for r in pii.annotate(spark.createDataFrame(rows, "doc_id long, text string")).collect():
        mine = want.get(r.text, {})
        mails = [m.span() for m in re.finditer(_PATTERNS["email"], r.text)]
        spans = [(("removed" if mine[m.group().lower()] >= pii.REMOVE_AT else "generalised"), *m.span()) for m in re.finditer(r"[^\W\d_]+", r.text) if m.group().lower() in mine]
        spans = sorted((s for s in spans if not any(a < s[2] and s[1] < b for a, b in mails)), key=lambda s: (s[0] != "removed", s[1]))
        assert [(s.kind, s.start, s.end) for s in r.spans if s.kind not in _PATTERNS] == spans


def test_terms_that_give_an_entity_away(spark):
    rows = [(i, f"contact Zebulon about case number{i} at bob.smith@corp.example.com please") for i in range(5)]
    rows += [(10 + i, f"contact someone about the case {chr(97 + i % 26) * 4} please") for i in range(60)]
    rows += [(100, "Zebulon alone"), (101, "write to amy@x.org about Quetzal")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.spans for r in pii.report(df).collect()}
    for i in range(5):
        at = rows[i][1].index("Zebulon")
        assert f":{at}:{at + 7}" in got[i] and f"email:{rows[i][1].index('bob')}" in got[i]
        assert not any(f":{rows[i][1].index(w)}:" in got[i] for w in ("contact", "about", "please", "case"))
    assert got[100] == "" and got[101] == "email:9:18"
    texts = {r.doc_id: r.text for r in pii.sanitised(df).collect()}
    assert "Zebulon" not in texts[0] and "[EMAIL]" in texts[0] and texts[100] == "Zebulon alone" and texts[20] == dict(rows)[20]


def test_terms_of_an_entity_that_one_or_two_texts_hold(spark):
    rows = [(i, f"contact someone about the case {chr(97 + i % 26)}{chr(97 + i // 26)}xx please") for i in range(300)]
    rows += [(1000, "contact Quetzal about the case at amy@x.org please")] * 3
    rows += [(1001, "contact Zebulon please at +1 (988) 555-2485"), (1002, "the case about Zebulon at +1 (988) 555-2485"), (1003, "contact someone at 10.0.0.1 please")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.spans for r in pii.report(df).collect()}
    assert got[1000] == "email:34:43,removed:8:15"
    assert [s.split(":", 1)[1] for s in got[1001].split(",")] == ["26:43", "8:15"]
    assert [s.split(":", 1)[1] for s in got[1002].split(",")] == ["26:43", "15:22"]
    assert got[1003] == "ip:19:27" and got[5] == ""


def test_quotes(spark):
    rows = [
        (1, 0, "user", "Hello there\nmy question is A\nand B"), (1, 1, "bot", "answer one"), (1, 2, "user", "On Monday X wrote:\n> my  QUESTION is A\n>> deep\n> and B\nthat is wrong"),
        (1, 5, "bot", "> answer one\n> > my question is A\nyes"), (2, 0, "user", "> and B\nfoo"), (2, 1, "bot", None), (None, None, "x", "> and B"), (3, 0, "u", ""), (3, 1, "u", "a > b"), (3, 1, "u", "a > b"),
    ]
    df = spark.createDataFrame([(*r, 1) for r in rows], "conv_id long, turn long, role string, text string, position int")
    got = {(r.conv_id, r.turn): r for r in quotes.link(df).collect()}
    assert quotes.link(df).count() == len(rows)
    assert (got[1, 0].reply_turn, got[1, 1].reply_turn, got[1, 2].reply_turn, got[1, 5].reply_turn) == (None, 0, 0, 1)
    assert (got[1, 2].quote_level, got[1, 2].quoted_lines, got[1, 2].linked_lines, got[1, 2].text) == (2, 3, 2, "that is wrong")
    assert [got[1, t].position for t in (0, 1, 2, 5)] == [1, 2, 3, 4]
    assert (got[2, 0].quoted_conv, got[2, 0].quoted_turn, got[2, 0].reply_turn, got[2, 0].text) == (1, 0, None, "foo")
    assert got[2, 1].text is None and got[3, 1].text == "a > b" and got[None, None].reply_turn is None
    assert quotes.link(df.limit(0)).count() == 0


def test_nested_rewrapped_and_foreign_quotations(spark):
    five = [f"line {k} of the first" for k in "abcde"]
    rows = [
        (1, 1, "u", "\n".join(five)), (1, 2, "u", "\n".join([*("> " + x for x in five), "one more"])), (1, 3, "u", "\n".join(["> one more", *(">> " + x for x in five), "end"])),
        (2, 0, "u", "a long sentence that\nis wrapped"), (2, 1, "u", "other"), (2, 2, "u", "> a long\n> sentence that is\n> wrapped\nyes"),
        (3, 0, "u", "> said later\nfoo"), (3, 1, "u", "said later"), (4, 0, "u", "Said later!"),
    ]
    got = {(r.conv_id, r.turn): r for r in quotes.link(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    assert [got[1, t].reply_turn for t in (1, 2, 3)] == [None, 1, 2] and got[1, 3].linked_lines == 6
    assert (got[2, 2].reply_turn, got[2, 2].linked_lines) == (0, 3)
    assert (got[3, 0].quoted_conv, got[3, 0].quoted_turn, got[3, 0].reply_turn) == (4, 0, None)


@pytest.mark.parametrize("n", [200])
def test_a_long_conversation_is_ordered(spark, n):
    rows = [(7, t, "u", f"line {t}" if t % 3 else f"> line {t // 2}\nreply {t}") for t in range(n)]
    got = {r.turn: r for r in quotes.link(spark.createDataFrame(rows, "conv_id int, turn int, role string, text string")).collect()}
    parent = {t: (t // 2 if t % 3 == 0 and t and (t // 2) % 3 else t - 1 if t else None) for t in range(n)}
    assert {t: r.reply_turn for t, r in got.items()} == parent
    order = sorted(range(n), key=lambda t: (-1 if parent[t] is None else parent[t], t))
    assert [got[t].position for t in order] == list(range(1, n + 1))


def test_very_long_quote_marks(spark):
    n = 300_000
    rows = [(1, 0, "u", "said first"), (1, 1, "u", ">" * n + " said first\nyes"), (1, 2, "u", "> " * n + "said first"), (1, 3, "u", ">" * n), (1, 4, "u", "\n".join(["> said first"] * 5000))]
    got = {r.turn: r for r in quotes.link(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    assert [got[t].quote_level for t in range(5)] == [0, n, n, n, 1]
    assert [got[t].reply_turn for t in range(5)] == [None, 0, 0, 2, 0] and got[4].linked_lines == 5000
