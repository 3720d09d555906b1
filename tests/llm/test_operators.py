"""Operators against plain versions, on small tables with odd rows."""

import random
import re
import time
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from depstrata.llm import ann, gam, html, licenses, line_rules, mixing, neardup, packing, pfp, pii
from tests.llm import brute

DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double, h long, text_ string"


def words(rng, n):
    return " ".join("".join(rng.choice(["ta", "ro", "ni", "ke", "su"]) for _ in range(rng.randint(1, 5))) for _ in range(n))


@pytest.fixture(scope="module")
def texts():
    rng = random.Random(2)
    base = [words(rng, rng.randint(5, 120)) for _ in range(30)]
    passage = words(rng, 60)
    odd = [None, "", " \n\t ", "a", "x" * 5000, "word " * 3000, "🙂 é ß " * 40, "Ünïcode space ΣΑΣ İ 漢字", "<|endoftext|> it's 12 we'll"]
    near = [base[0] + " extra", base[0], base[0].upper(), base[1] + "\n" + passage, passage + " tail", base[2] + passage + base[3]]
    pii_ = ["mail a@b.co, b@c.de.fg_x@y.zz ip 10.0.0.255 300.1.1.1 1.2.3.4.5.6.7.8 card 4111 1111 1111 1111 tel +44 (20) 7946-0958", "IBAN GB82 WEST 1234 5698 7654 32 token = 24be64439e3e49cf46b2d7c90f3602a3d0b907ff", "🙂 a@b.co +1 2 1234-5678-9"]
    law = ["CC BY cc by, all rights reserved", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files", "the GNU General Public License"]
    return [*base, *odd, *near, *pii_, *law]


@pytest.fixture(scope="module")
def docs(spark, texts):
    rows = [(i, t, None if i % 7 == 0 else "en", None if i % 5 == 0 else f"s{i % 3}", len(t or ""), 1.0, 1, "x") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def test_line_rules(docs, texts, empty):
    got = {r.doc_id: r for r in line_rules.judge(docs).collect()}
    for i, t in enumerate(texts):
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == brute.line_base(t), t
    assert line_rules.judge(empty).count() == 0


def test_frequent_lines_are_removed(spark):
    rng = random.Random(4)
    own = lambda: words(rng, 30)
    rows = [(i, f"Menu {i} home\n{own()}\n{own()}", "a") for i in range(40)]
    rows += [(100 + i, "Menu 1 home\nshort own line", "a") for i in range(3)]
    rows += [(200 + i, own(), None) for i in range(5)] + [(300 + i, rows[0][1], "b") for i in range(40)]
    got = {r.doc_id: r for r in line_rules.judge(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert all(got[i].n_removed_words == 3 and got[i].kept for i in range(40))
    assert not any(got[100 + i].kept for i in range(3))
    assert all(got[300 + i].kept for i in range(40))  # copies are one document


def test_pii(docs, texts, empty):
    got = {r.doc_id: r for r in pii.digest(pii.scan(docs)).collect()}
    for i, t in enumerate(texts):
        r = got[i]
        want, spans = brute.pii_base(t)
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone, r.base_sha256) == want, t
        assert spans <= set(r.spans.split(","))
    assert any("iban:" in r.spans and "key:" in r.spans for r in got.values())
    assert pii.digest(pii.scan(empty)).count() == 0


def test_pii_own_kinds(spark):
    """Account numbers and credentials against plain loops over every start."""
    rng = random.Random(15)

    def iban(country, body):
        rest = int("".join(str(int(c, 36)) for c in body + country + "00")) % 97
        return f"{country}{98 - rest:02d}{body}"

    made = []
    for i in range(120):
        good = iban(rng.choice(["GB", "DE", "FR"]), "".join(rng.choices("ABCDEFGH0123456789", k=rng.randint(11, 30))))
        good = " ".join(good[k : k + 4] for k in range(0, len(good), 4)) if i % 3 == 0 else good
        bad = good[:-1] + ("1" if good[-1] != "1" else "2") if i % 4 == 0 else good
        key = "".join(rng.choices("abcdefXYZ_-0123456789", k=rng.randint(20, 40)))
        made.append(f"{rng.choice(['konto', 'um', '🙂 é'])} {bad} {rng.choice(['token=', 'was ', 'api key: ', 'x'])}{key}. {rng.choice(['', 'a@b.co '])}{rng.choice(['secret', 'nix'])} {key[::-1]}!")

    def plain(t):
        found = set()
        for m in re.finditer(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){11,30}+(?![A-Za-z0-9])", t):
            s = m.group().replace(" ", "")
            if 15 <= len(s) <= 34 and int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1:
                found.add(f"iban:{m.start()}:{m.end()}")
        for m in re.finditer(r"(?<![A-Za-z0-9_-])[A-Za-z0-9_-]{24,}", t):
            if re.search("[0-9]", m.group()) and re.search("token|key|secret|passw|credential|auth", t[max(0, m.start() - 30) : m.start()].lower()):
                found.add(f"key:{m.start()}:{m.end()}")
        return found

    df = spark.createDataFrame(list(enumerate(made)), "doc_id long, text string")
    got = {r.doc_id: {x for x in r.spans.split(",") if x.startswith(("iban", "key"))} for r in pii.digest(pii.scan(df)).collect()}
    assert got == {i: plain(t) for i, t in enumerate(made)}
    assert {x.split(":")[0] for v in got.values() for x in v} == {"iban", "key"}


def test_pii_in_very_long_texts(spark):
    """A megabyte of addresses takes seconds."""
    n = 60_000
    text = "".join(f"u{i % 10}@b.co é " for i in range(n))
    df = spark.createDataFrame([(1, text), (2, "mail a@b.co"), (None, "+1 234 567 8901 a@b.co"), (None, None)], "doc_id long, text string")
    began = time.perf_counter()
    got = {r.doc_id: r for r in pii.digest(pii.scan(df.where("doc_id is not null"))).collect()}
    assert got[1].n_email == n and got[1].spans.startswith("email:0:7,email:10:17,") and got[1].spans.endswith(f"email:{10 * n - 10}:{10 * n - 3}")
    clean = pii.redact(df.where("doc_id = 1")).first().text
    assert clean == "<email> é " * n
    assert time.perf_counter() - began < 60
    assert sorted(r.n_email for r in pii.digest(pii.scan(df)).where("doc_id is null").collect()) == [0, 1]


def test_redaction_by_chunks(spark):
    """Overlapping spans and pieces that cross many chunks, against a plain loop."""
    rng = random.Random(16)
    rows = []
    for i in range(60):
        parts = [rng.choice(["a@b.co", "+49 (30) 123456789 10.1.1.1", "4111 1111 1111 1111", "🙂é " * rng.randint(0, 700), "x" * rng.randint(0, 3000), "\n", " 10.0.0.1.2.3.4 "]) for _ in range(rng.randint(0, 12))]
        rows.append((i, " ".join(parts)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    spans = {r.doc_id: r.spans for r in pii.scan(df).select("doc_id", "spans").collect()}
    for r in pii.redact(df).collect():
        text, out, pos = rows[r.doc_id][1], "", 0
        for x in spans[r.doc_id]:
            if x.s >= pos:
                out += text[pos : x.s] + f"<{x.kind}>"
            pos = max(pos, x.e)
        assert r.text == out + text[pos:]


def test_long_digit_runs_and_redaction(spark):
    long_ = "1 2 3 " * 20_000 + "a" * 50_000
    df = spark.createDataFrame([(1, long_, 5, "k"), (2, "write a@b.co now", 16, "k"), (3, None, 0, "k")], "doc_id long, text string, n_chars long, spans string")
    assert {r.doc_id: r.n_card for r in pii.digest(pii.scan(df)).collect()} == {1: 0, 2: 0, 3: 0}
    out = {r.doc_id: r for r in pii.redact(df).collect()}
    assert out[2].text == "write <email> now" and out[2].n_chars == 17 and out[2].spans == "k" and out[1].text == long_


def test_passages(docs, texts, empty):
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in pfp.dedup(docs).collect()}
    assert got == brute.passages(enumerate(texts))
    assert sum(v[1] for v in got.values()) > 1000
    assert pfp.dedup(empty).count() == 0


def test_passages_on_repetitive_bytes(spark):
    rng = random.Random(9)
    rows = [(i, "".join(rng.choice("ab") for _ in range(rng.randint(0, 60))) * rng.randint(1, 8) + "c" * rng.randint(0, 150)) for i in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    for share in (2_000, 3, 0):  # suffix arrays only, both ways, rows only
        got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in pfp.dedup(df, bits=12, max_share=share).collect()}
        assert got == brute.passages(rows)
    with pytest.raises(ValueError):
        pfp.dedup(df, length=40)


def test_passages_with_clashing_and_missing_ids(spark):
    rng = random.Random(20)
    shared = words(rng, 60)
    rows = [(5, "a " + shared), (5, "b " + shared + words(rng, 30)), (5, "a " + shared), (3, shared[:300]), (None, shared), (9, None), (9, "x" * 500), (None, None)]
    df = spark.createDataFrame([(*r, "k", 1) for r in rows], "doc_id long, text string, doc string, h int").repartition(3)
    th = dict(df.select("text", F.xxhash64("text")).collect())
    order = sorted({r for r in rows if r[0] is not None}, key=lambda r: (r[0], th[r[1]]))
    want = brute.passages([(i, t) for i, (_, t) in enumerate(order)])
    got = sorted((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in pfp.dedup(df).where("doc_id is not null").collect())
    assert got == sorted((order[i][0], *want[i]) for r in rows if r[0] is not None for i in [order.index(r)])
    assert sorted((r.n_bytes, r.n_removed) for r in pfp.dedup(df).where("doc_id is null").collect()) == [(0, 0), (len(shared), 0)]


def test_suffix_array_of_a_dictionary():
    """Order, common prefixes and corpus order of ties against plain sorting."""
    rng = random.Random(17)
    unit = [bytes(rng.choice(b"ab") for _ in range(130)) for _ in range(4)]
    pieces = [bytes(rng.choice(b"xyz") for _ in range(rng.randint(0, 20))) + rng.choice(unit)[rng.randint(0, 9) :] + b"\0" * rng.randint(0, 9) for _ in range(40)]
    doc, at = np.array([rng.randint(0, 9) for _ in pieces]), np.arange(len(pieces)) * 1000
    sa = pfp.SuffixArray(pieces, doc, at, 100)
    every = sorted((p[i : i + 100], int(d), int(a) + i) for p, d, a in zip(pieces, doc, at) for i in range(len(p) - 99))
    times = Counter(w for w, _, _ in every)
    want = [(d, a) for w, d, a in every if times[w] > 1]
    assert list(zip(sa.doc[sa.order].tolist(), sa.at[sa.order].tolist())) == want
    gone = {(d, a) for i, (w, d, a) in enumerate(every) if i and every[i - 1][0] == w}
    assert {(d, a + i) for d, a, n in zip(*map(np.ndarray.tolist, sa.repeats())) for i in range(n)} == gone


def test_licenses(docs, texts, empty):
    got = {r.doc_id: r for r in licenses.scan(docs).collect()}
    for i, t in enumerate(texts):
        r = got[i]
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == brute.license_base(t)
        assert set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(",")) and 0 <= r.score <= 1
    assert any(r.labels == "mit" and r.score == 1 for r in got.values())
    assert licenses.scan(empty).count() == 0


def test_several_licenses_and_stray_words(spark):
    full = {n: t for n, (t, _) in licenses.TEMPLATES.items()}
    names = sorted(full)
    pairs = [(a, b) for a in names for b in names if a < b]
    stray = " und ".join(sorted({w for t in full.values() for w in t.split()}, reverse=True))
    rows = [(i, f"{full[a]}\n{full[b]}") for i, (a, b) in enumerate(pairs)]
    rows += [(100 + i, f"{stray} {'la ' * 5000}{full[n]} {'le ' * 5000}{stray}") for i, n in enumerate(names)]
    rows += [(200, "\n".join(full.values())), (201, stray), (202, full["mit"].replace("software", "new and odd software"))]
    got = {r.doc_id: set(filter(None, r.labels.split(","))) & set(names) for r in licenses.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(got[i] == set(p) for i, p in enumerate(pairs))
    assert all(got[100 + i] == {n} for i, n in enumerate(names))
    assert got[200] == set(names) and got[201] == set() and got[202] == {"mit"}


def test_one_line_notices(spark):
    notices = {
        "la ro ni Licensed under the Apache License, Version 2.0": "apache-2.0", "see the Apache License, Version 2.0.": "apache-2.0", "code (Apache License 2.0)": "apache-2.0",
        "licensed under the apache license 2.0": "apache-2.0", "Released under the MIT License.": "mit", "mit licenses for sale": "", "This work is licensed under the GNU General Public License, version 3": "gpl",
        "This file is under the Mozilla Public License, version 2.0": "mpl-2.0", "distributed under the BSD license": "bsd", "released under the ISC license": "isc", "released under the Unlicense": "unlicense",
        "MIT License": "mit", "the apache people, license by license": "",
    }
    df = spark.createDataFrame(list(enumerate(notices)), "doc_id long, text string")
    got = {r.doc_id: r for r in licenses.scan(df).collect()}
    assert [got[i].labels for i in range(len(notices))] == list(notices.values())
    assert got[0].score == 1 and 0.6 <= got[1].score < 1 and got[11].score >= 0.6 and got[12].score == 0
    assert all(n / len(t.split()) >= 0.6 for _, t, key in licenses.NOTICES for n in [len(key.split())])


def test_license_index_misses_no_place():
    """Every form at every alignment, by a plain loop."""
    rng = random.Random(14)
    vocabulary = sorted({w for _, t, _ in licenses.FORMS for w in t.split()})
    index = licenses.Index({w: rng.randint(0, 50) for w in vocabulary}, 100)

    def plain(ws):
        out = {}
        for label, t, key in licenses.FORMS:
            t, key = t.encode().split(), key.encode().split()
            for at in range(len(ws) - len(key) + 1):
                if ws[at : at + len(key)] == key:
                    for s in range(max(0, at + len(key) - len(t) - 6), at + 1):
                        b = ws[s : s + len(t) + 6]
                        row = [0] * (len(t) + 1)
                        for y in b:
                            new = [0]
                            for i, x in enumerate(t):
                                new.append(row[i] + 1 if x == y else max(new[i], row[i + 1]))
                            row = new
                        if row[-1] / len(t) >= 0.6:
                            out[label] = max(out.get(label, 0), row[-1] / len(t))
        return out

    for _ in range(150):
        ws = []
        for _ in range(rng.randint(1, 4)):
            form = rng.choice(licenses.FORMS)[1].split()
            a, b = sorted((rng.randint(0, 3), len(form) - rng.randint(0, 3)))
            ws += rng.choices(vocabulary, k=rng.randint(0, 6)) + form[a:b]
            if ws and rng.random() < 0.5:
                ws[rng.randrange(len(ws))] = "odd"
        ws = [w.encode() for w in ws]
        assert index.match(ws) == pytest.approx(plain(ws))


def test_packing(docs, texts, empty):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.tokenizer_path())
    got = defaultdict(list)
    bins = defaultdict(list)
    for r in packing.pack(packing.pieces(docs), open_bins=8, group_rows=16).collect():
        got[r.doc_id].append(r)
        bins[r.sequence_id].append((r.offset, r.length))
    for i, t in enumerate(texts):
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 0], "<u4")
        rows = sorted(got[i], key=lambda r: r.piece)
        assert [(r.piece, r.start, r.length, r.ids_crc32) for r in rows] == [(k, a, len(c), zlib.crc32(c.tobytes())) for k, a in enumerate(range(0, len(ids), 2048)) for c in [ids[a : a + 2048]]]
    for b in bins.values():
        at = 0
        for o, n in sorted(b):
            assert o == at
            at += n
        assert at <= 2048
    assert packing.pack(packing.pieces(empty)).count() == 0


def test_best_fit_is_tight_and_closes_bins():
    rng = random.Random(1)
    lengths = [rng.choice([rng.randint(1, 2048), rng.randint(1, 200)]) for _ in range(4000)]
    order = packing.arrivals(lengths, 256)
    assert sorted(order) == list(range(4000)) and all(a // 256 <= b // 256 for a, b in zip(order, order[1:]))
    used = lambda k: max(b for b, _ in packing.best_fit([lengths[i] for i in order], 2048, k)) + 1
    assert used(64) <= 1.02 * sum(lengths) / 2048
    assert used(4) > used(64) > used(10**9) - 1  # fewer open bins, more that close early


def test_best_fit_takes_the_tightest_open_bin():
    """Against a plain list of bins."""
    rng = random.Random(2)
    for open_bins in (1, 2, 5, 1000):
        lengths = [rng.randint(1, 100) for _ in range(400)]
        bins, want, made = [], [], 0
        for n in lengths:
            fit = [b for b in bins if b[1] >= n]
            if fit:
                least = min(b[1] for b in fit)
                b = [x for x in fit if x[1] == least][-1]  # of equal ones the last touched
                bins.remove(b)
            else:
                b, made = [made, 100], made + 1
                if len(bins) >= open_bins:
                    least = min(x[1] for x in bins)
                    bins.remove([x for x in bins if x[1] == least][-1])
            want.append((b[0], 100 - b[1]))
            b[1] -= n
            if b[1]:
                bins.append(b)
        assert packing.best_fit(lengths, 100, open_bins) == want


def test_packing_spreads_repeated_and_null_ids(spark):
    df = spark.createDataFrame([(None, "a b c")] * 300 + [(7, "ta ro")] * 300 + [(8, None)], DOCS.split(", lang")[0]).repartition(6)
    got = packing.pack(packing.pieces(df), group_rows=50).collect()
    assert len(got) == 601 and Counter(r.doc_id for r in got) == {None: 300, 7: 300, 8: 1}
    assert max(Counter(r.sequence_id >> 32 for r in got).values()) < 120


def test_mixing(spark, docs, empty):
    rng = random.Random(6)
    rows = [(i, words(rng, rng.randint(1, 40)), f"s{i % 4}" if i % 4 else None) for i in range(3000)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    once = mixing.mix(df, chunk_rows=64, fan=4).toPandas()
    again = mixing.mix(df.repartition(5), chunk_rows=64, fan=4).toPandas()
    assert once.set_index("doc_id").copies.sort_index().equals(again.set_index("doc_id").copies.sort_index())
    assert (once.taken <= 3 * once["size"]).all() and len(once) == 3000
    by = once.groupby(once.source.fillna("~")).agg(taken=("taken", "sum"), target=("target", "first"))
    assert (abs(by.taken / by.target - 1) < 0.02).all()
    assert mixing.mix(empty).count() == 0
    assert mixing.mix(docs).count() == docs.count()
    assert mixing.targets({"a": 10, "b": 100, "c": 100}) == {"a": 30.0, "b": 120.0, "c": 60.0}


def test_targets_of_many_sources(spark):
    rng = random.Random(19)
    sizes = {f"s{i:03d}é" if i % 9 == 0 else f"s{i:03d}": rng.choice([0, 1, 5, 100, 10_000]) for i in range(200)} | {None: 70}
    df = spark.createDataFrame(list(sizes.items()), "source string, n long").repartition(7)
    got = {r.s: r.target for r in mixing.many_targets(df, (5, 2, 1), 3).collect()}
    assert got == pytest.approx(mixing.targets(sizes))
    rows = [(i, words(rng, 3 + i % 20), f"s{i % 40}") for i in range(800)]
    docs_ = spark.createDataFrame(rows, "doc_id long, text string, source string")
    few, many = (mixing.mix(docs_, max_broadcast=b).toPandas().sort_values("doc_id") for b in (100, 3))
    assert many.target.tolist() == pytest.approx(few.target.tolist())
    assert (abs(many.groupby("source").taken.sum() - many.groupby("source").target.first()) <= 25).all()


def test_scores_are_sums_of_tables():
    rng = np.random.default_rng(4)
    x = rng.normal(size=(4000, len(gam.FEATURES)))
    y = (x[:, 0] * x[:, 1] + 0.2 * x[:, 2] > 0).astype(float)
    m = gam.fit(x[:3000], y[:3000])

    def plain(row):
        total, bins = m.base, [sum(v >= c for c in cuts) for v, cuts in zip(row, m.cuts)]
        total += sum(t[b] for t, b in zip(m.tables, bins))
        total += sum(t[m.coarse[i][bins[i]], m.coarse[j][bins[j]]] for i, j, t in m.pairs)
        return 1 / (1 + np.exp(-total))

    assert m.score(x[:50]) == pytest.approx([plain(r) for r in x[:50]])
    alone = gam.fit(x[:3000], y[:3000], n_pairs=0)
    accuracy = lambda k: ((k.score(x[3000:]) >= 0.5) == y[3000:]).mean()
    assert accuracy(m) > 0.8 and accuracy(alone) < 0.7  # the product of two features is a pair's


def test_near_duplicates(spark, docs, texts, empty):
    rng = random.Random(8)
    base = [words(rng, 120).split() for _ in range(12)]
    rows, group = [], {}
    for i in range(240):
        b = i % 12
        w = list(base[b])
        for _ in range(rng.randint(0, 2)):
            w[rng.randrange(len(w))] = f"new{i}"
        rows.append((i, " ".join(w)))
        group[i] = b
    rows += [(1000 + i, words(rng, 50)) for i in range(60)] + [(2000, None), (2001, ""), (None, rows[0][1]), (0, rows[0][1])]
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()
    assert len(got) == len(rows)
    cls = {r.doc_id: r.class_id for r in got}
    sh = {i: {tuple(t.split()[k : k + 5]) for k in range(len(t.split()) - 4)} for i, t in rows if i is not None and t}
    for a in range(240):
        for b in range(a):
            s = len(sh[a] & sh[b]) / len(sh[a] | sh[b])
            if s >= 0.8:
                assert cls[a] == cls[b]
            if group[a] != group[b]:
                assert cls[a] != cls[b]
    assert all(cls[1000 + i] == 1000 + i for i in range(60)) and cls[2000] == 2000 and cls[None] == cls[0]
    assert neardup.near_duplicates(empty).count() == 0
    assert neardup.near_duplicates(docs).count() == docs.count()


def test_clashing_and_missing_ids_lose_no_text(spark):
    rng = random.Random(18)
    a, b, c = (words(rng, 60) for _ in range(3))
    rows = [(1, a, "s"), (1, b, "s"), (2, a + " x", "s"), (None, c, "s"), (None, c + " y", "t"), (None, b, "s"), (None, None, "s"), (3, "", "s"), (3, "", "s")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = neardup.grouped(df).collect()
    cls = {(r.doc_id, r.th): (r.class_id, r.class_th) for r in got}
    th = dict(df.select("text", F.xxhash64("text")).collect())
    assert len(got) == len(rows)
    assert cls[1, th[a]] == cls[2, th[a + " x"]] == (1, th[a]) and cls[1, th[b]] == cls[None, th[b]] == (1, th[b])
    assert cls[None, th[c]] == cls[None, th[c + " y"]] and cls[None, th[c]][0] is None
    kept = neardup.keep_one(df)
    texts_ = [r.text for r in kept.collect()]
    assert kept.columns == df.columns and Counter(t for t in texts_ if t) == Counter({a: 1, b: 1, min(c, c + " y", key=lambda t: th[t]): 1}) and texts_.count("") == 2 and texts_.count(None) == 1
    many = spark.createDataFrame([(7, t, f"s{k}") for k in range(3) for t in (a, b, c)] + [(None, a, None)], "doc_id long, text string, source string")
    out = mixing.repeat(many)
    total = mixing.mix(many).agg(F.sum("copies")).first()[0]
    assert out.columns == many.columns and out.count() == total
    alike = spark.createDataFrame([(None, "ta ro ni", "s")] * 900 + [(5, a, "t")] * 900, "doc_id long, text string, source string")
    mix_ = mixing.mix(alike, chunk_rows=32, fan=4).groupBy("source").agg(F.sum("taken").alias("taken"), F.first("target").alias("target")).collect()
    assert all(abs(r.taken / r.target - 1) < 0.02 for r in mix_)


def test_bucket_with_different_texts_loses_no_link(spark):
    """All texts in one bucket, the first of them unlike the others."""
    rng = random.Random(12)
    a, b = words(rng, 80), words(rng, 80)
    rows = [(0, words(rng, 80)), (1, a), (2, b), (3, a + " x"), (4, b + " y"), (5, words(rng, 80)), (6, a + " z")]
    texts = spark.createDataFrame(rows, "id long, text string")
    weigher = neardup.Weigher.of(texts)
    left = spark.createDataFrame([(9, i, True, 1.0, i) for i, _ in rows[1:]], "bucket long, id long, loose boolean, d double, c long")
    got = {frozenset((r.a, r.b)) for r in neardup._blocks(left, texts, weigher, 0.8, 2).collect()}
    edges = neardup.classes(neardup._blocks(left, texts, weigher, 0.8, 2)).collect()
    assert {r.id: r.class_id for r in edges} == {1: 1, 3: 1, 6: 1, 2: 2, 4: 2} and frozenset((2, 4)) in got


def test_consistent_samples_estimate_similarity():
    sampler = neardup.Sampler(2000)
    rng = np.random.default_rng(0)
    s = rng.integers(0, 2**63, 300, dtype=np.int64).astype(np.uint64)
    w = rng.gamma(2, 1, 300)
    a, b = (np.sort(s[:200]), w[:200][np.argsort(s[:200])]), (np.sort(s[50:]), w[50:][np.argsort(s[50:])])
    want = neardup.similarity(a, b)
    assert (sampler(*a) == sampler(*b)).mean() == pytest.approx(want, abs=0.04)


def _cloud(rng, n, dim=12, centres=24):
    """Vectors of length 1 in groups."""
    c = rng.normal(size=(centres, dim)) * 3
    x = c[rng.integers(0, centres, n)] + rng.normal(size=(n, dim)) * 0.3
    return (x / np.linalg.norm(x, axis=1, keepdims=True)).astype(np.float32)


def test_search_prunes_where_vectors_have_structure(spark):
    rng = np.random.default_rng(7)
    x = _cloud(rng, 3000)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    s = x[::20].astype(float) @ x.T.astype(float)
    s[np.arange(150), np.arange(0, 3000, 20)] = -np.inf
    best = np.argsort(-s, axis=1, kind="stable")[:, :20]
    for factor, most in ((1.0, 0.35), (2.0, 0.3)):
        got = ann.search(df, factor=factor, shard_rows=300, with_work=True).toPandas()
        recall = np.mean([len(set(g.vec_id) & set(best[q // 20])) / 20 for q, g in got.groupby("query_id")])
        assert recall == 1 if factor == 1 else recall >= 0.9
        assert got.groupby("query_id").scored.first().mean() < most * 3000


def test_search_with_a_very_common_vector(spark):
    rng = np.random.default_rng(8)
    x = rng.normal(size=(600, 8)).astype(np.float32)
    rows = [(i, x[i % 600].tolist() if i < 600 else x[3].tolist()) for i in range(2000)] + [(40, x[5].tolist()), (10**6, [1.0, 2.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = defaultdict(list)
    for r in ann.search(df, shard_rows=100, block_rows=30).orderBy("query_id", "rank").collect():
        got[r.query_id].append(r.vec_id)
    q = min(x[40].tolist(), x[5].tolist())
    for i in range(0, 2000, 20):
        v = np.array(q if i == 40 else dict(rows[:2000])[i], np.float32).astype(float)
        want = sorted((-np.cumsum(v * np.array(e, np.float32).astype(float))[-1], j) for j, e in rows[:-1] if j != i)[:20]
        assert got[i] == [j for _, j in want]
    assert 10**6 not in got  # nothing of its dimension


def test_vantage_point_search(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(900, 16)).astype(np.float32)
    x[300:500] = x[300]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(5000, None), (5020, [0.0] * 16), (5040, [float("nan")] * 16), (5060, [None, 1.0]), (None, x[0].tolist())]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = defaultdict(list)
    for r in ann.search(df, shard_rows=200, block_rows=20).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.vec_id, r.score))
    assert set(got) == set(range(0, 900, 20))
    for q, found in got.items():
        s = np.cumsum(x[q].astype(float) * x.astype(float), axis=1)[:, -1]
        want = sorted((-v, i) for i, v in enumerate(s) if i != q)[:20]
        assert found == [(i, -v) for v, i in want]
    loose = defaultdict(set)
    for r in ann.search(df, factor=1.3, shard_rows=200, block_rows=20).collect():
        loose[r.query_id].add(r.vec_id)
    recall = np.mean([len(loose[q] & {i for i, _ in got[q]}) / 20 for q in got])
    assert recall >= 0.9
    assert ann.search(df.where("vec_id < 0")).count() == 0
    assert ann.search(df.where("vec_id = 0")).count() == 0


def test_classifier_learns(spark):
    rng = random.Random(5)
    good = [(i, words(rng, 80), 1) for i in range(400)]
    bad = [(400 + i, " ".join(["###"] * 20 + [words(rng, 10).upper()]), 0) for i in range(100)]
    df = spark.createDataFrame(good + bad, "doc_id long, text string, y int")
    labels = df.select("doc_id", F.col("y").alias("quality")).unionByName(spark.createDataFrame([(None, 1), (3, None)], "doc_id long, quality int"))
    model = gam.train(df, labels)
    got = gam.classify(df, model, keep=("doc_id", "y")).withColumn("out", gam.held_out(F.col("doc_id"))).toPandas()
    assert (got[got.out].predicted == got[got.out].y).mean() > 0.98 and got.score.between(0, 1).all()
    again = gam.train(df.repartition(7), labels)
    assert [t.tolist() for t in again.tables] == [t.tolist() for t in model.tables]
    nothing = gam.train(df, labels.where("false"))
    assert set(gam.classify(df, nothing).toPandas().score) == {0.5}


def test_html(spark):
    page = lambda k, body: f"<html><head><title>t</title><style>p{{}}</style></head><body><nav><ul><li>Home<li>News {k}</ul></nav><div class='ad'>Buy {k}</div>{body}<div class='comments'><p>reader {k}</p></div><footer>&copy; x</footer></body></html>"
    art = lambda k: f"<article><h1>Title {k} &amp; more</h1><p>First   para <b>bold {k}</b><br>line<p>Second &lt;{k}&gt;</article>"
    rows = [(k, f"http://a.example/{k}", page(k, art(k))) for k in range(6)]
    rows += [(10 + k, f"http://b.example/{k}", page(k, f"<div><p>Same notice for all readers</p><p>Own story {k} {'x' * k}</p></div>")) for k in range(5)]
    rows += [(20, None, None), (21, None, ""), (22, "http://c.example/", "plain < text &amp; <script>var a='</p>'</script>more")]
    got = {r.page_id: r for r in html.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for k in range(6):
        assert got[k].text == f"Title {k} & more\n\nFirst para bold {k} line\n\nSecond <{k}>" and got[k].n_chars == len(got[k].text)
    for k in range(5):
        assert got[10 + k].text == f"Own story {k} {'x' * k}".strip()
    assert got[20].text == got[21].text == "" and len(got) == len(rows)
    assert got[22].text.startswith("plain < text &")


def test_html_names_in_articles(spark):
    parts = lambda k: [f"Title {k}", f"History {k}", f"Reform {k}", "We show that x=2 holds in all cases", f"Talk {k}", f"Networks {k}", f"Mind {k}"]
    body = lambda a: (
        f"<header class='entry-header'><h1>{a[0]}</h1></header><section class='social-history'><p>{a[1]}</p></section><div id='copyright-reform'>{a[2]}</div>"
        f"<p>{a[3].replace('x=2', '<math><mi>x</mi><mo>=</mo><mn>2</mn></math>')}</p><section id='discussion'><p>{a[4]}</p></section><div class='ad-hoc-networks'>{a[5]}</div><div class='alert'>{a[6]}</div>"
    )
    junk = lambda k: f"<div class='ad-slot'>Buy {k}</div><div class='post share-buttons'>Send {k}</div><div id='comments'>Reader {k}</div><nav>Go {k}</nav>"
    rows = [(k, f"http://a.example/{k}", f"<body><div class='site-header'>Top {k}</div><article>{body(parts(k))}{junk(k)}</article></body>") for k in range(5)]
    # Without a mark of the article; the plain header tag is the page's there, and what is constant is template.
    rows += [(10 + k, f"http://b.example/{k}", f"<body><div class='site-header main-menu'>Top {k}</div><div>{body(parts(k)).replace('header', 'div')}{junk(k)}</div></body>") for k in range(5)]
    got = {r.page_id: r.text.split("\n\n") for r in html.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for k in range(5):
        assert [t for t in got[k] if "x=2" not in t] == [t for t in got[10 + k] if "x=2" not in t] == [t for t in parts(k) if "x=2" not in t]
    lone = html.extract([rows[0][2]])
    assert lone == ["\n\n".join(parts(0))]


def test_html_deep_trees(spark):
    deep = lambda k: "<b>x" * 3000 + f"<div class='ad'>Buy {k}</div>" + "<div><span>" * (3000 + k) + f"<p>Own story {k}</p>"
    rows = [(k, f"http://a.example/{k}", f"<body><div>{deep(k)}</div></body>") for k in range(4)]
    rows += [(10 + k, f"http://b.example/{k}", f"<body><p>Same</p><p>Story {k}</p>" + f"<font color=red class=c{k}>" * 5000 + "</body>") for k in range(4)]
    rows += [(20 + k, f"http://c.example/{k}", "<em>" * 2000 + f"<p>Same</p><span class='ad'><b><div>Buy {k}</div></b> now</span><p>Tale {k}</p>") for k in range(4)]
    got = {r.page_id: r.text for r in html.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for k in range(4):
        assert got[k].endswith(f"Own story {k}") and "Buy" not in got[k]
        assert got[10 + k] == f"Story {k}" and got[20 + k] == f"Tale {k}"
    p = html.Page("<div><b>one<div>two</div>three</div>")
    assert p.texts == ["one", "two", "three"] and [n.label for n in html._listed(p.root)] == ["#root", "div", "b", "div"]


def _page(k, rng):
    """A page without any telling tag or name: menu, advert, article and footer in plain blocks, all of them varying."""
    link = "".join(f"<div><a href=/{w}>{w}</a></div>" for w in words(rng, 6).split())
    paragraphs = [words(rng, rng.randint(20, 60)) for _ in range(rng.randint(1, 6))]
    body = f"<h1>{words(rng, 6)}</h1>" + "".join(f"<p>{t}" for t in paragraphs)
    return f"<body><div>{link}</div><div>{words(rng, 8)}</div><div>{body}</div><div>Imprint of this site {words(rng, 9)}</div></body>", body.count("<p>") + 1


def test_html_induction_decides():
    rng = random.Random(11)
    pages = [_page(k, rng) for k in range(12)]
    with_, without = html.extract([h for h, _ in pages]), html.extract([h for h, _ in pages], least_pages=10**9)
    assert all(len(t.split("\n\n")) == n and "Imprint" not in t for t, (_, n) in zip(with_, pages))
    assert all("Imprint" in t and a != t for t, a in zip(without, with_))


def test_html_chunks_see_one_host(spark):
    """A host dealt over many partitions has one wrapper; copies, repeated rows, NULLs and other columns change nothing."""
    rng = random.Random(12)
    pages = [_page(k, rng)[0] for k in range(40)]
    rows = [(k, "http://a.example/" + str(k), h, "x", "y", 1) for k, h in enumerate(pages)] + [(0, "http://a.example/0", pages[0], "x", "y", 1)] * 30 + [(None, "HTTP://A.example/9", pages[9], None, None, None)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, host string, text string, node int")
    got = html.main_text(df.repartition(9)).collect()
    want = dict(enumerate(html.extract(pages)))
    assert len(got) == len(rows) and all(r.text == want[9 if r.page_id is None else r.page_id] for r in got)
    assert sorted((r.page_id, r.text) for r in html.main_text(df.where("page_id is not null"), max_broadcast=0).collect()) == sorted((r.page_id, r.text) for r in got if r.page_id is not None)
    assert html.main_text(df.where("false")).count() == 0


@pytest.mark.parametrize("junk", ["<div>" * 60_000, "<a " * 300_000, "<" + "a" * 1_000_000, "<a \">" * 40_000, "<p><b>" * 20_000, "<nav>" + "<b>" * 9_000 + "<div></div>" * 9_000 + "</nav>", "&" * 500_000])
def test_html_pages_in_linear_time(junk):
    began = time.perf_counter()
    page = html.Page(junk + "<p>end</p>")
    assert page.root.count and time.perf_counter() - began < 15


def test_tree_matching_agrees_with_plain_recursion():
    def plain(a, b):
        if a.label != b.label:
            return 0
        m = [[0] * (len(b.children) + 1) for _ in range(len(a.children) + 1)]
        for i, x in enumerate(a.children):
            for j, y in enumerate(b.children):
                m[i + 1][j + 1] = max(m[i][j + 1], m[i + 1][j], m[i][j] + plain(x, y))
        return m[-1][-1] + 1

    rng = random.Random(13)

    def grown(depth):
        tag = rng.choice(["div", "ul", "section"])
        return f"<{tag}>{''.join(grown(depth - 1) for _ in range(rng.randint(0, 3) if depth else 0))}</{tag}>"

    for _ in range(200):
        p, q = html.Page(grown(4)), html.Page(grown(4))
        size, pairs = html.match(p.root, q.root)
        assert size == len(pairs) == plain(p.root, q.root)


def test_tree_matching():
    p = html.Page("<div><p>a</p><ul><li>1<li>2</ul></div>")
    q = html.Page("<div><h2>x</h2><p>a</p><ul><li>1</ul></div>")
    size, pairs = html.match(p.root, q.root)
    assert size == len(pairs) == 5


def test_odd_rows_in_every_operator(spark, texts):
    """NULLs in every column, repeated rows, very long texts, clashing names: a row for each row, and the same for equal rows."""
    names = "row group chunk text_ size source_size target h hot of n words lines spans score predicted w ph place piece number near__id"
    rows = [(None, None), (1, None), (1, None), (2, ""), (3, texts[0]), (3, texts[0]), (None, texts[1]), (4, "word " * 120_000), (5, "é" * 300_000), (6, "a@b.co " * 3000), (7, texts[0] + " more")]
    extra = ", ".join(f"{c} string" for c in names.split())
    df = spark.createDataFrame([(d, t, None, None if (d or 0) % 3 else "s", None, *["x"] * len(names.split())) for d, t in rows], f"doc_id long, text string, lang string, source string, n_chars long, {extra}").repartition(3)
    labels = spark.createDataFrame([(3, 1, None), (None, 1, None), (4, 0, 1), (4, None, 0)], "doc_id long, quality int, toxic int")
    model = gam.train(df, labels)
    ids = Counter(d for d, _ in rows)
    for out in (line_rules.judge(df), pii.digest(pii.scan(df)), licenses.scan(df), mixing.mix(df), gam.classify(df, model), neardup.near_duplicates(df), pfp.dedup(df)):
        got = [tuple(v for k, v in r.asDict().items() if k not in ("copies", "taken")) for r in out.collect()]
        at = out.columns.index("doc_id")
        assert at == 0 and Counter(r[0] for r in got) == ids
        assert len({r for r in got if r[0] == 3}) == len({r for r in got if r[0] == 1}) == 1
    assert Counter(r.doc_id for r in packing.pack(packing.pieces(df)).where("piece = 0").collect()) == ids
    assert pii.redact(df).columns == neardup.keep_one(df).columns == mixing.repeat(df).columns == gam.keep_good(df, model).columns == df.columns
    none = df.where("false")
    assert gam.classify(none, model).count() == gam.keep_good(none, gam.train(none, labels)).count() == neardup.keep_one(none).count() == mixing.repeat(none).count() == pii.redact(none).count() == 0


def test_clean_copies_of_counts():
    assert Counter(brute.W.findall("a b\tc")) == Counter("abc")
