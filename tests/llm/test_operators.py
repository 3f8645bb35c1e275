"""The training-data operators against brute force, on small tables with every odd case."""

from __future__ import annotations

import gzip
import hashlib
import itertools
import json
import re
import unicodedata
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from sampledjoin.llm import ann, decontam, licenses, linededup, neardup, pii, secrets, spm, toxicity, warc
from sampledjoin.llm.common import cut, trim_driver

PROSE = [" ".join(f"w{(i * 37 + j * j * 11) % 997}" for j in range(60)) for i in range(30)]


def table(spark, rows):
    """doc_id and text, beside columns whose names clash with what operators add."""
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    return df.withColumn("hash", F.lit("x")).withColumn("band", F.lit(1)).withColumn("component", F.lit(2)).withColumn("n_chars", F.char_length("text").cast("bigint"))


@pytest.fixture(scope="module")
def odd(spark):
    return table(spark, [(1, None), (2, ""), (3, "one"), (3, "one"), (None, "two words"), (4, "long " * 30_000), (5, "\n\n"), (6, PROSE[0]), (7, PROSE[0])])


@pytest.fixture(scope="module")
def empty(spark):
    return table(spark, []).where("false")


def near_by_definition(rows, threshold=0.8):
    """doc_id: smallest doc_id of its class, by all pairs of weighted sets of word tuples with exact document frequencies."""
    sets = []
    for _, t in rows:
        w = re.findall(r"[^\W_]+", (t or "").lower())
        sets.append(Counter(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else Counter())
    df, n = Counter(x for s in sets for x in s), sum(map(bool, sets))
    weigh = lambda c: sum(k * np.log1p(n / df[x]) for x, k in c.items())
    parent = {i: i for i, _ in rows if i is not None}
    live = [(i, s) for (i, _), s in zip(rows, sets, strict=True) if i is not None and s]
    for x, (i, a) in enumerate(live):
        for j, b in live[:x]:
            if a.keys() & b.keys() and weigh(a & b) >= threshold * weigh(a | b) * (1 - 1e-12):
                lo, hi = sorted((parent[i], parent[j]))
                parent = {k: lo if v == hi else v for k, v in parent.items()}
    return parent


def near_found(spark, rows):
    return {r.doc_id: r.class_id for r in neardup.near_classes(table(spark, rows)).collect() if r.doc_id is not None}


def test_near_classes_match_brute_force(spark):
    rows = [(i, t) for i, t in enumerate(PROSE[:8])]
    rows += [(20, PROSE[0]), (21, PROSE[1].upper() + "!"), (22, PROSE[2] + " tail end"), (23, " ".join(PROSE[3].split()[:30] + ["x"] * 30)), (24, ""), (25, None), (None, PROSE[5]), (26, "two words"), (27, "two words"), (28, PROSE[7]), (28, PROSE[6])]
    got = near_found(spark, rows)
    assert got == near_by_definition(rows)
    assert {20: 0, 21: 1, 22: 2, 23: 23, 27: 26}.items() <= got.items() and got[7] == got[6] == got[28] == 6


def test_near_classes_of_a_hot_group_lose_no_link(spark):
    """Rows that are alike, many of them not alike enough: one text of 300 words whose last 1 to 12 words are exchanged."""
    base = [f"b{j}" for j in range(300)]
    rows = [(i, " ".join([*base[: 299 - i % 12], *(f"x{i}y{j}" for j in range(1 + i % 12))])) for i in range(150)]
    got, want = near_found(spark, rows), near_by_definition(rows)
    assert got == want and 2 < len(set(want.values())) < 150


def counted_shingles(text):
    w = text.split()
    return Counter(tuple(w[k : k + 5]) for k in range(len(w) - 4))


def classes_by_counts(rows, threshold=0.8):
    """As near_by_definition, all shingles weighing the same."""
    sets, parent = [counted_shingles(t) for _, t in rows], {i: i for i, _ in rows}
    for x, (i, _) in enumerate(rows):
        for y in range(x):
            if (sets[x] & sets[y]).total() >= threshold * (sets[x] | sets[y]).total():
                lo, hi = sorted((parent[i], parent[rows[y][0]]))
                parent = {k: lo if v == hi else v for k, v in parent.items()}
    return parent


@pytest.mark.parametrize("cell", [64, 4096])
def test_near_copies_of_a_large_group_are_found(spark, tmp_path, monkeypatch, cell):
    """Copies of one text, each with 1 to 5 words of its own, among other texts: by frequencies they grow apart as their group grows."""
    monkeypatch.setattr(neardup, "CELL", cell)
    g = np.random.default_rng(3)
    base = [f"b{j % 150}" for j in range(200)]  # some shingles stand there twice
    rows = [(i, " ".join(f"r{i}x{j}" for j in range(80))) for i in range(100)]
    for i in range(100):
        w = list(base)
        for j in g.choice(200, 1 + i % 5, replace=False):
            w[j] = f"y{i}x{j}"
        rows.append((1000 + i, " ".join(w)))
    want, by_weight = classes_by_counts(rows), near_by_definition(rows)
    table(spark, rows).write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r.class_id for r in neardup.op3(spark, str(tmp_path)).collect()}
    group = lambda c: Counter(c[i] for i, _ in rows if i >= 1000).most_common(1)[0][1]
    assert got == want and group(want) == 80 and group(by_weight) == 2


@pytest.mark.parametrize("tf", [1, 3])
def test_count_samples_agree_as_often_as_counted_sets_do(tf):
    g = np.random.default_rng(5)
    base = np.sort(g.integers(1 << 40, 1 << 63, 400, np.uint64))
    with np.errstate(over="ignore"):
        x, y = (neardup.count_samples(v, np.full(len(v), tf), np.array([0]), 512, 9) for v in (base[:360], base[40:]))
        z = neardup.count_samples(base, np.full(400, 2 * tf), np.array([0]), 512, 9)
        w = neardup.count_samples(base, np.full(400, tf), np.array([0]), 512, 9)
    assert abs((x == y).mean() - 0.8) < 0.08 and abs((z == w).mean() - 0.5) < 0.1


@pytest.mark.parametrize("cell", [64, 4096])
def test_near_classes_search_a_hot_band_to_its_end(spark, monkeypatch, cell):
    """One band that all rows share, and no other."""
    made = neardup.sketches
    monkeypatch.setattr(neardup, "CELL", cell)
    monkeypatch.setattr(neardup, "sketches", lambda *a: made(*a).withColumn("bands", F.array(F.lit(1).cast("bigint"))))
    rows = [(i, " ".join(f"r{i}x{j}" for j in range(60))) for i in range(200)]
    assert near_found(spark, [*rows, (500, rows[77][1] + " more")]) == {i: i for i, _ in rows} | {500: 77}


def test_cells_of_a_hot_band_hold_every_pair(spark, monkeypatch):
    monkeypatch.setattr(neardup, "CELL", 8)
    rows = [(i, [7, *(1000 * k + i for k in range(1, 16))]) for i in range(60)] + [(i, [9, *range(10**6 * i, 10**6 * i + 15)]) for i in (70, 71)]
    held: dict[int, set] = {}
    for r in neardup.cells(spark.createDataFrame(rows, "doc_id bigint, bands array<bigint>")).collect():
        held.setdefault(r.cell, set()).add(r.doc_id)
    pairs = {(i, j) for c in held.values() for i in c for j in c if i < j}
    assert {(i, j) for i in range(60) for j in range(i + 1, 60)} | {(70, 71)} == pairs and max(map(len, held.values())) <= 40


def test_near_classes_weigh_by_exact_frequencies(spark, monkeypatch):
    made = neardup.document_frequencies
    full = lambda d: neardup.Frequencies(made(d).n, np.maximum(made(d).codes, 65))  # noqa: E731  as full as the counters of a large table
    monkeypatch.setattr(neardup, "document_frequencies", full)
    common = [" ".join(f"c{k}x{j}" for j in range(24)) for k in range(2)]  # 20 shingles each
    own = " ".join(f"u{j}" for j in range(84))  # 80 shingles
    rows = [(i, f"{common[i % 2]}\n" + " ".join(f"r{i}x{j}" for j in range(120))) for i in range(400)]
    idf = lambda df: np.log1p(402 / df)
    assert 80 * idf(2) / (80 * idf(2) + 40 * idf(201) + 8 * idf(1)) >= 0.8 > 80 / (80 + 48)
    assert near_found(spark, [*rows, (500, f"{common[0]} {own}"), (501, f"{common[1]} {own}")]) == {i: i for i, _ in rows} | {500: 500, 501: 500}


def test_counters_bound_exact_frequencies(spark):
    rows = [(i, f"{PROSE[i % 5]} z{i}") for i in range(40)]
    f = neardup.document_frequencies(table(spark, rows))
    (h, _), = neardup.weighted_sets([PROSE[0]])
    bound = f.n / np.expm1(f.weight(h).astype(float))
    assert f.n == 40 and (bound >= 7.99).all() and np.median(bound) < 9.6


@pytest.mark.parametrize(("held", "row"), [(1 << 20, 1024), (100, 16)])
def test_exact_frequencies_are_looked_up_one_row_each(spark, monkeypatch, held, row):
    """However many tasks the copies of a text are dealt over, and without a further pass over the texts."""
    monkeypatch.setattr(neardup, "HELD", held)
    monkeypatch.setattr(neardup, "ROW", row)
    rows = [(i, f"{PROSE[i % 5]} z{i}") for i in range(40)]
    want = Counter(x for v, _ in neardup.weighted_sets([t for _, t in rows]) for x in v.view(np.int64).tolist())
    every = spark.sparkContext.broadcast(neardup.Wanted(np.full(1 << (neardup.WANTED_BITS - 3), 255, np.uint8)))
    counted = neardup.frequency_table(table(spark, rows).repartition(16))
    got = neardup.exact_frequencies(counted, every).collect()
    assert sorted((r.shingle, r.df) for r in got) == sorted((x, n) for x, n in want.items() if n > 1)
    assert set(want.values()) == {1, 8} and neardup.document_frequencies(counted).n == 40


def test_the_drivers_freed_memory_goes_back(spark):
    assert trim_driver(spark)


def test_weighted_samples_agree_as_often_as_sets_do():
    g = np.random.default_rng(5)
    base = np.sort(g.integers(1 << 40, 1 << 63, 400, np.uint64))
    a, b = base[:360], base[40:]
    s = neardup.Sampler()
    with np.errstate(over="ignore"):
        x, y = (s.samples(v, np.zeros(len(v), np.float32), np.array([0])) for v in (a, b))
    assert abs((x == y).mean() - 320 / 400) < 0.2


def test_components(spark):
    links = spark.createDataFrame([(2, 1), (3, 2), (9, 8), (5, 4), (6, 5), (6, 3)], "a bigint, b bigint")
    assert dict(tuple(r) for r in neardup.components(links).collect()) == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 6: 1, 8: 8, 9: 8}


def test_leaks_match_brute_force(spark):
    items = [(1, " ".join(PROSE[0].split()[5:40])), (2, PROSE[9]), (3, "tiny"), (4, None), (5, " ".join(PROSE[1].split()[:12]))]
    long = " ".join([*PROSE[10:25], items[0][1], *PROSE[25:]])
    docs = [(1, long), (2, PROSE[2]), (3, "tiny"), (4, None), (5, " ".join(PROSE[9].split()[:52])), (6, PROSE[1]), (6, PROSE[1])]
    shingle = lambda t: {tuple(w[k : k + 5]) for w in [re.findall(r"\w+", (t or "").lower())] for k in range(max(1, len(w) - 4)) if w}
    want = sorted((i, j) for i, t in docs for j, q in items if shingle(q) and (len(shingle(q) & shingle(t)) >= 0.8 * len(shingle(q))) and len(shingle(q) & shingle(t)))
    got = sorted((r.doc_id, r.item_id) for r in decontam.leaks(table(spark, docs), spark.createDataFrame(items, "item_id bigint, text string")).collect())
    assert got == want and (1, 1) in got and (6, 5) in got


def test_leaks_of_short_items_are_all_found(spark):
    items = [(i, " ".join(f"s{i}x{j}" for j in range(5 + i % 2))) for i in range(200)]
    docs = [(i, f"{PROSE[i % 30]} {t} {PROSE[(i + 1) % 30]}") for i, t in items]
    got = sorted((r.doc_id, r.item_id) for r in decontam.leaks(table(spark, docs), spark.createDataFrame(items, "item_id bigint, text string")).collect())
    assert got == [(i, i) for i, _ in items]


def test_line_dedup_matches_brute_force(spark):
    a, b = "A line that is long enough", "another line, also long enough"
    rows = [(1, f"{a}\nx\n{b}"), (2, f"  {a.upper()} \ny"), (3, f"{a}\t\n{a}\nz"), (4, b), (5, None), (6, ""), (7, f"short\n{b}\n\n")]
    want = {}
    held: dict[str, set] = {}
    key = lambda x: x.strip("\x20\x09\x0a\x0b\x0c\x0d").translate(str.maketrans(linededup.UPPER, linededup.LOWER))
    for i, t in rows:
        for x in (t or "").split("\n"):
            held.setdefault(key(x), set()).add(i)
    for i, t in rows:
        xs = (t or "").split("\n")
        kept = [x for x in xs if not (len(key(x)) >= 20 and len(held[key(x)]) >= 3 and max(held[key(x)]) != i)]
        want[i] = (len(xs), len(xs) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest())
    out = linededup.drop_common_lines(table(spark, rows)).select("doc_id", "line_total", "line_dropped", F.sha2("line_text", 256)).collect()
    assert {r[0]: tuple(r[1:]) for r in out} == want


def test_secrets_base_equals_finditer(spark):
    texts = ['token = "abcdef123" password:xyz', "AKIA" + "Z9" * 9 + " akia", "f" * 23 + " " + "0a" * 20, "Secret=short api_key='longenough1'", None, "", "passwordtoken=abcdefgh", "İtoken=abcdefg1"]
    assign = re.compile(secrets.ASSIGN.pattern, re.I | re.A)
    for t in texts:
        spans = [(m.start(), m.end(), "assign") for m in assign.finditer(t or "") if len(m[2]) >= 6]
        spans += [(m.start(), m.end(), "access") for m in re.finditer("AKIA[A-Z0-9]+", t or "") if m.end() - m.start() >= 20]
        spans += [(m.start(), m.end(), "hex") for m in re.finditer("[0-9a-f]+", t or "") if m.end() - m.start() >= 24]
        spans.sort(key=lambda s: (s[0], secrets.KINDS.index(s[2])))
        assert [s for s in secrets.scan(t, secrets.automaton()) if s[2] in secrets.KINDS[:3]] == spans
    body = "A" * 30
    good, bad = f"ghp_{body}{secrets.crc_suffix(body)}", f"ghp_{body}000000"
    found = [s[2] for s in secrets.scan(f"{good} {bad}", secrets.automaton())]
    assert found.count("github") == 1
    rows = secrets.find_secrets(table(spark, list(enumerate(texts)))).collect()
    assert len(rows) == len(texts) and rows[0].n_assign == 1
    assert "[assign]" in secrets.redact(table(spark, [(1, texts[0])])).first().text


def test_surrogates_keep_form_and_stay_distinct(spark):
    s = pii.Surrogates()
    digits = {"".join(map(str, s.permute([a, b, c], [10, 10, 10], "t"))) for a in range(10) for b in range(10) for c in range(10)}
    assert len(digits) == 1000 and all(s.permute([a, b], [10, 10], "u") != [a, b] for a in range(10) for b in range(10))
    card = "4111 1111 1111 1111"
    new = re.sub(r"\D", "", s.replace("card", card))
    assert new != card.replace(" ", "") and pii.luhn(new[:-1]) == int(new[-1]) and new[0] == "4"
    assert pii.mod97(s.replace("iban", "DE89370400440532013000")) == 1
    assert s.replace("email", "Ann@x.org").lower() == s.replace("email", "ann@X.org").lower()
    name = s.replace("name", "f/Anna Schmidt")
    assert name.split()[0].lower() in pii.GIVEN["latin", "f"] and name.split()[0] != "Anna"
    text = "Frau Anna Schmidt, ann.b@mail.example.com, +1 (499) 555-6503, 8.196.197.208, 123-45-6789 on 2024-01-02; again ANN.B@mail.example.com."
    docs = table(spark, [(1, text), (2, None), (3, ""), (4, text)])
    out = pii.replace_entities(docs)
    rows = {r.doc_id: r for r in out.collect()}
    assert [e.kind for e in rows[1].pii_entities] == ["name", "email", "phone", "ip", "ssn", "email"]
    assert rows[1].text == rows[4].text and "2024-01-02" in rows[1].text and "Schmidt" not in rows[1].text and "6503" not in rows[1].text
    assert rows[2].text is None and rows[3].text == "" and pii.collisions(out).count() == 0


def test_surrogates_match_gender_and_cover_all_letters(spark, tmp_path):
    s = pii.Surrogates()
    for gender in "fm":
        new = [s.replace("name", f"{gender}/{n} Novak").split(" ")[0] for n in ("Zuzana", "Zuzanb", "Łukasz", "Արամ")]
        assert len(set(new)) == 4 and all(pii._WHO[n.split("-")[0].lower()][1] == gender for n in new)
    assert s.replace("name", "f/Светозара Новак").split("-")[0].lower() in pii.GIVEN["cyrillic", "f"]
    for c in "łøšžßÆŁԱאم漢":
        assert s.like(c, "t") != c and s.like(c, "t").isalpha()
    assert s.replace("name", "m/Արամ") != "Արամ" and pii.canonical("ip", "010.0.0.1") == pii.canonical("ip", "10.0.0.1")
    table(spark, [(1, "Mrs Zuzana Novak at 10.0.0.1"), (2, "Mrs ZUZANA Novak at 010.0.0.1"), (3, "Mr Zuzana Novak"), (4, "Dr Zuzana Novak")]).write.parquet(f"{tmp_path}/documents.parquet")
    rows = pii.op1(spark, str(tmp_path)).collect()
    assert len(rows) == 4 and all(r.n_collisions == 0 for r in rows) and len({r.text.lower() for r in rows}) == 3


def test_surrogates_of_one_name_in_two_spellings_agree(spark):
    s = pii.Surrogates()
    texts = [unicodedata.normalize(f, "Señor José Núñez called Ελένη Παππά on 12.05.2024 and 3/4/1999 and 2024.05.12.") for f in ("NFC", "NFD")]
    found = [[(k, pii.canonical(k, e), s.replace(k, e)) for _, _, k, e in pii.detect(t)] for t in texts]
    assert found[0] == found[1] and [k for k, _, _ in found[0]] == ["name", "name"]
    rows = pii.replace_entities(table(spark, list(enumerate(texts)))).collect()
    assert unicodedata.normalize("NFC", rows[0].text) == unicodedata.normalize("NFC", rows[1].text) and "Núñez" not in rows[0].text and "12.05.2024" in rows[0].text


def test_licenses(spark):
    mit = licenses.TEMPLATES["MIT"]
    docs = [(1, "Prose here.\nReleased under the MIT License.\nmore"), (2, mit.upper().replace(" ", "\n", 3)), (3, PROSE[0]), (4, None), (5, "Licensed under the Apache License, Version 2.0."), (6, "mit")]
    got = {r.doc_id: (r.licenses, round(r.best_dice, 3)) for r in licenses.scan_licenses(table(spark, docs)).collect()}
    assert got[1] == ("MIT-notice", 1.0) and got[2] == ("MIT", 1.0) and got[3] == got[4] == got[6] == ("", 0.0) and got[5] == ("Apache-2.0-notice", 1.0)


def test_licenses_within_longer_texts_match_brute_force(spark):
    def best(text, template):
        grams = lambda w: {*zip(w, w[1:], strict=False)}
        w, t = re.findall(r"[^\W_]+", text.lower()), grams(template.split())
        return max((2 * len(g & t) / (len(g) + len(t)) for a in range(len(w)) for b in range(a + 2, min(len(w), a + 2 * len(t)) + 1) for g in [grams(w[a:b])]), default=0)

    mit, short = licenses.TEMPLATES["MIT"].split(), {k: licenses.TEMPLATES[k] for k in ("MIT", "MIT-notice")}
    parts = "\n\n".join(" ".join(mit[k : k + 60]) for k in range(0, len(mit), 60))
    docs = [(1, f"{PROSE[0]}\n\n{parts}\n\n{PROSE[1]}"), (2, f"{PROSE[2]} this project is released under the MIT license see LICENSE {PROSE[3]}"), (3, f"{PROSE[4]} {' '.join(mit[:80])} {PROSE[5]}"), (4, PROSE[6] + " license")]
    got = {r.doc_id: (r.n_matches, r.licenses, r.best_dice) for r in licenses.scan_licenses(table(spark, docs), short).collect()}
    for i, text in docs:
        want = {k: best(text, t) for k, t in short.items()}
        assert got[i][1] == ",".join(k for k in sorted(want) if want[k] >= 0.8) and got[i][2] == round(max([x for x in want.values() if x >= 0.8], default=0), 6)
    assert [got[i][:2] for i, _ in docs] == [(1, "MIT"), (1, "MIT-notice"), (0, ""), (0, "")]


def test_lines_are_dropped_whatever_other_columns_are_called(spark):
    line = "a line that three documents have"
    rows = [(i, f"{line}\nown {i}\n{line}") for i in (1, 2, 3)] + [(3, f"other\n{line}"), (3, f"other\n{line}"), (None, line)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    for c in ("doomed", "doomed_id", "line_left", "line_total", "line_text", "lost", "hash", "row", "kept", "n", "keeper"):
        docs = docs.withColumn(c, F.lit(f"mine {c}"))
    out = linededup.line_stage(spark, docs, "")
    assert out.columns == docs.columns
    got = out.collect()
    assert all(r[c] == f"mine {c}" for r in got for c in docs.columns[2:])
    assert sorted((r.doc_id or 0, r.text) for r in got) == sorted([(1, "own 1"), (2, "own 2"), *((i or 0, t) for i, t in rows[2:])])
    assert {r.line_total for r in linededup.drop_common_lines(docs).collect()} == {1, 2, 3}


def test_line_dedup_of_a_very_long_text(spark):
    rows = [(i, "\n".join(f"line number {j} of a long text" for j in range(40_000))) for i in range(3)]
    got = {r.doc_id: (r.line_dropped, len(r.line_text)) for r in linededup.drop_common_lines(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert got == {0: (40_000, 0), 1: (40_000, 0), 2: (0, len(rows[2][1]))}


def test_warc_keeps_repeated_headers_and_reads_files(spark, tmp_path):
    def record(kind, block, *fields):
        return warc.Record([("WARC-Type", kind), ("WARC-Record-ID", "<urn:uuid:1>"), ("WARC-Date", "2020-01-02T03:04:05Z"), ("WARC-Target-URI", "http://a.example/"), *fields], block)

    block = b"HTTP/1.1 404 Gone\r\nSet-Cookie: a=1\r\nX-Long: one\r\n  two\r\nset-cookie: b=2\r\nContent-Type: text/html\r\n\r\n<p>Hi</p>"
    source = record("response", block, ("WARC-Concurrent-To", "<x>"), ("WARC-Concurrent-To", "<y>"))
    meta = json.loads(warc.derivatives(source)[0].block)["Envelope"]
    http = meta["Payload-Metadata"]["HTTP-Response-Metadata"]
    assert http["Headers"] == {"Set-Cookie": ["a=1", "b=2"], "X-Long": "one two", "Content-Type": "text/html"} and http["Response-Message"] == "HTTP/1.1 404 Gone"
    assert meta["WARC-Header-Metadata"]["WARC-Concurrent-To"] == ["<x>", "<y>"]
    data = record("warcinfo", b"x").to_bytes() + source.to_bytes() + record("request", b"GET").to_bytes() + source.to_bytes()
    (tmp_path / "a.warc").write_bytes(data[:-12])  # its last record is cut
    (tmp_path / "b.warc.gz").write_bytes(b"".join(gzip.compress(r.to_bytes()) for r in (source, record("request", b"GET"), source)) + b"\x1f\x8bcut")
    (tmp_path / "c.warc").write_bytes(b"")
    rows = warc.read_warc(spark, f"file://{tmp_path}").collect()
    assert len(rows) == 2 * 3 and {r.block for r in rows if r.record_type == "conversion"} == {"Hi"} and {(r.refers_to, r.warc_date) for r in rows} == {("<urn:uuid:1>", "2020-01-02T03:04:05Z")}


def test_warc_of_odd_pages(spark):
    pages = spark.createDataFrame([(None, "u", "<p>x"), (1, "u", ""), (1, "u", ""), (2, None, None)], "page_id bigint, url string, html string").withColumn("block", F.lit(1)).withColumn("refers_to", F.lit("me"))
    rows = warc.build_derivatives(pages).collect()
    assert len(rows) == 8 and sum(r.page_id is None for r in rows) == 2 and len({r.record_id for r in rows}) == 6
    assert warc.build_derivatives(pages.where("false")).count() == 0


def test_warc_round_trip(spark):
    pages = spark.createDataFrame([(1, "http://a.example/x", "<html><title>T &amp; U</title><body><p>Hi<br>there</p><a href='/y'>l</a><script>no()</script></body>"), (2, None, None), (3, "u", "<p>open")], "page_id bigint, url string, html string")
    rows = warc.build_derivatives(pages).collect()
    assert len(rows) == 6
    meta, text = rows[0], rows[1]
    assert meta.refers_to == text.refers_to == warc.response(1, "http://a.example/x", pages.first().html).get("WARC-Record-ID")
    assert text.block == "Hi\nthere\nl" and '"Title":"T & U"' in meta.block and "http://a.example/y" in meta.block
    assert text.block_digest == warc.digest(text.block.encode()) and text.content_length == len(text.block.encode())
    data = b"".join(r.record for r in warc.record_bytes(warc.build_derivatives(pages)).collect())
    back = list(warc.parse(data))
    assert len(back) == 6 and back[1].block == text.block.encode() and back[1].get("WARC-Refers-To") == text.refers_to


@pytest.mark.parametrize("size", [64, 300])
def test_scan_equals_library(spark, size):
    model = spm.read_model()
    lattice = spm.lattice_of(model)
    texts = [PROSE[0], "x" * 500, "nospacehereatall" * 40, "  lead and   runs    of blanks  " * 9, "日本語テキスト🙂" * 60, "mixed\n\nlines\tand tabs " * 20, "a" + " " * 300 + "b", "▁▁ odd ▁ sign " * 20]
    docs = table(spark, list(enumerate(texts)) + [(None, texts[0]), (3, texts[3])])
    got = [(r.doc_id, r.spm_ids) for r in spm.encode(docs, model, size).collect()]
    assert len(got) == len(texts) + 2
    assert all(ids == lattice.sp.encode(texts[i if i is not None else 0]) for i, ids in got)
    back = spm.decode(spm.encode(docs.where("doc_id < 7"), model, size), model)
    assert back.where("text <> spm_text").count() == 0


class Toy(spm.Lattice):
    """A unigram model of a few pieces; no piece, and no text of its tests, has a blank."""

    def __init__(self):
        self.id = {p: i for i, p in enumerate(["a", "b", "c", "ab", "bc", "abc", "ca", "bca", "aa"])}
        self.score = dict(zip(self.id, [-2.0, -2.1, -2.2, -3.0, -3.3, -4.9, -3.1, -4.2, -3.9], strict=True))
        self.longest, self.bpe = 3, False


def test_scan_of_a_unigram_model_is_the_best_path(monkeypatch):
    lattice, g = Toy(), np.random.default_rng(6)
    monkeypatch.setattr(spm, "FAN", 3)
    for n in (1, 2, 7, 40, 101):
        x = "".join(g.choice(list("abc"), n))
        best = [(0.0, ())]
        for j in range(1, n + 1):
            best.append(max((best[i][0] + lattice.score[x[i:j]], (*best[i][1], lattice.id[x[i:j]])) for i in range(max(0, j - 3), j) if x[i:j] in lattice.score))
        for size in (3, 8):
            count = max(1, n // size)
            bounds = [(k * size, n if k == count - 1 else (k + 1) * size) for k in range(count)]
            chunks = [spm.Chunk(lattice, x, 0, lo, hi, n) for lo, hi in bounds]
            ms = [c.matrix() for c in chunks]
            states = spm.inner_states(ms, spm.BEGIN, spm.END)
            ids = [i for c, a, b in zip(chunks, states, states[1:], strict=False) for i in c.trace(a, b)]
            assert abs(sum(lattice.score[p] for i in ids for p in [list(lattice.id)[i]]) - best[n][0]) < 1e-9
            whole = ms[0]
            for m in ms[1:]:
                whole = spm.product(whole, m)
            pairs = [spm.product(ms[k], ms[k + 1]) if k + 1 < len(ms) else ms[k] for k in range(0, len(ms), 2)]
            again = pairs[0]
            for m in pairs[1:]:
                again = spm.product(again, m)
            assert abs(whole[spm.BEGIN, spm.END] - best[n][0]) < 1e-9 and abs(again[spm.BEGIN, spm.END] - best[n][0]) < 1e-9


def test_scan_by_a_tree_of_several_levels(spark, monkeypatch):
    monkeypatch.setattr(spm, "FAN", 3)
    model = spm.read_model()
    texts = ["nospacehereatall" * 60, " ".join(PROSE[:4]), "ab" * 200]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").withColumn("spm_key", F.lit("mine")).withColumn("key", F.lit("mine too"))
    got = spm.encode(docs, model, 32).collect()
    assert all(r.spm_ids == spm.lattice_of(model).sp.encode(texts[r.doc_id]) and (r.spm_key, r.key) == ("mine", "mine too") for r in got) and len(got) == 3


def test_grammar_matches_its_definition():
    T = toxicity
    table, scope = T.grammar(), range(6)
    for word in itertools.product(scope, repeat=5):
        want, near = Counter(), lambda kind, i, n: any(word[j] == kind for j in range(max(0, i - n), i))  # noqa: B023,E731
        for i, s in enumerate(word):
            seen = T.TARGET in word[:i]
            since = max((j + 1 for j in range(i) if word[j] == T.TARGET), default=0)
            insult = threat = None
            if s == T.INSULT:
                insult = "targeted" if seen else "plain"
            if s == T.THREAT:
                threat = "plain"
            if s == T.TARGET and not seen and near(T.INSULT, i, T.REACH):
                insult = "targeted"
            if s == T.TARGET and any(word[j] == T.THREAT for j in range(max(since, i - T.REACH), i)):
                threat = "threat"
            if insult or threat:
                want["negated" if near(T.NEGATION, i, T.SCOPE) else "reported" if near(T.REPORT, i, i) else "threat" if threat == "threat" else "targeted" if insult == "targeted" else "plain"] += 1
        out = np.zeros(len(T.CELLS))
        T.read_clause(np.array(word), np.ones(5), (0, 0.0), out, table)
        assert {c: n for c, n in zip(T.CELLS, out, strict=True) if n} == want


def test_a_clause_goes_on_over_pieces(monkeypatch):
    lexicon = toxicity.Lexicon([])
    text = "they said " + "word " * 200 + "idiot. " + "you " + "word " * 150 + "idiot"
    whole = toxicity.cells([text], lexicon)
    monkeypatch.setattr(toxicity, "cut", lambda t: cut(t, 64))
    assert (toxicity.cells([text], lexicon) == whole).all() and whole[0, toxicity.CELLS.index("reported")] and whole[0, toxicity.CELLS.index("targeted")]


def test_toxicity_learns_and_holds_out(spark):
    words = ["alpha", "bravo", "delta", "gamma", "omega"]
    rows = [(i, " ".join(words[(i * j) % 5] + str((i * j) % 13) for j in range(1, 40)) + (". zorgblat" + str(i % 3) + " you zorgblatish." if i % 4 == 0 else ".")) for i in range(400)]
    docs = table(spark, [*rows, (900, None), (901, "")])
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i, _ in rows], "doc_id bigint, toxic int")
    model = toxicity.fit(docs, labels)
    out = {r.doc_id: r for r in toxicity.score(docs, model).collect()}
    held = [i for i, _ in rows if zlib.crc32(str(i).encode()) % 4 == 2]
    assert sum(out[i].tox_predicted == (i % 4 == 0) for i in held) >= 0.95 * len(held)
    assert out[900].tox_predicted == out[901].tox_predicted == 0
    texts = ["you idiot", "idiot", "not an idiot", "he said idiot", "will kill him", "what an idiot he is", "hello"]
    found = toxicity.cells(texts, toxicity.Lexicon([]))
    assert [toxicity.CELLS[len(toxicity.CELLS) - 1 - r[::-1].argmax()] for r in found[:6]] == ["targeted", "plain", "negated", "reported", "threat", "targeted"] and found[6].sum() == 0


def test_toxicity_learns_nothing_from_held_out_rows(spark):
    rows = [(i, f"word{i % 7} " * 20 + ("zorgblat you" if i % 4 == 0 else "")) for i in range(300)]
    labels = [(i, int(i % 4 == 0)) for i, _ in rows]
    held = lambda i: zlib.crc32(str(i).encode()) % 4 == 2
    docs = table(spark, rows)
    models = [toxicity.fit(docs, spark.createDataFrame([(i, 1 - y if held(i) and flip else y) for i, y in labels], "doc_id bigint, toxic int")) for flip in (False, True)]
    assert sorted(models[0].stems) == sorted(models[1].stems) and np.allclose(models[0].weights, models[1].weights)


def test_nearest_match_brute_force(spark):
    g = np.random.default_rng(3)
    x = g.normal(size=(600, 16)).astype(np.float32)
    x[5] = x[6] = x[0]
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x)] + [(700, None), (701, [0.0] * 16), (702, [float("nan")] * 16), (703, [1.0, None] * 8), (704, [1.0]), (None, [1.0] * 16)]
    v = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>")
    got: dict[int, list] = {}
    for r in ann.nearest(v, F.col("vec_id") % 20 == 0).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append(r.vec_id)
    x64, hits = x.astype(np.float64), 0
    for q, found in got.items():
        s = x64 @ x64[q]
        s[q] = -np.inf
        hits += len(set(np.lexsort((np.arange(600), -s))[:20].tolist()) & set(found))
    assert len(got) == 30 and all(len(f) == 20 for f in got.values()) and hits >= 0.9 * 600
    few = ann.nearest(v.where("vec_id < 6"), F.col("vec_id") % 20 == 0).orderBy("rank").collect()
    assert len(few) == 5 and few[0].vec_id == 5
    assert ann.nearest(v.where("false"), F.col("vec_id") % 20 == 0).count() == 0


@pytest.mark.parametrize("kind", ["norms", "clusters"])
def test_nearest_of_other_rows_reach_their_recall(spark, kind):
    """Vectors of very different norms, and tight clusters of which one is asked for more than it holds."""
    g = np.random.default_rng(8)
    n, d = 6000, 48
    x = g.normal(size=(n, d)) if kind == "norms" else g.normal(size=(90, d))[g.integers(90, size=n)] + 0.3 * g.normal(size=(n, d))
    x = (x * np.exp(g.normal(size=n))[:, None] if kind == "norms" else x).astype(np.float32)
    v = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id bigint, embedding array<float>")
    got: dict[int, set] = {}
    for r in ann.nearest(v, F.col("vec_id") % 20 == 0).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    q, x = np.arange(0, n, 20), x.astype(np.float64)
    s = x[q] @ x.T
    s[np.arange(len(q)), q] = -np.inf
    hits = sum(len(got[i] & set(top.tolist())) for i, top in zip(q.tolist(), np.argpartition(-s, 20, 1)[:, :20], strict=True))
    assert set(map(len, got.values())) == {20} and hits >= 0.95 * 20 * len(q)


def test_odd_rows_and_empty_tables(spark, odd, empty):
    labels = spark.createDataFrame([(1, None, 0), (3, 1, None)], "doc_id bigint, quality int, toxic int")
    items = spark.createDataFrame([(1, None), (None, PROSE[0])], "item_id bigint, text string")
    for docs in (odd, empty):
        n = docs.count()
        assert neardup.near_classes(docs).count() == n
        assert linededup.drop_common_lines(docs).count() == n
        assert licenses.scan_licenses(docs).count() == n
        assert secrets.find_secrets(docs).count() == n
        assert spm.encoded(docs).count() == n
        assert pii.replace_entities(docs).count() == n
        assert toxicity.score(docs, toxicity.fit(docs, labels)).count() == n
        assert decontam.leaks(docs, items).count() == (2 if n else 0)


def test_pipeline_matches_brute_force(spark, tmp_path):
    """Planted documents through all stages, against a plain rendering of each rule."""
    import corpus_pipeline

    common = "this line stands in many of the documents"
    rows = [(i, f"{t}\n{common}") for i, t in enumerate(PROSE[:6])]
    rows += [(10, f"{PROSE[0]} tail"), (11, "you idiot. you idiot. shut up you moron, you idiot. " * 3), (12, f"{PROSE[7]} {PROSE[20]} {PROSE[8]}"), (13, ""), (14, None), (15, PROSE[9]), (16, PROSE[9])]
    items = [(1, PROSE[20]), (2, "none of this is there at all in the end")]
    spark.createDataFrame(rows, "doc_id bigint, text string").withColumn("n_chars", F.char_length("text").cast("bigint")).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(items, "item_id bigint, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame([], "doc_id bigint, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    left = [(i, t) for i, t in rows if "idiot" not in (t or "")]
    last = max(i for i, t in left if common in (t or ""))
    left = [(i, (t or "") if i == last else "\n".join(x for x in (t or "").split("\n") if x != common)) for i, t in left]
    classes = near_by_definition(left)
    left = [(i, t) for i, t in left if classes[i] == i]
    shingle = lambda t: {tuple(w[k : k + 5]) for w in [re.findall(r"\w+", t.lower())] for k in range(len(w) - 4)}
    left = [(i, t) for i, t in left if all(len(shingle(q) & shingle(t)) < 0.8 * len(shingle(q)) for _, q in items)]
    want = {i: spm.lattice_of(spm.read_model()).sp.encode(t) for i, t in left}
    got = {r.doc_id: r.ids for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert got == want and {10, 11, 12, 16}.isdisjoint(got) and {0, 5, 13, 14, 15} <= got.keys()


def test_pipeline_stages_keep_columns(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    want = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.common.materialise(stage(spark, docs, sf), name)
        assert docs.columns == want and docs.count() > 100
    out = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert out.count() == docs.count() and out.where("not round_trip").count() == 0
