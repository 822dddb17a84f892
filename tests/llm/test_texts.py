"""Toxicity, fingerprints, personal data, licences, URLs, language model and HTML against brute force."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from joincluster.llm import fingerprints, hmm, html_extract, licenses, pii, toxicity, urlfilter

WORDS = [f"w{i}" for i in range(300)]


# ---- toxicity


def test_search_is_exact():
    rng = np.random.default_rng(0)
    x = rng.random((500, 20)) * (rng.random((500, 20)) < 0.15)
    x = x[x.any(1)]
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    index = toxicity.BlockMaxIndex.of(np.arange(len(x)), np.zeros(len(x), int), x)
    q = x[:80]
    at, sim = index.search(q, 5)
    full = np.round(q @ index.rows.T, 9)
    for i in range(len(q)):
        best = sorted(((-s, index.ids[j]) for j, s in enumerate(full[i]) if s > 0))[:5]
        assert [(-s, index.ids[p]) for s, p in zip(sim[i], at[i], strict=True) if p >= 0] == [(b[0], b[1]) for b in best]
    skip = np.arange(10)
    assert all(s not in row for s, row in zip(skip, index.search(index.rows[:10], 5, skip)[0], strict=True))


def test_isotonic():
    x, y = toxicity.isotonic(np.array([1.0, 2, 3, 4]), np.array([0.0, 1, 0, 1]), np.ones(4))
    assert list(y) == [0, 0.5, 1] and list(x) == [1, 2.5, 4]


def toxic_corpus(n=400):
    rng = random.Random(1)
    rows, labels = [], []
    for i in range(n):
        bad = i % 5 == 0
        w = [rng.choice(WORDS) for _ in range(60)]
        for _ in range(4 if bad else 0):
            w.insert(rng.randrange(60), rng.choice(["vile", "rotten", "nasty", "stinkzzz", "stinkyyy", "stinkxxx"]))
        rows.append((i, " ".join(w)))
        labels.append((i, 1, int(bad)))
    return rows, labels


def test_toxicity(spark, docs_of):
    rows, labels = toxic_corpus()
    rows += [(1000, None), (1001, ""), (1002, "vile rotten nasty"), (0, rows[0][1])]
    lab = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = toxicity.score(docs_of(rows), lab).collect()
    assert len(got) == len(rows)
    by = {r["doc_id"]: r for r in got}
    for i, _, y in labels:
        assert by[i]["predicted"] == y, i
        assert by[i]["held_out"] == (zlib.crc32(str(i).encode()) % 3 == 1)
    assert by[1002]["predicted"] == 1 and by[1002]["evidence"] and by[1000]["predicted"] == 0 and by[1001]["score"] == by[1000]["score"]
    held = {i for i, _, _ in labels if zlib.crc32(str(i).encode()) % 3 == 1}
    assert not any(e["doc_id"] in held for r in got for e in r["evidence"])
    kept = toxicity.keep_clean(docs_of(rows), lab)
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(r["doc_id"] for r in got if not r["predicted"])


def test_toxicity_without_labels(spark, docs_of):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert [r["predicted"] for r in toxicity.score(docs_of([(1, "a b")]), none).collect()] == [0]
    assert toxicity.score(docs_of([]), none).count() == 0


# ---- fingerprints


def test_edited_fingerprints(spark, docs_of, monkeypatch):
    monkeypatch.setattr(fingerprints, "RANGE_ROWS", 7)
    rng = random.Random(3)
    rows = [(i * 3, " ".join(rng.choice(WORDS) for _ in range(rng.randrange(0, 120)))) for i in range(60)] + [(1, "😀 é"), (2, ""), (4, None), (7, "same"), (8, "same")]
    got = {r["doc_id"]: r for r in fingerprints.edited_fingerprints(docs_of(rows)).collect()}
    order = sorted(((i, t or "") for i, t in rows), reverse=True)
    for k, (i, t) in enumerate(order):
        cut = len(t) // 3
        edited = t[: len(t) - cut] + order[(k + 1) % len(order)][1][:cut]
        assert got[i]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest() and got[i]["n_chars"] == len(t)
        assert 0 <= got[i]["near_edited"] <= 1 and 0 <= got[i]["near_next"] <= 1
    assert got[7]["fingerprint"] == got[8]["fingerprint"] and got[8]["near_next"] == 1.0
    assert got[2]["fingerprint"] == got[4]["fingerprint"]
    long = [r for r in got.values() if r["n_chars"] > 200]
    assert np.mean([r["near_edited"] > r["near_next"] for r in long]) > 0.7


def test_fingerprint_edges(spark, docs_of):
    assert fingerprints.edited_fingerprints(docs_of([])).count() == 0
    one = fingerprints.edited_fingerprints(docs_of([(5, "abcdef")])).first()
    assert one["edited_sha256"] == hashlib.sha256(b"abcdab").hexdigest() and one["near_next"] == 1.0
    assert fingerprints.edited_fingerprints(docs_of([(5, "a b"), (5, "a b"), (None, "x")])).count() == 3


# ---- personal data

BASE = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def base_spans(t):
    out = []
    for k, (name, p) in enumerate(BASE.items()):
        for m in re.finditer(p, t):
            d = re.sub("[^0-9]", "", m[0])
            back = sum((x - 9 if x > 9 else x) for x in (int(ch) * (1 + i % 2) for i, ch in enumerate(reversed(d))))
            if {"email": True, "ip": name == "ip" and all(int(x) <= 255 for x in m[0].split(".")), "card": 14 <= len(d) <= 19 and back % 10 == 0, "phone": 10 <= len(d) <= 15}[name]:
                out.append((m.start(), k, m.end(), name))
    return sorted(out)


TEXTS = [
    "a@b.com_x@d.ef mail", "1.2.3.4.5.6.7.8 999.1.1.1 0000000255.1.1.1 00000000000000000000000007.1.2.3", "x" * 3000 + "@y.z", "+1 (979) 555-6697 card 4111 1111 1111 1111-",
    "é😀 a.b@c.de 😀 1.2.3.4", "", None, "4111111111111111 1", "+12345678901234567 +1-2-3-4-5-6-7-8-9-0 )", "a@b a@b. @c.d a@-.x", "5500-0000-0000-0004,5500000000000004", "1" * 4000, "+" * 500 + "1",
]


def test_base_spans(spark, docs_of):
    rows = list(enumerate(TEXTS)) + [(3, TEXTS[3]), (3, TEXTS[3])]
    got = pii.find(docs_of(rows)).collect()
    assert len(got) == len(rows)
    by = {r["doc_id"]: r for r in got}
    for i, t in rows:
        want = base_spans(t or "")
        assert by[i]["base_sha256"] == hashlib.sha256(",".join(f"{n}:{s}:{e}" for s, _, e, n in want).encode()).hexdigest(), t
        assert [by[i][f"n_{k}"] for k in BASE] == [sum(n == k for *_, n in want) for k in BASE]
        assert all(f"{n}:{s}:{e}" in by[i]["spans"].split(",") for s, _, e, n in want)


def test_terms_that_give_values_away(spark, docs_of):
    rows = [(i, f"line {i} of Zaphodia wrote bob@site.org about things {i}") for i in range(4)] + [(100 + i, f"common words about the things and line {i} of text wrote on") for i in range(500)] + [(50, "carl@x.org wrote of line about things"), (51, "10.0.0.1 about things of line wrote")]
    got = {r["doc_id"]: r for r in pii.find(docs_of(rows)).collect()}
    for i in range(4):
        at = rows[i][1].index("Zaphodia")
        assert f"term:{at}:{at + 8}" in got[i]["spans"] and got[i]["n_term"] == 1, got[i]
    assert got[50]["n_term"] == got[51]["n_term"] == got[120]["n_term"] == 0
    df = docs_of(rows)
    clean = pii.sanitise(df)
    assert clean.columns == df.columns
    by = {r["doc_id"]: r for r in clean.collect()}
    assert by[2]["text"] == "line 2 of <TERM> wrote <EMAIL> about things 2" and by[2]["n_chars"] == len(by[2]["text"])
    assert by[120]["text"] == rows[4 + 20][1] and by[51]["text"].startswith("<IP> about")


def test_pii_empty(spark, docs_of):
    assert pii.find(docs_of([])).count() == 0 and pii.sanitise(docs_of([])).count() == 0
    got = pii.sanitise(docs_of([(1, None), (2, "+1 (979) 555-6697 x")])).orderBy("doc_id").collect()
    assert got[1]["text"] == "<PHONE> x"


# ---- licences


def test_licenses(spark, docs_of):
    rows = [(1, "Some prose.\nLicensed under the Apache License, Version 2.0.\nmore"), (2, "Released under the MIT License."), (3, "This work is licensed under the GNU General Public License, version 3."), (4, "Licensed under CC BY-NC 4.0."), (5, "the license fee is free"), (6, None), (7, ""), (8, "a licensed driver"), (2, "Released under the MIT License.")]
    rows += [(100 + i, f"plain prose number {i} of the corpus\nsecond line") for i in range(30)]
    got = licenses.scan(docs_of(rows)).collect()
    assert len(got) == len(rows)
    by = {r["doc_id"]: r for r in got}
    assert [by[i]["families"] for i in range(1, 9)] == ["apache-2.0", "mit", "gpl-3.0", "cc-by-nc-4.0", "", "", "", ""]
    assert by[1]["paragraphs"][0]["paragraph"] == 1 and by[1]["n_paragraphs"] == 3 and by[7]["n_paragraphs"] == 0
    assert all(by[100 + i]["families"] == "" for i in range(30))
    assert licenses.scan(docs_of([])).count() == 0


# ---- urls


def fitting(url):
    if url is None or "://" not in url:
        return "", "", None
    rest = url.split("://", 1)[1]
    host = re.split(r"[/?#]", rest, maxsplit=1)[0]
    path = re.split(r"[?#]", rest[len(host) :], maxsplit=1)[0]
    host = "".join(ch.lower() if "A" <= ch <= "Z" else ch for ch in host)
    best = None
    for key, _ in urlfilter.RULES:
        h, p = key.split("/", 1)
        if host and (host == h or host.endswith("." + h)) and path.startswith("/" + p) and (best is None or len(key) > len(best)):
            best = key
    return host, path, best


def test_urls(spark):
    urls = ["http://a.example.net/en/x", "https://EXAMPLE.net/en/", "http://example.net/en", "http://x.net", "http://x.net?/", "http://x.net/#a", "http://y.org/fr/1", "http://example.com/de/3?q", "http://notexample.com/de/", "http://spam-farm.example.org/a", "http://spam-farm.example.org/fr/a", "no scheme", None, "", "://", "http:///p", "a://b://c/d", "http://é.net/x", "http://user@x.net:80/", "http://net/", "http://www.spam-farm.de"]
    df = spark.createDataFrame(list(enumerate(urls)) + [(0, urls[0])], "page_id long, url string").withColumn("host", F.lit("x")).withColumn("key", F.lit(1))
    got = urlfilter.filter_urls(df).collect()
    assert len(got) == len(urls) + 1
    verdicts = dict(urlfilter.RULES)
    for r in got:
        host, path, rule = fitting(urls[r["page_id"]])
        bad = any(x in urlfilter.BLOCKED_LABELS for x in host.split("."))
        assert (r["host"], r["path"], r["rule"], r["verdict"]) == (host, path, rule, verdicts[rule] if rule else "block" if bad else "allow"), urls[r["page_id"]]
    assert urlfilter.filter_urls(df.limit(0)).count() == 0


def test_cascade_is_exact(spark):
    universe = spark.range(5000).select(F.concat(F.lit("k"), "id").alias("key"))
    listed = universe.where("key like '%7'")
    cascade = urlfilter.build_cascade(listed, universe, hashes=1)
    assert len(cascade.levels) > 1
    assert universe.where(cascade.listed(F.col("key")) != F.col("key").like("%7")).count() == 0
    assert urlfilter.list_by_join(universe, listed).count() == listed.count()
    assert urlfilter.build_cascade(listed.limit(0), universe).levels == []


# ---- language model


def test_forward_is_the_sum_over_paths():
    rng = np.random.default_rng(2)
    start, move, emit = rng.dirichlet(np.ones(2)), rng.dirichlet(np.ones(2), 2), rng.dirichlet(np.ones(4), 2)
    seqs = [np.array([0, 3, 1]), np.array([2, 2]), np.array([1])]
    import itertools

    for part, x, width in hmm._groups(seqs):
        _, scale = hmm.forward(x, width, start, move, emit.T.copy())
        place = np.concatenate([np.arange(n) for n in width])
        got = np.bincount(place, weights=np.log(scale))
        for i, s in zip(part, got, strict=True):
            want = sum(start[p[0]] * emit[p[0], seqs[i][0]] * math.prod(move[p[t - 1], p[t]] * emit[p[t], seqs[i][t]] for t in range(1, len(p))) for p in itertools.product(range(2), repeat=len(seqs[i])))
            assert s == pytest.approx(math.log(want))
        (a, b, e), _ = hmm.expected(x, width, start, move, emit.T.copy())
        assert a.sum() == pytest.approx(3) and b.sum() == pytest.approx(3) and e.sum() == pytest.approx(6)


def test_language_model(spark, docs_of):
    rng = random.Random(6)
    rows = [(i, " ".join(rng.choice(WORDS[:150] if i % 2 else WORDS[150:]) for _ in range(rng.randrange(20, 60)))) for i in range(300)] + [(900, None), (901, ""), (902, "Never seen Wörds"), (5, None), (903, "W1 w1"), (903, "W1 w1")]
    got = hmm.score(docs_of(rows)).collect()
    assert len(got) == len(rows)
    tok = lambda t: [w.encode() for w in re.split(r"[\x20\x09-\x0D]+", "".join(ch.lower() if "A" <= ch <= "Z" else ch for ch in t or "")) if w] + [b"\n"]
    out = lambda i: zlib.crc32(str(i).encode()) % 7 == 2
    n = collections.Counter(w for i, t in rows if not out(i) for w in tok(t))
    total, types = sum(n.values()), len(n)
    want = sorted((i, out(i), len(tok(t)), sum(n[w] > 0 for w in tok(t)), total, round(sum(math.log10((n[w] + 1) / (total + types + 1)) for w in tok(t)), 6)) for i, t in rows)
    assert want == sorted((r["doc_id"], r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 6)) for r in got)
    held = [r for r in got if r["held_out"] and r["n_tokens"] > 10]
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)
    assert all(r["score"] < 0 for r in got)
    assert hmm.score(docs_of([])).count() == 0


def test_rare_words_are_joined(spark, docs_of, monkeypatch):
    monkeypatch.setattr(hmm, "HELD", 20)
    monkeypatch.setattr(hmm, "CLASSES", 10)
    test_language_model(spark, docs_of)


# ---- html

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{{}}</style><script>var t="</p>";</script></head><body><nav><ul><li><a href="/a">{nav}</a></li></ul></nav><!-- x --><div class="ad">Buy {nav}</div>
<header>Site</header><article><h1>Head &amp; {i}</h1><p><b>One   two</b> thr<i>ee</i>.<br>four<p>Next &eacute; {i}</p><aside>side</aside><form><input value="a>b">go</form><ul><li>item</li></ul></article><section class="comments"><p>I say</p></section><footer>&copy; x</footer></body></html>"""


def test_article():
    got = html_extract.article(PAGE.format(i=3, nav="menu"), None)
    assert got == "Head & 3\nOne two three. four\nNext é 3\nitem"
    assert html_extract.article(None, None) == "" == html_extract.article("", None)
    assert html_extract.article("<p>a < b &amp; c<p>d", None) == "a < b & c\nd"
    assert html_extract.article("<div id=sidebar>x</div><div>y<script>z", None) == "y"
    assert html_extract.article("<article><p>x &#65;&#x42;&nbsp;c</article> tail", None) == "x AB c"


def test_template_words_go(spark):
    body = lambda i: f"<html><body><p>Same line on every page</p><p>Story {i} of the day</p><div>Also same</div></body></html>"
    rows = [(i, f"http://h.org/{i}", body(i)) for i in range(8)] + [(20, "http://lone.org/", body(20)), (21, None, body(21)), (22, "http://h2.org", None)]
    rows += [(30 + i, f"http://same.org/{i}", body(1)) for i in range(6)]  # all alike: nothing tells template from story
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", F.lit("clash")).withColumn("host", F.lit("clash"))
    got = {r["page_id"]: r for r in html_extract.extract(df).collect()}
    assert len(got) == len(rows)
    assert all(got[i]["text"] == f"Story {i} of the day" for i in range(8))
    assert got[20]["text"].startswith("Same line") and got[21]["n_chars"] == len(got[21]["text"]) and got[22]["text"] == "" and got[30]["text"].startswith("Same line")
    assert html_extract.extract(df.limit(0)).count() == 0


def test_template_of_parts_and_counts(spark):
    item = lambda k: f"<li>More: <div>Read on</div>{k}</li>"
    promo = "<section><p>Special offer today</p></section>"
    body = lambda i: f"<html><body><article><h2>Share this story</h2><p>Story {i} here</p>{promo if i % 3 == 0 else ''}<ul>{''.join(item(f'{i}.{j}') for j in range(i % 4 + 1))}</ul></article></body></html>"
    rows = [(i, f"http://h.org/{i}", body(i)) for i in range(12)] + [(50, "http://h.org/e", ""), (51, "http://h.org/n", None), (52, "http://h.org/odd", "<p>Odd one</p>")]
    rows += [(60 + i, f"http://q.org/{i}", f"<html><body><article><p>Own {i}</p>{'<p>Quoted by some</p>' if i < 5 else '<p>Not so ' + str(i) + '</p>'}</article></body></html>") for i in range(12)]
    got = {r["page_id"]: r["text"] for r in html_extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for i in range(12):
        want = [f"Story {i} here"] + [f"{i}.{j}" for j in range(i % 4 + 1)]
        assert got[i].split("\n") == want, got[i]
        assert got[60 + i].split("\n") == [f"Own {i}", "Quoted by some" if i < 5 else f"Not so {i}"]
    assert got[50] == got[51] == "" and got[52] == "Odd one"


def test_classes_nest():
    assert html_extract._walk([(0, 0), (1, 1), (2, 1), (3, 0), (4, 0)], {0: 3, 1: 2}) == set()
    assert html_extract._walk([(0, 0), (1, 1), (2, 0), (3, 1)], {0: 2, 1: 2}) == {(0, 1)}
    t = html_extract.Template.read(4, [{"pages": 4, "tokens": [1, 3]}, {"pages": 4, "tokens": [4, 5]}], [], [{"a": 0, "b": 1}])
    assert t.of[1] == t.of[3] and t.of[4] != t.of[5]


LATE = ["CC BY-SA 4.0", "CC BY 4.0", "BSD 3-Clause", "Use in source and binary forms, with or without modification, are permitted"]


def test_licenses_without_the_usual_words(spark, docs_of):
    rows = list(enumerate(LATE)) + [(100 + i, f"plain prose number {i} of the corpus\nsecond line") for i in range(30)]
    by = {r["doc_id"]: r["families"] for r in licenses.scan(docs_of(rows)).collect()}
    assert [by[i] for i in range(4)] == ["cc-by-sa-4.0", "cc-by-4.0", "bsd", "bsd"] and not any(by[100 + i] for i in range(30))


def test_cues_lose_nothing():
    rng = random.Random(4)
    for background in ([], ["under the license of the public 4 0", "permission is by the terms"] * 9):
        cues = set(licenses.cues(background))
        for ts in licenses.TEMPLATES.values():
            for t in ts:
                whole = set(licenses.grams(licenses.tokens(t)))
                for _ in range(300):
                    got = [w for w in licenses.tokens(t) if rng.random() < 0.8]
                    assert len(whole & set(licenses.grams(got))) < licenses.COVER * len(whole) - 1e-9 or cues & set(got), (t, got)


def test_terms_anywhere(spark, docs_of):
    rows = [(i, f"line {i} wrote bob@site.org about all of the things that were said here. And then came Zaphodia, zaphodia, with words {i}") for i in range(4)]
    rows += [(10, "Of ZAPHODIA no more is said")] + [(100 + i, f"common words about all the things and line {i} that were said here then came with text wrote on") for i in range(500)]
    got = {r["doc_id"]: r for r in pii.find(docs_of(rows)).collect()}
    for i in (*range(4), 10):
        text = dict(rows)[i]
        places = [f"term:{m.start()}:{m.end()}" for m in re.finditer("zaphodia", text, re.I)]
        assert [s for s in got[i]["spans"].split(",") if s.startswith("term")] == places and got[i]["n_term"] == len(places)
    by = {r["doc_id"]: r["text"] for r in pii.sanitise(docs_of(rows)).collect()}
    assert by[10] == "Of <TERM> no more is said" and by[100] == dict(rows)[100] and by[1].endswith("came <TERM>, <TERM>, with words 1")


def test_spans_of_a_long_text(spark, docs_of):
    """Twenty thousand spans in one text: linear, and the same as one search a kind gives."""
    import time

    one = "mail me.{0}@mail{0}.example.com or +1 (555) 010-{0:05d}, ip 10.0.{1}.{2} é; "
    text = "".join(one.format(i, i % 256, i % 200) for i in range(6700))
    since = time.time()
    got = pii.find(docs_of([(1, text), (2, "short 1.2.3.4")])).where("doc_id = 1").first()
    want = base_spans(text)
    assert got["base_sha256"] == hashlib.sha256(",".join(f"{n}:{s}:{e}" for s, _, e, n in want).encode()).hexdigest() and len(want) > 20000
    clean = pii.sanitise(docs_of([(1, text)])).first()["text"]
    assert "@" not in clean and clean.count("<EMAIL>") == 6700 and clean.count("<PHONE>") == sum(n == "phone" for *_, n in want)
    assert time.time() - since < 120


def test_url_lists_of_any_length(spark, monkeypatch):
    """Many listed labels make several levels; beyond the bound the join gives the same rows."""
    from joincluster.llm import common

    urls = [(i, f"https://www.h{i % 97}.site{i % 13}.{'net' if i % 3 else 'org'}/{'en' if i % 2 else 'fr'}/p{i}") for i in range(400)] + [(900, None), (901, "no url"), (5, "http://h5.site5.net/"), (None, "http://h7.org/fr/x")]
    pages = spark.createDataFrame(urls, "page_id long, url string")
    labels = tuple(f"h{i}" for i in range(0, 97, 3))
    levels = []
    build = urlfilter.build_cascade
    monkeypatch.setattr(urlfilter, "build_cascade", lambda *a: levels.append(build(*a)) or levels[-1])
    key = lambda r: tuple(str(x) for x in r)
    one = sorted((tuple(r) for r in urlfilter.filter_urls(pages, blocked_labels=labels).collect()), key=key)
    assert len(levels[0].levels) > 2
    monkeypatch.setattr(common, "FILTER_BITS_MOST", 32)
    two = sorted((tuple(r) for r in urlfilter.filter_urls(pages, blocked_labels=labels).collect()), key=key)
    assert one == two and len(levels) == 1
    for page, host, path, rule, verdict in one:
        if rule is None:
            assert verdict == ("block" if set(host.split(".")) & set(labels) else "allow")


def test_null_ids_keep_their_licences(spark, docs_of):
    got = licenses.scan(docs_of([(None, "Released under the MIT License."), (None, "nothing")])).orderBy("n_licensed").collect()
    assert [r["families"] for r in got] == ["", "mit"]


def test_long_texts_in_stretches(monkeypatch):
    """Counts and likelihoods do not hang on where a long text is cut."""
    rng = np.random.default_rng(1)
    seqs = [rng.integers(0, 7, n) for n in (1, 90, 33, 5, 200)]
    start, move, emit_t = rng.dirichlet(np.ones(3)), rng.dirichlet(np.ones(3), 3), np.ascontiguousarray(rng.dirichlet(np.ones(7), 3).T)
    whole = [sum(x) for x in zip(*hmm.all_counts(seqs, start, move, emit_t), strict=True)], hmm.log_likelihoods(seqs, start, move, emit_t)
    monkeypatch.setattr(hmm, "STRETCH", 16)
    cut = [sum(x) for x in zip(*hmm.all_counts(seqs, start, move, emit_t), strict=True)], hmm.log_likelihoods(seqs, start, move, emit_t)
    assert all(np.allclose(a, b) for a, b in zip(whole[0], cut[0], strict=True)) and np.allclose(whole[1], cut[1])
    assert sum(x.sum() for x in whole[0][:1]) == pytest.approx(5) and whole[0][2].sum() == pytest.approx(329)


def test_a_very_long_text_is_scored(spark, docs_of):
    long = " ".join(f"w{i % 5000}" for i in range(400_000))
    got = {r["doc_id"]: r for r in hmm.score(docs_of([(1, long), (2, "w1 w2"), (3, None), (4, "w7 w8 w9")])).collect()}
    assert got[1]["n_tokens"] == 400_001 and np.isfinite(got[1]["score"]) and got[1]["score"] < got[2]["score"]


def test_names_of_paragraphs():
    page = '<body><div class="site-notice">x</div><article><p class="notice-of-meeting">They meet.</p><p id="share-price">It rose.</p><p class="cookie-notice">We bake.</p><div class="share-bar">Share</div></article></body>'
    assert html_extract.article(page, None) == "They meet.\nIt rose."
