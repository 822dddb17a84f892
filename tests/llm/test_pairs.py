"""Near copies, decontamination and packing against brute force."""

import hashlib
import random
import re
import sys
import zlib

import numpy as np
import pyarrow as pa
import pytest

from joincluster.llm import common as c
from joincluster.llm import decontam, ngram_join, packing

WORDS = [f"w{i}" for i in range(400)]


def words(t):
    return [w for w in re.split(r"[\x20\x09-\x0D]+", "".join(ch.lower() if "A" <= ch <= "Z" else ch for ch in t or "")) if w]


def sets_of(rows, size):
    out = {}
    for k, (i, t) in enumerate(rows):
        w = words(t)
        out[k] = {tuple(w[j : j + size]) for j in range(len(w) - size + 1)} if len(w) >= size else ({tuple(w)} if w else set())
    return out


def brute(rows, size, percent):
    sets, parent = sets_of(rows, size), list(range(len(rows)))

    def top(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                parent[top(a)] = top(b)
    least = {}
    for k, (i, _) in enumerate(rows):
        least[top(k)] = min(least.get(top(k), i), i)
    return sorted((i, len(sets[k]), least[top(k)] if sets[k] else i) for k, (i, _) in enumerate(rows))


def corpus(seed, n=60):
    rng = random.Random(seed)
    rows, passage = [], [rng.choice(WORDS) for _ in range(60)]
    for i in range(n):
        kind = rng.random()
        if rows and kind < 0.4:  # an edited copy
            w = words(rows[rng.randrange(len(rows))][1]) or ["x"]
            for _ in range(rng.randrange(0, 6)):
                w[rng.randrange(len(w))] = rng.choice(WORDS)
            rows.append((i, rng.choice([" ", "\n", "\t "]).join(w)))
        elif kind < 0.5:
            rows.append((i, " ".join([rng.choice(WORDS) for _ in range(20)] + passage + [rng.choice(WORDS) for _ in range(10)])))
        elif kind < 0.6:
            rows.append((i, rng.choice(["", None, " ", "One two", "one TWO", "Ünï cöde É", "one two three"])))
        else:
            rows.append((i, " ".join(rng.choice(WORDS) for _ in range(rng.randrange(3, 200)))))
    return rows


@pytest.mark.parametrize("seed,size,percent", [(1, 4, 85), (2, 5, 80), (3, 2, 50)])
def test_near_copies(spark, docs_of, seed, size, percent):
    rows = corpus(seed)
    rows += [rows[3], rows[5], (7, "repeated id with another text and some more words")]
    got = sorted(tuple(r) for r in ngram_join.near_copies(docs_of(rows), size, percent).select("doc_id", "n_shingles", "component_id").collect())
    assert got == brute(rows, size, percent)


def test_large_buckets_by_blocks(spark, docs_of, monkeypatch):
    monkeypatch.setattr(ngram_join, "FEW", 3)
    monkeypatch.setattr(ngram_join, "BLOCK", 4)
    rng = random.Random(9)
    base = [rng.choice(WORDS) for _ in range(120)]
    rows = []
    for i in range(40):  # a chain of copies, each a little further from the first
        w = list(base)
        for j in range(i // 2):
            w[(7 * j) % 120] = f"e{i % 5}{j}"
        rows.append((i, " ".join(w)))
    got = sorted(tuple(r) for r in ngram_join.near_copies(docs_of(rows)).select("doc_id", "n_shingles", "component_id").collect())
    assert got == brute(rows, 4, 85)


def test_keep_first(spark, docs_of):
    rows = [(5, "a b c d e f g h"), (2, "a b c d e f g h"), (2, "a b c d e f g h"), (9, ""), (9, ""), (11, "other words stand here now")]
    df = docs_of(rows)
    got = ngram_join.keep_first(df)
    assert got.columns == df.columns and sorted(r["doc_id"] for r in got.collect()) == [2, 9, 9, 11]


def test_empty_tables(spark, docs_of):
    none = docs_of([])
    assert ngram_join.near_copies(none).count() == 0
    assert decontam.decontaminate(none, spark.createDataFrame([(1, "a b")], "item_id long, text string")).count() == 0
    assert packing.pack(none).count() == 0


def test_word_hashes_cut_anywhere(monkeypatch):
    texts = ["One twO", None, "", " a\tb ", "x" * 50 + " y", "é ÉA\x0b1"]
    whole = c.word_hashes(pa.array(texts))
    monkeypatch.setattr(c, "STRETCH", 7)
    cut = c.word_hashes(pa.array(texts))
    assert all((a == b).all() for a, b in zip(whole, cut, strict=True))
    h, _, lo, hi = whole
    assert (hi - lo).tolist() == [2, 0, 0, 2, 2, 3] and len(np.unique(h)) == len(h)
    assert (c.word_hashes(pa.array(texts).slice(3))[0] == h[2:]).all()


def test_components(spark):
    edges = spark.createDataFrame([(1, 2), (2, 3), (10, 9), (3, 1), (5, 5), *[(100, i) for i in range(101, 140)]], "a long, b long")
    got = {r["node"]: r["root"] for r in c.components(edges).collect()}
    assert got[3] == got[2] == 1 and got[10] == 9 and got[139] == 100 and 5 not in got
    assert c.components(edges.limit(0)).count() == 0


# ---- decontamination


def item_words(t):
    return [w for w in re.split(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(ch.lower() if "A" <= ch <= "Z" else ch for ch in t or "")) if w]


def brute_hits(doc, items):
    w, hit, found = item_words(doc), set(), set()
    for i, t in items:
        v = item_words(t)
        if not v:
            continue
        n = min(10, len(v))
        wins = {tuple(v[j : j + n]) for j in range(len(v) - n + 1)}
        for j in range(len(w) - n + 1):
            if tuple(w[j : j + n]) in wins:
                hit |= set(range(j, j + n))
                found.add(str(i))
    return len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)


def test_decontamination(spark, docs_of):
    rng = random.Random(4)
    items = [(i, " ".join(rng.choice(WORDS) for _ in range(rng.randrange(10, 40)))) for i in range(12)]
    items += [(20, "Alpha, BETA gamma"), (21, "alpha"), (22, ""), (23, None), (24, "..!"), (3, items[3][1]), (101, items[0][1]), (25, "é ü ö")]
    rows = []
    for i in range(60):
        w = [rng.choice(WORDS) for _ in range(rng.randrange(0, 120))]
        if rng.random() < 0.6:
            v = item_words(items[rng.randrange(12)][1])
            lo = rng.randrange(0, max(1, len(v) - 8))
            at = rng.randrange(0, len(w) + 1)
            w[at:at] = v[lo : lo + rng.randrange(5, 40)]
        if rng.random() < 0.2:
            w.insert(len(w) // 2, rng.choice(["ALPHA beta. gamma", "x alphabet", "É Ü ö", "é-ü ö"]))
        rows.append((i, rng.choice([" ", ", ", "\n"]).join(w)))
    rows += [(100, None), (101, ""), rows[5], rows[5], (-1, " ".join(item_words(items[2][1])))]
    got = sorted(tuple(r) for r in decontam.decontaminate(docs_of(rows), spark.createDataFrame(items, "item_id long, text string")).collect())
    assert got == sorted((i, *brute_hits(t, items)) for i, t in rows)


def test_no_benchmark(spark, docs_of):
    got = decontam.decontaminate(docs_of([(1, "a b c")]), spark.createDataFrame([], "item_id long, text string")).first()
    assert (got["n_words"], got["n_hit"], got["contaminated"]) == (3, 0, False)


def test_keep_clean(spark, docs_of):
    item = " ".join(WORDS[:12])
    df = docs_of([(1, item), (2, "clean text"), (3, None), (2, item), (None, item), (None, "clean too")])
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    got = decontam.keep_clean(df, bench)
    assert got.columns == df.columns and sorted(str(r["doc_id"]) for r in got.collect()) == ["2", "3", "None"]
    assert [r["n_hit"] for r in decontam.decontaminate(df, bench).where("doc_id is null").orderBy("n_words").collect()] == [0, 12]


# ---- packing


def test_word_ids_are_the_tokenizers():
    ids = packing.WordIds(packing.tokenizer_path())
    for t in ["Hello, world! It's 42°", "ÀÉÎ õ ñ¿qué?", "a_b__c ²³ ½ x²", "日本語 text", "tab\tnew\nline \x1c\x85", "<|endoftext|> x", "İstanbul e\u0301", "don't we'll I'VE", "", "  ", "'''s 'tis", "x" * 3000]:
        assert ids(t) == ids.whole(t), t


def test_packing_is_a_round_trip(spark, docs_of):
    rng = random.Random(2)
    rows = [(i, " ".join(rng.choice(["alpha", "beta", "Gamma!", "42", "é"]) for _ in range(rng.choice([0, 1, 5, 60, 300])))) for i in range(80)] + [(80, None), (81, ""), (3, "same id"), (3, "same id")]
    cap = 64
    got = [r.asDict() for r in packing.pack(docs_of(rows), capacity=cap).collect()]
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.tokenizer_path())
    want = []
    for i, t in rows:
        ids = np.array(tok.encode(t or "", add_special_tokens=False).ids + [0], dtype="<u4")
        want += [(i, p, p * cap, len(x), zlib.crc32(x.tobytes())) for p, x in enumerate(np.split(ids, range(cap, len(ids), cap)))]
    assert sorted(want) == sorted((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got)
    seqs = {}
    for r in got:
        seqs.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for s in seqs.values():
        at = 0
        for off, n in sorted(s):
            assert off == at
            at += n
        assert at <= cap
    total = sum(r["length"] for r in got)
    assert len(seqs) <= 1.1 * -(-total // cap) + 1


def histogram(pieces, cap):
    return np.bincount(pieces, minlength=cap + 1).astype(np.int64)


def held_exactly(plan, hist, cap):
    back = np.zeros(cap + 1, dtype=np.int64)
    for conf, n in plan:
        assert sum(x * a for x, a in conf.items()) <= cap and n > 0
        for x, a in conf.items():
            back[x] += a * n
    return (back == hist).all()


@pytest.mark.parametrize("seed", range(6))
def test_plan_holds_the_histogram(seed):
    rng, cap = np.random.default_rng(seed), 50
    hist = histogram(rng.integers(1, cap + 1, rng.integers(1, 400)), cap)
    rounded, rest = packing.plan(hist, cap)
    assert held_exactly(rounded + rest, hist, cap) and held_exactly(packing.best_fit(hist, cap), hist, cap)
    many = sum(n for _, n in rounded + rest)
    assert packing.lower_bound(hist, cap) <= many + 1e-9 <= 1.03 * packing.lower_bound(hist, cap, packing.solve(hist, cap)[1]) + 2


def test_the_program_packs_nearly_all():
    """Many lengths as in texts: the rounded programs hold nearly all pieces, no more sequences are used than by best fit, and the bound is met."""
    rng, cap = np.random.default_rng(5), 512
    hist = histogram(np.minimum(rng.lognormal(4.8, 0.9, 20000).astype(int) + 1, cap), cap)
    rounded, rest = packing.plan(hist, cap)
    many = sum(n for _, n in rounded + rest)
    assert sum(n for _, n in rest) <= 0.02 * many
    assert many <= sum(n for _, n in packing.best_fit(hist, cap)) + 1 and many <= packing.lower_bound(hist, cap) + 3


def optimum(pieces, cap):
    """Fewest bins, by trying all ways to fill a bin with the longest piece."""
    from functools import cache
    from itertools import combinations

    @cache
    def least(left):
        if not left:
            return 0
        first, others = left[-1], left[:-1]
        best = len(left)
        for k in range(len(others) + 1):
            for more in set(combinations(range(len(others)), k)):
                if first + sum(others[i] for i in more) <= cap:
                    best = min(best, 1 + least(tuple(x for i, x in enumerate(others) if i not in more)))
        return best

    return least(tuple(sorted(pieces)))


@pytest.mark.parametrize("seed", range(8))
def test_bounds_of_small_histograms(seed):
    rng, cap = np.random.default_rng(seed), 10
    pieces = rng.integers(1, cap, 7)
    hist = histogram(pieces, cap)
    best = optimum(pieces.tolist(), cap)
    rounded, rest = packing.plan(hist, cap)
    assert packing.lower_bound(hist, cap) <= best + 1e-9 and best <= sum(n for _, n in rounded + rest) <= best + 1


def test_price_is_the_best_knapsack():
    values = np.zeros(11)
    values[[3, 4, 7]] = [3.0, 4.5, 7.6]
    conf, value = packing.price(values, np.full(11, 9), np.array([3, 4, 7]), 10)
    assert sum(values[x] * a for x, a in conf.items()) == pytest.approx(10.6) == value
    conf, value = packing.price(values, np.array([9, 9, 9, 0, 2, 9, 9, 1, 9, 9, 9]), np.array([3, 4, 7]), 10)
    assert value == pytest.approx(9.0) and conf == {4: 2}


def test_keep_first_of_repeated_ids(spark, docs_of):
    """Texts that do not link stay, whatever their ids; a null id is one like any other."""
    rows = [(1, "alpha beta gamma delta epsilon"), (1, "one two three four five six"), (2, "red green blue cyan pink"), (2, "one two three four five six"), (None, "red green blue cyan pink"), (None, "a lone text of null id"), (3, None), (3, None)]
    got = ngram_join.keep_first(docs_of(rows))
    key = lambda r: (r[0] is None, r[0] or 0, r[1] or "")
    assert sorted(((r["doc_id"], r["text"]) for r in got.collect()), key=key) == sorted([rows[0], rows[1], rows[2], rows[5], rows[6], rows[7]], key=key)


def test_sketches_lose_no_pair():
    rng = np.random.default_rng(3)
    for _ in range(400):
        n = int(rng.integers(1, 300))
        a = np.unique(rng.integers(0, 2**63, n).astype(np.uint64))
        b = np.unique(np.concatenate([a[rng.random(len(a)) > 0.1], rng.integers(0, 2**63, rng.integers(0, 20)).astype(np.uint64)]))
        if not len(b):
            continue
        none = np.empty(0, np.uint64)
        e = [tuple(ngram_join._numbered(ngram_join._hashes16(ngram_join._prefix(s, o, ngram_join._first(len(s), 85) - 1 + ngram_join._least(len(s), 85), ngram_join._late(s, none)))) for o in (1, 2)) for s in (a, b)]
        both = len(np.intersect1d(a, b))
        links = 100 * both >= 85 * (len(a) + len(b) - both)
        assert ngram_join._bits_differ(ngram_join.parity(a), ngram_join.parity(b)) <= len(a) + len(b) - 2 * both
        assert not links or ngram_join._agree(len(a), len(b), *e, 85) and ngram_join._near(len(a), len(b), ngram_join.parity(a), ngram_join.parity(b), 85)


def test_first_order_puts_common_words_late(spark, docs_of):
    """Texts that share shingles of common words by chance, and no others, have no prefix token in common."""
    rng = random.Random(6)
    rows = []
    for i in range(60):
        w = [rng.choice(WORDS[:5]) for _ in range(100)]
        w[50:50] = [f"r{i}x{j}" for j in range(30)]
        rows.append((i, " ".join(w)))
    docs = ngram_join._rows(docs_of(rows).select("doc_id", "text"))
    common = ngram_join.common_words(docs)
    none = np.empty(0, np.uint64), np.empty(0, np.uint8)
    plain, weighed = ([set(r["p1"]) for r in ngram_join._read(docs, none, x, 4, 85).select("p1").collect()] for x in (np.zeros_like(common), common))
    assert len(set().union(*plain)) < sum(map(len, plain)) and len(set().union(*weighed)) == sum(map(len, weighed))
    got = sorted(tuple(r) for r in ngram_join.near_copies(docs_of(rows + [(99, rows[7][1])])).select("doc_id", "n_shingles", "component_id").collect())
    assert got == brute(rows + [(99, rows[7][1])], 4, 85)


def test_frequent_shingles_come_last_by_their_counts():
    s = np.arange(1, 9, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    s.sort()
    late = ngram_join._late(s, s[2:], np.array([5, 1, 4, 2, 6, 3], np.uint8))
    for order in range(3):
        assert [set(ngram_join._prefix(s, order, n, late)) for n in range(2, 8)] == [{*s[:2], *(s[2:][i] for i in (1, 3, 5, 2, 0)[: n - 2])} for n in range(2, 8)]


def test_word_hashes_hold_one_stretch_at_a_time():
    """Hashing a long text takes little more than the text, since its stretches are short (52 MB with stretches of 1 MB)."""
    import tracemalloc

    texts = pa.array([("x" * 63 + " ") * (1 << 16)])
    sys.modules.pop("_joincluster_held", None)  # the powers count too
    tracemalloc.start()
    h = c.word_hashes(texts)[0]
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(h) == 1 << 16 and most < 40e6


def test_join_hands_small_batches_to_python(spark, docs_of, monkeypatch):
    """However many rows a task reads, its Python worker gets at most BATCH at once, and the session's own setting comes back."""
    most, read, name = ngram_join.BATCH, ngram_join._read, "spark.sql.execution.arrow.maxRecordsPerBatch"

    def seen(batches):
        for b in batches:
            if b.num_rows > most:
                raise ValueError(f"a batch of {b.num_rows} rows")
            yield b

    monkeypatch.setattr(ngram_join, "_read", lambda docs, *a: read(docs.select("doc_id", "row", "text").mapInArrow(seen, "doc_id long, row long, text string"), *a))
    rows = [(i, f"a{i % 700} b{i % 700} c{i % 700} d") for i in range(1300)]
    was = spark.conf.get(name)
    got = sorted(tuple(r) for r in ngram_join.near_copies(docs_of(rows).coalesce(1)).select("doc_id", "n_shingles", "component_id").collect())
    assert got == brute(rows, 4, 85) and spark.conf.get(name) == was
    spark.conf.set(name, "70")
    try:
        with pytest.raises(ZeroDivisionError), c.batches_of(spark, most):
            assert spark.conf.get(name) == "70"
            raise ZeroDivisionError
        spark.conf.set(name, "0")  # no bound
        with c.batches_of(spark, most):
            assert spark.conf.get(name) == str(most)
        assert spark.conf.get(name) == "0"
    finally:
        spark.conf.set(name, was)


def test_repeated_shingles_are_counted(spark, docs_of):
    """frequent_shingles names what FREQUENT_FROM texts or more share, with exact counts inside a task."""
    rows = [(i, f"a b c d {i}") for i in range(9)] + [(20 + i, f"e f g h {i}") for i in range(2)] + [(30, None), (31, "")]
    s, n = ngram_join.frequent_shingles(docs_of(rows).coalesce(1))
    want = next(ngram_join.shingle_sets(pa.array(["a b c d"]), 4))
    assert s.tolist() == want.tolist() and n.tolist() == [3]
    assert len(ngram_join.frequent_shingles(docs_of(rows[9:]).coalesce(1))[0]) == 0
