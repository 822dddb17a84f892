"""Benchmark decontamination by winnowing.

Both sides keep the smallest k-gram hash of each run of w consecutive k-grams. A shared span of
k + w - 1 words has the same smallest hash on both sides, so every shared window of that many words
is found by joining the kept hashes. Documents with a shared hash are extended: all their windows
are compared with the items' windows, which gives exact positions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common as c

#: Words of a window, of a k-gram, and k-grams of a winnowing run: K + RUN - 1 = WINDOW.
WINDOW, K, RUN = 10, 8, 3
BREAK = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_of(text: Column) -> Column:
    return F.filter(F.split(c.fold(text), BREAK), lambda w: w != "")


def _pairs(df: DataFrame, name: str, left: str, right: str, by: int, join) -> DataFrame:
    """Column name: left[i] joined with right[i + by], for the i where both exist."""
    n = F.greatest(F.least(F.size(left), F.size(right) - by), F.lit(0))
    return df.withColumn(name, F.zip_with(F.slice(left, 1, n), F.slice(right, by + 1, n), join))


def _grams(df: DataFrame) -> DataFrame:
    """Adds g8 (8-gram hashes) to a table with h (word hashes): each doubling joins two shifted arrays."""
    pair = lambda a, b: F.xxhash64(a, b)
    df = _pairs(df, "g2", "h", "h", 1, pair)
    df = _pairs(df, "g4", "g2", "g2", 2, pair).drop("g2")
    return _pairs(df, "g8", "g4", "g4", 4, pair).drop("g4")


def _kept(df: DataFrame) -> DataFrame:
    """Adds kept: the winnowed 8-gram hashes."""
    low = lambda a, b: F.least(a, b)
    df = _pairs(df, "m2", "g8", "g8", 1, low)
    return _pairs(df, "kept", "m2", "m2", 1, low).drop("m2")


def _windows(df: DataFrame) -> DataFrame:
    """Adds g10: two overlapping 8-grams name a window of ten words."""
    return _pairs(df, "g10", "g8", "g8", WINDOW - K, lambda a, b: F.xxhash64(a, b))


def _short(h: str, n: int) -> Column:
    """Hashes of all runs of n words, n under WINDOW."""
    return F.transform(F.sequence(F.lit(1), F.size(h) - n + 1), lambda i: F.xxhash64(F.lit(n), F.slice(h, i, F.lit(n))))


def decontaminate(documents: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated for every row of documents; see scanned."""
    return scanned(documents, benchmark).drop("row")


def scanned(documents: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, row (a hash of the text), n_words, n_hit, n_items, items_sha256, contaminated for every row of documents.

    A word is hit inside any occurrence of a window (ten consecutive words) of an item; an item of
    one to nine words is one window. Null, empty or wordless texts have no words and no hit;
    wordless items match nothing. Rows repeated in documents stay repeated.
    """
    items = benchmark.select("item_id", "text").distinct().select("item_id", F.transform(words_of(F.col("text")), lambda w: F.xxhash64(w)).alias("h")).where(F.size("h") > 0)
    items = c.written(_windows(_kept(_grams(items))))
    lengths = sorted(r[0] for r in items.where(F.size("h") < WINDOW).select(F.size("h")).distinct().collect())
    spans = items.select("item_id", F.explode("g10").alias("gram"), F.lit(WINDOW).alias("len"))
    if lengths:
        spans = spans.unionByName(items.where(F.size("h") < WINDOW).select("item_id", F.xxhash64(F.size("h"), F.col("h")).alias("gram"), F.size("h").alias("len")))
    spans = c.written(spans.distinct())
    marks = c.written(items.select(F.explode("kept").alias("gram")).distinct())

    # A null id is a key like any other: what a text hits does not hang on its id.
    docs = documents.select("doc_id", "text").select(
        "doc_id", F.coalesce("doc_id", F.lit(0)).alias("id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("row"), F.transform(words_of(F.col("text")), lambda w: F.xxhash64(w)).alias("h")
    )
    docs = _kept(_grams(docs))
    n_marks = marks.count()
    bits = c.filter_bits(max(1, n_marks), 128)
    near = F.lit(True)
    if bits <= c.FILTER_BITS_MOST:  # else every document's kept hashes go to the join below
        held = c.bit_words(marks, "gram", bits, (0, 1))
        near = F.exists("kept", lambda x: c.in_filter(x, held, (0, 1)))
    if lengths:
        shorts = c.written(spans.where(F.col("len") < WINDOW).select("gram").distinct())
        short_bits = c.filter_bits(shorts.count())
        if short_bits <= c.FILTER_BITS_MOST:
            short_held = c.bit_words(shorts, "gram", short_bits)
            for n in lengths:
                near = near | ((F.size("h") >= n) & F.exists(F.when(F.size("h") >= n, _short("h", n)), lambda x: c.in_filter(x, short_held)))
        else:
            near = F.lit(True)
    read = c.written(docs.withColumn("near", near).select(
        "doc_id", "id", "row", F.size("h").alias("n_words"), *[F.when(F.col("near"), F.col(x)).alias(x) for x in ("h", "kept")]
    ))

    maybe = read.where("h is not null")
    seeds = maybe.select("id", "row", F.explode(F.array_distinct("kept")).alias("gram")).join(marks, "gram", "left_semi").select("id", "row").distinct()
    if lengths:
        found = [maybe.where(F.size("h") >= n).select("id", "row", F.explode(F.array_distinct(_short("h", n))).alias("gram")).join(spans.where(F.col("len") == n), "gram", "left_semi").select("id", "row") for n in lengths]
        for f in found:
            seeds = seeds.unionByName(f)
        seeds = seeds.distinct()
    grown = maybe.select("id", "row", "h").join(seeds, ["id", "row"], "left_semi").dropDuplicates(["id", "row"])
    # Written first: a filter inferred from the explode below would be pushed through, and repeat, every level of the hashes.
    grown = c.written(_windows(_grams(grown)))
    at = grown.select("id", "row", F.posexplode("g10").alias("pos", "gram"))
    for n in lengths:
        at = at.unionByName(grown.where(F.size("h") >= n).select("id", "row", F.posexplode(_short("h", n)).alias("pos", "gram")))
    hits = at.join(spans, "gram").groupBy("id", "row").agg(
        F.array_sort(F.collect_set(F.struct("pos", "len"))).alias("at"), F.array_sort(F.collect_set(F.col("item_id").cast("string"))).alias("items")
    )
    cover = F.aggregate(
        "at", F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("n")),
        lambda a, x: F.struct(
            F.greatest(a["end"], x["pos"] + x["len"]).alias("end"),
            (a["n"] + F.greatest(F.lit(0), x["pos"] + x["len"] - F.greatest(a["end"], x["pos"])).cast("long")).alias("n"),
        ),
    )["n"]
    hits = hits.select("id", "row", cover.alias("n_hit"), "items")
    none = F.array().cast("array<string>")
    return read.select("doc_id", "id", "row", "n_words").join(hits, ["id", "row"], "left").select(
        "doc_id", "row", F.col("n_words").cast("long").alias("n_words"), F.coalesce("n_hit", F.lit(0).cast("long")).alias("n_hit"),
        F.size(F.coalesce("items", none)).cast("long").alias("n_items"),
        F.sha2(F.array_join(F.coalesce("items", none), ",").cast("binary"), 256).alias("items_sha256"),
        (F.coalesce("n_hit", F.lit(0).cast("long")) > 0).alias("contaminated"),
    )


def keep_clean(documents: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of documents, all columns, whose text has no hit.

    Rows are told apart by their texts, so rows of one id or of a null id go or stay each for itself.
    Null and empty texts stay. An empty table gives an empty result.
    """
    bad = c.written(scanned(documents, benchmark).where("contaminated").select(F.col("row").alias("__row")).distinct())
    rows = documents.withColumn("__row", F.xxhash64(F.coalesce("text", F.lit(""))))
    return c.without(rows, bad, "__row").select([F.col(f"`{x}`") for x in documents.columns])


ORACLE_SQL = r"""
WITH d0 AS (
  SELECT DISTINCT doc_id, coalesce(text,'') AS text,
         list_filter(regexp_split_to_array(translate(coalesce(text,''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda w: w <> '') AS w
  FROM documents),
b0 AS (
  SELECT item_id, list_filter(regexp_split_to_array(translate(coalesce(text,''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda w: w <> '') AS w
  FROM benchmark),
b1 AS (
  SELECT DISTINCT item_id, least(len(w), 10) AS n, array_to_string(w[i:i+least(len(w),10)-1], ' ') AS g
  FROM (SELECT item_id, w, unnest(range(1, greatest(len(w)-9,1)+1)) AS i FROM b0 WHERE len(w) > 0)),
ns AS (SELECT DISTINCT n FROM b1),
d1 AS (
  SELECT doc_id, text, n, i, array_to_string(w[i:i+n-1], ' ') AS g
  FROM (SELECT doc_id, text, w, n, unnest(range(1, len(w)-n+2)) AS i FROM d0, ns WHERE len(w) >= n)),
h AS (SELECT d1.doc_id, d1.text, d1.i, d1.n, b1.item_id FROM d1 JOIN b1 ON d1.g = b1.g AND d1.n = b1.n),
p AS (SELECT doc_id, text, count(DISTINCT q) AS n_hit FROM (SELECT doc_id, text, unnest(range(i, i+n)) AS q FROM (SELECT DISTINCT doc_id, text, i, n FROM h)) GROUP BY 1, 2),
t AS (SELECT doc_id, text, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS s FROM h GROUP BY 1, 2)
SELECT o.doc_id, len(d0.w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM documents o JOIN d0 ON o.doc_id = d0.doc_id AND coalesce(o.text,'') = d0.text
LEFT JOIN p ON p.doc_id = d0.doc_id AND p.text = d0.text LEFT JOIN t ON t.doc_id = d0.doc_id AND t.text = d0.text
"""
