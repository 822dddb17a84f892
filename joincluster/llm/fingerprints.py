"""I-Match document fingerprints with randomised lexicons, in DataFrame functions alone.

Words fall into a fixed number of slots. The lexicon is the band of slots whose document frequency
lies between two shares of the corpus, so it has a bounded number of entries whatever the corpus,
and travels as one bit array. A document's terms inside the band are split into randomised
sub-lexicons of several densities, SEEDS of each; the sorted distinct terms of each are hashed.
Equal texts agree in all hashes; two versions of a text agree in those sub-lexicons that the edit
did not touch, and the density with most agreement gives their likeness.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from . import common as c

SLOTS = 1 << 20
#: The band, as shares of all documents, and the terms under which a text is read without a lexicon.
RARE, COMMON, LEAST_TERMS = 0.001, 0.01, 4
#: A sub-lexicon of density d keeps one term in d.
SEEDS, DENSITIES = 8, (2, 4, 8, 16, 32, 64, 128, 256, 512)
#: Rows of a range of neighbouring ids, and ranges at most.
RANGE_ROWS, RANGES_MOST = 1500, 1000


def slots(text: Column) -> Column:
    words = F.filter(F.split(c.fold(text), r"[\x20\x09-\x0D]+"), lambda w: w != "")
    return F.array_distinct(F.transform(words, lambda w: F.pmod(F.xxhash64(w), F.lit(SLOTS)).cast("int")))


def band(documents: DataFrame, rare: float = RARE, common: float = COMMON) -> list[int]:
    """The lexicon's slots as a bit array of 64-bit words, from the document frequencies of the whole table."""
    n = documents.count()
    counts = documents.select(F.explode(slots(F.col("text"))).alias("slot")).groupBy("slot").agg(F.count("*").alias("df"))
    kept = counts.where((F.col("df") >= max(2.0, rare * n)) & (F.col("df") <= max(2.0, common * n)))
    words = [0] * (SLOTS // 64)
    for r in kept.groupBy(F.shiftright("slot", 6).alias("word")).agg(F.expr("bit_or(shiftleft(1L, slot % 64))").alias("bits")).collect():  # at most SLOTS / 64 rows
        words[r["word"]] = r["bits"]
    return words


def _hashes(df: DataFrame, text: str, out: str, lexicon: list[int]) -> DataFrame:
    """Adds out: the sub-lexicons' hashes of 24 bits, by density, null for one without terms. Each step is a column, so none is repeated."""
    import numpy as np

    held = F.lit(np.array(lexicon, dtype=np.int64))
    df = df.withColumn("_all", slots(F.col(text)))
    df = df.withColumn("_in", F.filter("_all", lambda x: F.getbit(F.element_at(held, F.shiftright(x, 6) + 1), x % 64) == 1))
    df = df.withColumn("_use", F.array_sort(F.when(F.size("_in") >= LEAST_TERMS, F.col("_in")).otherwise(F.col("_all")))).drop("_all", "_in")
    seeded = lambda s: lambda x: F.xxhash64(F.lit(s), x)
    kept = lambda d: lambda g: g.bitwiseAND(F.lit(d - 1)) == 0
    for s in range(SEEDS):
        last = f"_t{s}"
        df = df.withColumn(last, F.transform("_use", seeded(s)))
        for d in DENSITIES:
            df = df.withColumn(f"_k{s}_{d}", F.filter(last, kept(d)))
            last = f"_k{s}_{d}"
    short = lambda name: F.xxhash64(name).bitwiseAND(F.lit(0xFFFFFF)).cast("int")
    parts = [F.when(F.size(f"_k{s}_{d}") > 0, short(f"_k{s}_{d}")) for d in DENSITIES for s in range(SEEDS)]
    df = df.withColumn(out, F.array(short("_use"), *parts))
    return df.drop("_use", *[f"_t{s}" for s in range(SEEDS)], *[f"_k{s}_{d}" for s in range(SEEDS) for d in DENSITIES])


def printed(hashes: Column) -> Column:
    """The fingerprint as text: six hex digits a hash, a dash where there is none."""
    return F.array_join(F.transform(hashes, lambda h: F.coalesce(F.lower(F.lpad(F.hex(h), 6, "0")), F.lit("-"))), ".")


def likeness(x: str, y: str) -> Column:
    """0 to 1: 1 for equal fingerprints, else the best share of agreeing sub-lexicons over the densities where three or more of them have terms."""
    same = F.zip_with(x, y, lambda a, b: F.when(a.isNull() & b.isNull(), F.lit(None)).otherwise(F.coalesce(a == b, F.lit(False)).cast("int")))
    shares = [F.aggregate(F.filter(F.slice(same, 2 + i * SEEDS, SEEDS), lambda z: z.isNotNull()), F.struct(F.lit(0).alias("n"), F.lit(0).alias("eq")), lambda a, z: F.struct((a["n"] + 1).alias("n"), (a["eq"] + z).alias("eq"))) for i in range(len(DENSITIES))]
    share = lambda a: F.when(a["n"] >= 3, a["eq"] / a["n"]).otherwise(F.lit(0.0))
    return F.when(F.col(x) == F.col(y), F.lit(1.0)).otherwise(F.array_max(F.transform(F.array(*shares), share))).cast("double")


def fingerprints(documents: DataFrame, lexicon: list[int] | None = None) -> DataFrame:
    """doc_id, fingerprint for every row of documents. A null text is the empty text, whose fingerprint has no terms."""
    docs = documents.select("doc_id", "text")
    return _hashes(docs, "text", "hashes", band(docs) if lexicon is None else lexicon).select("doc_id", printed(F.col("hashes")).alias("fingerprint"))


def with_next(documents: DataFrame, columns: list[str]) -> DataFrame:
    """Adds next_<column>: that of the row of the next smaller doc_id (of the greatest, after the smallest).

    Rows are dealt into ranges of ids; the top row of each range also goes to the range above, and
    the top row of all to the lowest, so no range waits for another and no task sees all rows. Rows
    of one id follow each other by the hash of their text. A null id comes after all others.
    """
    at = documents.withColumn("_id", F.coalesce("doc_id", F.lit(-(1 << 63)).cast("long")))
    n = at.count()
    ranges = max(1, min(RANGES_MOST, n // RANGE_ROWS))
    cuts = []
    if ranges > 1:
        shares = F.array(*[F.lit(i / ranges) for i in range(1, ranges)])
        cuts = sorted(set(at.select(F.percentile_approx("_id", shares, F.lit(10 * ranges))).first()[0]))
    bounds = F.array(*[F.lit(x) for x in cuts]).cast("array<bigint>")
    at = at.withColumn("_range", F.size(F.filter(bounds, lambda b: b < F.col("_id")))).withColumn("_ghost", F.lit(0))
    tops = sorted((r["_range"], r["top"]) for r in at.groupBy("_range").agg(F.max("_id").alias("top")).collect())  # at most RANGES_MOST + 1 rows
    if not tops:
        return at.withColumns({f"next_{x}": F.col(x) for x in columns}).drop("_id", "_range", "_ghost")
    above = [(top, tops[(i + 1) % len(tops)][0], 1 + (i + 1 == len(tops))) for i, (_, top) in enumerate(tops)]
    ghosts = at.drop("_range", "_ghost").where(F.col("_id").isin([t for t, _, _ in above])).join(F.broadcast(documents.sparkSession.createDataFrame(above, "_id long, _range int, _ghost int")), "_id")
    both = at.unionByName(ghosts)
    order = W.partitionBy("_range").orderBy("_ghost", F.desc("_id"), "_row")
    return both.withColumns({f"next_{x}": F.lead(x).over(order) for x in columns}).where("_ghost = 0").drop("_id", "_range", "_ghost")


def edited_fingerprints(documents: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next for every row of documents.

    The edited text ends in the first floor(n_chars / 3) code points of the next document instead of
    its own last ones. A null text is empty: no terms, and its edited text is empty too. A lone row is
    its own next one. Rows that repeat stay repeated. An empty table gives an empty result.
    """
    docs = documents.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    lexicon = band(docs)
    first = _hashes(docs, "text", "hashes", lexicon).withColumn("_row", F.xxhash64("text"))
    both = with_next(first, ["text", "hashes"])
    cut = F.floor(F.col("n_chars") / 3).cast("int")
    both = both.withColumn("n_chars", F.length("text").cast("long"))
    both = both.withColumn("edited", F.concat(F.substring("text", F.lit(1), (F.col("n_chars") - cut).cast("int")), F.substring("next_text", F.lit(1), cut))).drop("text", "next_text")
    both = _hashes(both, "edited", "edited_hashes", lexicon)
    return both.select(
        "doc_id", "n_chars", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), printed(F.col("hashes")).alias("fingerprint"), printed(F.col("edited_hashes")).alias("edited_fingerprint"),
        likeness("hashes", "edited_hashes").alias("near_edited"), likeness("hashes", "next_hashes").alias("near_next"),
    )
