"""Personal data and what gives it away, in DataFrame functions alone.

Base spans (email, ip, card, phone) come from patterns and checks. The words of the texts that hold
them are then weighed by the corpus: a word that shares several different texts with one protected
value and hardly stands in any other tells a reader which value was there. Its disclosure is the
point-wise mutual information of word and value over texts, log2(P(word, value) / (P(word) P(value))),
with P(value | word) as its certainty. Every place of a word over both thresholds, in whatever text,
becomes a span of kind term and is generalised too.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common as c

#: Kinds in their order, and patterns. \\G and the look-behind only keep a search from starting inside a run it has passed.
KINDS = ("email", "ip", "card", "phone")
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: A text without this cannot hold the kind.
HINTS = {"email": "@", "ip": r"[0-9]\.[0-9]+\.[0-9]", "card": r"[0-9](?:[\x20-]?[0-9]){13}", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
#: The least length of a word.
LEAST_LETTERS = 3
#: Different texts that must show word and value together, P(value | word), and bits of mutual information.
SUPPORT, CERTAINTY, BITS = 2, 0.5, 6.0
WORD = r"[\p{L}\p{N}]+"


#: Matches that are walked together, so that a text of many matches costs little more than its length.
WALK = 256
_SPAN = "array<struct<start:int,end:int,value:string>>"


def let(value: Column, then: Callable[[Column], Column]) -> Column:
    """then(value), with value computed once however often then uses it, also inside lambdas."""
    return F.element_at(F.transform(F.array(value), then), 1)


def _walks(items: Column) -> Column:
    """items cut into arrays of at most WALK."""
    return let(items, lambda x: F.when(F.size(x) > 0, F.transform(F.sequence(F.lit(0), F.floor((F.size(x) - 1) / WALK).cast("int")), lambda i: F.slice(x, i * WALK + 1, F.lit(WALK)))))


def _placed(steps: Column) -> Column:
    """array<struct<start, end, value>> of steps (gap, value) that have a value: each stands gap code points after the one before."""
    none = F.array().cast(_SPAN)
    one = lambda a, x: let(F.struct((a["at"] + x["gap"]).alias("start"), F.coalesce(F.length(x["value"]), F.lit(0)).alias("n")), lambda p: F.struct(
        (p["start"] + p["n"]).alias("at"),
        F.when(x["value"].isNull(), a["out"]).otherwise(F.concat(a["out"], F.array(F.struct(p["start"].alias("start"), (p["start"] + p["n"]).alias("end"), x["value"].alias("value"))))).alias("out"),
    ))
    walk = lambda a, part: let(F.aggregate(part, F.struct(a["at"].alias("at"), none.alias("out")), one), lambda w: F.struct(w["at"].alias("at"), F.concat(a["out"], F.array(w["out"])).alias("out")))
    return let(_walks(steps), lambda parts: F.when(parts.isNull(), none).otherwise(F.flatten(F.aggregate(parts, F.struct(F.lit(0).alias("at"), F.array().cast(f"array<{_SPAN}>").alias("out")), walk)["out"])))


def _found(text: Column, pattern: str) -> Column:
    """array<struct<start, end, value>> of all matches, in code points: pieces between matches give the places."""
    values, pieces = F.regexp_extract_all(text, F.lit(pattern), 0), F.split(text, pattern, -1)
    step = F.zip_with(values, pieces, lambda v, p: F.struct(F.length(p).alias("gap"), v.alias("value")))
    return _placed(F.filter(step, lambda x: x["value"].isNotNull()))


def _luhn(digits: Column) -> Column:
    back = F.reverse(digits)
    at = lambda i: F.substring(back, i, F.lit(1)).cast("int") * F.when(i % 2 == 0, 2).otherwise(1)
    return F.aggregate(F.sequence(F.lit(1), F.length(back)), F.lit(0), lambda a, i: a + F.when(at(i) > 9, at(i) - 9).otherwise(at(i))) % 10 == 0


def _valid(kind: str, value: Column) -> Column:
    digits = F.regexp_replace(value, "[^0-9]", "")
    if kind == "ip":
        return F.forall(F.split(value, r"\."), lambda x: F.coalesce(F.ltrim(x, F.lit("0")).try_cast("int") <= 255, F.regexp_like(x, F.lit("^0+$"))))
    if kind == "card":
        return F.length(digits).between(14, 19) & _luhn(digits)
    if kind == "phone":
        return F.length(digits).between(10, 15)
    return F.lit(True)


def _spans(docs: DataFrame) -> DataFrame:
    """Adds base: array<struct<start, kind, end, value>> by start, then kind; each kind is a column of its own, so nothing is computed twice."""
    for k, kind in enumerate(KINDS):
        hint = F.col("text").contains(HINTS[kind]) if kind == "email" else F.regexp_like("text", F.lit(HINTS[kind]))
        none = F.array().cast("array<struct<start:int,end:int,value:string>>")
        docs = docs.withColumn(f"_f{k}", F.when(hint, _found(F.col("text"), PATTERNS[kind])).otherwise(none))
        docs = docs.withColumn(f"_k{k}", F.transform(F.filter(f"_f{k}", _valid_of(kind)), _struct_of(k))).drop(f"_f{k}")
    return docs.withColumn("base", F.array_sort(F.concat(*[f"_k{k}" for k in range(len(KINDS))]))).drop(*[f"_k{k}" for k in range(len(KINDS))])


def _valid_of(kind: str):
    return lambda m: _valid(kind, m["value"])


def _struct_of(k: int):
    return lambda m: F.struct(m["start"].alias("start"), F.lit(k).alias("kind"), m["end"].alias("end"), m["value"].alias("value"))


def _replaced(text: Column, spans: Column, mark) -> Column:
    """text with mark(span) in the place of each span (sorted by start); overlapping spans become one, marked by the first."""

    def one(part: Column, base: Column):
        return lambda a, s: F.when(s["start"] < a["at"], F.struct(F.greatest(a["at"], s["end"]).alias("at"), a["out"].alias("out"))).otherwise(
            F.struct(s["end"].alias("at"), F.concat(a["out"], F.substring(part, a["at"] - base + 1, s["start"] - a["at"]), mark(s)).alias("out"))
        )

    def walk(a: Column, spans: Column) -> Column:
        # Only the stretch of text that these spans reach is looked at.
        part = F.substring(text, a["at"] + 1, F.greatest(F.array_max(spans["end"]), a["at"]) - a["at"])
        done = let(part, lambda p: F.aggregate(spans, F.struct(a["at"].alias("at"), F.lit("").alias("out")), one(p, a["at"])))
        return let(done, lambda w: F.struct(w["at"].alias("at"), F.concat(a["out"], F.array(w["out"])).alias("out")))

    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out"))
    built = lambda parts: F.aggregate(parts, start, walk, lambda a: F.concat(F.array_join(a["out"], ""), F.substring(text, a["at"] + 1, F.length(text))))
    return let(_walks(spans), lambda parts: F.when(parts.isNull(), text).otherwise(built(parts)))


def _words(text: Column) -> Column:
    """The different words of text that can be terms, in lower case."""
    words = F.array_distinct(F.transform(F.split(text, r"[^\p{L}\p{N}]+"), F.lower))
    return F.filter(words, lambda w: (F.length(w) >= LEAST_LETTERS) & F.regexp_like(w, F.lit(r"\p{L}")))


def _together(some: DataFrame) -> DataFrame:
    """value (hash), word, row: the words outside the base spans of each different text with base spans, for values of enough texts.

    A pair stands in no more texts than its value, so values of fewer than SUPPORT texts cannot have a term.
    """
    values = some.select("row", F.explode(F.array_distinct("base.value")).alias("v")).select("row", F.xxhash64("v").alias("value")).distinct()
    often = values.groupBy("value").agg(F.count("*").alias("of_value")).where(f"of_value >= {SUPPORT}").select("value")
    values = c.written(values.join(often, "value", "left_semi"))
    texts = some.join(values.select("row").distinct(), "row", "left_semi").dropDuplicates(["row"])
    words = texts.select("row", _words(_replaced(F.col("text"), F.col("base"), lambda s: F.lit(" "))).alias("words"))
    return words.join(values, "row").select("value", F.explode("words").alias("word"), "row")


def disclosures(docs: DataFrame, together: DataFrame) -> DataFrame:
    """value, word, bits, certainty of the words over both thresholds. docs (row, text) gives the words' counts of different texts over the whole corpus."""
    pairs = together.groupBy("value", "word").agg(F.count("*").alias("both"))
    # A word stands in at least as many texts as it shares with any values, so most common words are out before the corpus is read.
    least = together.groupBy("word").agg(F.count_distinct("row").alias("least"))
    pairs = c.written(pairs.where(f"both >= {SUPPORT}").join(least, "word").where(F.col("both") >= CERTAINTY * F.col("least")).drop("least"))
    words = c.written(pairs.select("word").distinct())
    n_words = words.count()
    n = docs.select("row").distinct().count()
    if n_words:
        totals = _holding(docs, words, n_words).groupBy("word").agg(F.count("*").alias("of_word"))
    else:
        totals = words.withColumn("of_word", F.lit(1).cast("long"))
    values = together.select("value", "row").distinct().groupBy("value").agg(F.count("*").alias("of_value"))
    return (
        pairs.join(totals, "word").join(values, "value")
        .withColumn("certainty", F.col("both") / F.col("of_word")).withColumn("bits", F.log2(F.col("both") * F.lit(float(n)) / (F.col("of_word") * F.col("of_value"))))
        .where((F.col("certainty") >= CERTAINTY) & (F.col("bits") >= BITS)).select("value", "word", "bits", "certainty")
    )


def _holding(docs: DataFrame, words: DataFrame, n_words: int) -> DataFrame:
    """row, word: which different texts of docs (row, text) hold which of words; a bit filter of the words goes first where it is small enough."""
    seen, bits = _words(F.col("text")), c.filter_bits(max(1, n_words), 128)
    if bits <= c.FILTER_BITS_MOST:
        held = c.bit_words(words, "word", bits, (0, 1))
        seen = F.filter(seen, lambda w: c.in_filter(w, held, (0, 1)))
    return docs.select("row", F.explode(seen).alias("word")).join(words, "word", "left_semi").distinct()


def _terms(steps: Column, words: Column) -> Column:
    """array<struct<start, end, value>> of those words of steps (gap, word) that are in words, in lower case."""
    kept = lambda w: F.when(F.array_contains(words, F.lower(w)), F.lower(w))
    # A run of other words is one step: its code points go to the gap of the next term.
    one = lambda a, x: let(kept(x["word"]), lambda w: F.when(w.isNull(), F.struct((a["gap"] + x["gap"] + F.coalesce(F.length(x["word"]), F.lit(0))).alias("gap"), a["out"].alias("out"))).otherwise(
        F.struct(F.lit(0).alias("gap"), F.concat(a["out"], F.array(F.struct((a["gap"] + x["gap"]).alias("gap"), w.alias("value")))).alias("out"))
    ))
    walk = lambda a, part: let(F.aggregate(part, F.struct(a["gap"].alias("gap"), F.array().cast("array<struct<gap:int,value:string>>").alias("out")), one), lambda w: F.struct(w["gap"].alias("gap"), F.concat(a["out"], F.array(w["out"])).alias("out")))
    start = F.struct(F.lit(0).alias("gap"), F.array().cast("array<array<struct<gap:int,value:string>>>").alias("out"))
    return let(_walks(steps), lambda parts: F.when(parts.isNull(), F.array().cast(_SPAN)).otherwise(_placed(F.flatten(F.aggregate(parts, start, walk)["out"]))))


def _named(spans: Column) -> Column:
    kinds = F.array(*[F.lit(k) for k in (*KINDS, "term")])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(kinds, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def _all_spans(documents: DataFrame, keep: list[str]) -> DataFrame:
    """All rows with base (their base spans) and spans (these and the terms), and the columns of keep."""
    docs = documents.withColumn("text", F.coalesce("text", F.lit(""))).withColumn("row", F.xxhash64("text"))
    texts, none = docs.select("row", "text"), F.array().cast("array<struct<start:int,kind:int,end:int,value:string>>")
    some = c.written(_spans(texts).where(F.size("base") > 0))
    words = c.written(disclosures(texts, c.written(_together(some))).select("word").distinct())
    n_words = words.count()
    docs = _spans(docs.select("doc_id", "row", *keep))
    if not n_words:
        return docs.withColumn("spans", F.col("base"))
    held = c.written(_holding(texts, words, n_words).groupBy("row").agg(F.collect_set("word").alias("_words")))
    # Words and what is before each of them, walked once; a step without a value is a word that is no term.
    steps = F.zip_with(F.split("text", WORD, -1), F.regexp_extract_all("text", F.lit(WORD), 0), lambda p, w: F.struct(F.length(p).alias("gap"), w.alias("word")))
    docs = docs.join(held, "row", "left").withColumn("_terms", F.when(F.col("_words").isNotNull(), F.transform(_terms(steps, F.col("_words")), _struct_of(len(KINDS)))).otherwise(none))
    # A word inside a base span is covered already.
    outside = F.filter("_terms", lambda t: ~F.exists("base", lambda b: (t["start"] < b["end"]) & (b["start"] < t["end"])))
    return docs.withColumn("spans", F.array_sort(F.concat("base", outside))).drop("_terms", "_words")


def find(documents: DataFrame) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_term for every row of documents.

    A null text is empty and has no spans. Rows that repeat stay repeated; a text counts once for the
    disclosure of a word however often its row repeats. An empty table gives an empty result.
    """
    docs = _all_spans(documents.select("doc_id", "text"), ["text"])
    counts = [F.size(F.filter("spans", _is(k))).cast("long").alias(f"n_{kind}") for k, kind in enumerate((*KINDS, "term"))]
    return docs.select("doc_id", *counts, F.sha2(_named(F.col("base")).cast("binary"), 256).alias("base_sha256"), _named(F.col("spans")).alias("spans"))


def _is(k: int):
    return lambda s: s["kind"] == k


def sanitise(documents: DataFrame) -> DataFrame:
    """documents with every span replaced by its kind in angle brackets; overlapping spans become one, named by the first.

    All columns stay, n_chars (if there) follows the new text. Rows without spans stay as they are.
    """
    others = [x for x in documents.columns if x not in ("doc_id", "text")]
    plain = documents.select("doc_id", "text", F.struct(*[F.col(f"`{x}`") for x in others]).alias("_rest")) if others else documents.select("doc_id", "text", F.lit(None).cast("string").alias("_rest"))
    docs = _all_spans(plain, ["text", "_rest"])
    kinds = F.array(*[F.lit(f"<{k.upper()}>") for k in (*KINDS, "term")])
    changed = F.size("spans") > 0
    docs = docs.withColumn("_new", F.when(changed, _replaced(F.col("text"), F.col("spans"), lambda s: F.element_at(kinds, s["kind"] + 1))).otherwise(F.col("text")))
    cols = []
    for x in documents.columns:
        if x == "text":
            cols.append(F.col("_new").alias(x))
        elif x == "doc_id":
            cols.append(F.col(x))
        elif x == "n_chars":
            cols.append(F.when(changed, F.length("_new").cast(documents.schema[x].dataType)).otherwise(F.col(f"_rest.`{x}`")).alias(x))
        else:
            cols.append(F.col(f"_rest.`{x}`").alias(x))
    return docs.select(*cols)
