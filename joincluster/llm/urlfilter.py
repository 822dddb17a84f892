"""URL filtering by a cascade of Bloom filters: exact membership of listed keys without a join.

Level 1 encodes the listed keys. Level 2 encodes those keys of the corpus's own key universe that
level 1 wrongly admits, level 3 the listed keys that level 2 wrongly catches, and so on until a
level makes no error over the universe. A key of the universe is listed exactly if the first level
that rejects it has an even number (or, if none rejects it, the last level has an odd one).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common as c

#: Rules of the query: key (host and start of the path) and verdict.
RULES = (("net/", "block"), ("example.net/en/", "allow"), ("example.com/de/", "block"), ("org/fr/", "allow"))
#: Host labels that the method itself blocks where no rule fits.
BLOCKED_LABELS = ("ads-track", "adult-x", "casino-win", "cheap-pills", "free-bets", "spam-farm")


#: Bits of a level for each key it encodes.
PER_KEY = 3


@dataclass
class Cascade:
    """levels: (words of the bit filter, seeds of its hashes)."""

    levels: list[tuple[list[int], tuple[int, ...]]]

    def listed(self, key: Column) -> Column:
        out: Column = F.lit(False)
        for i in range(len(self.levels) - 1, -1, -1):
            words, seeds = self.levels[i]
            hit = c.in_filter(key, words, seeds)
            last = i == len(self.levels) - 1
            out = hit if last else hit & ~out
        return out


def build_cascade(listed: DataFrame, universe: DataFrame, hashes: int = 2) -> Cascade:
    """A cascade for the keys of listed (column key), exact over universe (column key).

    Both are distinct tables in the shared folder; each level reads only the keys that the level
    before it got wrong. Levels are small (PER_KEY bits a key), as the next ones mend their errors. A
    level over common.FILTER_BITS_MOST bits raises ValueError: list_by_join is the way for such lists.
    """
    levels: list[tuple[list[int], tuple[int, ...]]] = []
    inside, outside = listed.select("key"), universe.select("key").join(listed.select("key"), "key", "left_anti")
    n = inside.count()
    while n:
        seeds = tuple(range(100 * len(levels), 100 * len(levels) + hashes))
        words = c.bit_words(inside, "key", c.filter_bits(n, PER_KEY, 64), seeds)
        levels.append((words, seeds))
        wrong = c.written(outside.where(c.in_filter(F.col("key"), words, seeds)))
        inside, outside = wrong, inside
        n = wrong.count()
    return Cascade(levels)


def list_by_join(keys: DataFrame, listed: DataFrame) -> DataFrame:
    """The way for lists whose filters are over the bound: keys (column key) that are listed, by a semi join."""
    return keys.join(listed.select("key"), "key", "left_semi")


def split_url(url: Column) -> tuple[Column, Column]:
    """host (A-Z lower-cased) and path; both empty without a :// or for null."""
    pattern = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    text = F.coalesce(url, F.lit(""))
    return c.fold(F.regexp_extract(text, pattern, 1)), F.regexp_extract(text, pattern, 2)


def candidate_keys(host: Column, path: Column, lengths: list[int]) -> Column:
    """Every host suffix joined to every start of the path that has the length of some rule's path."""
    parts = F.split(host, r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(parts)), lambda i: F.array_join(F.slice(parts, i, F.size(parts)), "."))
    starts = F.filter(F.array(*[F.when(F.length(path) >= n, F.substring(path, 1, n)) for n in lengths]), lambda p: p.isNotNull())
    keys = F.flatten(F.transform(suffixes, lambda s: F.transform(starts, lambda p: F.concat(s, p))))
    return F.when(host != "", keys).otherwise(F.array().cast("array<string>"))


def filter_urls(pages: DataFrame, rules=RULES, blocked_labels=BLOCKED_LABELS) -> DataFrame:
    """page_id, host, path, rule, verdict for every row of pages.

    rule is the longest fitting rule or null; verdict is the rule's, else block if a label of the
    host is listed, else allow. A null url or one without :// has empty host and path, no rule and
    verdict allow. Repeated rows stay repeated; an empty table gives an empty result.
    """
    spark = pages.sparkSession
    host, path = split_url(F.col("url"))
    base = pages.select("page_id", "url").select("page_id", host.alias("host"), path.alias("path"))
    lengths = sorted({len(k[k.index("/"):]) for k, _ in rules})
    keyed = base.select(
        "page_id", "host", "path",
        candidate_keys(F.col("host"), F.col("path"), lengths).alias("keys"),
        F.transform(F.split("host", r"\."), lambda x: F.concat(F.lit("label:"), x)).alias("labels"),
    )
    universe = c.written(keyed.select(F.explode(F.concat("keys", "labels")).alias("key")).distinct())
    listed = c.written(spark.createDataFrame([(k,) for k, _ in rules] + [(f"label:{x}",) for x in blocked_labels], "key string").distinct())
    if c.filter_bits(listed.count(), PER_KEY, 64) <= c.FILTER_BITS_MOST:
        cascade = build_cascade(listed, universe)
        judged = keyed.select("page_id", "host", "path", F.filter("keys", cascade.listed).alias("fits"), F.exists("labels", cascade.listed).alias("bad"))
    else:
        judged = _judged_by_join(keyed, list_by_join(universe, listed))
    best = F.aggregate("fits", F.lit("").cast("string"), lambda a, k: F.when(F.length(k) >= F.length(a), k).otherwise(a))
    verdicts = F.create_map(*[F.lit(x) for r in rules for x in r])
    return (
        judged.select("page_id", "host", "path", F.nullif(best, F.lit("")).alias("rule"), "bad")
        .select("page_id", "host", "path", "rule", F.coalesce(F.element_at(verdicts, F.col("rule")), F.when(F.col("bad"), "block").otherwise("allow")).alias("verdict"))
    )


def _judged_by_join(keyed: DataFrame, hits: DataFrame) -> DataFrame:
    """page_id, host, path, fits, bad as the cascade gives them, from the listed keys of the corpus (column key)."""
    places = keyed.select("host", "path", "keys", "labels").distinct()
    found = places.select("host", "path", F.explode(F.concat("keys", "labels")).alias("key")).join(hits, "key", "left_semi").groupBy("host", "path").agg(F.collect_set("key").alias("found"))
    none = F.array().cast("array<string>")
    both = keyed.join(found, ["host", "path"], "left").withColumn("found", F.coalesce("found", none))
    return both.select("page_id", "host", "path", F.array_intersect("keys", "found").alias("fits"), F.arrays_overlap("labels", "found").alias("bad"))


ORACLE_SQL = """
WITH u AS (
  SELECT page_id,
         coalesce(translate(regexp_extract(coalesce(url,''), '^.*?://([^/?#]*)([^?#]*)', 1, 's'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
         coalesce(regexp_extract(coalesce(url,''), '^.*?://([^/?#]*)([^?#]*)', 2, 's'), '') AS path
  FROM pages),
r AS (
  SELECT *, CASE
    WHEN host <> '' AND (host = 'example.net' OR host LIKE '%.example.net') AND path LIKE '/en/%' THEN 'example.net/en/'
    WHEN host <> '' AND (host = 'example.com' OR host LIKE '%.example.com') AND path LIKE '/de/%' THEN 'example.com/de/'
    WHEN (host = 'org' OR host LIKE '%.org') AND path LIKE '/fr/%' THEN 'org/fr/'
    WHEN (host = 'net' OR host LIKE '%.net') AND path LIKE '/%' THEN 'net/' END AS rule
  FROM u)
SELECT page_id, host, path, rule,
  CASE WHEN rule IN ('net/', 'example.com/de/') THEN 'block'
       WHEN rule IS NOT NULL THEN 'allow'
       WHEN regexp_matches('.' || host || '.', '[.](ads-track|adult-x|casino-win|cheap-pills|free-bets|spam-farm)[.]') THEN 'block'
       ELSE 'allow' END AS verdict
FROM r
"""
