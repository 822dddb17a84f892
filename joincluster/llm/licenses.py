"""Licence statements found by a trained paragraph classifier, confirmed by comparison with templates.

A softmax regression over word one- and two-grams is fitted on the driver: on variants of the
families' templates, on sentences that only use such words, and on a bounded sample of the corpus's
own paragraphs, all but the first being of the class unknown. Features that no template holds have
no weight, so the weights are sparse and small. Its temperature is set on held-out variants, so
probabilities are calibrated; a paragraph whose best family is less likely than LIMIT, or whose
words do not cover the family's template, is unknown. Scoring uses DataFrame functions alone.
"""

from __future__ import annotations

import re
from itertools import combinations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common as c

#: Families and short forms of their notices (fixed values).
TEMPLATES = {
    "apache-2.0": ("Licensed under the Apache License, Version 2.0", "Apache License 2.0", "you may not use this file except in compliance with the Apache License Version 2.0"),
    "mit": ("Released under the MIT License", "This software is licensed under the MIT license", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software"),
    "gpl-3.0": ("This work is licensed under the GNU General Public License, version 3", "GNU General Public License version 3 or later", "GPL version 3 license"),
    "gpl-2.0": ("licensed under the GNU General Public License, version 2", "GPL version 2 license"),
    "lgpl": ("licensed under the GNU Lesser General Public License", "LGPL license"),
    "agpl-3.0": ("licensed under the GNU Affero General Public License, version 3", "AGPL version 3 license"),
    "bsd": ("Redistribution and use in source and binary forms, with or without modification, are permitted", "Released under the BSD License", "BSD 3 clause license"),
    "mpl-2.0": ("subject to the terms of the Mozilla Public License, version 2.0", "Mozilla Public License 2.0"),
    "cc-by-4.0": ("Licensed under CC BY 4.0", "Creative Commons Attribution 4.0 International License"),
    "cc-by-sa-4.0": ("Licensed under CC BY-SA 4.0", "Creative Commons Attribution ShareAlike 4.0 International License"),
    "cc-by-nc-4.0": ("Licensed under CC BY-NC 4.0", "Creative Commons Attribution NonCommercial 4.0 International License"),
    "cc0": ("Dedicated to the public domain under CC0 1.0", "Creative Commons CC0 1.0 Universal"),
}
#: Sentences with such words that name no licence (fixed values).
OTHERS = (
    "the licensed driver showed a license at the public office", "general public opinion on version 2 of the plan", "he was released under the bridge", "a work of art under the general",
    "the commons is a public place", "permission to use the room is granted", "redistribution of land in forms", "version 3 of the software is out", "this file is not in use", "an apache helicopter landed",
    "the license fee is free of charge", "public domain name", "all rights reserved", "terms of the contract", "the international office", "creative work and attribution of causes",
)
#: Paragraphs of the corpus that the classifier is fitted on, and their length at most.
SAMPLE_CHARS = 2000
SAMPLE, VARIANTS, ROUNDS, LIMIT, COVER = 2000, 40, 300, 0.6, 0.6
BREAK = r"[^a-z0-9]+"


def tokens(text: str) -> list[str]:
    return [w for w in re.split(BREAK, text.translate(str.maketrans(c.UPPER, c.LOWER))) if w]


def grams(words: list[str]) -> list[str]:
    return [*words, *(f"{a} {b}" for a, b in zip(words, words[1:], strict=False))]


class Model:
    """weights: for each known gram, its log-odds by class; all other grams weigh nothing."""

    def __init__(self, background: list[str], seed: int = 5):
        rng = np.random.default_rng(seed)
        self.families = list(TEMPLATES)
        self.vocabulary = {g: i for i, g in enumerate(sorted({g for ts in TEMPLATES.values() for t in ts for g in grams(tokens(t))}))}
        noise = [w for t in background for w in tokens(t)] or ["of", "the", "and"]
        x, y = [], []
        for k, ts in enumerate(TEMPLATES.values()):
            for t in ts:
                for i in range(VARIANTS):
                    words = [w for w in tokens(t) if i == 0 or rng.random() > 0.05]
                    before, after = (list(rng.choice(noise, rng.integers(0, 12))) if i % 2 else [] for _ in range(2))
                    x.append([*before, *words, *after])
                    y.append(k)
        for t in (*OTHERS, *background):
            x.append(tokens(t))
            y.append(len(self.families))
        words = [w for t in TEMPLATES.values() for s in t for w in tokens(s)]
        for _ in range(VARIANTS * 10):  # stray words of templates in other text
            x.append([*rng.choice(noise, rng.integers(3, 20)), *rng.choice(words, rng.integers(1, 3))])
            y.append(len(self.families))
        m, y = np.zeros((len(x), len(self.vocabulary))), np.array(y)
        for i, ws in enumerate(x):
            m[i, [self.vocabulary[g] for g in set(grams(ws)) if g in self.vocabulary]] = 1
        held = rng.random(len(x)) < 0.2
        self.w, self.b = self._fit(m[~held], y[~held], len(self.families) + 1)
        logits = m[held] @ self.w + self.b
        loss = lambda t: -np.log(_softmax(logits * t)[np.arange(len(logits)), y[held]] + 1e-12).mean()
        scale = min(np.linspace(0.3, 3, 55), key=loss) if len(logits) else 1.0
        self.w, self.b = self.w * scale, self.b * scale

    @staticmethod
    def _fit(x: np.ndarray, y: np.ndarray, n: int, rate: float = 1.0, ridge: float = 1e-4) -> tuple[np.ndarray, np.ndarray]:
        w, b, one = np.zeros((x.shape[1], n)), np.zeros(n), np.eye(n)[y]
        balance = (len(y) / (n * np.maximum(np.bincount(y, minlength=n), 1)))[y][:, None]
        for i in range(ROUNDS):
            g = (_softmax(x @ w + b) - one) * balance / len(y)
            step = rate * 20 / (1 + i / 100)
            w -= step * (x.T @ g + ridge * w)
            b -= step * g.sum(0) * 0.2
        return w, b


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def _numbered(words: Column, vocabulary: dict[str, int]) -> Column:
    pairs = F.zip_with(F.slice(words, 1, F.greatest(F.size(words) - 1, F.lit(0))), F.slice(words, 2, F.greatest(F.size(words) - 1, F.lit(0))), lambda a, b: F.concat_ws(" ", a, b))
    held = F.array(*[F.lit(g) for g in vocabulary])
    return F.filter(F.transform(F.array_distinct(F.concat(words, pairs)), lambda g: F.array_position(held, g).cast("int")), lambda i: i > 0)


def needed(template: str) -> tuple[set[str], int]:
    """A template's different words, and how many of them any text that covers it holds: pairs count only with both of their words."""
    ws = tokens(template)
    words, pairs = sorted(set(ws)), set(zip(ws, ws[1:], strict=False))
    for n in range(1, len(words) + 1):
        if any(n + sum(a in held and b in held for a, b in pairs) >= COVER * (len(words) + len(pairs)) - 1e-9 for held in map(set, combinations(words, n))):
            return set(words), n
    return set(words), len(words)


def cues(background: list[str]) -> list[str]:
    """Words of which any text that covers a template holds one: of each template's w words, n of them needed, any w - n + 1; those rarest in background are taken."""
    seen: dict[str, int] = {}
    for t in background:
        for w in set(tokens(t)):
            seen[w] = seen.get(w, 0) + 1
    out: set[str] = set()
    for ts in TEMPLATES.values():
        for t in ts:
            words, n = needed(t)
            out.update(sorted(words, key=lambda w: (seen.get(w, 0), -len(w), w))[: len(words) - n + 1])
    return sorted(out)


def scan(documents: DataFrame) -> DataFrame:
    """doc_id, n_paragraphs, n_licensed, families, paragraphs for every row of documents.

    A paragraph is a line with a word. families are the distinct families found, sorted and joined by
    commas; paragraphs holds for each licensed one its number (from 0), family, probability and the
    share of a template's one- and two-grams that it covers. A null or empty text has no paragraphs.
    Rows that repeat stay repeated. An empty table gives an empty result.
    """
    docs = documents.select("doc_id", F.coalesce("doc_id", F.lit(0)).alias("id"), F.coalesce("text", F.lit("")).alias("text"))  # a null id is a key like any other
    lines = F.filter(F.split("text", r"\n+"), lambda x: F.regexp_like(x, F.lit("[A-Za-z0-9]")))
    some = docs.select("doc_id", lines.alias("lines")).where(F.size("lines") > 0).select(F.xxhash64("doc_id").alias("h"), F.element_at("lines", F.pmod(F.xxhash64("doc_id"), F.size("lines")).cast("int") + 1).alias("line"))
    # A sort keeps SAMPLE lines a task; a bound on the hash, four times what SAMPLE rows need, leaves few to be kept. Ids are spread evenly by it.
    many = docs.count()
    if many > 8 * SAMPLE:
        some = some.where(F.col("h") <= F.lit(int(-(1 << 63) + (1 << 64) * (4 * SAMPLE / many))))
    named = {"license", "licensed", "copyright", "gnu", "apache", "mozilla", "commons"}
    background = [r["line"] for r in some.where(F.length("line") <= SAMPLE_CHARS).orderBy("h", "line").limit(SAMPLE).collect() if not named & set(tokens(r["line"]))]
    model = Model(background)
    names = list(model.vocabulary)
    base = docs.withColumn("row", F.xxhash64("text"))
    # Of each template any paragraph that covers it holds one of these words, so no licensed one is passed over.
    cue = rf"(?i)(?<![a-z0-9])(?:{'|'.join(cues(background))})(?![a-z0-9])"
    maybe = base.where(F.regexp_like("text", F.lit(cue))).dropDuplicates(["id", "row"]).select("id", "row", F.posexplode(lines).alias("paragraph", "line")).where(F.regexp_like("line", F.lit(cue)))
    words = F.filter(F.split(c.fold(F.col("line")), BREAK), lambda w: w != "")
    hit = c.written(maybe.withColumn("words", words).withColumn("g", _numbered(F.col("words"), model.vocabulary)).where(F.size("g") > 0).select("id", "row", "paragraph", "g"))
    flat = F.array(*[F.lit(float(v)) for v in np.round(model.w, 6).ravel()])
    n = len(model.families) + 1
    logit = lambda k: F.aggregate("g", F.lit(float(model.b[k])), lambda a, i: a + F.element_at(flat, (i - 1) * n + k + 1))
    hit = hit.withColumn("z", F.array(*[logit(k) for k in range(n)])).withColumn("top", F.array_max("z"))
    hit = hit.withColumn("e", F.transform("z", lambda v: F.exp(v - F.col("top")))).withColumn("sum", F.aggregate("e", F.lit(0.0), lambda a, v: a + v))
    hit = hit.withColumn("k", F.array_position("z", F.col("top")).cast("int")).withColumn("probability", F.element_at("e", F.col("k")) / F.col("sum"))
    templates = F.array(*[F.array(*[F.array(*[F.lit(names.index(g) + 1) for g in sorted(set(grams(tokens(t))))]) for t in ts]) for ts in TEMPLATES.values()])
    covered = F.array_max(F.transform(F.element_at(templates, F.col("k")), lambda t: F.size(F.array_intersect(t, F.col("g"))) / F.size(t)))
    hit = hit.where((F.col("k") < n) & (F.col("probability") >= LIMIT)).withColumn("cover", covered).where(F.col("cover") >= COVER)
    family = F.element_at(F.array(*[F.lit(x) for x in model.families]), F.col("k"))
    rows = hit.groupBy("id", "row").agg(F.array_sort(F.collect_list(F.struct("paragraph", family.alias("family"), F.round("probability", 6).alias("probability"), F.round("cover", 6).alias("cover")))).alias("paragraphs"))
    kind = "array<struct<paragraph:int,family:string,probability:double,cover:double>>"
    return base.select("doc_id", "id", "row", F.size(lines).cast("long").alias("n_paragraphs")).join(rows, ["id", "row"], "left").select(
        "doc_id", "n_paragraphs", F.size(F.coalesce("paragraphs", F.array().cast(kind))).cast("long").alias("n_licensed"),
        F.array_join(F.array_sort(F.array_distinct(F.coalesce(F.col("paragraphs.family"), F.array().cast("array<string>")))), ",").alias("families"), F.coalesce("paragraphs", F.array().cast(kind)).alias("paragraphs"),
    )
