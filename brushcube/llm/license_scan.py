"""Licence scans: a trained paragraph classifier. Documents are scanned with DataFrame functions only.

A paragraph is a line with the lines that it is wrapped into: a line that doesn't end a sentence goes on in the next one that isn't blank. Features are word 1- to 3-grams that hold a trigger (a word of a licence notice that a sample of ordinary paragraphs hardly
has, and of every notice its rarest words at least, so many that a paragraph that the notice could confirm holds one), so a paragraph without
triggers has no features and is unknown by the model itself. How often a notice occurs in the documents decides nothing: the sample is of distinct paragraphs, and those
that a notice would confirm aren't ordinary. A multinomial logistic regression over the families and
``unknown`` is trained on varied notices and on ordinary paragraphs (a bounded sample); a family counts
where its probability reaches the threshold, which is calibrated on held-out samples (a fifth of the ordinary paragraphs and of the
varied notices, not learnt from; ``held_out`` has their shares), and a comparison with the family's notices (share of the
notice's words that stand in the paragraph) confirms it.

Training runs on the driver on at most ORDINARY paragraphs, from anywhere in the documents, of at most PARAGRAPH characters; scanning reads every paragraph of every text.

Two notices on neighbouring lines that end no sentence are one paragraph, which is given the more probable family.

Defined results: null and empty texts have no paragraphs and no licence; of several licences in a document all are
listed, the most probable is named (ties by name); repeated rows are scanned each; other columns are kept by ``scan``.
"""

from __future__ import annotations

import random
from collections import Counter

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import LETTER_WORD, hand_over, table, words_of

#: Short notices by which works name their licence, by family.
NOTICES = {
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0.", "This project is released under the Apache License 2.0.", "Distributed under the Apache 2.0 license."],
    "BSD-3-Clause": ["Redistribution and use in source and binary forms, with or without modification, are permitted.", "Released under the BSD 3-Clause License.", "Licensed under the 3-clause BSD license."],
    "CC-BY-4.0": ["Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "CC-BY-SA-4.0": ["Licensed under CC BY-SA 4.0.", "Content is available under the Creative Commons Attribution-ShareAlike 4.0 License."],
    "CC0-1.0": ["Dedicated to the public domain under CC0 1.0.", "To the extent possible under law, the author has waived all copyright under CC0."],
    "GPL-2.0": ["This program is licensed under the GNU General Public License, version 2.", "Released under the GPLv2 license."],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3.", "This program is free software under the GNU General Public License version 3.", "Released under the GPLv3 license."],
    "LGPL-3.0": ["Licensed under the GNU Lesser General Public License, version 3.", "Released under the LGPLv3 license."],
    "MIT": ["Released under the MIT License.", "Licensed under the MIT license.", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software."],
    "MPL-2.0": ["This file is subject to the terms of the Mozilla Public License, version 2.0.", "Licensed under the MPL 2.0 license."],
}
UNKNOWN = "unknown"
ORDINARY, PARAGRAPH, VARIANTS, CONFIRM = 4000, 2000, 40, 0.6
#: A line break inside a sentence. Blanks are only tried from the first of a run, so long runs cost no more than their length.
WRAP = r"(?<![.!?:;\s])[ \t\r]*\n(?=[ \t]*[^\s])"


def _words(text: str) -> list[str]:
    import re

    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", text.lower())


_NOTICE_WORDS = [set(_words(n)) for ns in NOTICES.values() for n in ns]


def grams(words: list[str], triggers: set[str]) -> set[str]:
    return {" ".join(g) for n in (1, 2, 3) for i in range(len(words) - n + 1) if triggers & set(g := words[i : i + n])}


def paragraphs_of(text) -> Column:
    return F.split(F.regexp_replace(F.coalesce(text, F.lit("")), WRAP, " "), "\n")


def likeness_of(words: list[str]) -> float:
    """The largest share of a notice's words that stand in a paragraph, as ``scan`` compares them."""
    have = set(words)
    return max(len(n & have) / len(n) for n in _NOTICE_WORDS)


class LicenceModel:
    """Triggers, features, weights (feature x class) and the threshold. Bounded by the notices."""

    def __init__(self, ordinary: list[str], seed: int = 7):
        rng = random.Random(seed)
        plain = [w for p in ordinary if (w := _words(p))]
        marked = {w for ns in NOTICES.values() for n in ns for w in _words(n)}
        plain = [w for w in plain if not {"licensed", "license", "licence", "copyright"} & set(w) and likeness_of(w) < CONFIRM]
        often = Counter(w for p in plain for w in set(p))
        self.triggers = {w for w in marked if often[w] * 500 <= len(plain) and not w.isdigit() and len(w) > 1}
        for n in _NOTICE_WORDS:  # a paragraph with CONFIRM of the words lacks fewer of them than are taken here
            self.triggers |= set(sorted((w for w in n if not w.isdigit() and len(w) > 1), key=lambda w: (often[w], w))[: int((1 - CONFIRM) * len(n)) + 1])
        self.classes = [UNKNOWN, *sorted(NOTICES)]
        samples = [(w, 0) for w in plain]
        apart = [i % 5 == 4 for i in range(len(plain))]  # held out
        filler = [w for p in plain for w in p] or ["text"]
        for k, name in enumerate(self.classes[1:], 1):
            for i in range(VARIANTS):
                w = _words(NOTICES[name][i % len(NOTICES[name])])
                if i >= len(NOTICES[name]):  # varied: a word lost, words of other text around
                    w = [x for x in w if rng.random() > 0.08]
                    w = [rng.choice(filler) for _ in range(rng.choice((0, 0, 2, 5)))] + w + [rng.choice(filler) for _ in range(rng.choice((0, 0, 2, 5)))]
                samples.append((w, k))
                apart.append(i >= len(NOTICES[name]) and i % 5 == 4)
        for t in sorted(self.triggers):  # a single word out of a notice names no licence
            samples += [([*rng.choices(filler, k=4), t, *rng.choices(filler, k=4)], 0)] * 3
        self.features = sorted({g for w, _ in samples for g in grams(w, self.triggers)} & {g for n in NOTICES.values() for t in n for g in grams(_words(t), self.triggers)})
        at = {g: i for i, g in enumerate(self.features)}
        x, y = np.zeros((len(samples), len(at) + 1)), np.zeros((len(samples), len(self.classes)))
        for i, (w, k) in enumerate(samples):
            x[i, 0], y[i, k] = 1, 1
            for g in grams(w, self.triggers) & at.keys():
                x[i, at[g] + 1] = 1
        out = np.array(apart + [False] * (len(samples) - len(apart)), dtype=bool)
        xs, ys, x, y = x[out], y[out], x[~out], y[~out]
        b = np.zeros((x.shape[1], y.shape[1]))
        weight = np.where(y[:, 0] == 1, min(1.0, 4 * VARIANTS / max(1, y[:, 0].sum())), 1.0)[:, None]
        for _ in range(400):
            p = self._soft(x @ b)
            b -= 0.02 * (x.T @ (weight * (p - y)) + 0.02 * np.vstack([np.zeros(b.shape[1]), b[1:]]))
        # The least threshold, of at most 0.9, that no held-out ordinary paragraph reaches.
        p, plain_ones = self._soft(xs @ b), ys[:, 0] == 1
        self.threshold = float(np.clip(p[plain_ones, 1:].max() + 1e-3 if plain_ones.any() else 0.5, 0.5, 0.9))
        named = np.where(p[:, 1:].max(axis=1, initial=0.0) >= self.threshold, p[:, 1:].argmax(axis=1) + 1, 0) if len(p) else np.zeros(0, int)
        right = named == ys.argmax(axis=1)
        share = lambda of: (int(of.sum()), float(right[of].mean()) if of.any() else 1.0)
        self.held_out = {"ordinary": share(plain_ones), "notices": share(~plain_ones)}
        self.weights = b

    @staticmethod
    def _soft(z: np.ndarray) -> np.ndarray:
        e = np.exp(z - z.max(axis=1, keepdims=True))
        return e / e.sum(axis=1, keepdims=True)


def train_on(docs: DataFrame, text: str = "text") -> LicenceModel:
    """Learn from the notices and at most ORDINARY distinct paragraphs (those lowest by hash, wherever they stand)."""
    lines = docs.select(F.explode(paragraphs_of(F.col(text))).alias("t")).where(F.length(F.trim("t")) > 0).select(F.substring("t", 1, PARAGRAPH).alias("t"))
    lines = lines.withColumn("h", F.xxhash64("t"))
    last = lines.select("h").distinct().orderBy("h").limit(ORDINARY).agg(F.max("h")).first()[0]  # hashes travel, not texts
    first = lines.where(F.col("h") <= F.lit(last)).groupBy("h").agg(F.min("t").alias("t")).orderBy("h")
    return LicenceModel([r["t"] for r in first.collect()])


def scan(docs: DataFrame, model: LicenceModel, text: str = "text") -> DataFrame:
    """``docs`` without its text, with n_paragraphs, n_licensed, licence, families, probability and confirmed."""
    spark = docs.sparkSession
    own = ("n_paragraphs", "n_licensed", "licence", "families", "probability", "confirmed", "row_no", "paragraphs", "hot")
    docs = docs.drop(*[c for c in own if c in docs.columns])
    keep = [c for c in docs.columns if c != text]
    triggers = sorted(model.triggers)
    rows = docs.select(F.monotonically_increasing_id().alias("row_no"), *keep, paragraphs_of(F.lower(F.col(text))).alias("paragraphs"))
    split = F.transform("paragraphs", lambda p, i: F.struct(i.alias("no"), words_of(p, LETTER_WORD).alias("w")))
    hot = F.filter(split, lambda s: F.exists(s["w"], lambda w: w.isin(triggers)))
    count = F.size(F.filter("paragraphs", lambda p: F.length(F.trim(p)) > 0)).cast("long")
    rows = hand_over(rows.select("row_no", *keep, count.alias("n_paragraphs"), hot.alias("hot")), "paragraphs")  # written once: row numbers of two evaluations need not agree
    spread = rows.select("row_no", *keep, "n_paragraphs", F.explode_outer("hot").alias("h"))

    # Distinct n-grams of the few paragraphs with triggers, against the weights (a table bounded by the notices).
    w, n = F.col("h.w"), F.size("h.w")
    of = lambda k: F.when(n >= k, F.transform(F.sequence(F.lit(1), n - k + 1), lambda i: F.array_join(F.slice(w, i, F.lit(k)), " "))).otherwise(F.array().cast("array<string>"))
    spread = spread.withColumn("grams", F.array_distinct(F.concat(of(1), of(2), of(3))))
    table_rows = ", ".join(f"struct('{g}' as gram, array({', '.join(f'{v:.12e}D' for v in model.weights[i + 1])}) as weight)" for i, g in enumerate(model.features))
    weights = F.broadcast(spark.sql(f"select inline(array({table_rows}))"))
    gram = spread.where("h is not null").select("row_no", F.col("h.no").alias("no"), F.explode("grams").alias("gram"), w.alias("w"))
    sums = gram.join(weights, "gram").groupBy("row_no", "no").agg(F.first("w").alias("w"), *[F.sum(F.col("weight")[k]).alias(f"z{k}") for k in range(len(model.classes))])
    z = [F.col(f"z{k}") + F.lit(float(model.weights[0][k])) for k in range(len(model.classes))]
    total = sum((F.exp(x) for x in z[1:]), F.exp(z[0]))
    best = F.array_max(F.array(*[F.struct((F.exp(x) / total).alias("p"), F.lit(c).alias("family")) for x, c in zip(z, model.classes)]))
    likeness = F.lit(0.0)
    for c in model.classes[1:]:
        shares = [F.size(F.array_intersect(F.array(*[F.lit(x) for x in sorted(set(_words(t)))]), F.col("w"))) / F.lit(float(len(set(_words(t))))) for t in NOTICES[c]]
        likeness = F.when(F.col("b.family") == c, F.greatest(*shares, F.lit(0.0))).otherwise(likeness)
    found = sums.withColumn("b", best).where((F.col("b.family") != UNKNOWN) & (F.col("b.p") >= model.threshold))
    found = found.withColumn("sure", likeness >= CONFIRM).groupBy("row_no").agg(
        F.count("*").alias("n"), F.max(F.struct("sure", "b.p", "b.family")).alias("top"), F.array_join(F.array_sort(F.collect_set(F.when(F.col("sure"), F.col("b.family")))), ",").alias("fam"))
    out = rows.drop("hot").join(found.withColumnRenamed("row_no", "found_no"), F.col("row_no") == F.col("found_no"), "left")
    return out.select(*keep, "n_paragraphs", F.coalesce("n", F.lit(0)).alias("n_licensed"), F.when(F.col("top.sure"), F.col("top.family")).otherwise(UNKNOWN).alias("licence"),
                      F.coalesce("fam", F.lit("")).alias("families"), F.coalesce("top.p", F.lit(0.0)).alias("probability"), F.coalesce("top.sure", F.lit(False)).alias("confirmed"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return scan(docs, train_on(docs))


ORACLE_SQL = None  # a trained model; tests hold it against planted notices
