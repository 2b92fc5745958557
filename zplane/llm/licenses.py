"""Licence scans by a trained paragraph classifier, in DataFrame operations only.

Paragraphs (lines, wrapped ones joined) become word 1- to 3-grams. A sparse logistic regression over the grams of known notices
gives each licence family and an unknown class a score; a temperature fitted on paragraphs that were kept
apart calibrates the probabilities. A family that wins is confirmed by comparing the paragraph with the
family's notices. Training runs on a bounded set on the driver; scanning joins the exploded grams with the
weight table (a fixed number of rows) and sums. Paragraphs without any of the words that a family needs
at least (a bound that follows from the weights) are unknown and skip that.
"""

from __future__ import annotations

import random
from collections import Counter

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Common licence notices by family.
NOTICES = {
    "mit": [
        "Released under the MIT License.", "This software is licensed under the MIT License.", "Distributed under the terms of the MIT license.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files",
    ],
    "apache": [
        "Licensed under the Apache License, Version 2.0.", "You may not use this file except in compliance with the License. You may obtain a copy of the License at apache.org",
        "This project is released under the Apache 2.0 license.", "SPDX-License-Identifier: Apache-2.0",
    ],
    "gpl": [
        "This work is licensed under the GNU General Public License, version 3.", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License",
        "Released under the GNU GPL version 2 or later.", "SPDX-License-Identifier: GPL-3.0-only",
    ],
    "lgpl": ["This library is licensed under the GNU Lesser General Public License, version 2.1.", "under the terms of the GNU Lesser General Public License as published by the Free Software Foundation", "Released under the LGPL."],
    "agpl": ["This work is licensed under the GNU Affero General Public License, version 3.", "under the terms of the GNU Affero General Public License", "Released under the AGPL version 3."],
    "bsd": [
        "Released under the BSD License.", "Licensed under the 3-Clause BSD License.", "Distributed under the terms of the Modified BSD License.",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    ],
    "mpl": ["Licensed under the Mozilla Public License, version 2.0.", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."],
    "isc": ["Released under the ISC License.", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"],
    "epl": ["Licensed under the Eclipse Public License, version 2.0.", "made available under the terms of the Eclipse Public License"],
    "cc-by": ["Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License.", "Licensed under CC BY-SA 4.0.", "licensed under a Creative Commons Attribution-ShareAlike License"],
    "cc-by-nc": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.", "Licensed under CC BY-NC-SA 4.0.", "Licensed under CC BY-NC-ND 4.0."],
    "cc0": ["Dedicated to the public domain under CC0 1.0.", "To the extent possible under law, the author has waived all copyright and related rights to this work", "released under CC0 1.0 Universal"],
    "unlicense": ["This is free and unencumbered software released into the public domain.", "Released under the Unlicense."],
    "proprietary": ["All rights reserved.", "Unauthorized copying of this file is strictly prohibited.", "This software is proprietary and confidential."],
}
#: Paragraphs that speak of licences without granting one.
OTHERS = [
    "He renewed his driving license at the public office last week.", "The general had a license to build, and the public came to see the work.", "Version 2.0 of the software was released under budget.",
    "She was granted permission to use the library free of charge.", "The university of California at Berkeley is known for its software.", "Common attribution errors are creative work.",
    "The following conditions are met by most persons.", "The terms of the agreement were published by the foundation.", "The restaurant lost its license after an inspection.",
]
FAMILIES = list(NOTICES)
UNKNOWN = len(FAMILIES)
#: Paragraphs of the corpus and documents they are drawn from (about), variants of each notice, and the probability that a family must reach.
PLAIN_PARAGRAPHS, PLAIN_DOCS, VARIANTS, LEAST, SIMILAR = 1500, 3000, 24, 0.5, 0.6
#: A line that ends without a closing mark goes on in the next one if that begins with a small letter.
_WRAP = r"(?<![.!?:;])[ \t\r]*\n[ \t]*(?=[a-z])"
#: A word in COMMON plain paragraphs is common; STOP words always are.
COMMON, STOP = 4, "a an and any are as at be by for from he his in is it of on or she that the this to was with you".split()


def word_array(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit("([a-z0-9]+)"), F.lit(1))


def grams(words: str) -> Column:
    """The 1- to 3-grams of a column of words."""
    two = f"filter(transform({words}, (x, i) -> IF(i + 1 < size({words}), concat(x, ' ', {words}[i + 1]), NULL)), x -> x IS NOT NULL)"
    three = f"filter(transform({words}, (x, i) -> IF(i + 2 < size({words}), concat(x, ' ', {words}[i + 1], ' ', {words}[i + 2]), NULL)), x -> x IS NOT NULL)"
    return F.expr(f"concat({words}, {two}, {three})")


def paragraphs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, para, words): the paragraphs of each text with their words; those without words are left out."""
    whole = F.regexp_replace(F.coalesce(F.col(text_col).cast("string"), F.lit("")), _WRAP, " ")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.posexplode(F.split(whole, "\n")).alias("para", "line"))
    return rows.select("doc_id", "para", word_array(F.col("line")).alias("words")).where(F.size("words") > 0)


def _variants(notice: str, rng: random.Random) -> list[str]:
    words, out = notice.split(" "), [notice]
    fill = ["see", "file", "author", "2019", "project", "code", "here", "team", "note", "data"]
    for _ in range(VARIANTS - 1):
        w = list(words)
        for _ in range(rng.randint(0, max(1, len(w) // 8))):
            if len(w) > 4:
                w.pop(rng.randrange(len(w)))
        if rng.random() < 0.3:
            w.insert(rng.randrange(len(w) + 1), rng.choice(fill))
        before, after = (rng.choices(fill, k=rng.randint(0, 6)) for _ in range(2))
        out.append(" ".join([*before, *w, *after]))
    return out


def train_licenses(docs: DataFrame, seed: int = 11) -> dict:
    """{"anchors", "grams": [(gram, weights)], "bias", "temperature", "accuracy"}; weights for each family and unknown.

    The training set is bounded: VARIANTS of each notice, and PLAIN_PARAGRAPHS paragraphs of about PLAIN_DOCS
    documents, both by hash, so what reaches the driver does not grow with the table (paragraphs that share a
    3-gram with a notice are not used, so notices in the corpus don't teach unknown).
    """
    spark = docs.sparkSession
    rng = random.Random(seed)
    known = [(f, v) for f, family in enumerate(FAMILIES) for n in NOTICES[family] for v in _variants(n, rng)] + [(UNKNOWN, v) for n in OTHERS for v in _variants(n, rng)]
    local = spark.createDataFrame([(i, t) for i, (_, t) in enumerate(known)], "doc_id long, text string")
    share = min(1 << 30, (PLAIN_DOCS << 30) // max(1, docs.count()))
    drawn = docs.select("doc_id", "text").where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 30)) < share)
    plain = paragraphs(drawn).orderBy(F.xxhash64("doc_id", "para"), "doc_id", "para", "words").limit(PLAIN_PARAGRAPHS)
    feats = [(known[r["doc_id"]][0], r["g"]) for r in paragraphs(local).select("doc_id", grams("words").alias("g")).orderBy("doc_id").collect()]  # bounded
    vocab = sorted({g for y, gs in feats if y != UNKNOWN for g in gs if " " in g or len(g) > 3 or g in ("mit", "gpl", "bsd", "mpl", "isc", "epl", "cc0", "cc", "gnu")})
    telling = {g for y, gs in feats if y != UNKNOWN for g in gs if g.count(" ") == 2}
    extra = [g for r in plain.select(grams("words").alias("g")).collect() if not telling.intersection(g := r["g"])]  # bounded
    feats += [(UNKNOWN, g) for g in extra]
    seen = Counter(x for g in extra for x in {x for x in g if " " not in x})
    common = {x for x, n in seen.items() if n >= COMMON} | set(STOP)
    vocab = [g for g in vocab if not common.issuperset(g.split(" "))]  # a gram of common words alone tells nothing
    at = {g: i for i, g in enumerate(vocab)}
    x = np.zeros((len(feats), len(vocab)), np.float32)
    for r, (_, gs) in enumerate(feats):
        x[r, [at[g] for g in set(gs) if g in at]] = 1
    y = np.array([f for f, _ in feats])
    apart = np.arange(len(feats)) % 5 == 0
    w, b = _fit(x[~apart], y[~apart])
    logit = x[apart] @ w + b
    temperature = min(np.linspace(0.5, 3, 26), key=lambda t: _loss(logit / t, y[apart]))
    keep = np.abs(w).max(1) > 0.05
    w = np.where(keep[:, None], w, 0)
    return {"anchors": _anchors(vocab, w, b, common), "grams": [(g, [float(v) for v in w[i]]) for g, i in at.items() if keep[i]], "bias": [float(v) for v in b], "temperature": float(temperature), "accuracy": float((logit.argmax(1) == y[apart]).mean())}


def _anchors(vocab: list[str], w: np.ndarray, b: np.ndarray, common: set[str]) -> list[str] | None:
    """Words of which a paragraph must hold one to be given a family: without them all other grams together can't lift any
    family over unknown. None if unknown doesn't win without evidence."""
    margin = np.maximum(0, w[:, :UNKNOWN] - w[:, [UNKNOWN]])
    gap = b[UNKNOWN] - b[:UNKNOWN]
    if (gap <= 0).any():
        return None
    of: dict[str, list[int]] = {}
    for i, g in enumerate(vocab):
        for word in set(g.split(" ")) - common:
            of.setdefault(word, []).append(i)
    left, out = np.ones(len(vocab), bool), []
    while ((total := margin[left].sum(0)) >= gap * (1 - 1e-6)).any():
        over = total >= gap * (1 - 1e-6)
        best = max(sorted(of), key=lambda x: margin[[i for i in of[x] if left[i]]][:, over].sum())
        left[of.pop(best)] = False
        out.append(best)
    return out


def _loss(logit: np.ndarray, y: np.ndarray) -> float:
    z = logit - logit.max(1, keepdims=True)
    return float(np.mean(np.log(np.exp(z).sum(1)) - z[np.arange(len(y)), y]))


def _fit(x: np.ndarray, y: np.ndarray, steps: int = 250, rate: float = 0.1, l1: float = 2e-4) -> tuple[np.ndarray, np.ndarray]:
    """Multinomial logistic regression with an L1 penalty, by Adam and soft thresholding."""
    classes = UNKNOWN + 1
    w, b = np.zeros((x.shape[1], classes), np.float32), np.zeros(classes, np.float32)
    target = np.eye(classes, dtype=np.float32)[y]
    share = np.bincount(y, minlength=classes)
    weight = (len(y) / classes / np.maximum(share, 1))[y].astype(np.float32)
    mw, vw, mb, vb = np.zeros_like(w), np.zeros_like(w), np.zeros_like(b), np.zeros_like(b)
    for t in range(1, steps + 1):
        z = x @ w + b
        p = np.exp(z - z.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        d = (p - target) * weight[:, None] / len(y)
        for v, m, s, g in ((w, mw, vw, x.T @ d), (b, mb, vb, d.sum(0))):
            m += 0.1 * (g - m)
            s += 0.01 * (g * g - s)
            v -= rate * (m / (1 - 0.9**t)) / (np.sqrt(s / (1 - 0.99**t)) + 1e-8)
        w[:] = np.sign(w) * np.maximum(0, np.abs(w) - rate * l1)
    return w, b


def scan_licenses(docs: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text", least: float = LEAST, similar: float = SIMILAR) -> DataFrame:
    """(doc_id, para, family, probability, similarity, confirmed): paragraphs that the classifier gives a family.

    similarity is the largest share of the 2-grams of one of the family's notices that the paragraph holds
    (1-grams for one-word notices); confirmed tells whether it reaches `similar`. Null and empty texts
    have no paragraphs. Rows with a null id are scanned like others. Rows that agree in id, place and words of a
    paragraph give one result; rows that share an id but not the paragraph give one each.
    """
    spark = docs.sparkSession
    lines = paragraphs(docs, id_col, text_col)
    if model["anchors"] is not None:  # the rest is unknown whatever else it holds
        lines = lines.where(F.arrays_overlap("words", F.array(*(F.lit(a) for a in model["anchors"]))))
    sums, picks = _scores(spark, lines.distinct(), model)
    found = sums.select("doc_id", "para", "words", *picks).where((F.col("family") != F.lit("unknown")) & (F.col("probability") >= least))
    notices = [(f, i, t) for f in FAMILIES for i, t in enumerate(NOTICES[f])]
    known = spark.createDataFrame(notices, "family string, notice int, text string")
    pairs = lambda words: F.array_distinct(F.expr(f"filter(transform({words}, (x, i) -> IF(i + 1 < size({words}) OR size({words}) = 1, concat(x, ' ', coalesce({words}[least(i + 1, size({words}) - 1)], '')), NULL)), x -> x IS NOT NULL)"))
    known = known.withColumn("words", word_array(F.col("text"))).select("family", pairs("words").alias("of"))
    known = known.groupBy("family").agg(F.collect_list("of").alias("notices"))  # a fixed table
    hits = found.join(F.broadcast(known), "family").withColumn("mine", pairs("words"))
    best = hits.withColumn("similarity", F.array_max(F.transform("notices", lambda of: F.size(F.array_intersect(of, F.col("mine"))) / F.size(of))))
    return best.select("doc_id", "para", "family", F.round("probability", 6).alias("probability"), F.round("similarity", 6).alias("similarity"), (F.col("similarity") >= similar).alias("confirmed"))


def _scores(spark: SparkSession, lines: DataFrame, model: dict) -> tuple[DataFrame, list[Column]]:
    classes = [*FAMILIES, "unknown"]
    cols = [f"w{i}" for i in range(len(classes))]
    table = spark.createDataFrame([(g, *w) for g, w in model["grams"]], "gram string, " + ", ".join(f"{c} double" for c in cols))
    table = table.withColumn("key", F.xxhash64("gram")).select("key", *cols)
    vocab = F.split(F.lit("|".join(g for g, _ in model["grams"])), r"\|")  # only known grams go on, so a long paragraph is not copied for each of its own
    rows = lines.select("doc_id", "para", "words", F.explode(F.array_intersect(grams("words"), vocab)).alias("gram")).withColumn("key", F.xxhash64("gram")).drop("gram")
    sums = rows.join(F.broadcast(table), "key").groupBy("doc_id", "para", "words").agg(*(F.sum(c).alias(c) for c in cols))
    logit = [(F.round(F.col(c), 9) + b) / model["temperature"] for c, b in zip(cols, model["bias"])]
    top = F.greatest(*logit)
    probability = 1.0 / sum((F.exp(z - top) for z in logit[1:]), F.exp(logit[0] - top))
    family = F.when(logit[-1] >= top, F.lit(classes[-1]))
    for z, name in zip(logit[:-1], classes):
        family = family.when(z >= top, F.lit(name))
    return sums, [family.alias("family"), probability.alias("probability")]
