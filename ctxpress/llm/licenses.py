"""Licence families in documents, paragraph by paragraph, in DataFrame operations.

Lines and stretches of eight lines, which hold notices that are wrapped, are split to words; their word n-grams are joined to
the sparse weights of a logistic regression over licence families, a class for licences of no known family and one for other
text. The softmax is calibrated by a temperature. A family has to be confirmed by a template: its words are compared with
those of the paragraph. What the model takes for a licence and no template confirms is ``unknown``.

The model is trained here, on the driver, from the templates below and variations of them; no corpus row is an input. A first
fit ranks words by how much they speak for any licence; the model proper is fitted on n-grams that hold one of the foremost
of them, its anchors. Text without an anchor has the biases alone for a score, which say ``other``, so it need not be scored.
"""

from __future__ import annotations

import random
import re

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ctxpress.llm.common import cut_lineage

#: Lines of a stretch, and words of a line that are scored together.
STRETCH, WIDE = 8, 64
# Words of every text, which are no anchors.
FUNCTION_WORDS = frozenset("a all an and any are as at be but by can for from general in into is it may new no not of on or part public see terms that the this to under use was with without work you code version v 1 2 3 4 1.0 2.0 2.1 3.0 4.0 v2 v3".split())
OTHER, UNKNOWN = "other", "unknown"
# Notices of each family.
TEMPLATES = {
    "mit": [
        "Released under the MIT License.",
        "MIT License",
        "This project is licensed under the MIT License, see the LICENSE file for details.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction",
    ],
    "apache-2.0": [
        "Licensed under the Apache License, Version 2.0.",
        "Apache License 2.0",
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License.",
        "SPDX-License-Identifier: Apache-2.0",
    ],
    "gpl": [
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
        "Licensed under the GNU GPL v2 or later.",
        "SPDX-License-Identifier: GPL-3.0-or-later",
    ],
    "lgpl": ["This library is licensed under the GNU Lesser General Public License, version 2.1.", "Distributed under the terms of the GNU LGPL."],
    "agpl": ["This program is licensed under the GNU Affero General Public License, version 3.", "Released under the AGPL."],
    "bsd": [
        "Licensed under the BSD 3-Clause License.",
        "BSD License",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
        "Released under a BSD-style license.",
    ],
    "mpl-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.", "Licensed under the Mozilla Public License, version 2.0."],
    "cc-by": ["Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "cc-by-sa": ["Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."],
    "cc-by-nc": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "cc0": ["Dedicated to the public domain under CC0 1.0 Universal.", "Released under CC0."],
    "unlicense": ["This is free and unencumbered software released into the public domain.", "Released under the Unlicense."],
    "proprietary": ["All rights reserved.", "Copyright by the author. All rights reserved.", "All rights reserved. No part of this publication may be reproduced without the prior written permission of the publisher."],
}
# What families are called, and how a notice mentions them.
NAMES = {
    "mit": ["MIT License", "MIT Licence", "MIT"],
    "apache-2.0": ["Apache License 2.0", "Apache 2.0", "Apache-2.0", "Apache License, Version 2.0", "Apache Software License"],
    "gpl": ["GPL", "GPLv2", "GPLv3", "GPL-3.0", "GPL-2.0", "GNU GPL", "GNU General Public License", "GPL v3"],
    "lgpl": ["LGPL", "LGPLv3", "LGPL-2.1", "GNU LGPL", "GNU Lesser General Public License"],
    "agpl": ["AGPL", "AGPLv3", "AGPL-3.0", "GNU AGPL", "GNU Affero General Public License"],
    "bsd": ["BSD License", "BSD-3-Clause", "BSD-2-Clause", "BSD 3-Clause License", "3-Clause BSD", "BSD", "New BSD License"],
    "mpl-2.0": ["MPL 2.0", "MPL-2.0", "Mozilla Public License 2.0", "MPL"],
    "cc-by": ["CC BY 4.0", "CC BY 3.0", "CC-BY-4.0", "CC BY", "Creative Commons Attribution 4.0"],
    "cc-by-sa": ["CC BY-SA 4.0", "CC BY-SA 3.0", "CC-BY-SA-4.0", "CC BY-SA", "Creative Commons Attribution-ShareAlike"],
    "cc-by-nc": ["CC BY-NC 4.0", "CC BY-NC 3.0", "CC-BY-NC-4.0", "CC BY-NC", "Creative Commons Attribution-NonCommercial"],
    "cc0": ["CC0", "CC0 1.0", "CC0-1.0", "CC0 Universal"],
    "unlicense": ["Unlicense"],
    "proprietary": ["proprietary license"],
}
FORMS = [
    "Released under {}.", "Released under the {} terms.", "Licensed under the {}.", "Available under {}.", "Distributed under {}.", "Distributed under the terms of the {}.",
    "This work is licensed under the {}.", "Published under {} by the authors.", "SPDX-License-Identifier: {}", "The code is covered by the {}.", "License: {}", "See the {} for details.", "Content is under {} unless noted.",
]
UNKNOWN_TEXTS = [
    "Licensed under the {} License.", "Released under the {} Public License, version {}.", "This work is licensed under the {} Software Agreement.", "Distributed under the terms of the {} licence.",
    "SPDX-License-Identifier: {}", "Use of this work is subject to the {} license terms.", "Permission to use is granted under the {} Community License.",
]
OTHER_TEXTS = [
    "He renewed his driving licence at the town hall.", "The licence plate was never found.", "Poetic license is granted to every writer.", "They asked for permission to enter the hall.",
    "The minister resigned without permission of the crown.", "The restaurant lost its liquor license last year.", "A fishing licence costs ten coins a year.", "Her permission slip was missing.",
    "The copyright debate went on in parliament for years.", "The committee will redistribute the seats next spring.", "The public domain of the city lies by the river.", "The gnu is an antelope of the plains.",
    "The apache helicopter landed on the field.", "The warranty of the washing machine ended in May.", "Licensed taxi drivers met in the square.", "MIT opened a new building.",
    "Er fuhr mit dem Zug nach Hause und sprach mit der Frau.", "Das Kind mit dem Ball spielt mit den anderen.", "She studied at MIT under a famous teacher.", "Please cc the team on your mail.", "The engine has 900 cc and runs on petrol.",
    "The terms of the sale were agreed under the old law.", "This work was published by the university and is available in the library.", "The software is used by the public and by the state in general.",
    "No part of the house was free from dust, and the source of the noise was not found.", "The form of the notice, the conditions of the work and the use of the library are described in the file.",
    "All people have rights, and the rights of others were reserved for later.", "The version of the story that you may read is subject to change in the next text.", "Any person who would copy the documents without charge will deal with the guard.",
    "The following list of names and dates was associated with a project in the commons.", "In the general election the public voted for the creative minister.", "The foundation gave the program to a school and the clause was removed.",
    "The BSD meeting was held by the river.", "The attribution of the painting is not certain.", "It was modified, sold and distributed in the north, under this or that name, with or without reason.",
]
#: A word may hold dots and hyphens, but does not end in one. No repeated group: those recurse on long matches.
WORD = r"[\p{L}\p{N}][\p{L}\p{N}.-]*"


def words_py(text: str) -> list[str]:
    return [w.rstrip(".-") for w in re.findall(r"[^\W_](?:[^\W_]|[.-])*", text.lower())]


def ngrams_py(words: list[str]) -> set[str]:
    padded = ["^", *words, "$"]
    return {*words, *(f"{a} {b}" for a, b in zip(padded, padded[1:]))}


def templates(family: str) -> list[str]:
    return TEMPLATES[family] + [f"under {name}" for name in NAMES[family]]


def variations(rng: random.Random, each: int = 24) -> list[tuple[list[str], str]]:
    """Templates, mentions of names and other texts, whole and with words dropped, repeated, or put around them."""
    def word() -> str:
        return "".join(rng.choice("bcdfglmnprstv") + rng.choice("aeiou") for _ in range(rng.randint(1, 3)))

    def varied(text: str, lost: float = 0.08) -> list[str]:
        w = [x for x in words_py(text) if rng.random() > lost]
        around = [word() for _ in range(rng.choice((0, 0, 2, 6)))]
        return around[: len(around) // 2] + w + around[len(around) // 2 :]

    out = []
    for family, texts in TEMPLATES.items():
        for t in texts:
            out += [(words_py(t), family)] * 3 + [(varied(t), family) for _ in range(each)]
        for name in NAMES[family]:
            out += [(varied(form.format(name), 0.0), family) for form in FORMS]
    for t in UNKNOWN_TEXTS:
        out += [(varied(t.format(word() + word(), rng.randint(1, 4))), UNKNOWN) for _ in range(5 * each)]
    for t in OTHER_TEXTS:
        out += [(words_py(t), OTHER)] * 3 + [(varied(t), OTHER) for _ in range(2 * each)]
        out += [([word() for _ in range(rng.randint(3, 30))] + rng.sample(["permission", "license", "copyright", "warranty", "mit", "public", "terms", "by"], 1) + [word()] * rng.randint(0, 3), OTHER) for _ in range(each)]
    return out


class LicenceModel:
    """Weights of n-grams for each class, biases, a temperature, and the anchors, of which every n-gram holds one."""

    def __init__(self, seed: int = 3, steps: int = 300, damp: float = 1e-3, most_anchors: int = 200):
        rng = random.Random(seed)
        rows = variations(rng)
        rng.shuffle(rows)
        self.classes = [*TEMPLATES, UNKNOWN, OTHER]
        grams = [ngrams_py(w) for w, _ in rows]
        y = np.array([self.classes.index(c) for _, c in rows])
        fit = np.arange(len(rows)) % 5 != 0
        counts: dict[str, int] = {}
        for g in grams:
            for k in g:
                counts[k] = counts.get(k, 0) + 1
        common = sorted(k for k, n in counts.items() if n >= 8)
        single = [k for k in common if " " not in k]
        w = self._fit(_ones(grams, single), y, fit, steps // 3, damp)[0]
        margin = w[:, :-1].max(1) - w[:, -1]
        named = {k for names in NAMES.values() for name in names for k in words_py(name)}  # a family's own words are anchors whatever their margin
        best = [single[i] for i in np.argsort(-margin)[:most_anchors] if margin[i] > 0.08 * margin.max()]
        self.anchors = sorted(({*best} | {k for k in named if k in counts}) - FUNCTION_WORDS)
        own = set(self.anchors)
        self.grams = [k for k in common if own & set(k.split(" "))]
        x = _ones(grams, self.grams)
        w, b = self._fit(x, y, fit, steps, damp)
        z = x[~fit] @ w + b
        losses = {t: -np.log(softmax(z / t)[np.arange(len(z)), y[~fit]] + 1e-12).mean() for t in (0.5, 0.7, 1.0, 1.4, 2.0, 3.0)}
        self.temperature = min(losses, key=losses.get)
        self.accuracy = float((z.argmax(1) == y[~fit]).mean())
        self.weights, self.bias = np.round(w.astype(float), 6), np.round(b.astype(float), 6)
        assert self.bias.argmax() == len(self.classes) - 1  # what holds no anchor is other text

    @staticmethod
    def _fit(x: np.ndarray, y: np.ndarray, fit: np.ndarray, steps: int, damp: float) -> tuple[np.ndarray, np.ndarray]:
        k = int(y.max()) + 1
        w, b = np.zeros((x.shape[1], k), np.float32), np.zeros(k, np.float32)
        mw, mb = np.full_like(w, 1e-8), np.full_like(b, 1e-8)
        xf, hot = x[fit], np.eye(k, dtype=np.float32)[y[fit]]
        for _ in range(steps):
            p = softmax(xf @ w + b) - hot
            gw, gb = xf.T @ p / fit.sum() + damp * w, p.mean(0)
            mw += gw * gw
            mb += gb * gb
            w -= 0.3 * gw / np.sqrt(mw)
            b -= 0.3 * gb / np.sqrt(mb)
        return w, b

    def table(self, spark: SparkSession) -> DataFrame:
        """A row for each n-gram; the size of the model, some thousand rows, whatever the corpus."""
        return spark.createDataFrame([(g, [float(v) for v in w]) for g, w in zip(self.grams, self.weights)], "gram string, weight array<double>")


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def _ones(rows: list[set[str]], columns: list[str]) -> np.ndarray:
    at = {k: i for i, k in enumerate(columns)}
    x = np.zeros((len(rows), len(at)), np.float32)
    for i, r in enumerate(rows):
        x[i, [at[k] for k in r if k in at]] = 1
    return x


def has_anchor(text: Column, model: LicenceModel) -> Column:
    """Whether a text holds the longest part of an anchor as a word; no word of the model is missed."""
    parts = sorted({max(re.findall(r"[^\W_]+", a), key=lambda p: (p not in FUNCTION_WORDS, len(p))) for a in model.anchors})
    return F.arrays_overlap(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), F.array(*[F.lit(p) for p in parts]))


def with_similarity(hits: DataFrame, model: LicenceModel) -> DataFrame:
    """Adds close to rows (row, words, best): the largest share of distinct words that a template of the class has in common."""
    rows = []
    for k, family in enumerate(model.classes):
        for i, t in enumerate(templates(family) if family in TEMPLATES else []):
            own = set(words_py(t))
            rows += [(w, k + 1, i, len(own)) for w in sorted(own)]
    table = hits.sparkSession.createDataFrame(rows, "word string, class int, template int, size int")  # some thousand rows, whatever the corpus
    words = hits.select("row", F.col("best").alias("class"), F.explode(F.array_distinct("words")).alias("word"))
    shares = words.join(F.broadcast(table), ["word", "class"]).groupBy("row", "template", "size").agg(F.count("*").alias("n"))
    close = shares.groupBy("row").agg(F.max(F.col("n") / F.col("size")).alias("close"))
    return hits.join(close, "row", "left").withColumn("close", F.coalesce("close", F.lit(0.0)))


def scan_licences(docs: DataFrame, model: LicenceModel | None = None, sure: float = 0.5, alike: float = 0.7) -> DataFrame:
    """(doc_id, paragraph, family, probability, similarity, excerpt): one row for each notice.

    ``docs`` has doc_id and text. ``paragraph`` is the number of the line that a notice begins in, from 0 over all lines of
    the text; null and empty texts have none. Lines are scored, of longer ones every ``WIDE`` words, and so is every stretch
    of ``STRETCH`` lines, each beginning half a stretch after the one before; a stretch counts where a template confirms it
    and none of its lines has been confirmed for the same family, and adjoining ones of a family are one notice.
    ``probability`` is the calibrated one of the class; ``family`` is the class if a template of it shares at least
    ``alike`` of its words, else ``unknown``. What the model takes for other text, or is not ``sure`` to be a licence, is left
    out. Rows of equal doc_id and text are each scanned, however long the text.
    """
    model = model or LicenceModel()
    n, half = len(model.classes), STRETCH // 2
    texts = docs.where(has_anchor(F.col("text"), model)).select("doc_id", F.split("text", "\n", -1).alias("lines"), F.monotonically_increasing_id().alias("text_row"))
    part = lambda at, wide, text: F.struct(at.cast("int").alias("at"), F.lit(wide).alias("wide"), text.alias("part"))
    alone = F.transform("lines", lambda v, i: part(i, False, v))
    starts = F.when(F.size("lines") > 1, F.sequence(F.lit(0), F.floor((F.size("lines") - 2) / half).cast("int"))).otherwise(F.array().cast("array<int>"))
    stretch = F.transform(starts, lambda i: part(i * half, True, F.array_join(F.slice("lines", i * half + 1, STRETCH), " ")))
    units = texts.select("doc_id", "text_row", F.explode(F.concat(alone, stretch)).alias("u")).select("doc_id", "text_row", "u.*").where(has_anchor(F.col("part"), model))
    units = cut_lineage(units.withColumn("unit", F.monotonically_increasing_id()))  # numbered once, whatever is computed again
    words = F.transform(F.regexp_extract_all(F.lower("part"), F.lit(WORD), F.lit(0)), lambda w: F.rtrim(w, F.lit(".-")))
    pieces = F.transform(F.sequence(F.lit(0), F.floor(F.greatest(F.size("words") - WIDE // 2 - 1, F.lit(0)) / (WIDE // 2)).cast("int")), lambda i: F.slice("words", i * (WIDE // 2) + 1, WIDE))
    split = units.select("unit", "wide", words.alias("words")).select("unit", F.posexplode(F.when(F.col("wide"), F.array("words")).otherwise(pieces)).alias("piece", "words"))
    pairs = F.zip_with(F.concat(F.array(F.lit("^")), F.col("words")), F.concat(F.col("words"), F.array(F.lit("$"))), lambda a, b: F.concat(a, F.lit(" "), b))
    grams = split.select("unit", "piece", F.explode(F.array_distinct(F.concat("words", pairs))).alias("gram"))
    z = grams.join(F.broadcast(model.table(docs.sparkSession)), "gram").groupBy("unit", "piece").agg(*[F.sum(F.element_at("weight", i + 1)).alias(f"z{i}") for i in range(n)])
    logits = [(F.round(f"z{i}", 6) + F.lit(float(model.bias[i]))) / F.lit(float(model.temperature)) for i in range(n)]
    z = z.withColumn("z", F.array(*logits)).withColumn("top", F.array_max("z"))
    z = z.withColumn("best", F.array_position("z", F.col("top")).cast("int"))
    mass = F.aggregate("z", F.lit(0.0), lambda a, v: a + F.exp(v - F.col("top")))
    other = F.exp(F.element_at("z", n) - F.col("top")) / mass
    z = z.select("unit", "piece", "best", (F.lit(1.0) / mass).alias("p"), other.alias("other"))
    z = cut_lineage(z.where((F.col("best") < n) & (F.lit(1.0) - F.col("other") >= sure)).withColumn("row", F.monotonically_increasing_id()))
    if z.count() <= 500_000:  # the notices; beyond, both sides are shuffled
        z = F.broadcast(z)
    found = units.join(z, "unit").withColumn("words", words)
    found = found.withColumn("words", F.when(F.col("wide"), F.col("words")).otherwise(F.slice("words", F.col("piece") * (WIDE // 2) + 1, WIDE)))
    z = cut_lineage(found.select("row", "doc_id", "text_row", "at", "wide", F.substring("part", 1, 200).alias("excerpt"), "words", "best", "p"))
    family = F.element_at(F.array(*[F.lit(c) for c in model.classes]), F.col("best"))
    z = with_similarity(z, model).drop("words")
    z = z.withColumn("family", F.when(F.col("close") >= alike, family).otherwise(UNKNOWN))
    return _notices(cut_lineage(z), half).select("doc_id", "paragraph", "family", F.round("p", 6).alias("probability"), F.round("close", 6).alias("similarity"), "excerpt")


def _notices(z: DataFrame, half: int) -> DataFrame:
    """One row for each line with a notice and for each chain of stretches, of scored units."""
    best = lambda by: F.max_by(F.struct("doc_id", "family", "p", "close", "excerpt"), by)
    lines = z.where("not wide").groupBy("text_row", "at").agg(best(F.struct(F.col("family") != UNKNOWN, "close", "p", "family")).alias("b")).select("text_row", F.col("at").alias("paragraph"), "b.*")
    lines = lines.withColumn("block", F.floor(F.col("paragraph") / half))
    sure = lines.where(F.col("family") != UNKNOWN).select("text_row", "family", "block")
    near = sure.union(sure.withColumn("block", F.col("block") - 1)).distinct()  # the stretches that such a line is in
    wide = z.where(F.col("wide") & (F.col("family") != UNKNOWN)).withColumn("block", F.floor(F.col("at") / half)).join(near, ["text_row", "family", "block"], "left_anti")
    order = Window.partitionBy("text_row", "family").orderBy("block")
    wide = wide.withColumn("chain", F.sum((F.coalesce(F.col("block") - F.lag("block").over(order), F.lit(9)) > 1).cast("int")).over(order))
    chains = wide.groupBy("text_row", "family", "chain").agg(F.min("at").alias("paragraph"), best(F.struct("close", "p", F.negative("at"))).alias("b"))
    covered = wide.select("text_row", "block").union(wide.select("text_row", F.col("block") + 1)).distinct()
    beside = lines.where(F.col("family") != UNKNOWN).select("text_row", F.explode(F.array(F.col("paragraph") - 1, F.col("paragraph") + 1)).alias("paragraph")).distinct()
    doubtful = lines.where(F.col("family") == UNKNOWN).join(covered, ["text_row", "block"], "left_anti").join(beside, ["text_row", "paragraph"], "left_anti")  # rests of a notice
    columns = ["doc_id", "paragraph", "family", "p", "close", "excerpt"]
    kept = lines.where(F.col("family") != UNKNOWN).select(columns).unionAll(doubtful.select(columns))
    return kept.unionAll(chains.select("b.doc_id", "paragraph", "family", "b.p", "b.close", "b.excerpt"))


def op5_license_scan(spark, sf_dir: str) -> DataFrame:
    """All rows of ``documents``; nulls, empty and long texts, ties and empty tables as in ``scan_licences``."""
    return scan_licences(spark.read.parquet(f"{sf_dir}/documents.parquet"))
