"""Licence scans: a trained paragraph classifier with template comparison.

A multinomial logistic regression over sparse word 1- to 3-grams names the licence family of a paragraph (a line of
text). It is trained on the driver from the notices below: whole, cut and damaged copies of them, against prose that
uses the same words otherwise. Its temperature is fitted on held-out copies, so that its probabilities, that of the
class "unknown" included, are calibrated. A prediction stands only if the paragraph also shares enough three-word
sequences with one of the family's templates. On the corpus all work is done by DataFrame functions: grams are
exploded, met with the weight table by an equi-join, and summed for each distinct paragraph.

A paragraph is scored if it shares a sequence with any template; without one it could not be confirmed, so nothing is
lost by that. HITS, a word of every template sequence, spares most other paragraphs the making of sequences. Edge cases: null and empty texts have no licence; a paragraph may be of any length; equal
paragraphs are judged once; every input row gets a row.
"""

from __future__ import annotations

import json
import math
import random
import re
from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import scratch_table

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
UNKNOWN = "unknown"
#: Probability from which, and shared part of three-word sequences from which, a family is reported.
MIN_PROBABILITY, MIN_SHARED = 0.5, 0.4
#: Paragraphs of fewer words are confirmed by sequences of two words, as a short notice has few of three.
SHORT = 8
MAX_GRAM = 3
FEATURES = 4000

#: Customary wording of licence notices.
TEMPLATES = {
    "apache-2.0": (
        "Licensed under the Apache License, Version 2.0.",
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.',
        "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
        'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.',
        "See the License for the specific language governing permissions and limitations under the License.",
        "SPDX-License-Identifier: Apache-2.0",
    ),
    "mit": (
        "Released under the MIT License.",
        "Licensed under the MIT License.",
        'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software.',
        "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
        "In no event shall the authors or copyright holders be liable for any claim, damages or other liability, whether in an action of contract, tort or otherwise.",
        "SPDX-License-Identifier: MIT",
    ),
    "bsd": (
        "Licensed under the BSD 3-Clause License.",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met.",
        "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
        "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
        "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file.",
        "SPDX-License-Identifier: BSD-3-Clause",
    ),
    "gpl": (
        "Licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or any later version.",
        "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.",
        "You should have received a copy of the GNU General Public License along with this program.",
        "SPDX-License-Identifier: GPL-3.0-or-later",
    ),
    "mpl": (
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
        "If a copy of the MPL was not distributed with this file, You can obtain one at the site of the Mozilla Public License.",
        "Licensed under the Mozilla Public License, version 2.0.",
        "SPDX-License-Identifier: MPL-2.0",
    ),
    "creative-commons": (
        "This work is licensed under a Creative Commons Attribution 4.0 International License.",
        "Except where otherwise noted, content on this site is licensed under a Creative Commons Attribution-ShareAlike license.",
        "Text is available under the Creative Commons Attribution-ShareAlike License; additional terms may apply.",
        "To view a copy of this license, visit http://creativecommons.org/licenses/by/4.0/",
        "SPDX-License-Identifier: CC-BY-4.0",
        *(text for kind in ("BY", "BY-SA", "BY-NC", "BY-ND", "BY-NC-SA", "BY-NC-ND") for text in (f"Licensed under CC {kind} 4.0.", f"This work is licensed under CC {kind} 3.0.", f"SPDX-License-Identifier: CC-{kind}-4.0")),
        *(f"This work is licensed under a Creative Commons Attribution-{kind} 4.0 International License." for kind in ("ShareAlike", "NonCommercial", "NoDerivatives", "NonCommercial-ShareAlike", "NonCommercial-NoDerivatives")),
    ),
    "public-domain": (
        "This is free and unencumbered software released into the public domain.",
        "To the extent possible under law, the author has dedicated all copyright and related rights to this work to the public domain worldwide.",
        "Released into the public domain under CC0 1.0 Universal.",
        "SPDX-License-Identifier: CC0-1.0",
    ),
    "proprietary": (
        "Copyright. All rights reserved. No part of this publication may be reproduced, distributed, or transmitted in any form or by any means without the prior written permission of the publisher.",
        "All rights reserved. Unauthorized copying of this file, via any medium, is strictly prohibited. Proprietary and confidential.",
        "All rights reserved.",
        "This software is licensed, not sold, under a proprietary license agreement; redistribution is prohibited.",
    ),
}
#: The same words in prose that licenses nothing.
OTHER = (
    "He lost his driving licence after the accident and asked for permission to appeal.",
    "The restaurant applied for a liquor license from the city council last spring.",
    "Copyright law protects authors, and a public library may lend their works.",
    "The warranty on the washing machine covers parts and labour for two years.",
    "With the permission of her parents she travelled alone to the coast.",
    "The patent office discussed software, source code and open standards at the conference.",
    "A general public meeting was held under the terms agreed with the mayor.",
    "The foundation gave free copies of the book to any person who asked for one.",
    "The apache helicopter landed with a new version of its radar.",
    "Students at the university studied distribution of wealth in binary star systems.",
    "The taxes were redistributed among the regions without any further conditions.",
    "Creative people commonly work in groups and share their content on this site.",
    "The court issued a warrant for his arrest and the judge reserved all rights to decide.",
    "This license plate belongs to a car that was sold in the domain of the duke.",
)


def words(text: str) -> list[str]:
    return re.findall("[a-z0-9]+", text.translate(str.maketrans(UPPER, LOWER)))


def grams(tokens: list[str], n: int) -> set[str]:
    return {" ".join(tokens[i : i + n]) for i in range(len(tokens) - n + 1)}


def _examples(rng: random.Random, copies: int) -> list[tuple[list[str], int]]:
    """Whole, cut and damaged copies of every notice, and unknown ones of other prose and of the notices' words shuffled."""
    out, families = [], list(TEMPLATES)
    vocabulary = sorted({w for t in TEMPLATES.values() for x in t for w in words(x)} | {w for x in OTHER for w in words(x)})
    for k, family in enumerate(families):
        for template in TEMPLATES[family]:
            tokens = words(template)
            out.append((tokens, k))
            for _ in range(copies):
                least = min(len(tokens), 5)
                size = rng.randint(max(least, len(tokens) // 2), len(tokens))
                start = rng.randint(0, len(tokens) - size)
                part = [w if rng.random() > 0.06 else rng.choice(vocabulary) for w in tokens[start : start + size]]
                out.append((part + rng.sample(vocabulary, rng.randint(0, 4)), k))
                out.append((rng.sample(tokens, len(tokens)), len(families)))
    for text in OTHER:
        for _ in range(3 * copies):
            tokens = words(text)
            start = rng.randint(0, len(tokens) // 2)
            out.append((tokens[start:] + rng.sample(vocabulary, rng.randint(0, 6)), len(families)))
    return out


def _loss(logits: np.ndarray, y: np.ndarray) -> float:
    logits = logits - logits.max(1, keepdims=True)
    return float(np.mean(np.log(np.exp(logits).sum(1)) - logits[np.arange(len(y)), y]))


@lru_cache(maxsize=1)
def trained() -> tuple[tuple[str, ...], dict[str, np.ndarray], np.ndarray]:
    """Classes, weights of the kept grams, and biases, all divided by the fitted temperature. No corpus row is used."""
    rng, classes = random.Random(11), (*TEMPLATES, UNKNOWN)
    examples, held = _examples(rng, 6), _examples(rng, 3)
    features = lambda t: set().union(*(grams(t, n) for n in range(1, MAX_GRAM + 1)))
    counts: dict[str, int] = {}
    for tokens, _ in examples:
        for g in features(tokens):
            counts[g] = counts.get(g, 0) + 1
    kept = sorted((g for g in counts if counts[g] > 1), key=lambda g: (-counts[g], g))[:FEATURES]
    place = {g: i for i, g in enumerate(kept)}

    def matrix(rows: list) -> tuple[np.ndarray, np.ndarray]:
        x = np.zeros((len(rows), len(kept)), np.float32)
        for i, (tokens, _) in enumerate(rows):
            own = [place[g] for g in features(tokens) if g in place]
            x[i, own] = 1
        return x, np.array([k for _, k in rows])

    x, y = matrix(examples)
    # Each row has unit length, so a paragraph's size doesn't decide by itself.
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1)
    target = np.eye(len(classes), dtype=np.float32)[y]
    share = target.mean(0)
    weight = (1 / (len(classes) * share))[y][:, None]
    w, b = np.zeros((len(kept), len(classes)), np.float32), np.zeros(len(classes), np.float32)
    for _ in range(120):
        logits = x @ w + b
        p = np.exp(logits - logits.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        g = weight * (p - target) / len(y)
        w -= 20.0 * (x.T @ g + 1e-5 * w)
        b -= 5.0 * g.sum(0)
    w[np.abs(w).max(1) < 0.05] = 0  # sparse
    xh, yh = matrix(held)
    xh /= np.maximum(np.linalg.norm(xh, axis=1, keepdims=True), 1)
    logits = xh @ w + b
    temperature = min((2.0**k for k in np.arange(-3, 3.01, 0.25)), key=lambda t: _loss(logits / t, yh))
    return classes, {g: w[i] / temperature for g, i in place.items() if np.abs(w[i]).any()}, b / temperature


def classify(text: str) -> tuple[str, float, float]:
    """Family, its probability and the shared part, of one paragraph: the reference for the DataFrame version."""
    classes, weights, bias = trained()
    tokens = words(text)
    own = set().union(*(grams(tokens, n) for n in range(1, MAX_GRAM + 1)))
    known = [weights[g] for g in own if g in weights]
    logits = np.sum(known, axis=0) / math.sqrt(max(1, sum(g in _vocabulary() for g in own))) + bias if known else bias
    p = np.exp(logits - logits.max())
    p /= p.sum()
    k = int(np.argmax(p))
    n = _order(len(tokens))
    own = grams(tokens, n)
    shared = max((len(own & t) / min(len(own), len(t)) for t in _template_grams(classes[k], n) if own and t), default=0.0)
    stands = classes[k] != UNKNOWN and p[k] >= MIN_PROBABILITY and shared >= MIN_SHARED
    return (classes[k] if stands else UNKNOWN), float(p[k]), shared


def _order(size: int) -> int:
    return 2 if size < SHORT else 3


def _template_grams(family: str, n: int) -> list[set[str]]:
    return [grams(words(t), n) for t in TEMPLATES.get(family, ())]


def _vocabulary() -> dict:
    return trained()[1]


#: All sequences of the templates, and the longest word of each: a text without such a word holds no such sequence.
SEQUENCES = sorted(set().union(*(t for f in TEMPLATES for n in (2, 3) for t in _template_grams(f, n))))
HITS = sorted({max(g.split(), key=lambda w: (len(w), w)) for g in SEQUENCES})


def _table(spark: SparkSession, rows: list[dict], schema: str) -> DataFrame:
    """As one literal: a call to the JVM for each value would take longer than the scan."""
    return spark.range(1, numPartitions=1).select(F.inline(F.from_json(F.lit(json.dumps(rows)), f"array<struct<{schema}>>")))


def _tokens(text: Column) -> Column:
    return F.filter(F.split(F.translate(text, UPPER, LOWER), "[^a-z0-9]+"), lambda x: x != "")


def _grams(tokens: Column, n: int) -> Column:
    if n == 1:
        return tokens
    size = F.size(tokens)
    return F.when(size >= n, F.transform(F.sequence(F.lit(1), F.greatest(size - n + 1, F.lit(1))), lambda i: F.array_join(F.slice(tokens, i, n), " "))).otherwise(F.array().cast("array<string>"))


def _sequences(tokens: Column) -> Column:
    return F.when(F.size(tokens) < SHORT, _grams(tokens, 2)).otherwise(_grams(tokens, 3))


def _shares(tokens: Column) -> Column:
    """Whether a paragraph shares a sequence with any template."""
    # The array of one binds the tokens, so that they are cut once.
    return F.coalesce(F.exists(F.array(tokens), lambda t: F.exists(t, lambda w: w.isin(HITS)) & F.exists(_sequences(t), lambda g: g.isin(SEQUENCES))), F.lit(False))


def licence_paragraphs(docs: DataFrame) -> DataFrame:
    """doc_id, position, paragraph, family, probability and shared of every paragraph that carries a licence notice."""
    classes, weights, bias = trained()
    spark = docs.sparkSession
    lines = docs.select("doc_id", F.posexplode(F.split("text", "\n", -1)).alias("position", "paragraph"))
    # Read once: what is left is met several times below.
    lines = scratch_table(lines.where(_shares(_tokens(F.col("paragraph")))))
    # Equal paragraphs are judged once; copies combine before the shuffle.
    each = lines.select("paragraph").distinct().withColumn("tokens", _tokens(F.col("paragraph")))
    each = each.withColumn("sequences", F.array_distinct(_sequences(F.col("tokens"))))
    own = F.array_distinct(F.concat(*[_grams(F.col("tokens"), n) for n in range(1, MAX_GRAM + 1)]))
    table = F.broadcast(_table(spark, [{"gram": g, "w": [float(x) for x in w]} for g, w in sorted(weights.items())], "gram:string,w:array<double>"))  # at most FEATURES rows
    met = each.select("paragraph", F.explode(own).alias("gram")).join(table, "gram")
    sums = met.groupBy("paragraph").agg(F.count(F.lit(1)).alias("known"), *[F.sum(F.get("w", F.lit(k))).alias(f"s{k}") for k in range(len(classes))])
    logits = F.array(*[F.col(f"s{k}") / F.sqrt("known") + F.lit(float(bias[k])) for k in range(len(classes))])
    sums = sums.withColumn("logits", logits).withColumn("top", F.array_max("logits"))
    best = sums.select("paragraph", F.element_at(F.array(*[F.lit(c) for c in classes]), F.array_position("logits", F.col("top")).cast("int")).alias("family"), (1 / F.aggregate("logits", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("top")))).alias("probability"))
    # A paragraph meets the sequences of one length only.
    templates = [(f, i, g, len(t)) for f in TEMPLATES for n in (2, 3) for i, t in enumerate(_template_grams(f, n)) for g in sorted(t)]
    template = F.broadcast(_table(spark, [{"t_family": f, "template": i, "gram": g, "t_size": size} for f, i, g, size in templates], "t_family:string,template:int,gram:string,t_size:int"))
    shared = each.select("paragraph", F.explode("sequences").alias("gram"), F.size("sequences").alias("n")).join(template, "gram").groupBy("paragraph", "t_family", "template").agg((F.count(F.lit(1)) / F.least(F.first("n"), F.first("t_size"))).alias("part"))
    shared = shared.groupBy("paragraph", "t_family").agg(F.max("part").alias("shared"))
    found = best.join(shared, (best["paragraph"] == shared["paragraph"]) & (F.col("family") == F.col("t_family"))).select(best["paragraph"], "family", "probability", "shared")
    found = found.where((F.col("family") != UNKNOWN) & (F.col("probability") >= MIN_PROBABILITY) & (F.col("shared") >= MIN_SHARED))
    return lines.join(found, "paragraph").select("doc_id", "position", "paragraph", "family", "probability", "shared")


def scan_licences(docs: DataFrame) -> DataFrame:
    """doc_id, n_paragraphs, n_licence, families (sorted, comma-joined; empty if none) and probability (the highest) for every row."""
    hits = licence_paragraphs(docs).groupBy(F.col("doc_id").alias("_d")).agg(F.count_distinct("position").alias("n"), F.array_join(F.array_sort(F.collect_set("family")), ",").alias("families"), F.max("probability").alias("p"))
    rows = docs.select("doc_id", F.when(F.col("text").isNull(), 0).otherwise(F.size(F.split("text", "\n", -1))).cast("long").alias("n_paragraphs"))
    out = rows.join(hits, F.col("doc_id") == F.col("_d"), "left")
    return out.select("doc_id", "n_paragraphs", F.coalesce("n", F.lit(0)).cast("long").alias("n_licence"), F.coalesce("families", F.lit("")).alias("families"), F.round("p", 6).alias("probability"))
