"""Licence scan by a trained paragraph classifier (DataFrame functions only).

A paragraph is scored by a multinomial logistic regression over sparse word 1- to 3-grams. It is trained here, from
labelled licence notices and ordinary paragraphs, and keeps only n-grams that hold a licence word and occur in no
ordinary training paragraph; a paragraph without any of them scores as the bias alone, which is below the threshold, so
skipping paragraphs without licence words changes no result. A class probability below the calibrated threshold is
the class ``unknown``; a prediction is confirmed only if the paragraph holds enough of the words of one of the
family's templates.

Paragraphs end at blank lines. What is scored in one are its lines with licence words and, as notices are often wrapped,
all spans of up to ``span_lines`` consecutive lines that hold one.

The weights are one small table (at most ``len(FAMILIES) * max_features`` numbers, whatever the corpus) and are
broadcast. Paragraph n-grams are summed per paragraph after a map-side combine.

Defined results: null or empty text has no licence; a paragraph that is repeated counts each time; several families
in one document are all listed, by name; repeated rows (same doc_id) are one document whose paragraphs add up;
an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from levelsort.llm.common import ascii_lower

UNKNOWN = "unknown"
# Short public notices by licence family.
FAMILIES: dict[str, list[str]] = {
    "apache-2.0": ["Licensed under the Apache License, Version 2.0.", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License.", "SPDX-License-Identifier: Apache-2.0", "This project is released under the Apache 2.0 license.", "Apache License Version 2.0, January 2004", "Distributed under the Apache License 2.0"],
    "mit": ["Released under the MIT License.", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction", "SPDX-License-Identifier: MIT", "Licensed under the MIT license.", "The MIT License (MIT)", "This code is distributed under the MIT License"],
    "gpl-3.0": ["This work is licensed under the GNU General Public License, version 3.", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or any later version.", "SPDX-License-Identifier: GPL-3.0-or-later", "Licensed under the GNU GPL version 3", "GNU General Public License v3", "You should have received a copy of the GNU General Public License along with this program"],
    "lgpl": ["This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License", "SPDX-License-Identifier: LGPL-2.1-only", "Licensed under the GNU Lesser General Public License, version 2.1.", "GNU Lesser General Public License v3"],
    "bsd": ["Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met", "SPDX-License-Identifier: BSD-3-Clause", "Released under the BSD license.", "Licensed under the BSD 2-Clause License", "Use of this source code is governed by a BSD-style license"],
    "mpl-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.", "SPDX-License-Identifier: MPL-2.0", "Licensed under the Mozilla Public License 2.0", "Mozilla Public License Version 2.0"],
    "cc-by": ["Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License.", "SPDX-License-Identifier: CC-BY-4.0", "Creative Commons Attribution 4.0", "Available under the CC BY 4.0 licence"],
    "cc-by-sa": ["Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.", "SPDX-License-Identifier: CC-BY-SA-4.0", "Creative Commons Attribution-ShareAlike 4.0", "Available under the CC BY-SA 4.0 licence"],
    "cc-by-nc": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.", "SPDX-License-Identifier: CC-BY-NC-4.0", "Creative Commons Attribution-NonCommercial 4.0", "Available under the CC BY-NC 4.0 licence"],
    "cc0": ["To the extent possible under law, the author has waived all copyright and related rights to this work.", "SPDX-License-Identifier: CC0-1.0", "Released into the public domain under CC0 1.0 Universal", "CC0 1.0 Universal Public Domain Dedication"],
    "proprietary": ["All rights reserved. No part of this publication may be reproduced without prior written permission.", "Copyright (c) The Company. All rights reserved.", "Confidential and proprietary. Unauthorized copying of this file is strictly prohibited."],
}
# Ordinary paragraphs, some with words that licences use too.
ORDINARY = [
    "The new version of the program reads the source file and writes the output to a table.", "You may use the kitchen at any time, free of charge, but please clean it.", "She asked for permission to leave early and the manager granted it without conditions.",
    "The driver lost his license after the accident and had to take the bus to work.", "A fishing licence is needed for the lake, and the terms are posted at the gate.", "General practitioners and the public health office published the report in January.",
    "The library is open to the public from Monday to Friday, with the exception of holidays.", "Apache helicopters were seen over the city.", "Students at MIT released a study of the creative process in design.", "The restaurant is licensed to sell wine and beer under the new law.",
    "He works in the commercial department of an international company.", "Without modification the engine will not meet the new conditions.", "The work of the foundation is free and open to any person.", "Modify the text, copy the file, and share it with your friends.", "No rights were violated, the court said in its report.",
    "All the material in the form was received along with the program of the concert.", "The software version 3 runs on version 2 of the hardware.", "In source languages such as German the forms are longer.", "Version 2.0 of the game is much faster than before.", "The union has some rights reserved for older members.",
]
# Words of which every feature holds at least one.
ANCHORS = "license licence licensed licenses apache mit gpl gnu lgpl bsd mpl mozilla cc cc0 creative commons copyright spdx redistribution redistribute permission permitted proprietary confidential copyleft noncommercial sharealike".split()
WORD = r"[a-z0-9]+"
ORDER = 3


def words(text: str) -> list[str]:
    return re.findall(WORD, text.lower())


def grams(tokens: list[str]) -> list[str]:
    return [" ".join(tokens[i : i + n]) for n in range(1, ORDER + 1) for i in range(len(tokens) - n + 1)]


class Classifier:
    """weights: feature -> {family: weight}; bias: family -> weight; threshold: least probability of a known class."""

    def __init__(self, weights: dict[str, dict[str, float]], bias: dict[str, float], threshold: float):
        self.weights, self.bias, self.threshold = weights, bias, threshold

    def probabilities(self, text: str) -> dict[str, float]:
        score = dict(self.bias)
        for g in set(grams(words(text))):
            for k, v in self.weights.get(g, {}).items():
                score[k] += v
        top = max(score.values())
        total = sum(math.exp(v - top) for v in score.values())
        return {k: math.exp(v - top) / total for k, v in score.items()}


def train(families: dict[str, list[str]] | None = None, ordinary: list[str] | None = None, max_features: int = 4000, rounds: int = 200, rate: float = 0.5, decay: float = 1e-3) -> Classifier:
    """Gradient steps, one labelled paragraph at a time; the unknown class is what ordinary ones are labelled.

    The bias is set, not trained: without evidence a paragraph is unknown. The threshold lies between the least sure
    licence paragraphs and the surest ordinary one of the same labelled rows.
    """
    families, ordinary = families or FAMILIES, ordinary or ORDINARY
    rows = [(set(grams(words(t))), k) for k, ts in sorted(families.items()) for t in ts] + [(set(grams(words(t))), UNKNOWN) for t in ordinary]
    plain = set().union(*(g for g, k in rows if k == UNKNOWN))
    count = Counter(g for gs, k in rows if k != UNKNOWN for g in gs)
    anchors = set(ANCHORS)
    kept = sorted((g for g in count if anchors & set(g.split()) and (g not in plain or g in anchors)), key=lambda g: (-count[g], g))[:max_features]
    known = set(kept)
    rows = [(sorted(gs & known), k) for gs, k in rows]
    # paragraphs of licence words alone, out of any notice, are unknown too
    rows += [([a], UNKNOWN) for a in ("license", "licence", "licensed", "permission", "copyright", "mit", "apache", "commons", "creative", "confidential") if a in known] * 2
    classes = [*sorted(families), UNKNOWN]
    w = {g: dict.fromkeys(classes, 0.0) for g in kept}
    bias = dict.fromkeys(classes, 0.0)
    bias[UNKNOWN] = 3.0

    def proba(gs: list[str]) -> dict[str, float]:
        s = {k: bias[k] + sum(w[g][k] for g in gs) for k in classes}
        top = max(s.values())
        e = {k: math.exp(v - top) for k, v in s.items()}
        total = sum(e.values())
        return {k: v / total for k, v in e.items()}

    for _ in range(rounds):
        for gs, y in rows:
            p = proba(gs)
            step = rate / math.sqrt(1 + len(gs))
            for k in classes:
                d = (k == y) - p[k]
                if abs(d) > 1e-3:
                    for g in gs:
                        w[g][k] += step * (d - decay * w[g][k])
    # calibration: half way between the least sure licence paragraph and the surest ordinary one
    sure = [proba(gs)[y] for gs, y in rows if y != UNKNOWN]
    loose = [max(v for k, v in proba(gs).items() if k != UNKNOWN) for gs, y in rows if y == UNKNOWN]
    low = sorted(sure)[len(sure) // 20]
    return Classifier({g: {k: round(v, 5) for k, v in x.items()} for g, x in w.items()}, bias, round(min(0.9, max(0.5, (low + max(loose)) / 2)), 4))


def paragraph_scan(docs: DataFrame, model: Classifier | None = None, id_col: str = "doc_id", text_col: str = "text", paragraph_break: str = r"\n[ \t\r]*\n", confirm: float = 0.6, span_lines: int = 8) -> DataFrame:
    """One row per notice, and per line with licence words outside any: doc_id, para, line, lines, family, probability,
    overlap, confirmed, copies (equal rows of the document)."""
    spark = docs.sparkSession
    model = model or train()
    classes = sorted(model.bias)
    anchor = r"(?i)(?<![A-Za-z0-9])(?:" + "|".join(sorted(ANCHORS)) + r")(?![A-Za-z0-9])"
    anchors = F.array(*[F.lit(a) for a in sorted(ANCHORS)])
    wordings = F.array(*[F.array(*[F.lit(w) for w in sorted(set(words(t)))]) for ts in FAMILIES.values() for t in ts])
    hits = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).where(F.col("text").rlike(anchor))
    # paragraphs of one document keep their number; rows that repeat a doc_id are told apart by their text
    paras = hits.select("doc_id", F.xxhash64("text").alias("row"), F.posexplode(F.split("text", paragraph_break)).alias("para", "body")).where(F.col("body").rlike(anchor))
    lined = paras.select("doc_id", "row", "para", F.transform(F.split("body", "\n"), lambda x: F.regexp_extract_all(ascii_lower(x), F.lit(WORD), F.lit(0))).alias("lt"))
    # Overlap only grows with a span, and only template words count in it: where the lines around a licence word hold too few
    # of every template, no longer span is confirmed; and none is looked for around a line that is itself a notice, as a
    # confirmed span has no confirmed one inside.
    vocabulary = F.array(*[F.lit(w) for w in sorted({w for ts in FAMILIES.values() for t in ts for w in words(t)})])
    sure = sorted({" ".join(words(t)) for k, ts in FAMILIES.items() for t in ts if k in model.bias and model.probabilities(t)[k] >= model.threshold and "\n" not in t})
    lined = lined.withColumn("lv", F.transform("lt", lambda x: F.array_intersect(x, vocabulary)))
    first = lambda i: F.greatest(i - (span_lines - 1), F.lit(0))

    def entry(x: Column, i: Column) -> Column:
        held = F.flatten(F.slice("lv", first(i) + 1, i - first(i) + span_lines))
        wide = ~F.array_join(x, " ").isin(sure) & F.exists(wordings, lambda t: F.size(F.array_intersect(t, held)) >= confirm * F.size(t))
        around = F.struct(i.alias("at"), (i - first(i)).alias("off"), F.slice("lt", first(i) + 1, i - first(i) + span_lines).alias("ctx"), F.slice("lv", first(i) + 1, i - first(i) + span_lines).alias("ctv"), F.lit(True).alias("wide"))
        return F.when(wide, around).otherwise(F.struct(i.alias("at"), F.lit(0).alias("off"), F.array(x).alias("ctx"), F.slice("lv", i + 1, 1).alias("ctv"), F.lit(False).alias("wide")))

    near = F.transform("lt", lambda x, i: F.when(F.arrays_overlap(x, anchors), entry(x, i)))
    around = lined.select("doc_id", "row", "para", F.explode(F.array_compact(near)).alias("x")).select("doc_id", "row", "para", "x.*")
    line = F.array(F.struct(F.col("off").alias("a"), F.col("off").alias("z")))
    starts = F.filter(F.sequence(F.lit(0), "off"), lambda a: ~F.arrays_overlap(F.flatten(F.slice("ctx", a + 1, F.col("off") - a)), anchors))  # a span is named by its first such line
    spans = F.flatten(F.transform(starts, lambda a: F.transform(F.sequence(F.col("off"), F.least(a + (span_lines - 1), F.size("ctx") - 1)), lambda z: F.struct(a.alias("a"), z.alias("z")))))
    cut = around.select("doc_id", "row", "para", "at", "off", "ctx", "ctv", F.explode(F.when(F.col("wide"), spans).otherwise(line)).alias("p"))
    of_span = lambda c: F.flatten(F.slice(c, F.col("p.a") + 1, F.col("p.z") - F.col("p.a") + 1))
    families = F.array(*[F.array(*[F.array(*[F.lit(w) for w in sorted(set(words(t)))]) for t in ts]) for _, ts in sorted(FAMILIES.items())])
    fits = F.transform(families, lambda ts: F.array_max(F.transform(ts, lambda t: F.size(F.array_intersect(t, of_span("ctv"))) / F.size(t))))
    toks = cut.select("doc_id", "row", "para", (F.col("at") - F.col("off") + F.col("p.a")).alias("lo"), (F.col("at") - F.col("off") + F.col("p.z")).alias("hi"), of_span("ctx").alias("t"), fits.alias("fits"))
    key = ["doc_id", "row", "para", "lo", "hi"]

    def grams_at(i: Column) -> Column:
        fits = lambda n, d: (i - d >= 1) & (i - d + n - 1 <= F.size("t"))
        return F.array(*[F.when(fits(n, d), F.array_join(F.slice("t", i - d, n), " ")) for n in range(1, ORDER + 1) for d in range(n)])

    # every feature holds a licence word, so only n-grams around one are looked up
    at = F.array_compact(F.transform("t", lambda x, i: F.when(F.array_contains(anchors, x), i + 1)))
    # rows that repeat a document's text sum up the same n-grams again: the empty one, in each row once, counts them
    gram_rows = toks.select(*key, "fits", F.explode(F.array_append(F.array_distinct(F.array_compact(F.flatten(F.transform(at, grams_at)))), F.lit(""))).alias("g"))
    gram_rows = gram_rows.withColumn("fits", F.when(F.col("g") == "", F.col("fits")))
    weighted = [("", [0.0] * len(classes)), *((g, [float(x.get(k, 0.0)) for k in classes]) for g, x in sorted(model.weights.items()))]
    table = spark.createDataFrame(weighted, "g string, w array<double>")
    rows = F.sum((F.col("g") == "").cast("int"))
    sums = gram_rows.join(F.broadcast(table), "g").groupBy(*key).agg(*[(F.sum(F.get("w", F.lit(i))) / rows).alias(f"s{i}") for i in range(len(classes))], F.max("fits").alias("fits"), F.count("*").alias("terms"), rows.alias("times")).where("terms > times")
    score = [F.col(f"s{i}") + F.lit(float(model.bias[k])) for i, k in enumerate(classes)]
    top = F.greatest(*score)
    scored = sums.select(*key, "fits", "times", top.alias("top"), F.array(*score).alias("s"))
    scored = scored.withColumn("probability", 1 / F.aggregate("s", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("top"))))
    scored = scored.withColumn("label", F.get(F.array(*[F.lit(k) for k in classes]), F.array_position("s", F.col("top")).cast("int") - 1))
    named = scored.withColumn("family", F.when((F.col("label") == UNKNOWN) | (F.col("probability") < model.threshold), F.lit(UNKNOWN)).otherwise(F.col("label")))
    overlap = F.coalesce(F.get("fits", F.array_position(F.array(*[F.lit(k) for k in sorted(FAMILIES)]), F.col("family")).cast("int") - 1), F.lit(0.0))
    found = named.select(*key, "family", F.round("probability", 6).alias("probability"), F.round(overlap, 6).alias("overlap"), ((F.col("family") != UNKNOWN) & (overlap >= confirm)).alias("confirmed"), F.col("times").alias("copies"))
    found = found.where("confirmed or lo = hi")
    # a notice is a confirmed span with none inside it; overlapping ones of a family are one, and cover their lines
    place = W.partitionBy("doc_id", "row", "para")
    end = F.when(F.col("confirmed"), F.col("hi"))
    inner = F.min(end).over(place.orderBy(F.desc("lo"), "hi").rowsBetween(W.unboundedPreceding, -1))
    found = found.withColumn("inner", inner).where("not confirmed or inner is null or inner > hi")
    cover = F.max(end).over(place.orderBy("lo").rangeBetween(W.unboundedPreceding, 0))
    before = F.max("hi").over(W.partitionBy("doc_id", "row", "para", "family", "confirmed").orderBy("lo").rowsBetween(W.unboundedPreceding, -1))
    found = found.withColumn("seen", F.when(F.col("confirmed"), before).otherwise(cover)).where("seen is null or seen < lo")
    return found.select("doc_id", "para", F.col("lo").alias("line"), (F.col("hi") - F.col("lo") + 1).alias("lines"), "family", "probability", "overlap", "confirmed", "copies")


def document_licences(docs: DataFrame, model: Classifier | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per doc_id: licences (confirmed families, comma-joined, by name; empty: none), n_confirmed, n_unknown."""
    found = paragraph_scan(docs, model, id_col, text_col).groupBy("doc_id").agg(
        F.array_join(F.array_sort(F.collect_set(F.when(F.col("confirmed"), F.col("family")))), ",").alias("licences"),
        F.sum(F.when(F.col("confirmed"), F.col("copies")).otherwise(0)).alias("n_confirmed"), F.sum(F.when(F.col("confirmed"), 0).otherwise(F.col("copies"))).alias("n_unknown"),
    ).withColumnRenamed("doc_id", "_id")
    ids = docs.select(F.col(id_col).alias("doc_id")).distinct()
    return ids.join(found, ids["doc_id"].eqNullSafe(found["_id"]), "left").select("doc_id", F.coalesce("licences", F.lit("")).alias("licences"), F.coalesce("n_confirmed", F.lit(0)).alias("n_confirmed"), F.coalesce("n_unknown", F.lit(0)).alias("n_unknown"))
