"""License scans by a trained paragraph classifier, in DataFrame and ML-pipeline functions only.

A multinomial logistic regression with an L1 share over word uni- and bigrams tells licence families from an unknown class. It is trained on the notice
templates below set among background lines, and on a bounded sample of different background lines (`BACKGROUND_ROWS` and `TRAIN_CHARS` of each, documented bounds on the weights alone); the unknown class is
calibrated by a threshold that all but `FALSE_SHARE` of all background lines of the table stay under, each read whole: lines that match no template, those with a cue word too. A predicted
family is confirmed where a template of it shares at least 0.8 of its five-word shingles with the paragraph. A paragraph is a run of lines wrapped at a margin: a line of
WRAPPED characters that ends within a sentence goes on in the next one, unless that is blank or opens a notice of its own. Other lines are paragraphs by themselves; so a text
whose lines all end so is one paragraph, however long. Paragraphs are called lines below.

Only lines with an anchor are scored: the weights of all other features together do not lift any family to the threshold, so this is no approximation.
Null and empty texts have no paragraphs of any family; repeated rows are told apart by an internal row number; extra columns are ignored.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.ml import Pipeline
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import CountVectorizer, StringIndexer
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACE, stored

UNKNOWN = "unknown"
BACKGROUND_ROWS, TRAIN_CHARS, FALSE_SHARE, SHINGLE, CONFIRM = 1500, 2000, 0.001, 5, 0.8
#: Least and most characters of a line that goes on in the next one, and the line break between them: behind a letter, number, comma, closing mark, slash or hyphen.
WRAPPED = (40, 120)
WRAP = (
    r"\r?\n(?<=[^\n]{%d}[\p{L}\p{N},)\"'/-]\r?\n)(?<![^\r\n]{%d}\r?\n)" % (WRAPPED[0] - 1, WRAPPED[1] + 1)
    + r"(?=[^\S\n]*+\S)(?![^\p{L}\n]*+(?:SPDX|Copyright))"
)
#: The threshold is at least LOWEST; it is read off a histogram of log-odds in steps of 1 / STEPS, up to MOST, where probabilities come near the precision of doubles.
LOWEST, STEPS, MOST = 0.5, 1000, 27.0
#: Public licence notices by family.
TEMPLATES = [
    ("apache", "Licensed under the Apache License, Version 2.0."),
    ("apache", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.'),
    ("apache", "SPDX-License-Identifier: Apache-2.0"),
    ("mit", "Released under the MIT License."),
    ("mit", "This project is licensed under the terms of the MIT license."),
    ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"),
    ("mit", "SPDX-License-Identifier: MIT"),
    ("mit", "Available under the MIT licence."),
    ("gpl", "This work is licensed under the GNU General Public License, version 3."),
    ("gpl", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation"),
    ("gpl", "SPDX-License-Identifier: GPL-3.0-or-later"),
    ("gpl", "SPDX-License-Identifier: GPL-2.0-only"),
    ("agpl", "it under the terms of the GNU Affero General Public License as published by the Free Software Foundation"),
    ("agpl", "SPDX-License-Identifier: AGPL-3.0-or-later"),
    ("lgpl", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License"),
    ("lgpl", "SPDX-License-Identifier: LGPL-2.1-or-later"),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("bsd", "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file."),
    ("bsd", "SPDX-License-Identifier: BSD-3-Clause"),
    ("bsd", "SPDX-License-Identifier: BSD-2-Clause"),
    ("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"),
    ("isc", "SPDX-License-Identifier: ISC"),
    ("boost", "Distributed under the Boost Software License, Version 1.0."),
    ("boost", "SPDX-License-Identifier: BSL-1.0"),
    ("public-domain", "This is free and unencumbered software released into the public domain."),
    ("public-domain", "SPDX-License-Identifier: CC0-1.0"),
    ("cc-by-nc", "Licensed under CC BY-NC 4.0."),
    ("cc-by-nc", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("cc-by", "Licensed under CC BY 4.0."),
    ("cc-by", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("cc-by-sa", "Licensed under CC BY-SA 4.0."),
    ("cc-by-sa", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("mpl", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("mpl", "SPDX-License-Identifier: MPL-2.0"),
    ("epl", "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0"),
    ("proprietary", "Copyright. All rights reserved. Unauthorized copying of this file is strictly prohibited."),
]
#: Words too common to be features.
STOP = "a an and any are as at be by can for from in is it may not of on or that the this to under use used was with without you your".split()


def tokens(line: Column) -> Column:
    return F.filter(F.split(F.lower(line), r"[^\p{L}\d]+"), lambda w: w != "")


def _once(value: Column, use) -> Column:
    """use(value) with value computed once: inside a lambda of `use` the expression itself would be evaluated anew for each element."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _runs(words: Column, width: int) -> Column:
    return F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size(words) - width + 1)), lambda i: F.array_join(F.slice(words, i, width), " "))


def grams(words: Column) -> Column:
    return _once(F.filter(words, lambda w: ~w.isin(*STOP)), lambda kept: F.array_distinct(F.concat(kept, _runs(kept, 2))))


def shingles(words: Column, width: int = SHINGLE) -> Column:
    """All runs of `width` words, or the whole of fewer."""
    return _once(words, lambda w: F.array_distinct(_runs(w, width)))


def paragraphs(text: Column) -> Column:
    """All paragraphs of a text, the lines of each joined by spaces."""
    return F.filter(F.split(F.regexp_replace(F.coalesce(text, F.lit("")), WRAP, " "), "\n"), lambda x: F.btrim(x, F.lit(SPACE)) != "")


class Model:
    """Weights (feature, family -> weight relative to unknown), intercepts and the calibrated threshold; false_share is the share of background lines that reach it, None before calibration."""

    def __init__(self, weights: dict[str, dict[str, float]], intercepts: dict[str, float], threshold: float, frequent: dict[str, int] | None = None):
        self.weights, self.intercepts, self.threshold, self.frequent = weights, intercepts, threshold, frequent or {}
        self.false_share: float | None = None

    @property
    def anchors(self) -> list[list[str]]:
        """Features of which a line needs one to leave unknown, each as the words that it is made of.

        A family reaches the threshold only if its weights sum to the threshold's log-odds less its intercept. Features are set aside, those whose words most
        background lines hold first, as long as all set aside together leave every family below that sum; a line of these alone is unknown for certain.
        """
        room = {f: math.log(self.threshold / (1 - self.threshold)) - b - 1e-6 for f, b in self.intercepts.items()}
        kept = []
        for feature in sorted(self.weights, key=lambda x: (-self.frequent.get(x, 0), max(self.weights[x].values()), x)):
            gain = {f: max(0.0, w) for f, w in self.weights[feature].items()}
            if not any(gain.values()):
                continue
            if all(room[f] - g > 0 for f, g in gain.items()):
                room = {f: left - gain.get(f, 0.0) for f, left in room.items()}
            else:
                kept.append(feature.split(" "))
        single = {words[0] for words in kept if len(words) == 1}
        return sorted(words for words in kept if len(words) == 1 or not single & set(words))

    def anchored(self, text: Column) -> Column:
        """Whether lower-cased text holds the words of an anchor."""
        tests = [reduce(Column.__and__, [text.contains(w) for w in words]) for words in self.anchors]
        return reduce(Column.__or__, tests, F.lit(False))

    def table(self, spark: SparkSession) -> DataFrame:
        rows = [(f, k, w) for f, by in self.weights.items() for k, w in by.items() if w]
        return spark.createDataFrame(rows or [("", UNKNOWN, 0.0)], "feature string, family string, weight double")


def template_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(TEMPLATES, "family string, line string").select("family", shingles(tokens(F.col("line"))).alias("template"), tokens(F.col("line")).alias("words"), "line")


def background(lines: DataFrame, buckets: int) -> DataFrame:
    """Different lines, at most one of each digest bucket: the one with the least digest, so a line's repeats give it no better chance. A task shuffles one number for each bucket, and the lines chosen."""
    digest = F.xxhash64("line")
    least = lines.groupBy(F.pmod(digest, F.lit(buckets)).alias("bucket")).agg(F.min(digest).alias("digest"))  # `buckets` rows
    return lines.withColumn("digest", digest).join(F.broadcast(least.select("digest")), "digest", "left_semi").select("line").distinct()


def train(docs: DataFrame, rows: int = BACKGROUND_ROWS, text_col: str = "text") -> Model:
    """Weights from templates alone, between background lines and behind them, and from background lines; its threshold is LOWEST, not yet calibrated."""
    lines = docs.select(F.explode(paragraphs(F.col(text_col))).alias("line")).select(F.substring("line", 1, TRAIN_CHARS).alias("line"))
    lines = stored(background(lines, 2 * rows), "licence-background")  # stored first: else Catalyst moves the test for cue words below the choice, to all lines of the table
    known = F.lower("line").rlike("(?i)licen[sc]e|copyright|spdx|permission is hereby|hereby granted|public domain|redistribut")
    sample = stored(lines.filter(~known & (F.pmod(F.xxhash64("line", F.lit(1)), F.lit(2)) == 0)), "licence-lines")
    spark = docs.sparkSession
    few = sample.orderBy(F.xxhash64("line")).limit(12)
    made = template_table(spark).select("family", "line").crossJoin(few.select(F.col("line").alias("other")))  # a fixed number of templates by twelve lines
    positive = template_table(spark).select("family", "line").unionByName(made.select("family", F.concat_ws(" ", "line", F.substring("other", 1, 60)).alias("line")))
    positive = positive.unionByName(made.select("family", F.concat_ws(" ", F.substring("other", 1, 40), "line").alias("line")))
    train = positive.unionByName(sample.select(F.lit(UNKNOWN).alias("family"), "line")).select("family", grams(tokens(F.col("line"))).alias("grams"))
    steps = [StringIndexer(inputCol="family", outputCol="label", stringOrderType="alphabetAsc"), CountVectorizer(inputCol="grams", outputCol="features", binary=True, minDF=3.0, vocabSize=1 << 14)]
    fitted = Pipeline(stages=[*steps, LogisticRegression(family="multinomial", regParam=0.0005, elasticNetParam=0.5, maxIter=25, standardization=False)]).fit(stored(train, "licence-train").coalesce(1))
    families, words, best = fitted.stages[0].labels, fitted.stages[1].vocabulary, fitted.stages[2]
    matrix, bias = best.coefficientMatrix.toArray(), best.interceptVector.toArray()
    zero = families.index(UNKNOWN) if UNKNOWN in families else None
    base = matrix[zero] if zero is not None else 0 * matrix[0]
    weights = {w: {f: float(matrix[k][j] - base[j]) for k, f in enumerate(families) if k != zero} for j, w in enumerate(words) if abs(matrix[:, j] - base[j]).max() > 1e-9}
    shift = {f: float(bias[k] - (bias[zero] if zero is not None else 0)) for k, f in enumerate(families) if k != zero}
    low, lifting = F.lower("line"), sorted(w for w, by in weights.items() if max(by.values()) > 0)
    holds = [reduce(Column.__and__, [low.contains(x) for x in w.split(" ")]) for w in lifting]
    seen = sample.agg(*(F.count_if(h).alias(str(k)) for k, h in enumerate(holds))).first() if lifting else []
    return Model(weights, shift, LOWEST, dict(zip(lifting, seen)))


def calibrate(model: Model, told: DataFrame, n_lines: int) -> Model:
    """Sets the least threshold that at most FALSE_SHARE of the background lines reach, or the highest there is, and false_share.

    told: the scored lines of the whole table, of n_lines, with probability and known. Lines left out have less than LOWEST and count as background; so does a line that matches a
    template and still has less, which can only enlarge the number that the share is taken of.
    """
    odds = F.ln(F.col("probability") / (1 - F.col("probability")))
    at = F.floor(F.least(F.when(F.col("probability") < 1, odds).otherwise(MOST), F.lit(MOST)) * STEPS).cast("long")
    counts = told.filter(F.col("probability") >= LOWEST).groupBy(F.when(F.col("known"), -1).otherwise(at).alias("at")).agg(F.count(F.lit(1)).alias("n")).collect()  # at most MOST * STEPS + 2 rows
    bins = {r["at"]: r["n"] for r in counts}
    total, over, top = n_lines - bins.pop(-1, 0), 0, int(MOST * STEPS)
    start = top + 1  # the threshold is the lower edge of the bin `start`
    while start > 0 and over + bins.get(start - 1, 0) <= FALSE_SHARE * total:
        start -= 1
        over += bins.get(start, 0)
    if start > top:  # too many lines at the top of the histogram: no threshold reaches the share
        start, over = top, bins.get(top, 0)
    model.threshold = max(LOWEST, 1 / (1 + math.exp(-start / STEPS)))
    model.false_share = over / total if total else 0.0
    return model


def fit(docs: DataFrame, rows: int = BACKGROUND_ROWS, text_col: str = "text") -> Model:
    """Trains on a bounded sample and calibrates on all lines of docs."""
    model = train(docs, rows, text_col)
    counted, told = scored(docs, model, text_col=text_col)
    return calibrate(model, told, counted.agg(F.sum("n_paragraphs")).first()[0] or 0)


def classified(lines: DataFrame, model: Model) -> DataFrame:
    """(row, place, line) -> with family (or unknown), probability of the likeliest family, confirmed, and known: whether it matches a template of any family."""
    spark = lines.sparkSession
    families = sorted(model.intercepts)
    features = lines.select("row", "place", "line", F.explode(grams(tokens(F.col("line")))).alias("feature"))
    summed = features.join(F.broadcast(model.table(spark)), "feature").groupBy("row", "place", "line").agg(*(F.sum(F.when(F.col("family") == f, F.col("weight")).otherwise(0.0)).alias(f"_{k}") for k, f in enumerate(families)))
    values = F.array(*(F.struct(F.exp(F.col(f"_{k}") + F.lit(model.intercepts[f])).alias("value"), F.lit(f).alias("family")) for k, f in enumerate(families)))
    valued = summed.select("row", "place", "line", values.alias("values"))
    total = F.aggregate("values", F.lit(1.0), lambda a, x: a + x["value"])
    told = valued.select("row", "place", "line", F.array_max("values").alias("best"), total.alias("total")).select("row", "place", "line", "best.family", (F.col("best.value") / F.col("total")).alias("probability"))
    told = told.withColumn("family", F.when(F.col("probability") >= model.threshold, F.col("family")).otherwise(UNKNOWN))
    own = told.withColumn("_own", F.when(F.col("family") != UNKNOWN, shingles(tokens(F.col("line")))))
    templates = template_table(spark).agg(F.collect_list(F.struct("family", "template")).alias("templates"))  # one row, as many as TEMPLATES
    paired = own.crossJoin(F.broadcast(templates))
    met = F.filter("templates", lambda t: F.size(F.array_intersect(t["template"], F.col("_own"))) >= CONFIRM * F.size(t["template"]))
    paired = paired.withColumn("_met", F.when(F.col("_own").isNotNull(), F.transform(met, lambda t: t["family"])).otherwise(F.array().cast("array<string>")))
    return paired.select("row", "place", "line", "family", "probability", F.array_contains("_met", F.col("family")).alias("confirmed"), (F.size("_met") > 0).alias("known"))


def scored(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """Stored (doc_id, row, n_paragraphs), one row per row of docs, and the lines that reach the model's threshold as `classified` gives them, without their text."""
    found = paragraphs(F.col(text_col))
    some = F.when(model.anchored(F.col("low")), F.filter("lines", lambda x: F.exists(F.array(F.lower(x)), model.anchored)))
    rows = docs.select(F.col(id_col).alias("doc_id"), F.monotonically_increasing_id().alias("row"), found.alias("lines"), F.lower(F.col(text_col)).alias("low"))
    rows = stored(rows.select("doc_id", "row", F.size("lines").cast("long").alias("n_paragraphs"), some.alias("cued")), "licence-rows")
    told = classified(rows.select("row", F.posexplode("cued").alias("place", "line")), model).filter(F.col("family") != UNKNOWN).drop("line")
    return rows.drop("cued"), stored(told, "licence-told")


def scanned(docs: DataFrame, model: Model | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: doc_id, n_paragraphs, n_licensed, families, confirmed_families (sorted, comma-joined), probability (of the surest line)."""
    given, model = model, model or train(docs, text_col=text_col)
    rows, told = scored(docs, model, id_col, text_col)
    if given is None:
        calibrate(model, told, rows.agg(F.sum("n_paragraphs")).first()[0] or 0)
        told = told.filter(F.col("probability") >= model.threshold)
    by_row = told.groupBy("row").agg(F.count(F.lit(1)).alias("n_licensed"), F.array_join(F.sort_array(F.collect_set("family")), ",").alias("families"), F.array_join(F.sort_array(F.collect_set(F.when(F.col("confirmed"), F.col("family")))), ",").alias("confirmed_families"), F.max("probability").alias("probability"))
    out = rows.join(by_row, "row", "left")
    return out.select("doc_id", "n_paragraphs", F.coalesce("n_licensed", F.lit(0)).cast("long").alias("n_licensed"), F.coalesce("families", F.lit("")).alias("families"), F.coalesce("confirmed_families", F.lit("")).alias("confirmed_families"), F.round(F.coalesce("probability", F.lit(0.0)), 4).alias("probability"))
