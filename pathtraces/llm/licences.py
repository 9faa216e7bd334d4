"""Licence scans with DataFrame functions only.

A paragraph (a line, with those that it is wrapped into: a break after ``WRAPPED`` printable characters that end in no stop, before more text, is a
space) is classified by multinomial logistic regression over its word n-grams (one to three words, present or not). The classes are
licence families, ``unknown`` (a licence of no listed family) and ``none``. The model is trained on the driver, from notices that are
made by rule: the families' names in the usual frames, sentences of the licences' texts, invented licences, and sentences that use the
same words otherwise. Only n-grams that hold a telling word (one of the notices that is no function word) are features, so a
paragraph without telling words has none, scores as ``none``, and is set aside by one array test before anything is exploded. A
temperature calibrates the probabilities; it is fitted on a model that has not seen some of the names (``HELD_OUT``), with these names in frames
that no model has seen. Below ``CERTAIN`` a family becomes ``unknown``; ties go to the first class of the model's list.

A predicted family is confirmed by comparison with its templates: the share of a template's n-grams that the paragraph holds must reach
``CONFIRM`` for one of them; a name of one word is no template by itself, only with the words of a notice. Unconfirmed families become ``unknown`` too.

Null and empty texts have no paragraphs and no licence. The result has a row for every row of the table: rows that share an id share their
paragraphs (each counts). Rows of a null id are matched among each other. Very long texts are read whole. Columns beside id and text are ignored,
whatever their names."""

from __future__ import annotations

import functools
import json
import re
from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pathtraces.llm.quality import COMMON_WORDS

CERTAIN, CONFIRM, LONGEST = 0.5, 0.6, 3
NONE, UNKNOWN = "none", "unknown"

# Names of licence families as notices write them.
FAMILIES = {
    "apache-2.0": ["Apache License, Version 2.0", "Apache License 2.0", "Apache 2.0 license", "Apache-2.0", "ASL 2.0"],
    "mit": ["MIT License", "MIT licence", "Expat license", "X11 license", "MIT"],
    "bsd": ["BSD License", "BSD 3-Clause License", "BSD 2-Clause License", "BSD-3-Clause", "BSD-2-Clause", "New BSD license", "Simplified BSD license"],
    "gpl": ["GNU General Public License, version 3", "GNU General Public License, version 2", "GNU General Public License", "GNU GPL", "GPL version 3", "GPL-3.0-or-later", "GPL-2.0-only", "GPLv3", "GPLv2"],
    "lgpl": ["GNU Lesser General Public License, version 3", "GNU Lesser General Public License", "GNU LGPL", "LGPL version 2.1", "LGPL-3.0-or-later", "LGPLv3"],
    "agpl": ["GNU Affero General Public License, version 3", "GNU Affero General Public License", "GNU AGPL", "AGPL-3.0-only", "AGPLv3"],
    "mpl-2.0": ["Mozilla Public License, version 2.0", "Mozilla Public License 2.0", "Mozilla Public License", "MPL-2.0", "MPL 2.0"],
    "cc-by": ["CC BY 4.0", "CC BY 3.0", "Creative Commons Attribution 4.0 International License", "Creative Commons Attribution License", "CC-BY-4.0"],
    "cc-by-sa": ["CC BY-SA 4.0", "CC BY-SA 3.0", "Creative Commons Attribution-ShareAlike 4.0 International License", "Creative Commons Attribution-ShareAlike License", "CC-BY-SA-4.0"],
    "cc-by-nc": ["CC BY-NC 4.0", "CC BY-NC-SA 4.0", "CC BY-NC 3.0", "CC BY-NC-ND 4.0", "Creative Commons Attribution-NonCommercial 4.0 International License", "Creative Commons Attribution-NonCommercial License", "CC-BY-NC-4.0"],
    "public-domain": ["CC0 1.0", "CC0 1.0 Universal", "Creative Commons Zero", "public domain dedication", "Unlicense", "CC0-1.0"],
}
# Opening sentences of licence texts and of their notices.
SENTENCES = {
    "apache-2.0": ["you may not use this file except in compliance with the License", "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS"],
    "mit": ["Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software"],
    "bsd": ["Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met", "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer"],
    "gpl": ["This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation"],
    "lgpl": ["This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation"],
    "agpl": ["This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation"],
    "mpl-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0", "If a copy of the MPL was not distributed with this file, You can obtain one at mozilla.org"],
    "public-domain": ["This is free and unencumbered software released into the public domain", "The person who associated a work with this deed has dedicated the work to the public domain"],
}
# Licences of no family, and sentences that use the words otherwise.
OTHER_NAMES = ["Acme Source License", "Foo Community Licence 1.1", "Company Software Agreement", "Sample Data License, version 1.0", "Example Corp Public License", "Open Content Licence", "Custom License 3.0", "Research Use License", "Vendor End User License Agreement", "Artistic License", "Eclipse Public License", "Server Side License"]
OTHER_SENTENCES = ["All rights reserved.", "Copyright 2020 the authors, all rights reserved", "No part of this work may be reproduced without written permission", "Use of this software is governed by the license agreement of the vendor", "This file is proprietary and confidential", "See the LICENSE file for license terms"]
BACKGROUND = ["The general public may use this version of the work.", "A driving license is required to distribute goods at work.", "The museum is open to the public free of charge.", "The software released this year is free to use.", "Students at MIT met with the authors.", "The Apache helicopter was under repair.", "He is licensed to work as a nurse.", "The terms of the agreement were read in public.", "Creative people share work under common rules.", "Any person may obtain a copy of the public file.", "The conditions were met with or without a source.", "Version 2.0 of the program is distributed to all users.", "The commons were open to the general public.", "The source and binary forms of the file are here.", "The foundation published a list of conditions.", "We use the library and the program at work.", "Its domain is public and its license plate is new."]
FRAMES = ["Licensed under the {}.", "Licensed under {}.", "Released under the {}.", "This work is licensed under the {}.", "This work is licensed under {}", "Distributed under the terms of the {}", "SPDX-License-Identifier: {}", "This file is made available under the {}", "License: {}", "The code is covered by the {}, see the file for details", "{}"]
HELD_OUT_FRAMES = ["This project is published under the {}.", "Available under the {}", "Copyright the authors. Licensed under the {}.", "You may copy this text under the {}"]
_STOP = {*COMMON_WORDS, "you", "may", "any", "its", "as", "were", "we", "are", "here", "see", "these", "met", "read", "new", "no"}
SHORT_FRAMES = ["Licensed under {}", "under the {}", "License: {}", "{} License", "SPDX-License-Identifier: {}"]
HELD_OUT = {names[1] for names in FAMILIES.values()} | set(OTHER_NAMES[::3])
WRAPPED = 40
_TOKEN = r"[a-z0-9]+(?:\.[0-9]+)*"
_FULL = rf"[\x20-\x7E]{{{WRAPPED - 1}}}[\x22-\x2D\x2F-\x39\x3C-\x3E\x40-\x7E]"  # ends in none of . ! ? : ;
_WRAP = rf"\n(?:(?<={_FULL}\n)|(?<={_FULL}\r\n))(?=[ \t]*[\x21-\x7E])"


def words_of(text: str) -> list[str]:
    return re.findall(_TOKEN, text.lower())


def paragraphs_of(text: str) -> list[str]:
    return re.sub(_WRAP, " ", text).split("\n")


def grams_of(words: list[str]) -> set[str]:
    return {" ".join(words[a : a + n]) for n in range(1, LONGEST + 1) for a in range(len(words) - n + 1)}


def notices(frames: list[str], whole: bool, names_of: Callable[[str], bool] = lambda name: True) -> list[tuple[str, str]]:
    """(class, text) for training (``whole``: with sentences and background) or calibration, of the names that ``names_of`` lets through."""
    made = [(family, frame.format(name)) for family, names in FAMILIES.items() for name in filter(names_of, names) for frame in frames]
    made += [(UNKNOWN, frame.format(name)) for name in filter(names_of, OTHER_NAMES) for frame in frames]
    if whole:
        made += [(family, s) for family, sentences in SENTENCES.items() for s in sentences for _ in range(5)]
        made += [(UNKNOWN, s) for s in OTHER_SENTENCES for _ in range(5)] + [(NONE, s) for s in BACKGROUND for _ in range(8)] + [(NONE, "")] * 40
    return made


class LicenceModel:
    """Weights by n-gram, per class; plain data that becomes a small table. ``blind``: trained without the names of ``HELD_OUT``."""

    def __init__(self, rounds: int = 400, rate: float = 4.0, shrink: float = 2e-5, blind: bool = False):
        rows = [(c, words_of(t)) for c, t in notices(FRAMES, True, lambda name: not blind or name not in HELD_OUT)]
        self.classes = [NONE, UNKNOWN, *FAMILIES]
        self.telling = sorted({w for c, ws in rows if c != NONE for w in ws if w not in _STOP and not w.isdigit()})
        telling = set(self.telling)
        features = [{g for g in grams_of(ws) if not telling.isdisjoint(g.split(" "))} for _, ws in rows]
        names = sorted(set().union(*features))
        at = {g: k for k, g in enumerate(names)}
        x, y = np.zeros((len(rows), len(names))), np.zeros((len(rows), len(self.classes)))
        for k, (c, _) in enumerate(rows):
            x[k, [at[g] for g in features[k]]] = 1
            y[k, self.classes.index(c)] = 1
        share = 1 / y.sum(axis=0)
        weight = (y @ share)[:, None] / len(self.classes)
        w, b = np.zeros((len(names), len(self.classes))), np.zeros(len(self.classes))
        for _ in range(rounds):
            off = (self._softmax(x @ w + b) - y) * weight
            w -= rate * (x.T @ off)
            w = np.sign(w) * np.maximum(np.abs(w) - rate * shrink, 0)  # sparse: small weights become zero
            b -= rate * off.sum(axis=0)
        used = np.abs(w).sum(axis=1) > 0
        self.weights = {g: w[k].tolist() for k, g in enumerate(names) if used[k]}
        self.bias = b.tolist()
        self.temperature = self._fit_temperature() if blind else LicenceModel(rounds, rate, shrink, blind=True).temperature
        # a template is what a frame leaves of a name, or a sentence
        told = [(c, t) for c, names_ in FAMILIES.items() for name in names_ for t in ([name] if len(words_of(name)) > 1 else [f.format(name) for f in SHORT_FRAMES])]
        self.templates = told + [(c, t) for c, ts in SENTENCES.items() for t in ts]

    @staticmethod
    def _softmax(z: np.ndarray) -> np.ndarray:
        e = np.exp(z - z.max(axis=1, keepdims=True))
        return e / e.sum(axis=1, keepdims=True)

    def raw(self, text: str) -> np.ndarray:
        zero = [0.0] * len(self.classes)
        return np.array(self.bias) + np.sum([self.weights.get(g, zero) for g in sorted(grams_of(words_of(text)))] or [zero], axis=0)

    def _fit_temperature(self) -> float:
        """The one of a ladder that makes notices of new names in new frames likeliest."""
        held = notices(HELD_OUT_FRAMES, False, HELD_OUT.__contains__)
        z, y = np.array([self.raw(t) for _, t in held]), [self.classes.index(c) for c, _ in held]
        return min((0.5, 0.7, 1.0, 1.4, 2.0, 2.8, 4.0), key=lambda t: -np.log(self._softmax(z / t)[range(len(y)), y] + 1e-12).mean())

    def classify(self, text: str) -> tuple[str, float, bool]:
        """Class, probability, whether a template confirms it; the plain version of the scan."""
        p = self._softmax(self.raw(text)[None, :] / self.temperature)[0]
        k = int(p.argmax())
        family = self.classes[k]
        grams = grams_of(words_of(text))
        best = max((len(grams & (own := grams_of(words_of(t)))) / len(own) for c, t in self.templates if c == family), default=0.0)
        confirmed = family in FAMILIES and p[k] >= CERTAIN and best >= CONFIRM
        return (family if confirmed or family in (NONE, UNKNOWN) else UNKNOWN), float(p[k]), bool(confirmed)


@functools.lru_cache(1)
def model() -> LicenceModel:
    return LicenceModel()


def _table(spark: SparkSession, rows: list, schema: str) -> DataFrame:
    """Rows known to the driver, as a literal of the plan. Both tables follow the lists above, some thousand short rows."""
    return F.broadcast(spark.range(1).select(F.inline(F.from_json(F.lit(json.dumps(rows)), f"array<struct<{schema}>>"))))


def _words(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(f"({_TOKEN})"), F.lit(1))


def _gram(n: int):
    return lambda k: F.concat_ws(" ", F.slice("words", k, n))


def licence_paragraphs(docs: DataFrame, id: str = "doc_id", text: str = "text", trained: LicenceModel | None = None) -> DataFrame:
    """``id``, ``paragraph`` (its number, from 0, empty ones counted), ``licence`` (a family or ``unknown``), ``score``, ``confirmed``: the paragraphs that aren't ``none``."""
    m, spark = trained or model(), docs.sparkSession
    lines = docs.select(F.col(id).alias("id"), F.posexplode(F.split(F.regexp_replace(text, _WRAP, " "), "\n")).alias("paragraph", "line"), F.monotonically_increasing_id().alias("row"))
    told = lines.select("id", "row", "paragraph", _words(F.col("line")).alias("words")).where(F.arrays_overlap("words", F.array(*map(F.lit, m.telling))))
    grams = [F.transform(F.sequence(F.lit(1), F.size("words") - (n - 1)), _gram(n)) for n in range(1, LONGEST + 1)]
    grams = [F.when(F.size("words") >= n, g).otherwise(F.array().cast("array<string>")) for n, g in enumerate(grams, 1)]
    each = told.select("id", "row", "paragraph", F.explode(F.array_distinct(F.concat(*grams))).alias("gram"))
    weights = _table(spark, [{"gram": g, "w": w} for g, w in m.weights.items()], "gram string, w array<double>")
    templates = [(k, c, grams_of(words_of(t))) for k, (c, t) in enumerate(m.templates)]
    of = _table(spark, [{"gram": g, "hits": hits} for g, hits in sorted({g: [{"t": k, "f": c, "n": len(gs)} for k, c, gs in templates if g in gs] for _, _, own in templates for g in own}.items())], "gram string, hits array<struct<t:int,f:string,n:int>>")
    met = each.join(weights, "gram", "left").join(of, "gram", "left").where("w is not null or hits is not null")
    key = ["id", "row", "paragraph"]
    sums = [F.sum(F.coalesce(F.element_at("w", k + 1), F.lit(0.0))).alias(f"z{k}") for k in range(len(m.classes))]
    scored = met.groupBy(*key).agg(*sums, F.flatten(F.collect_list("hits")).alias("hits"))
    z = F.transform(F.array(*[(F.col(f"z{k}") + b) / m.temperature for k, b in enumerate(m.bias)]), lambda v: v)
    scored = scored.select(*key, "hits", z.alias("z")).withColumn("top", F.array_max("z"))
    scored = scored.withColumn("score", 1 / F.aggregate("z", F.lit(0.0), lambda s, v: s + F.exp(v - F.col("top"))))
    scored = scored.withColumn("family", F.element_at(F.array(*map(F.lit, m.classes)), F.array_position("z", F.col("top")).cast("int"))).where(F.col("family") != NONE)
    mine = F.filter("hits", lambda h: h["f"] == F.col("family"))
    best = F.array_max(F.transform(mine, lambda h: F.size(F.filter(mine, lambda g: g["t"] == h["t"])) / h["n"]))
    sure = F.coalesce((F.col("family") != UNKNOWN) & (F.col("score") >= CERTAIN) & (best >= CONFIRM), F.lit(False))
    return scored.select("id", "paragraph", F.when(sure, F.col("family")).otherwise(UNKNOWN).alias("licence"), "score", sure.alias("confirmed")).withColumnRenamed("id", id)


def licences(docs: DataFrame, id: str = "doc_id", text: str = "text", trained: LicenceModel | None = None) -> DataFrame:
    """Per row: ``id``, ``n_paragraphs`` (of licences), ``licences`` (distinct, ascending, joined by commas; null if there is none), ``score`` (the
    highest), ``confirmed`` (some paragraph is)."""
    found = licence_paragraphs(docs, id, text, trained).groupBy(F.col(id).alias("__id")).agg(F.count(F.lit(1)).alias("n_paragraphs"), F.array_join(F.array_sort(F.collect_set("licence")), ",").alias("licences"), F.max("score").alias("score"), F.max("confirmed").alias("confirmed"))
    out = docs.select(F.col(id)).join(found, F.col(id).eqNullSafe(F.col("__id")), "left")
    return out.select(id, F.coalesce("n_paragraphs", F.lit(0)).cast("long").alias("n_paragraphs"), "licences", F.coalesce("score", F.lit(0.0)).alias("score"), F.coalesce("confirmed", F.lit(False)).alias("confirmed"))
