"""Licence scans by a trained paragraph classifier (native: DataFrame functions only on the data).

A paragraph is a run of lines with an ASCII letter or digit. Its passages begin at each line that,
with the next one, holds a cue (a stem of the notices below, or a family's name or id): the line, the
line and the next, and the lines that hold REACH words beyond the first, so wrapped notices are met
whole. Sparse word uni- and bigrams of a passage feed a softmax regression over licence families
and an unknown class; it is fitted on the driver to the notices below (a fixed, bounded set), its
temperature is calibrated on notices that the fit did not see, in any copy, and its weights go into
the plan as one constant of small maps, dealt by a hash of the gram. A predicted family is confirmed
by comparing the passage with that family's notices: a part of CONFIRM of some notice's bigrams must
occur, and the name in it as a whole ("MIT-style" is another word than "MIT").

A paragraph gets an entry for each family that a passage confirms (its best passage; where passages
of two families share lines, the family whose notice is held better has them), or one for its
likeliest passage when none does.

Defined cases: null and empty texts have no paragraph; a paragraph whose likeliest class is unknown,
or whose chance is below SURE, counts as unknown; ties between families go to the first in code
point order, between passages to the first line; very long lines are scored whole; repeated rows
give a row each; null ids are kept; other columns are ignored, whatever their names; an empty table
gives an empty result.
"""

from __future__ import annotations

import json
import math
import re
import zlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from driftlattice.llm.shared import field, let

SURE = 0.5
CONFIRM = 0.6
#: Words of a stretch beyond its first line; no notice below is longer.
REACH = 40
WORDY = "[A-Za-z0-9]"
#: Words keep their inner dots and hyphens.
TOKEN = "[a-z0-9]+(?:[.-][a-z0-9]+)*"
#: Maps that the weights are dealt to.
MAPS = 512
#: Every notice below passes, hyphenated or not and in any case; bare MIT and ISC only in capitals, as "mit" is a common German word.
CUE = (
    r"(?i:licen[cs]|copyright|copyleft|public\s+domain|warrant|permission|redistribut|creative\s+commons|cc[\s-]*by|cc0|spdx|gnu\s|gpl|apache|mozilla|\bmpl|\bbsd|expat|internet\s+systems\s+consortium"
    r"|(?:released|distributed)\s+under|under\s+(?:the\s+)?(?:mit|isc)\b)|\b(?:MIT|ISC)\b"
)

#: Names of the families as notices use them. Fixed values.
NAMES = {
    "AGPL-3.0": ("GNU Affero General Public License, version 3", "GNU Affero General Public License v3.0", "AGPL-3.0", "AGPLv3"),
    "Apache-2.0": ("Apache License, Version 2.0", "Apache License 2.0", "Apache-2.0", "Apache 2.0 License"),
    "BSD-2-Clause": ("BSD 2-Clause License", "Simplified BSD License", "BSD-2-Clause", "two clause BSD License"),
    "BSD-3-Clause": ("BSD 3-Clause License", "New BSD License", "BSD-3-Clause", "three clause BSD License"),
    "CC-BY-4.0": ("CC BY 4.0", "Creative Commons Attribution 4.0 International License", "CC-BY-4.0", "Creative Commons Attribution License"),
    "CC-BY-NC-4.0": ("CC BY-NC 4.0", "Creative Commons Attribution-NonCommercial 4.0 International License", "CC-BY-NC-4.0", "Creative Commons Attribution NonCommercial License"),
    "CC-BY-SA-4.0": ("CC BY-SA 4.0", "Creative Commons Attribution-ShareAlike 4.0 International License", "CC-BY-SA-4.0", "Creative Commons Attribution ShareAlike License"),
    "CC0-1.0": ("CC0 1.0", "Creative Commons CC0 1.0 Universal public domain dedication", "CC0-1.0", "CC0 Universal"),
    "GPL-2.0": ("GNU General Public License, version 2", "GNU General Public License v2.0", "GPL-2.0", "GPLv2"),
    "GPL-3.0": ("GNU General Public License, version 3", "GNU General Public License v3.0", "GPL-3.0", "GPLv3"),
    "ISC": ("ISC License", "Internet Systems Consortium License", "ISC", "ISC Licence"),
    "LGPL-3.0": ("GNU Lesser General Public License, version 3", "GNU Lesser General Public License v3.0", "LGPL-3.0", "LGPLv3"),
    "MIT": ("MIT License", "Expat License", "MIT", "MIT Licence"),
    "MPL-2.0": ("Mozilla Public License, version 2.0", "Mozilla Public License 2.0", "MPL-2.0", "MPL 2.0 License"),
}
FRAMES = ("Released under the {}.", "Licensed under {}.", "Licensed under the {}.", "This work is licensed under the {}.", "Distributed under the terms of the {}.", "SPDX-License-Identifier: {}", "This project is made available under the {}, see the LICENSE file.", "You may use this file under the {}.")
#: Passages typical of one family.
PASSAGES = {
    "AGPL-3.0": (
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License",
        "You should have received a copy of the GNU Affero General Public License along with this program",
    ),
    "Apache-2.0": (
        "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License",
        "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied",
    ),
    "BSD-2-Clause": ("Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following two conditions are met",),
    "BSD-3-Clause": ("Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",),
    "CC0-1.0": ("To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work under CC0",),
    "GPL-2.0": ("This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License",),
    "GPL-3.0": ("This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License",),
    "ISC": (
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted",
        "THE SOFTWARE IS PROVIDED AS IS AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS",
    ),
    "LGPL-3.0": ("This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 3 of the License",),
    "MIT": (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction",
        "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software",
        "The Software is provided as is, without warranty of any kind, express or implied, including but not limited to the warranties of merchantability, fitness for a particular purpose and noninfringement",
    ),
    "MPL-2.0": (
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0",
        "If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/",
    ),
}
#: Sentences with cue words that name no licence.
OTHERS = (
    "The driver lost the driving license after the second offence.", "A fishing licence is needed in this river.", "The license fee is due every month.", "All rights reserved, copyright of the publisher.",
    "No permission was given to enter the building.", "The warranty covers two years of use.", "They asked for permission to leave early.", "The shop sells beer under a liquor license.",
    "Copyright 2020 the authors.", "The software license expired and must be renewed.", "This is licensed under a custom agreement with the vendor.", "Unauthorised redistribution is prohibited.",
    "The terms of the licence were never published.", "A search warrant was issued by the court.", "The work was released under the name of the editor.", "Licensed premises close at eleven.",
    "Distributed under the bridge by volunteers.", "This project is made available to members only with permission.", "You may use this file at the desk with permission of the clerk.", "Licensed under proprietary terms, all rights reserved.",
    "Released under the MIT-style licence of the band.", "Released under a MIT style licence of our own.", "Distributed under terms similar to the Apache License.", "Licensed under a GPL-like custom license.",
    "This work is licensed under a BSD-style agreement.", "It is not released under the MIT License.", "Students of the MIT were given permission to stay.", "The Apache tribe kept the licence to fish.",
)


def words_of(text: str) -> list[str]:
    return re.findall(TOKEN, text.lower())


def grams_of(text: str) -> list[str]:
    words = words_of(text)
    return sorted({*words, *(f"{a} {b}" for a, b in zip(words, words[1:]))})


def notices() -> list[tuple[str, str]]:
    """(family, text); copies of a text weigh it more."""
    out = [(family, frame.format(name)) for family, names in NAMES.items() for name in names for frame in FRAMES]
    out += [(family, text) for family, texts in PASSAGES.items() for text in texts for _ in range(4)]
    return out + [("unknown", text) for text in OTHERS for _ in range(6)]


def templates() -> dict[str, list[dict]]:
    """family -> its notices as the name that must occur in them, between spaces, and their bigrams."""
    out: dict[str, list[dict]] = {}
    for family, names in NAMES.items():
        texts = [(f" {' '.join(words_of(name))} ", frame.format(name)) for name in names for frame in FRAMES] + [(" ", text) for text in PASSAGES.get(family, ())]
        out[family] = [{"name": name, "grams": [g for g in grams_of(text) if " " in g]} for name, text in texts]
    return out


def fit(rows: list[tuple[str, str]], steps: int = 80, rate: float = 0.5, decay: float = 1e-4) -> tuple[list[str], dict[str, list[float]]]:
    """Softmax regression by AdaGrad over single rows, in a fixed order."""
    classes = sorted({c for c, _ in rows})
    place = {c: k for k, c in enumerate(classes)}
    weights: dict[str, list[float]] = {"": [0.0] * len(classes)}
    grown: dict[str, list[float]] = {"": [1e-6] * len(classes)}
    data = [(place[c], ["", *grams_of(t)]) for c, t in rows]
    for _ in range(steps):
        for k in range(len(data)):
            label, grams = data[k * 7919 % len(data)]
            odds = [sum(weights[g][c] for g in grams if g in weights) for c in range(len(classes))]
            top = max(odds)
            part = [math.exp(x - top) for x in odds]
            total = sum(part)
            miss = [p / total - (c == label) for c, p in enumerate(part)]
            if max(abs(m) for m in miss) < 0.02:
                continue
            for g in grams:
                w, s = weights.setdefault(g, [0.0] * len(classes)), grown.setdefault(g, [1e-6] * len(classes))
                for c, m in enumerate(miss):
                    d = m + decay * w[c]
                    s[c] += d * d
                    w[c] -= rate * d / math.sqrt(s[c])
    return classes, weights


def calibrated(rows: list[tuple[str, str]]) -> float:
    """Temperature that makes left-out notices' chances most likely, over a small grid. All copies of a text are in one half."""
    odds, half = [], {t: zlib.crc32(t.encode()) % 2 for _, t in rows}
    for part in range(2):
        classes, weights = fit([r for r in rows if half[r[1]] != part], 12)
        for c, t in sorted({r for r in rows if half[r[1]] == part}):
            odds.append((classes.index(c), [sum(weights[g][j] for g in ["", *grams_of(t)] if g in weights) for j in range(len(classes))]))

    def loss(heat: float) -> float:
        return sum(math.log(sum(math.exp((x - o[c]) / heat) for x in o)) for c, o in odds)

    return min((0.5, 0.75, 1.0, 1.5, 2.0, 3.0), key=loss)


_MODEL: dict = {}


def model() -> dict:
    """The fitted classifier; it depends on the notices only, so a process fits it once."""
    if not _MODEL:
        rows = notices()
        classes, weights = fit(rows, 20)
        _MODEL.update(classes=classes, weights={g: w for g, w in weights.items() if max(map(abs, w)) > 0.05}, heat=calibrated(rows))
    return _MODEL


def constant(value, kind: str) -> Column:
    """A nested constant, parsed once when the plan is optimized."""
    return F.from_json(F.lit(json.dumps(value)), kind)


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(TOKEN), F.lit(0))


def distinct_grams(words: Column) -> Column:
    pairs = F.when(F.size(words) > 1, F.zip_with(F.slice(words, 1, F.size(words) - 1), F.slice(words, 2, F.size(words) - 1), lambda a, b: F.concat_ws(" ", a, b))).otherwise(F.array().cast("array<string>"))
    return F.array_distinct(F.concat(words, pairs))


def passages(text: Column) -> Column:
    """array<struct<para, line, stop, words>>: the passages of all paragraphs in order; para: lines without a word before."""

    def from_line(lines, blanks):
        def at(i):
            end = F.coalesce(F.array_min(F.filter(blanks, lambda b: b > i)), F.size(lines))
            para = F.size(F.filter(blanks, lambda b: b < i))
            # each line has a word, so REACH lines beyond the first always hold REACH words
            rows = F.slice(lines, i + 1, F.least(end - i, F.lit(REACH + 1)))
            more = lambda s, t: F.when(s["n"] >= REACH, s).otherwise(F.struct((s["n"] + F.when(s["k"] > 0, F.size(tokens(t))).otherwise(0)).alias("n"), (s["k"] + 1).alias("k")))
            enough = lambda rows: F.aggregate(rows, F.struct(F.lit(0).alias("n"), F.lit(0).alias("k")), more, lambda s: s["k"])
            return let(rows, lambda rows: F.transform(
                F.filter(F.array_distinct(F.array(F.lit(1), F.least(F.lit(2), F.size(rows)), enough(rows))), lambda k: (k > 1) | F.rlike(F.get(rows, F.lit(0)), F.lit(CUE))),
                lambda k: F.struct(para.alias("para"), i.alias("line"), (i + k).alias("stop"), tokens(F.array_join(F.slice(rows, F.lit(1), k), "\n")).alias("words")),
            ))

        return at

    def cued(lines, blanks):
        worded = lambda i: (i < F.size(lines)) & ~F.array_contains(blanks, i)
        two = lambda i: F.when(worded(i + 1), F.concat_ws("\n", F.get(lines, i), F.get(lines, i + 1))).otherwise(F.get(lines, i))
        return F.filter(F.sequence(F.lit(0), F.size(lines) - 1), lambda i: worded(i) & F.rlike(two(i), F.lit(CUE)))

    def all_of(lines):
        blanks = F.filter(F.sequence(F.lit(0), F.size(lines) - 1), lambda i: ~F.rlike(F.get(lines, i), F.lit(WORDY)))
        return let(blanks, lambda blanks: F.flatten(F.transform(cued(lines, blanks), from_line(lines, blanks))))

    return let(F.split(text, "\n"), all_of)


def classified(docs: DataFrame, keep=("doc_id",)) -> DataFrame:
    """docs(text, *keep) -> (*keep, found array<struct<line, stop, family, chance, part, confirmed>>), entries of the cue paragraphs in order."""
    m = model()
    k = len(m["classes"])
    dealt: list[dict] = [{} for _ in range(MAPS)]
    for g, w in sorted(m["weights"].items()):
        if g:
            dealt[zlib.crc32(g.encode()) % MAPS][g] = [float(x) for x in w]
    weights, notice = constant(dealt, "array<map<string,array<double>>>"), constant(templates(), "map<string,array<struct<name:string,grams:array<string>>>>")
    classes, bias = constant(m["classes"], "array<string>"), constant([float(x) for x in m["weights"].get("", [0.0] * k)], "array<double>")
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    kind = "array<struct<para:int,line:int,stop:int,words:array<string>>>"
    found = F.when(F.rlike(text, F.lit(CUE)), passages(text)).otherwise(F.array().cast(kind))
    rows = docs.select(*[field(c) for c in keep], found.alias("found"))

    def weight(g):
        return F.try_element_at(F.get(weights, (F.crc32(g.cast("binary")) % MAPS).cast("int")), g)

    def decide(x):
        def of_grams(grams):
            known = F.filter(F.transform(grams, weight), lambda w: w.isNotNull())
            return let(F.transform(F.aggregate(known, bias, lambda s, w: F.zip_with(s, w, lambda a, b: a + b)), lambda o: o / m["heat"]), lambda odds: of_odds(grams, odds))

        def of_odds(grams, odds):
            top = F.array_max(odds)
            chance = 1 / F.aggregate(F.transform(odds, lambda o: F.exp(o - top)), F.lit(0.0), lambda s, e: s + e)
            family = F.get(classes, F.array_position(odds, top).cast("int") - 1)
            return let(F.struct(F.when(chance >= SURE, family).otherwise("unknown").alias("family"), chance.alias("chance")), lambda y: confirm(grams, y))

        def confirm(grams, y):
            line = F.concat(F.lit(" "), F.array_join(x["words"], " "), F.lit(" "))
            own = F.filter(F.coalesce(F.try_element_at(notice, y["family"]), F.array().cast("array<struct<name:string,grams:array<string>>>")), lambda t: F.contains(line, t["name"]))
            part = F.coalesce(F.array_max(F.transform(own, lambda t: F.size(F.array_intersect(t["grams"], grams)) / F.size(t["grams"]))), F.lit(0.0))
            return let(part, lambda part: F.struct(x["para"].alias("para"), x["line"].alias("line"), x["stop"].alias("stop"), y["family"].alias("family"), y["chance"].alias("chance"), part.alias("part"), (part >= CONFIRM).alias("confirmed")))

        return let(distinct_grams(x["words"]), of_grams)

    order = lambda *by: lambda a, b: F.coalesce(*[F.when(f(a) < f(b), -1).when(f(a) > f(b), 1) for f in by], F.lit(0))
    likely = order(lambda x: (x["family"] == "unknown").cast("int"), lambda x: -x["chance"], lambda x: x["line"], lambda x: x["stop"])
    held = order(lambda x: -x["part"], lambda x: x["stop"] - x["line"], lambda x: x["line"])

    def entries(ps):
        """Each confirmed family's best passage, or the likeliest known (else any) passage of the paragraph."""
        best = lambda firm: F.transform(F.array_distinct(F.transform(firm, lambda x: x["family"])), lambda f: F.get(F.filter(firm, lambda x: x["family"] == f), F.lit(0)))
        beaten = lambda x, tops: F.exists(tops, lambda y: (y["family"] != x["family"]) & (y["part"] > x["part"]) & (y["line"] < x["stop"]) & (x["line"] < y["stop"]))
        settled = lambda firm: let(best(firm), lambda tops: let(F.filter(firm, lambda x: ~beaten(x, tops)), best))
        return let(let(F.array_sort(F.filter(ps, lambda x: x["confirmed"]), held), settled), lambda out: F.when(F.size(out) > 0, out).otherwise(F.slice(F.array_sort(ps, likely), 1, 1)))

    def by_paragraph(ps):
        paras = F.array_distinct(F.transform(ps, lambda x: x["para"]))
        return F.flatten(F.transform(paras, lambda p: let(F.filter(ps, lambda x: x["para"] == p), entries)))

    return rows.select(*[field(c) for c in keep], let(F.transform("found", decide), by_paragraph).alias("found"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = classified(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    sure = F.filter("found", lambda x: x["confirmed"])
    return found.select(
        "doc_id", F.size("found").cast("long").alias("n_paragraphs"), F.size(sure).cast("long").alias("n_confirmed"),
        F.array_join(F.array_sort(F.array_distinct(F.transform(sure, lambda x: x["family"]))), ",").alias("licences"),
        F.array_join(F.transform("found", lambda x: F.concat_ws(":", x["line"].cast("string"), x["family"])), ",").alias("paragraphs"),
        F.coalesce(F.array_max(F.transform(sure, lambda x: F.round(x["chance"], 6))), F.lit(0.0)).alias("chance"),
    )
