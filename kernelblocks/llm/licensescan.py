"""Licence scans with DataFrame functions only.

A text's lines that hold a cue word of licensing, and the joined runs of up to WINDOW_LINES adjacent
lines that do, are judged by multinomial logistic regression on sparse word n-grams (one and two words);
no run goes over a blank line. So a notice is found whole where it is wrapped, at 30 columns or more. The
classifier is trained on the driver from labelled samples; an unknown class takes the rest, and a temperature
calibrates all classes on notices that the fit hasn't seen in any form. A prediction counts once a template
of the predicted family, none of which is a sample, confirms it: the template's word pairs must lie in the
paragraph to a given share. Every template holds a cue word, so a paragraph without one could not be
confirmed and leaving it out loses nothing.

Weights and templates are one small broadcast table by gram, so a paragraph costs its grams alone. Each
different paragraph is judged once, however often it occurs, and the findings go back to the lines by its
SHA-256, without the text: by a broadcast where they are small, else by a shuffle in which paragraphs that very
many texts hold are salted. Where confirmed findings overlap, the one with the larger
share stays, then the one with fewer lines.

Defined results: null and empty texts have no paragraphs; repeated rows give their findings each; of classes
that tie the first by name wins, unknown last; texts of any length are read whole, line by line, in time that
grows with their lines; an empty table gives no row; other columns don't matter.
"""

from __future__ import annotations

import re
from collections.abc import Iterable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kernelblocks.llm.arrays import running
from kernelblocks.llm.runtime import cut, id_and_text

UNKNOWN = "unknown"
LEAST_PROBABILITY = 0.5
LEAST_SHARE = 0.6
WINDOW_LINES = 6
#: What a paragraph must hold to be judged; every template below does.
CUES = (
    r"(?i:licen[sc]|copyright|copyleft|warrant|permission|redistribut|public[\s#*/;>-]+domain|spdx|creative[\s#*/;>-]+commons|"
    r"\bcc[\s-](?:by|0)|\bcc0|\bgpl|\blgpl|\bagpl|apache|mozilla|\bbsd\b)|\bMIT\b"
)
#: The first part of a cue that can go on in the next line.
BROKEN_CUES = r"(?i)(?:public|creative)[\s#*/;>-]*$|\bcc\s*$"
#: Findings of different paragraphs are broadcast up to so many bytes; beyond, they are joined by a shuffle.
BROADCAST_BYTES, FINDING_BYTES = 8 << 20, 128
#: In the shuffle a paragraph that stands in more than so many places is dealt to so many tasks.
HOT_ROWS, SALTS = 20_000, 32
WORDS = r"[a-z0-9][a-z0-9.+-]*[a-z0-9]|[a-z0-9]"

#: Short notices of each family (fixed values): the templates that confirm. None of them trains the classifier.
TEMPLATES: dict[str, tuple[str, ...]] = {
    "MIT": (
        "Released under the MIT License.",
        "Licensed under the MIT license.",
        "This project is available under the terms of the MIT License.",
        "SPDX-License-Identifier: MIT",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files",
    ),
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0.",
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License.",
        "Released under the Apache License 2.0.",
        "SPDX-License-Identifier: Apache-2.0",
    ),
    "GPL": (
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License",
        "Released under the GPL version 2 or later.",
        "Licensed under the GPLv3.",
        "SPDX-License-Identifier: GPL-3.0-or-later",
    ),
    "LGPL": (
        "This library is licensed under the GNU Lesser General Public License, version 2.1.",
        "you can redistribute it under the terms of the GNU Lesser General Public License",
        "SPDX-License-Identifier: LGPL-2.1-only",
    ),
    "AGPL": (
        "Licensed under the GNU Affero General Public License, version 3.",
        "under the terms of the GNU Affero General Public License as published by the Free Software Foundation",
        "SPDX-License-Identifier: AGPL-3.0-only",
    ),
    "BSD": (
        "Released under the BSD 3-Clause License.",
        "Licensed under the BSD license.",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
        "SPDX-License-Identifier: BSD-3-Clause",
    ),
    "MPL": (
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
        "Licensed under the Mozilla Public License 2.0.",
        "SPDX-License-Identifier: MPL-2.0",
    ),
    "CC-BY": (
        "Licensed under CC BY 4.0.",
        "This work is licensed under a Creative Commons Attribution 4.0 International License.",
        "This article is distributed under CC-BY 4.0.",
    ),
    "CC-BY-SA": (
        "Licensed under CC BY-SA 4.0.",
        "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
        "Text is available under the Creative Commons Attribution-ShareAlike License.",
    ),
    "CC-BY-NC": (
        "Licensed under CC BY-NC 4.0.",
        "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
        "Shared under CC BY-NC-SA 4.0 for non-commercial use.",
    ),
    "CC0": (
        "To the extent possible under law, the author has dedicated all copyright to the public domain under CC0 1.0.",
        "Released into the public domain under CC0.",
        "This is free and unencumbered software released into the public domain.",
    ),
    "ALL-RIGHTS": (
        "Copyright (c) 2020 the authors. All rights reserved.",
        "All rights reserved. No part of this publication may be reproduced without permission of the copyright holder.",
    ),
}
#: Notices in other words (fixed values): what the classifier learns from.
NOTICES: dict[str, tuple[str, ...]] = {
    "MIT": (
        "This software is distributed under the MIT License, see the file LICENSE.",
        "The code is MIT licensed.",
        "License: MIT",
        "Use of this source code is governed by an MIT-style license.",
        "Permission is granted, free of charge, to any person obtaining a copy of this software and its documentation files, to deal in the software without restriction",
        "Available under the MIT license, copyright the contributors.",
    ),
    "Apache-2.0": (
        "This library is distributed under the terms of the Apache License, Version 2.0.",
        "License: Apache 2.0",
        "You may not use this file except in compliance with the Apache License, Version 2.0.",
        "The project is Apache-2.0 licensed.",
        "You may obtain a copy of the License at www.apache.org/licenses/LICENSE-2.0",
        "All code here is covered by the Apache License, Version 2.0.",
    ),
    "GPL": (
        "This package is distributed under the GNU General Public License, version 2 or any later version.",
        "It is free software; redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
        "License: GPL-3.0",
        "The program is covered by the GNU GPL version 3.",
        "You should have received a copy of the GNU General Public License along with this program",
        "The sources are licensed under GPLv2 or GPLv3.",
    ),
    "LGPL": (
        "The library is distributed under the GNU Lesser General Public License, version 3.",
        "License: LGPL-2.1",
        "It may be redistributed under the terms of the GNU Lesser General Public License.",
        "You should have received a copy of the GNU Lesser General Public License along with this library",
        "The bindings are LGPL licensed.",
        "Covered by the GNU LGPL version 2.1 or later.",
    ),
    "AGPL": (
        "The server is distributed under the GNU Affero General Public License, version 3.",
        "License: AGPL-3.0",
        "It may be redistributed under the terms of the GNU Affero General Public License.",
        "You should have received a copy of the GNU Affero General Public License along with this program",
        "The service is AGPL licensed.",
        "Covered by the GNU AGPL version 3 or later.",
    ),
    "BSD": (
        "This software is distributed under the 3-clause BSD License.",
        "License: BSD-2-Clause",
        "Use of this source code is governed by a BSD-style license.",
        "Redistribution in source and binary forms is permitted provided that the following conditions are met",
        "The code is BSD licensed.",
        "Available under the BSD license, copyright the contributors.",
    ),
    "MPL": (
        "The file is distributed under the Mozilla Public License, version 2.0.",
        "License: MPL-2.0",
        "This source code is subject to the Mozilla Public License, v. 2.0.",
        "You can obtain a copy of the Mozilla Public License at mozilla.org/MPL/2.0",
        "The add-on is MPL licensed.",
        "Covered by the Mozilla Public License 2.0.",
    ),
    "CC-BY": (
        "The text is published under CC BY 4.0.",
        "License: CC-BY-4.0",
        "Distributed under the Creative Commons Attribution 4.0 International License.",
        "This is an open access article under the CC BY license.",
        "Available under a Creative Commons Attribution License, which permits reuse with credit.",
        "The figures are licensed CC-BY 4.0.",
    ),
    "CC-BY-SA": (
        "The text is published under CC BY-SA 4.0.",
        "License: CC-BY-SA-4.0",
        "Distributed under the Creative Commons Attribution-ShareAlike 4.0 International License.",
        "This page may be shared under the CC BY-SA license.",
        "Content is available under a Creative Commons Attribution-ShareAlike License.",
        "The maps are licensed CC-BY-SA 3.0.",
    ),
    "CC-BY-NC": (
        "The text is published under CC BY-NC 4.0.",
        "License: CC-BY-NC-4.0",
        "Distributed under the Creative Commons Attribution-NonCommercial 4.0 International License.",
        "This is an open access article under the CC BY-NC license for non-commercial use.",
        "Available under a Creative Commons Attribution-NonCommercial License.",
        "The figures are licensed CC-BY-NC-SA 4.0.",
    ),
    "CC0": (
        "The data are published under CC0 1.0.",
        "License: CC0-1.0",
        "The author has waived all copyright under the CC0 public domain dedication, to the extent possible under law.",
        "This work is in the public domain under CC0.",
        "Free and unencumbered, released into the public domain.",
        "The records are dedicated to the public domain with CC0 1.0.",
    ),
    "ALL-RIGHTS": (
        "Copyright (c) 2018 the publisher. All rights reserved.",
        "All rights reserved by the copyright holder.",
        "No part of this book may be reproduced in any form without written permission of the publisher. All rights reserved.",
        "Copyright 2021 by the authors, all rights reserved.",
        "(c) the company. All rights reserved worldwide.",
        "No part of this publication may be copied or reproduced without the permission of the copyright holder.",
    ),
}
#: Paragraphs with a cue word that grant no licence (fixed values).
UNLICENSED: tuple[str, ...] = (
    "She renewed her driving licence before the journey.",
    "The licence plate of the car was covered with mud.",
    "You need a licence to fish in this river and a permit to camp.",
    "The bar lost its liquor license after the second warning.",
    "He asked for permission to leave the room.",
    "The pilot holds a commercial license and flies every weekend.",
    "Warranty repairs are handled by the shop on Main Street.",
    "The apache helicopter landed near the village.",
    "Students of mit built a small robot for the contest.",
    "The court discussed copyright and trade for two days.",
    "Poetic license allows the author to bend the facts.",
    "Their license server was down and nobody could work.",
    "Read the permission slip and sign it.",
    "The museum moved into the public domain of the old harbour.",
    "Der Vertrag ist mit dem Kunden und mit der Firma geschlossen.",
    "Sie kam mit dem Zug und ging mit ihm nach Hause.",
)
DRESSING: tuple[tuple[str, str], ...] = (
    ("", ""),
    ("", " See the file for details."),
    ("Note: ", ""),
    ("The text of this page is ", " "),
    ("Please note that this material is ", " and may be shared."),
)


def grams(text: str) -> list[str]:
    """Single words and word pairs, each once, as the query below makes them."""
    words = re.findall(WORDS, text.lower())
    return list(dict.fromkeys(words + [f"{a} {b}" for a, b in zip(words, words[1:], strict=False)]))


def built_in_samples() -> list[tuple[str, str]]:
    """(paragraph, family) for training, the same at every call: each notice in all its dressings, one after the other."""
    out = [(f"{a}{t}{b}", name) for name, texts in NOTICES.items() for t in texts for a, b in DRESSING]
    return out + [(f"{a}{t}{b}", UNKNOWN) for t in UNLICENSED for a, b in DRESSING]


class LicenceModel:
    """Weights of each gram for each class, bias and temperature.

    The temperature is fitted on samples of which no sample that shares most words trains that fit: samples are
    held out by what they have in common, not one by one.
    """

    TEMPERATURES = np.geomspace(0.02, 8, 61)

    def __init__(self, samples: Iterable[tuple[str, str]], rounds: int = 300, rate: float = 2.0, l2: float = 1e-3) -> None:
        rows = [(grams(t), name) for t, name in samples]
        self.classes = sorted({n for _, n in rows} - {UNKNOWN}) + [UNKNOWN]
        self.vocabulary = sorted({g for gs, _ in rows for g in gs})
        spot = {g: i for i, g in enumerate(self.vocabulary)}
        x = np.zeros((len(rows), len(self.vocabulary)))
        for i, (gs, _) in enumerate(rows):
            x[i, [spot[g] for g in gs]] = 1.0
        y = np.array([self.classes.index(n) for _, n in rows])
        part = self._parts(x, y)
        z = np.zeros((len(rows), len(self.classes)))
        for k in range(3):
            held = part % 3 == k
            if held.any() and not held.all():
                w, b = self._fit(x[~held], y[~held], rounds, rate, l2)
                z[held] = x[held] @ w + b
        at = np.arange(len(rows))
        self.held_out_accuracy = float((z.argmax(axis=1) == y).mean())
        self.temperature = min(self.TEMPERATURES, key=lambda t: -self._log_softmax(z / t)[at, y].mean()) if z.any() else 1.0
        self.held_out_unknown = float((self._log_softmax(z[y < len(self.classes) - 1] / self.temperature).max(axis=1) < np.log(LEAST_PROBABILITY)).mean()) if z.any() else 0.0
        self.weights, self.bias = self._fit(x, y, rounds, rate, l2)

    @staticmethod
    def _parts(x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """A number for each sample, the same for samples of a class that share half of their grams."""
        part, count = np.full(len(x), -1), {}
        for i in range(len(x)):
            same = np.flatnonzero((part[:i] >= 0) & (y[:i] == y[i]))
            both = x[same] @ x[i]
            near = same[both >= 0.5 * np.minimum(x[same].sum(axis=1), x[i].sum())] if len(same) else same
            if len(near):
                part[i] = part[near[0]]
            else:
                part[i] = count[y[i]] = count.get(y[i], -1) + 1
        return part

    def _fit(self, x: np.ndarray, y: np.ndarray, rounds: int, rate: float, l2: float) -> tuple[np.ndarray, np.ndarray]:
        k = len(self.classes)
        w, b = np.zeros((x.shape[1], k)), np.zeros(k)
        b[-1] = 1.0  # a paragraph that shows nothing is unknown
        target = np.eye(k)[y]
        for _ in range(rounds):
            gap = (np.exp(self._log_softmax(x @ w + b)) - target) / max(len(y), 1)
            w -= rate * (x.T @ gap + l2 * w)
            b[:-1] -= rate * 0.1 * gap.sum(axis=0)[:-1]
        return w, b

    @staticmethod
    def _log_softmax(z: np.ndarray) -> np.ndarray:
        z = z - z.max(axis=1, keepdims=True)
        return z - np.log(np.exp(z).sum(axis=1, keepdims=True))

    def gram_table(self, spark: SparkSession, templates: list[list[str]]) -> DataFrame:
        """(gram, w0.., t0..): a gram's weight for each class, and whether it lies in each template."""
        spot = {g: i for i, g in enumerate(self.vocabulary)}
        sets = [set(t) for t in templates]
        zero = [0.0] * len(self.classes)
        rows = [
            (g, *((self.weights[spot[g]] / self.temperature).tolist() if g in spot else zero), *(int(g in t) for t in sets))
            for g in sorted(spot.keys() | {g for t in templates for g in t})
        ]
        kinds = [f"w{j} double" for j in range(len(self.classes))] + [f"t{k} int" for k in range(len(templates))]
        return spark.createDataFrame(rows, ", ".join(["gram string", *kinds]))


def _grams_sql(text: str) -> str:
    words = f"regexp_extract_all(lower({text}), r'({WORDS})', 1)"
    pairs = (
        f"transform(arrays_zip(slice(w, 1, size(w) - 1), slice(w, 2, size(w) - 1)), p -> concat(p.`0`, ' ', p.`1`))"
    )
    return f"array_distinct(aggregate(array({words}), cast(array() AS array<string>), (z, w) -> concat(w, CASE WHEN size(w) > 1 THEN {pairs} ELSE cast(array() AS array<string>) END)))"


def _paragraphs(docs: DataFrame, cues: str) -> DataFrame:
    """(doc_id, row, paragraph, start, stop, size, body): the lines with a cue and the joined runs of lines that hold one."""
    src = id_and_text(docs).where(F.col("text").rlike(cues)).withColumn("row", F.monotonically_increasing_id())
    src = src.withColumn("lines", F.split("text", "\n", -1)).drop("text")
    starts = running("transform(lines, x -> length(x) + 1)", "+")
    blanks = running("transform(lines, (x, i) -> CASE WHEN x RLIKE r'\\S' THEN -1 ELSE i END)", "greatest")
    src = src.withColumn("stops", F.expr(starts)).withColumn("blank", F.expr(blanks))
    # a run holds a cue only where one of its lines does, or the beginning of one
    hot = f"filter(transform(lines, (x, i) -> CASE WHEN x RLIKE r'{cues}' OR x RLIKE r'{BROKEN_CUES}' THEN i END), i -> i IS NOT NULL)"
    src = src.withColumn("hot", F.expr(hot))
    ends = f"array_distinct(flatten(transform(hot, i -> sequence(i, least(i + {WINDOW_LINES - 1}, size(lines) - 1)))))"
    src = src.withColumn("z", F.arrays_zip("lines", "stops", "blank")).withColumn("ends", F.expr(ends)).select("doc_id", "row", "lines", "z", "ends")
    # the runs of 1 to WINDOW_LINES lines that end with line i and begin after the last blank one
    begin = "CASE WHEN i - k < 0 THEN 0 ELSE z[i - k].stops END"
    run = f"""named_struct('paragraph', i - k + 1, 'start', {begin}, 'stop', z[i].stops - 1, 'size', k, 'body', array_join(slice(lines, i - k + 2, k), ' '))"""
    most = f"least({WINDOW_LINES}, i - z[i].blank)"
    runs = f"CASE WHEN i > z[i].blank THEN filter(transform(sequence(1, {most}), k -> {run}), w -> w.body RLIKE r'{cues}') END"
    return src.select("doc_id", "row", F.expr(f"inline(flatten(filter(transform(ends, i -> {runs}), w -> w IS NOT NULL)))"))


def _key() -> Column:
    """What a paragraph is known by where its text isn't needed."""
    return F.unhex(F.sha2("body", 256))


def _shuffled(lines: DataFrame, scored: DataFrame) -> DataFrame:
    """lines with their findings; a key of more than HOT_ROWS lines is dealt by salt, the others once."""
    hot = cut(lines.groupBy("key").count().where(F.col("count") > HOT_ROWS).select("key", F.lit(SALTS).alias("salts")))
    salts = F.coalesce("salts", F.lit(1))
    dealt = lines.join(F.broadcast(hot), "key", "left").withColumn("salt", F.pmod(F.xxhash64("row", "start"), salts).cast("int")).drop("salts")
    salted = scored.join(F.broadcast(hot), "key", "left").withColumn("salt", F.explode(F.sequence(F.lit(0), salts - 1))).drop("salts")
    return dealt.join(salted, ["key", "salt"]).drop("key", "salt")


def licences(
    docs: DataFrame,
    samples: Iterable[tuple[str, str]] | None = None,
    confirmed_only: bool = True,
    templates: dict[str, tuple[str, ...]] | None = None,
    cues: str = CUES,
) -> DataFrame:
    """(doc_id, paragraph, start, stop, family, probability, share, confirmed): the findings in all texts.

    paragraph is the first line's number from 0; start and stop are code points of the text, the end
    exclusive. A finding is a line, or a joined run of lines, whose best class is a family, at
    LEAST_PROBABILITY or more; confirmed says whether a template of that family lies in it to LEAST_SHARE
    or more. Runs of several lines are returned only confirmed. templates replaces the built-in ones; a
    family of samples without a template is confirmed by its samples. cues is what a paragraph must hold
    to be read; a template or sample without one is an error, since its family could not be found.
    """
    spark = docs.sparkSession
    rows = built_in_samples() if samples is None else list(samples)
    model = LicenceModel(rows)
    known = dict(TEMPLATES if templates is None else templates)
    for family in set(model.classes) - {UNKNOWN} - known.keys():
        known[family] = tuple(t for t, name in rows if name == family)
    texts = [(c, t) for c in model.classes[:-1] for t in known[c]]
    for family, t in texts:
        if not re.search(cues, t):
            raise ValueError(f"a template of {family} holds no cue: {t[:60]!r}; pass cues that it holds")
    sets = [[g for g in grams(t) if " " in g] or grams(t) for _, t in texts]
    lines = cut(_paragraphs(docs, cues))  # the few lines that hold a cue, so that the texts are searched once
    width = len(model.classes)
    weights = [F.sum(f"w{j}").alias(f"w{j}") for j in range(width)]
    counts = [F.sum(f"t{k}").alias(f"t{k}") for k in range(len(texts))]
    sums = (
        lines.select("body")
        .distinct()
        .select("body", F.explode(F.expr(_grams_sql("body"))).alias("gram"))
        .join(F.broadcast(model.gram_table(spark, sets)), "gram")
        .groupBy("body")
        .agg(*weights, *counts)
    )
    z = F.array(*(F.col(f"w{j}") + float(b / model.temperature) for j, b in enumerate(model.bias)))
    of_class = {c: [F.col(f"t{k}") / float(len(sets[k])) for k, (name, _) in enumerate(texts) if name == c] for c in model.classes[:-1]}
    shares = F.array(*(F.greatest(F.lit(0.0), *of_class[c]) for c in model.classes[:-1]), F.lit(0.0))
    scored = (
        sums.withColumn("z", z)
        .withColumn("best", F.array_max("z"))
        .withColumn("at", F.array_position("z", F.col("best")).cast("int"))
        .withColumn("probability", F.expr("1D / aggregate(z, 0D, (a, k) -> a + exp(k - best))"))
        .withColumn("share", F.element_at(shares, F.col("at")))
        .where((F.col("at") < width) & (F.col("probability") >= LEAST_PROBABILITY))
        .select(_key().alias("key"), F.element_at(F.array(*map(F.lit, model.classes)), F.col("at")).alias("family"), F.round("probability", 9).alias("probability"), "share")
    )
    if confirmed_only:
        scored = scored.where(F.col("share") >= LEAST_SHARE)
    scored = cut(scored)
    keyed = lines.withColumn("key", _key()).drop("body")  # texts stay where they are
    if scored.count() * FINDING_BYTES <= BROADCAST_BYTES:
        found = keyed.join(F.broadcast(scored), "key").drop("key")
    else:
        found = _shuffled(keyed, scored)
    found = found.withColumn("confirmed", F.col("share") >= LEAST_SHARE).where("size = 1 OR confirmed")
    # a run in which a shorter one confirms as well never stays: what would take that one's place overlaps the run too
    ahead = Window.partitionBy("row").orderBy("paragraph").rangeBetween(0, WINDOW_LINES - 1)
    inner = F.collect_list(F.when(F.col("confirmed"), F.struct("paragraph", "size", "share"))).over(ahead)
    found = found.withColumn("inner", inner).where(
        """NOT confirmed OR NOT exists(inner, v -> v.size < size AND v.paragraph >= paragraph
             AND v.paragraph + v.size <= paragraph + size AND v.share >= share)"""
    )
    # findings that touch no other are settled apart
    place = Window.partitionBy("row").orderBy("start", "stop")
    found = found.withColumn("far", F.max("stop").over(place.rowsBetween(Window.unboundedPreceding, -1)))
    found = found.withColumn("island", F.sum(F.when(F.col("far") > F.col("start"), 0).otherwise(1)).over(place))
    columns = "paragraph start stop family probability share confirmed".split()
    ranked = F.struct((~F.col("confirmed")).alias("open"), (-F.col("share")).alias("less"), "size", *columns)
    best = found.groupBy("row", "island", "doc_id").agg(F.array_sort(F.collect_list(ranked)).alias("all"))
    best = best.withColumn(
        "kept",
        F.expr(
            """aggregate(all, slice(all, 1, 0), (z, w) -> CASE
                 WHEN w.confirmed AND exists(z, k -> k.start < w.stop AND w.start < k.stop) THEN z
                 ELSE concat(z, array(w)) END)"""
        ),
    )
    return best.select("doc_id", F.inline("kept")).select("doc_id", *columns)
