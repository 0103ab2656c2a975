"""License scan: a trained paragraph classifier, confirmed by comparison with templates.

The classifier is a multinomial logistic regression with a lasso penalty over word unigrams and
bigrams, trained on notices of each family and on paragraphs of none. Its few weights become
column expressions: scanning runs on built-in functions only. Paragraphs are scored where they
hold one of the stems that every notice has. The unknown class takes all others, and those whose
calibrated probability stays under a threshold. A family is confirmed where, of the templates of
all families and of licenses outside them, the nearest one is its own.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Callable
from dataclasses import dataclass
from functools import cache, reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UNKNOWN = "unknown"
#: Usual notices of each family, which are both templates and training rows.
TEMPLATES = {
    "MIT": [
        "Released under the MIT License.",
        "This project is licensed under the MIT license.",
        "Distributed under the terms of the MIT License, see the file LICENSE for details.",
        "SPDX-License-Identifier: MIT",
        "MIT License",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files",
    ],
    "Apache-2.0": [
        "Licensed under the Apache License, Version 2.0.",
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License.",
        "SPDX-License-Identifier: Apache-2.0",
        "Apache License 2.0",
        "This software is released under the Apache 2.0 license.",
        "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
    ],
    "GPL-3.0": [
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or any later version.",
        "SPDX-License-Identifier: GPL-3.0-or-later",
        "GNU General Public License v3.0",
        "Licensed under GPL-3.0.",
        "Released under the GPL v3, the GNU General Public License version 3.",
        "Licensed under the GPLv3.",
    ],
    "GPL-2.0": [
        "This work is licensed under the GNU General Public License, version 2.",
        "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or any later version.",
        "SPDX-License-Identifier: GPL-2.0-only",
        "GNU General Public License v2.0",
        "Licensed under GPL-2.0.",
        "Released under the GPL v2, the GNU General Public License version 2.",
        "Licensed under the GPLv2.",
    ],
    "LGPL": [
        "This work is licensed under the GNU Lesser General Public License, version 3.",
        "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or any later version.",
        "SPDX-License-Identifier: LGPL-3.0-or-later",
        "GNU Lesser General Public License",
        "Released under the LGPL, the GNU Lesser General Public License version 2.1.",
        "Licensed under the LGPL 3.",
    ],
    "AGPL-3.0": [
        "This work is licensed under the GNU Affero General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or any later version.",
        "SPDX-License-Identifier: AGPL-3.0-or-later",
        "GNU Affero General Public License",
        "Released under the AGPL v3, the GNU Affero General Public License version 3.",
        "Licensed under AGPL-3.0.",
    ],
    "CC-BY-NC-4.0": [
        "Licensed under CC BY-NC 4.0.",
        "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
        "Content is available under CC BY-NC 4.0 unless otherwise noted.",
        "SPDX-License-Identifier: CC-BY-NC-4.0",
        "Creative Commons Attribution-NonCommercial 4.0",
    ],
    "CC-BY-4.0": [
        "Licensed under CC BY 4.0.",
        "This work is licensed under a Creative Commons Attribution 4.0 International License.",
        "Content is available under CC BY 4.0 unless otherwise noted.",
        "SPDX-License-Identifier: CC-BY-4.0",
        "Creative Commons Attribution 4.0",
    ],
    "CC-BY-SA-4.0": [
        "Licensed under CC BY-SA 4.0.",
        "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
        "Content is available under CC BY-SA 4.0 unless otherwise noted.",
        "SPDX-License-Identifier: CC-BY-SA-4.0",
        "Creative Commons Attribution-ShareAlike 4.0",
    ],
    "BSD-3-Clause": [
        "Released under the BSD 3-Clause License.",
        "Licensed under the three clause BSD license.",
        "SPDX-License-Identifier: BSD-3-Clause",
        "The 3-Clause BSD License",
        "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    ],
    "BSD-2-Clause": [
        "Released under the BSD 2-Clause License.",
        "Licensed under the two clause BSD license, the simplified BSD license.",
        "SPDX-License-Identifier: BSD-2-Clause",
        "The 2-Clause BSD License",
        "This software is distributed under the BSD-2-Clause license.",
    ],
    "BSD": [
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
        "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
        "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
        "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file.",
    ],
    "MPL-2.0": [
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
        "Licensed under the Mozilla Public License, version 2.0.",
        "SPDX-License-Identifier: MPL-2.0",
        "Released under the Mozilla Public License 2.0.",
        "Mozilla Public License 2.0",
    ],
    "ISC": [
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
        "Released under the ISC License.",
        "This project is licensed under the ISC license.",
        "SPDX-License-Identifier: ISC",
        "ISC License",
    ],
}
#: Notices of licenses that are of none of the families, also compared as templates.
STRANGERS = [
    "Licensed under CC BY-NC-SA 4.0.",
    "Licensed under CC BY-NC-ND 4.0.",
    "Licensed under CC BY-ND 4.0.",
    "SPDX-License-Identifier: CC-BY-NC-SA-4.0",
    "SPDX-License-Identifier: CC-BY-ND-4.0",
    "This work is licensed under a Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License.",
    "This work is licensed under a Creative Commons Attribution-NonCommercial-NoDerivatives 4.0 International License.",
    "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License.",
    "This work is licensed under a Creative Commons Attribution 3.0 Unported License.",
    "Creative Commons Zero, CC0 1.0 Universal.",
    "SPDX-License-Identifier: CC0-1.0",
    "Licensed under the Eclipse Public License, version 2.0.",
    "Licensed under the European Union Public License, version 1.2.",
    "Released under the Artistic License 2.0.",
    "Released under the Apache Software License, version 1.1.",
    "Licensed under the Apache License, Version 1.0.",
    "Licensed under the Mozilla Public License, version 1.1.",
    "Licensed under the Boost Software License, version 1.0.",
    "Released under the zlib license.",
    "SPDX-License-Identifier: Zlib",
    "SPDX-License-Identifier: EPL-2.0",
    "Eclipse Public License 2.0",
    "GNU Free Documentation License",
    "SPDX-License-Identifier: Unlicense",
    "This is free and unencumbered software released into the public domain.",
    "This work is licensed under the GNU General Public License, version 1.",
    "This work is licensed under the GNU Free Documentation License, version 1.3.",
    "Released under a proprietary license; see the license agreement for details.",
    "This software is licensed under a commercial license from the vendor.",
    "Licensed under the Academic Free License, version 3.0.",
    "Released under the Open Software License, version 3.0.",
    "Licensed under the SIL Open Font License, version 1.1.",
    "Released under the BSD 4-Clause License.",
]
#: Paragraphs that speak of licenses without granting one, and plain prose.
OTHERS = [
    "The license plate of the car was found near the river.",
    "You need a driving license, version of 2019 or later, to rent this car.",
    "Permission to enter was granted by the general manager.",
    "The public may use the library free of charge from Monday on.",
    "All rights reserved by the author and the publisher.",
    "The terms of use of this site are listed below.",
    "Any person found in the building after ten will be asked to leave.",
    "A copy of this file was sent to the office and published later.",
    "The software was released last week under a new name.",
    "This work is the result of many years under difficult conditions.",
    "The commons were open to the creative people of the town.",
    "Apache helicopters flew over the town; the general was pleased.",
    "Version 3 of the report is available, see the details below.",
    "He studied at MIT and later at the public university.",
    "The license of the restaurant was not renewed this year.",
    "The foundation distributes free meals under strict conditions.",
    "Use of this form is permitted provided that the following page is signed.",
    "The new license fee is due in March, the older license has expired.",
    "The GNU project was founded to write free software.",
    "The Apache web server is a popular program of the foundation.",
    "Contact us for a license; the license terms depend on the number of users.",
    "Der Wagen mit dem Anhänger fährt mit vollen Tanks auf der Straße.",
    "Mit freundlichen Grüßen, und mit Dank für die gute Arbeit.",
    "Er kommt mit der Bahn, sie geht mit dem Hund, die Stadt ist leer.",
]
#: Words too plain to speak for a family alone.
_PLAIN = frozenset("a all and any are at be by for from has in is it its may mit more not note of on or page see text that the this to use was will with without work you".split())
#: Every notice has one of these; a paragraph without any is of the unknown class.
STEMS = ("licen", "gpl", "gnu", "creative commons", "cc by", "cc-by", "redistribut", "copyright", "hereby granted")
#: Fixed value: notices that keep all rights, so that they grant no license.
_RESERVED = r"(?i)\ball\s+rights\s+(?:are\s+)?reserved\b"
#: Fixed value: words that deny a grant, right before the verb that would make it.
_DENIED = r" (?:not|never|no longer|neither|isn t|aren t) (?:currently |yet |be |been |being )?(?:licensed |(?:released|distributed|available|published|covered|governed|provided) (?:under|by) )"
_NOT_WORD = r"[^\p{L}\p{N}.]+"
#: A paragraph ends where a line without a word lies between, or a line ends a sentence; other line breaks only wrap it.
PARAGRAPH_END = r"\n[^\p{L}\p{N}]*\n|(?<=[.!?][^\p{L}\p{N}\s]{0,8})[ \t\r]*\n"


def words(text: str) -> list[str]:
    """Lower-cased runs of letters, digits and dots, without dots at their ends."""
    return [w for w in (x.strip(".") for x in re.split(r"[^\w.]+|_", text.lower())) if w]


def terms(text: str) -> set[str]:
    """Unigrams and bigrams, but for those of plain words only."""
    w = words(text)
    pairs = (f"{a} {b}" for a, b in zip(w, w[1:], strict=False) if a not in _PLAIN or b not in _PLAIN)
    return {*(x for x in w if x not in _PLAIN and len(x) > 2), *pairs}


@dataclass
class LicenseModel:
    """Weights by term for each family against the unknown class, temperature and threshold."""

    families: list[str]
    bias: np.ndarray
    weights: dict[str, np.ndarray]
    temperature: float
    threshold: float

    def probabilities(self, text: str) -> np.ndarray:
        """Calibrated probabilities of the families; what is missing to 1 is the unknown class."""
        z = self.bias + sum((self.weights[t] for t in terms(text) if t in self.weights), np.zeros(len(self.families)))
        e = np.exp(z / self.temperature)
        return e / (1 + e.sum())


def _variants(text: str, rng: np.random.Generator, n: int) -> list[str]:
    """A notice with some words left out or others put around it."""
    w, filler = text.split(), "and of the for this with page note see text all more".split()
    out = [text]
    for _ in range(n):
        kept = [x for x in w if rng.random() > 0.12]
        out.append(" ".join([*rng.choice(filler, rng.integers(0, 4)), *kept, *rng.choice(filler, rng.integers(0, 4))]))
    return out


def _fit(x: np.ndarray, y: np.ndarray, penalty: float, steps: int) -> tuple[np.ndarray, np.ndarray]:
    """Weights and biases of the families against the unknown class, by accelerated proximal steps."""
    w = np.zeros((x.shape[1], y.shape[1] - 1))
    at, momentum, bias = w.copy(), 1.0, np.full(y.shape[1] - 1, -2.0)
    rate = 2 / np.linalg.eigvalsh(x @ x.T / len(x)).max()
    for _ in range(steps):
        z = np.column_stack([x @ at + bias, np.zeros(len(x))])
        p = np.exp(z - z.max(axis=1, keepdims=True))
        error = (p / p.sum(axis=1, keepdims=True) - y)[:, :-1]
        step = at - rate * (x.T @ error) / len(x)
        new = np.sign(step) * np.maximum(np.abs(step) - rate * penalty, 0)
        # The bias stays below zero: a paragraph without a term that counts is of no family.
        bias = np.minimum(bias - rate * error.mean(axis=0), -2.0)
        faster = (1 + np.sqrt(1 + 4 * momentum**2)) / 2
        at = new + (momentum - 1) / faster * (new - w)
        w, momentum = new, faster
    return w, bias


def confirms(text: str, family: str, without: str | None = None, min_overlap: float = 0.6) -> bool:
    """Whether the nearest template (but for one that is left out) is the family's, alike enough, and nothing is denied."""
    have = set(words(text))
    if re.search(_DENIED, f" {' '.join(words(text))} "):
        return False
    left = set(words(without)) if without else None
    nearest = max((round(sum(x for w, x in own.items() if w in have), 6), len(own), f) for f, own in template_list() if set(own) != left)
    return nearest[0] >= min_overlap and nearest[2] == family


def denied(text: str) -> str:
    """The notice with its grant denied."""
    return re.sub(r"(?i)\b(licensed|released|distributed|available|subject|granted)\b", r"not \1", text, count=1)


def train(seed: int = 7, penalty: float = 4e-4, steps: int = 250, folds: int = 4) -> LicenseModel:
    """Fit on all notices and their variants; temperature and threshold come from held-out notices.

    For calibration, whole notices, with all their variants, are left out by folds and judged by
    a model that never saw them.
    """
    rng = np.random.default_rng(seed)
    families = sorted(TEMPLATES)
    notices = [(t, k, i % folds) for k, f in enumerate(families) for i, t in enumerate(TEMPLATES[f])]
    unknown = [*STRANGERS, *OTHERS, *(d for f in families for t in TEMPLATES[f][:2] if (d := denied(t)) != t)]
    notices += [(t, len(families), i % folds) for i, t in enumerate(unknown)]
    rows, own = [], []
    for t, k, fold in notices:
        made = _variants(t, rng, 4)
        rows += [(v, k, fold) for v in made]
        own += [t] * len(made)
    sets = [terms(t) for t, _, _ in rows]
    vocabulary = sorted({t for s, (_, k, _) in zip(sets, rows, strict=True) for t in s if k < len(families)} | {t for d in unknown[-40:] for t in terms(d) if t.startswith("not ")})
    place = {t: i for i, t in enumerate(vocabulary)}
    x = np.zeros((len(rows), len(vocabulary)))
    for i, s in enumerate(sets):
        x[i, [place[t] for t in s if t in place]] = 1
    y = np.eye(len(families) + 1)[[k for _, k, _ in rows]]
    fold = np.array([f for _, _, f in rows])
    z = np.zeros_like(y)
    for f in range(folds):
        w, bias = _fit(x[fold != f], y[fold != f], penalty, steps)
        z[fold == f, :-1] = x[fold == f] @ w + bias

    def shares(t: float) -> np.ndarray:
        p = np.exp(z / t - (z / t).max(axis=1, keepdims=True))
        return p / p.sum(axis=1, keepdims=True)

    temperature = float(min(np.geomspace(0.2, 4, 40), key=lambda t: -np.log(np.maximum((shares(t) * y).sum(axis=1), 1e-12)).mean()))
    # Of held-out paragraphs of no family that templates of other notices would confirm, nineteen in twenty stay under.
    p = shares(temperature)
    fooled = [
        p[i, :-1].max()
        for i, (text, k, _) in enumerate(rows)
        if k == len(families) and confirms(text, families[int(p[i, :-1].argmax())], own[i])
    ]
    threshold = float(np.clip(np.quantile(fooled, 0.95) if fooled else 0.0, 0.3, 0.5))
    w, bias = _fit(x, y, penalty, steps)
    kept = {t: w[i] for t, i in place.items() if np.any(w[i] != 0)}
    return LicenseModel(families, bias, kept, temperature, threshold)


def _bind(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value), with the value worked out once however often the body names it."""
    return F.transform(F.array(value), body)[0]


def _any_stem(text: Column) -> Column:
    return _bind(F.lower(text), lambda low: reduce(lambda a, b: a | b, [low.contains(w) for w in STEMS]))


def _spaced(text: Column) -> Column:
    """The words of a paragraph, as words() has them, with a space on either side of each."""
    plain = F.regexp_replace(F.lower(text), _NOT_WORD, " ")
    # Runs of dots are met at their first dot only, so that long ones cost no more than their length.
    return F.concat(F.lit(" "), F.regexp_replace(plain, r"(^|\s)\.++|(?<!\.)\.++(?=\s|$)", "$1"), F.lit(" "))


def _sum(parts: list[str]) -> str:
    """A balanced sum in SQL, which keeps the expression shallow."""
    while len(parts) > 1:
        parts = [f"({a} + {b})" for a, b in zip(parts[::2], parts[1::2], strict=False)] + parts[len(parts) & ~1 :]
    return parts[0]


def _weighed(shares: dict[str, float]) -> list[str]:
    """The weight of every term that the spaced text p has, in SQL."""
    return [f"IF(contains(p, ' {term} '), {weight!r}D, 0D)" for term, weight in shares.items()]


def _bound(body: str) -> Column:
    """SQL over p, the column spaced, which is worked out once however often the body names it.

    One parsed text stands for thousands of column calls.
    """
    return F.expr(f"transform(array(spaced), p -> {body})[0]")


def _judgement(model: LicenseModel) -> Column:
    """family and probability of a paragraph's best family, over the column spaced."""
    logits = [
        _sum([f"{float(b)!r}D", *_weighed({t: float(w[k]) for t, w in model.weights.items() if w[k]})]) for k, b in enumerate(model.bias)
    ]

    def best(z: Column) -> Column:
        whole = F.aggregate(z, F.lit(1.0), lambda acc, x: acc + F.exp(x / model.temperature))
        named = F.array(*[F.struct(z[k].alias("z"), F.lit(f).alias("family")) for k, f in enumerate(model.families)])
        top = F.array_max(named)
        return F.struct(top["family"].alias("family"), (F.exp(top["z"] / model.temperature) / whole).alias("probability"))

    return _bind(_bound(f"array({', '.join(logits)})"), best)


@cache
def template_list() -> list[tuple[str, dict[str, float]]]:
    """(family or unknown, share by word) of every template that paragraphs are compared with.

    A word's share in its template is the larger the fewer templates have it, so that names
    count for more than what all notices say.
    """
    named = [(f, set(words(t))) for f, templates in TEMPLATES.items() for t in templates] + [(UNKNOWN, set(words(t))) for t in STRANGERS]
    spread = Counter(w for _, own in named for w in own)
    weighed = [(f, {w: float(np.log(1 + len(named) / spread[w])) for w in sorted(own)}) for f, own in named]
    return [(f, {w: x / sum(own.values()) for w, x in own.items()}) for f, own in weighed]


def _nearest_template() -> Column:
    """overlap, size and family of the template that the paragraph has the largest share of; ties to more words.

    Rivals differ in few words (a version, "lesser", "sharealike"), so the words that set a
    template apart from its nearest rival decide.
    """

    shares = [
        f"named_struct('overlap', round({_sum(_weighed(own))}, 6), 'size', {len(own)}, 'family', '{f}')" for f, own in template_list()
    ]
    return _bound(f"array_max(array({', '.join(shares)}))")


def scan_licenses(
    docs: DataFrame, model: LicenseModel, id_column: str = "doc_id", text_column: str = "text", min_overlap: float = 0.6
) -> DataFrame:
    """License findings of every row, with built-in functions only.

    Rows: the id, family (of the most probable confirmed paragraph, else null), probability,
    overlap (share of a template's words the paragraph has), families (all confirmed ones,
    sorted), n_paragraphs (confirmed ones), n_unconfirmed (likely, but nearer to a template of
    another family or of none, unlike each template, or a denied grant) and n_reserved (notices
    that reserve all rights, which are of no family). A paragraph goes over line breaks that only
    wrap it (see PARAGRAPH_END). A null or empty text has no findings. Every row stays, repeated
    ones too; ties go to more overlap, then the family last by name. Other columns are ignored.
    Texts of any length are scanned whole, in time linear in their length; a row's own text and
    its paragraphs are held at once.
    """
    source = docs.select(F.col(id_column).alias("id"), F.coalesce(F.col(text_column), F.lit("")).alias("text"))
    source = source.withColumn("code", F.xxhash64("text"))
    parts = source.where(_any_stem(F.col("text"))).select("id", "code", F.posexplode(F.split("text", PARAGRAPH_END)).alias("place", "part"))
    spaced = parts.where(_any_stem(F.col("part"))).select("id", "code", "place", _spaced(F.col("part")).alias("spaced"))
    judged = spaced.select("id", "code", "place", "spaced", _judgement(model).alias("j"))
    likely = judged.where(F.col("j.probability") >= model.threshold)
    found = likely.select("id", "code", "place", "j", _nearest_template().alias("near"), F.col("spaced").rlike(_DENIED).alias("denied"))
    # Repeated rows have the same findings, which count once.
    found = found.groupBy("id", "code", "place").agg(*[F.first(c).alias(c) for c in ("j", "near", "denied")])
    good = (F.col("near.overlap") >= min_overlap) & (F.col("near.family") == F.col("j.family")) & ~F.col("denied")
    per_text = found.groupBy("id", "code").agg(
        F.max(F.when(good, F.struct("j.probability", "near.overlap", "j.family"))).alias("best"),
        F.array_join(F.array_sort(F.collect_set(F.when(good, F.col("j.family")))), ",").alias("families"),
        F.count(F.when(good, 1)).alias("n_paragraphs"),
        F.count(F.when(~good, 1)).alias("n_unconfirmed"),
    )
    reserved = F.regexp_count("text", F.lit(_RESERVED)).alias("n_reserved")
    rows, own = source.select("id", "code", reserved).alias("r"), per_text.alias("f")
    joined = rows.join(own, F.col("r.id").eqNullSafe(F.col("f.id")) & (F.col("r.code") == F.col("f.code")), "left")
    return joined.select(
        F.col("r.id").alias(id_column),
        F.col("f.best.family").alias("family"),
        F.col("f.best.probability").alias("probability"),
        F.col("f.best.overlap").alias("overlap"),
        F.coalesce("f.families", F.lit("")).alias("families"),
        F.coalesce("f.n_paragraphs", F.lit(0)).alias("n_paragraphs"),
        F.coalesce("f.n_unconfirmed", F.lit(0)).alias("n_unconfirmed"),
        F.col("r.n_reserved").alias("n_reserved"),
    )
