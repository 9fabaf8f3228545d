"""Licence notices: normalised text against templates by Dice coefficient over word bigrams, pruned by size.

Normalising lower-cases A-Z and keeps runs of letters and digits as words; a piece of text is the set of its distinct
word bigrams. Compared are

* *units*: the lines of a text and the text as a whole. Dice = 2 |A and B| / (|A| + |B|) can reach t only if
  t / (2 - t) <= |A| / |B| <= (2 - t) / t, so a unit is compared only with templates in these bounds;
* *windows*: stretches of as many words as a template has, wherever lines end, for notices that are wrapped or stand
  among other words. A window is placed by each probe bigram that occurs in the text, so that the bigram has the same
  place in the window as in the template; its size is the template's by construction.

A match must share one of a few *probe* bigrams: of m template bigrams at least ceil(t m / (2 - t)) must be shared, so
all but that many less one suffice as probes. Probes are chosen to hold one of a few long keywords, so that texts and
then units without any keyword go first, before they are cut into words.

All work is row-local built-in functions: one pass over the text, no shuffle but for the final count per document
and licence. Templates are literals, bounded by ``TEMPLATES``: one-line notices, headers and whole licence texts.

Defined cases: null, blank and one-word texts have no bigrams and match nothing; a text matches every licence that it
reaches the threshold for; repeated rows add to the counts; a null doc_id is kept as its own group; extra columns are
ignored.
"""

from __future__ import annotations

import re
from fractions import Fraction
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

THRESHOLD = Fraction(4, 5)
#: Public short notices, by SPDX id.
TEMPLATES = [
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0-header", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License."),
    ("BSD-3-Clause", "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0-header", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("MIT", "Released under the MIT License."),
    ("MIT-grant", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    (
        "MIT-text",
        """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the
Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice
shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING
BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE
FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER
DEALINGS IN THE SOFTWARE.""",
    ),
    (
        "ISC-text",
        """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright
notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL
IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES
WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE
OR PERFORMANCE OF THIS SOFTWARE.""",
    ),
]
#: Words too frequent in prose to tell a notice.
COMMON = {"a", "all", "and", "any", "at", "be", "by", "can", "for", "from", "in", "is", "it", "of", "or", "that", "the", "this", "to", "under", "with", "work", "you", "your"}
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_SPLIT = r"[^\p{L}\p{N}]+"


def template_words(text: str) -> list[str]:
    return [x for x in re.split(r"[\W_]+", text.translate(str.maketrans(_UPPER, _LOWER))) if x]


def bigrams(text: str) -> list[str]:
    w = template_words(text)
    return sorted({f"{a} {b}" for a, b in zip(w, w[1:], strict=False)})


def anchors(templates, probe: list[str]) -> dict[str, list[tuple[int, int]]]:
    """For each probe bigram the templates (by number) that hold it, and where."""
    out: dict[str, list[tuple[int, int]]] = {}
    for k, (_, text) in enumerate(templates):
        w = template_words(text)
        for j, pair in enumerate(zip(w, w[1:], strict=False)):
            if " ".join(pair) in probe:
                out.setdefault(" ".join(pair), []).append((k, j))
    return out


def probes(templates=TEMPLATES, t: Fraction = THRESHOLD) -> tuple[list[str], list[str]]:
    """(probe bigrams, keywords): enough probes of each template, each holding one of a few long words.

    Keywords are taken one after another, widest reach first and common words last, until every template has enough
    bigrams with one.
    """
    sets = {name: bigrams(text) for name, text in templates}
    open_ = {name: len(s) - int(-(-t * len(s) // (2 - t))) + 1 for name, s in sets.items()}
    words = sorted({w for s in sets.values() for b in s for w in b.split()})
    keys: list[str] = []

    def held(name: str) -> list[str]:
        return [b for b in sets[name] if set(b.split()) & set(keys)]

    while lacking := [name for name in sets if len(held(name)) < open_[name]]:
        gain = {w: sum(w in b.split() and b not in held(name) for name in lacking for b in sets[name]) for w in words}
        keys.append(max(words, key=lambda w: (gain[w] > 0, w not in COMMON and not w.isdigit(), gain[w], len(w), w)))
    return sorted({b for name in sets for b in held(name)}), keys


def _words(unit: Column) -> Column:
    return F.filter(F.split(F.translate(unit, _UPPER, _LOWER), _SPLIT), lambda w: w != "")


def _near(b: Column, x: Column, t: Fraction) -> Column:
    """(license_id, dice) of a bigram set and a template, null if they are too far apart."""
    n, m = F.size(b), F.size(x["grams"])
    fits = (n * (2 * t.denominator - t.numerator) >= m * t.numerator) & (n * t.numerator <= m * (2 * t.denominator - t.numerator))
    both = F.size(F.array_intersect(b, x["grams"]))
    return F.when(fits, F.when(both * 2 * t.denominator >= (n + m) * t.numerator, F.struct(x["license_id"].alias("license_id"), (both * 2 / (n + m)).alias("dice"))))


def scan(docs: DataFrame, templates=TEMPLATES, t: Fraction = THRESHOLD) -> DataFrame:
    """doc_id, license_id, n_units, n_windows, best_dice: one row per document and licence found in it."""
    sizes = [len(bigrams(text)) for _, text in templates]
    most = int(max(sizes) * (2 - t) / t)
    least = -(-min(sizes) * t // (2 - t))
    text = F.coalesce("text", F.lit(""))
    probe_bigrams, keywords = probes(templates, t)

    def hopeful(column: str) -> Column:  # lower() maps at least A-Z, so no unit with a probe is lost
        return reduce(lambda x, y: x | y, [F.contains(F.lower(column), F.lit(k)) for k in keywords])

    lines = F.split(text, "\n")
    unit = F.transform(lines, lambda x: F.struct(x.alias("unit"), (F.size(lines) == 1).alias("whole")))
    unit = F.when(F.size(lines) > 1, F.concat(unit, F.array(F.struct(text.alias("unit"), F.lit(True).alias("whole"))))).otherwise(unit)
    units = docs.where(hopeful("text")).select("doc_id", F.explode(unit).alias("x")).select("doc_id", "x.unit", "x.whole")
    # A unit of n distinct bigrams has at least 2 n + 1 characters, and its bigrams number at most (characters - 1) / 2.
    units = units.where((F.length("unit") >= int(least) * 2 + 1) & hopeful("unit"))
    w, p = F.col("w"), F.col("p")
    words = units.withColumn("w", _words(F.col("unit"))).where(F.size(w) > int(least)).drop("unit")
    pairs = F.zip_with(F.slice(w, F.lit(1), F.greatest(F.size(w) - 1, F.lit(0))), F.slice(w, F.lit(2), F.size(w)), lambda a, b: F.concat_ws(" ", a, b))
    probe = F.array(*[F.lit(x) for x in probe_bigrams])
    held = words.withColumn("p", pairs).drop("w").where(F.arrays_overlap("p", probe))
    table = F.array(*[F.struct(F.lit(name).alias("license_id"), F.array(*[F.lit(b) for b in bigrams(x)]).alias("grams"), F.lit(len(template_words(x)) - 1).alias("long")) for name, x in templates])
    # Units: a set beyond the largest template's bounds is compared with none.
    own = F.when(F.size(F.array_distinct(p)) <= most, F.transform(table, lambda x: _near(F.array_distinct(p), x, t))).otherwise(F.array().cast("array<struct<license_id:string,dice:double>>"))
    # Windows: where a probe stands in the text and in a template gives the window's first bigram.
    places = anchors(templates, probe_bigrams)
    where = F.create_map(*[y for b, ps in places.items() for y in (F.lit(b), F.array(*[F.struct(F.lit(k).alias("k"), F.lit(j).alias("j")) for k, j in ps]))])
    hits = F.filter(F.transform(p, lambda b, i: F.struct(b.alias("b"), i.alias("i"))), lambda h: h["b"].isin(list(places)))
    starts = F.array_distinct(F.flatten(F.transform(hits, lambda h: F.transform(F.element_at(where, h["b"]), lambda y: F.struct(y["k"].alias("k"), (h["i"] - y["j"]).alias("s"))))))

    def window(y: Column) -> Column:
        x = F.get(table, y["k"])
        first = F.greatest(y["s"], F.lit(0))
        return _near(F.array_distinct(F.slice(p, first + 1, y["s"] + x["long"] - first)), x, t)

    windows = F.when(F.col("whole"), F.transform(starts, window)).otherwise(F.array().cast("array<struct<license_id:string,dice:double>>"))
    tagged = lambda rows, kind: F.transform(F.filter(rows, lambda m: m.isNotNull()), lambda m: F.struct(m["license_id"].alias("license_id"), m["dice"].alias("dice"), F.lit(kind).alias("kind")))
    near = held.select("doc_id", F.explode(F.concat(tagged(own, 0), tagged(windows, 1))).alias("m"))
    return near.groupBy("doc_id", F.col("m.license_id").alias("license_id")).agg(F.count_if(F.col("m.kind") == 0).alias("n_units"), F.count_if(F.col("m.kind") == 1).alias("n_windows"), F.round(F.max("m.dice"), 6).alias("best_dice"))


def oracle(templates=TEMPLATES, t: Fraction = THRESHOLD) -> str:
    rows = ", ".join(f"('{name}', '{b}')" for name, text in templates for b in bigrams(text))
    names = [name for name, _ in templates]
    places = ", ".join(f"('{names[k]}', '{b}', {j})" for b, ps in anchors(templates, probes(templates, t)[0]).items() for k, j in ps)
    lengths = ", ".join(f"('{name}', {len(template_words(text)) - 1})" for name, text in templates)
    return rf"""
WITH grams(license_id, b) AS (VALUES {rows}), sizes AS (SELECT license_id, count(*) AS m FROM grams GROUP BY 1), places(license_id, b, j) AS (VALUES {places}), lengths(license_id, long) AS (VALUES {lengths}),
lines AS MATERIALIZED (SELECT doc_id, unnest(CASE WHEN len(l) > 1 THEN list_append(l, text) ELSE l END) AS unit, unnest(CASE WHEN len(l) > 1 THEN list_append([false FOR x IN l], true) ELSE [true] END) AS whole
          FROM (SELECT doc_id, text, string_split(coalesce(text, ''), chr(10)) AS l FROM documents)),
units AS MATERIALIZED (SELECT doc_id, whole, row_number() OVER () AS u, list_filter(regexp_split_to_array(translate(unit, '{_UPPER}', '{_LOWER}'), '[^\p{{L}}\p{{N}}]+'), lambda x: x <> '') AS w FROM lines),
spots AS MATERIALIZED (SELECT doc_id, u, whole, i - 1 AS i, w[i] || ' ' || w[i + 1] AS b FROM (SELECT doc_id, u, whole, w, unnest(range(1, len(w))) AS i FROM units)),
pairs AS (SELECT DISTINCT doc_id, u, b FROM spots),
counts AS (SELECT u, count(*) AS n FROM pairs GROUP BY 1),
shared AS (SELECT p.doc_id, p.u, g.license_id, count(*) AS k FROM pairs p JOIN grams g USING (b) GROUP BY ALL),
near AS (SELECT doc_id, license_id, 0 AS kind, 2.0::DOUBLE * k / (n + m) AS dice FROM shared JOIN counts USING (u) JOIN sizes USING (license_id) WHERE 2 * k * {t.denominator} >= (n + m) * {t.numerator}),
starts AS MATERIALIZED (SELECT DISTINCT s.doc_id, s.u, p.license_id, s.i - p.j AS s FROM spots s JOIN places p USING (b) WHERE s.whole),
held AS (SELECT DISTINCT a.doc_id, a.u, a.license_id, a.s, s.b FROM starts a JOIN lengths USING (license_id) JOIN spots s ON s.u = a.u AND s.i >= a.s AND s.i < a.s + long),
fit AS (SELECT h.doc_id, h.u, h.license_id, h.s, count(*) AS n, count(g.b) AS k FROM held h LEFT JOIN grams g ON g.license_id = h.license_id AND g.b = h.b GROUP BY ALL),
windows AS (SELECT doc_id, license_id, 1 AS kind, 2.0::DOUBLE * k / (n + m) AS dice FROM fit JOIN sizes USING (license_id) WHERE 2 * k * {t.denominator} >= (n + m) * {t.numerator})
SELECT doc_id, license_id, count(*) FILTER (kind = 0) AS n_units, count(*) FILTER (kind = 1) AS n_windows, round(max(dice), 6) AS best_dice FROM (FROM near UNION ALL FROM windows) GROUP BY 1, 2"""
