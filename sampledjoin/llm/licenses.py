"""Licence scan, in DataFrame expressions only: normalised text against licence templates by the Dice coefficient over word bigrams.

Units of a document are its whole text, its paragraphs and its lines. Beyond the units that match, all runs of words are
searched that begin and end with a bigram of a template and are at most (2-t)/t as long as it, so that a licence of
several paragraphs within a longer text, or a notice within a line, is found; of overlapping runs the one with the most
of its template's bigrams counts. Two exact bounds prune: a unit and a template of
n bigrams can reach the threshold t only if the unit has between n·t/(2-t) and n·(2-t)/t distinct bigrams; and only if
it holds more than n·t/(2-t)-1 of the template's bigrams, so that a few key words, whose bigrams are more than the rest
may miss, must occur in it. Key words are chosen from the templates themselves.

Defined cases: null and empty texts, and texts of one word, match nothing; units of a document that are equal in lower case count once;
a unit counts for the template of the largest coefficient, ties by name; a run counts unless it lies in a unit that matched, or holds one that matched the same template; each row is scanned by itself, so repeated rows and null ids are kept.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

THRESHOLD = 0.8

#: The templates.
_AS_IS = "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software"
_BSD = "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution"
_BSD_END = "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed in no event shall the copyright holder or contributors be liable for any direct indirect incidental special exemplary or consequential damages including but not limited to procurement of substitute goods or services loss of use data or profits or business interruption however caused and on any theory of liability whether in contract strict liability or tort including negligence or otherwise arising in any way out of the use of this software even if advised of the possibility of such damage"
TEMPLATES = {
    "MIT": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software " + _AS_IS,
    "MIT-notice": "released under the mit license",
    "ISC": "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness in no event shall the author be liable for any special direct indirect or consequential damages or any damages whatsoever resulting from loss of use data or profits whether in an action of contract negligence or other tortious action arising out of or in connection with the use or performance of this software",
    "BSD-2-Clause": f"{_BSD} {_BSD_END}",
    "BSD-3-Clause": f"{_BSD} neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission {_BSD_END}",
    "BSD-notice": "use of this source code is governed by a bsd style license that can be found in the license file",
    "Apache-2.0-header": "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0 unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied see the license for the specific language governing permissions and limitations under the license",
    "Apache-2.0-notice": "licensed under the apache license version 2 0",
    "GPL-2.0-header": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose see the gnu general public license for more details",
    "GPL-3.0-header": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose see the gnu general public license for more details",
    "GPL-3.0-notice": "this work is licensed under the gnu general public license version 3",
    "MPL-2.0-header": "this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0",
    "Zlib": "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions the origin of this software must not be misrepresented you must not claim that you wrote the original software if you use this software in a product an acknowledgment in the product documentation would be appreciated but is not required altered source versions must be plainly marked as such and must not be misrepresented as being the original software this notice may not be removed or altered from any source distribution",
    "Unlicense": "this is free and unencumbered software released into the public domain anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary for any purpose commercial or non commercial and by any means",
    "CC-BY-NC-4.0-notice": "licensed under cc by nc 4 0",
    "CC-BY-4.0-notice": "this work is licensed under a creative commons attribution 4 0 international license",
    "CC-BY-SA-4.0-notice": "this work is licensed under a creative commons attribution sharealike 4 0 international license",
    "CC0-1.0-notice": "to the extent possible under law the author has waived all copyright and related or neighboring rights to this work",
    "All-rights-reserved": "copyright all rights reserved",
}


#: Words that any prose has; as key words they come last.
FUNCTION_WORDS = frozenset("a and any as at be by can for found from have if in is it may must no of on or that the this to under use was with without you your".split())


def bigrams(text: str) -> list[str]:
    w = text.split()
    return sorted({f"{a} {b}" for a, b in zip(w, w[1:], strict=False)})


def bounds(n: int, threshold: float) -> tuple[int, int]:
    """Least and most distinct bigrams of a unit that can reach the threshold against n."""
    return math.ceil(n * threshold / (2 - threshold) - 1e-9), math.floor(n * (2 - threshold) / threshold + 1e-9)


def key_words(templates: dict[str, str], threshold: float) -> list[str]:
    """Words of which a matching unit must hold one: for each template, its bigrams with such a word are more than a match may miss. Words that serve many templates, and long ones, come first."""
    grams = {k: set(bigrams(t)) for k, t in templates.items()}
    need = {k: len(g) - bounds(len(g), threshold)[0] + 1 for k, g in grams.items()}
    chosen: list[str] = []
    while any(n > 0 for n in need.values()):
        gain: Counter = Counter()
        for k, g in grams.items():
            own = Counter(w for x in g for w in set(x.split()))
            for w, n in own.items():
                gain[w] += min(n, max(0, need[k]))
        best = max(gain, key=lambda w: (gain[w] > 0 and w not in FUNCTION_WORDS, min(len(w), 4), gain[w], len(w), w))
        chosen.append(best)
        for k, g in grams.items():
            hit = {x for x in g if best in x.split()}
            need[k] -= len(hit)
            grams[k] = g - hit
    return sorted(chosen)


def holds_key_word(text: Column, words: list[str]) -> Column:
    """Whether the lower-cased text may hold a key word: by plain substring search, short ones as whole words."""
    edge = r"[\p{L}\p{N}]"
    return reduce(lambda a, b: a | b, (F.contains(text, F.lit(w)) if len(w) > 3 else F.rlike(text, F.lit(f"{w}(?<!{edge}{w})(?!{edge})")) for w in words))


def _words(values: list[str]) -> Column:
    """An array of constants, which the optimizer folds to one literal."""
    return F.split(F.lit("|".join(values)), r"\|")


def normalised(c: Column) -> Column:
    """Lower-cased text with one blank between words."""
    return F.trim(F.regexp_replace(c, r"[^\p{L}\p{N}]+", " "))


def word_bigrams(w: Column) -> Column:
    """The distinct bigrams of a unit's words, as an array."""
    return F.array_distinct(F.transform(F.slice(w, 2, F.greatest(F.size(w) - 1, F.lit(0))), lambda x, i: F.concat_ws(" ", F.element_at(w, i + 1), x)))


def _match(name: str, threshold: float) -> Callable[[Column], Column]:
    return lambda d: F.when(d >= threshold, F.struct((-F.round(d, 6)).alias("less"), F.lit(name).alias("template")))


def best_template(w: Column, templates: dict[str, str], threshold: float) -> Column:
    """For a unit's words, the struct (template, dice) of the best match, or null."""
    grams = {k: bigrams(v) for k, v in sorted(templates.items())}

    def against(g: Column) -> Column:
        options = []
        for name, t in grams.items():
            lo, hi = bounds(len(t), threshold)
            dice = 2.0 * F.size(F.array_intersect(g, _words(t))) / (F.size(g) + len(t))
            options.append(F.when(F.size(g).between(lo, hi), F.element_at(F.transform(F.array(dice), _match(name, threshold)), 1)))
        return F.array_min(F.array_compact(F.array(*options)))

    return F.element_at(F.transform(F.array(word_bigrams(w)), against), 1)


def _let(x: Column, f: Callable[[Column], Column]) -> Column:
    """f of x, which is evaluated once."""
    return F.element_at(F.transform(F.array(x), f), 1)


def runs(w: Column, templates: dict[str, str], threshold: float) -> Column:
    """For a text's words an array of (fewer, less, template, first, last), without overlaps: the runs that reach the threshold, as their template's bigrams and coefficient (both negative), name, first word and last word + 1."""
    fields = []
    for name, text in sorted(templates.items()):
        t = bigrams(text)
        most = bounds(len(text.split()) - 1, threshold)[1]
        fields.append(F.struct(F.lit(name).alias("name"), _words(t).alias("grams"), F.lit(len(t)).alias("n"), F.lit(bounds(len(t), threshold)[0]).alias("lo"), F.lit(most).alias("most")))

    def of(own: Column) -> Column:
        def against(t: Column) -> Column:
            def from_start(hits: Column, i: Column) -> Column:
                def measured(j: Column) -> Column:
                    dice = lambda g: lambda n: F.struct((-2.0 * n / (F.size(g) + t["n"])).alias("less"), (-n).alias("fewer"), (j + 2).alias("last"))
                    return _let(F.array_distinct(F.slice(own, i + 1, j - i + 1)), lambda g: _let(F.size(F.array_intersect(g, t["grams"])), dice(g)))

                ends = F.filter(hits, lambda j: j.between(i + t["lo"] - 1, i + t["most"] - 1))
                best = F.array_min(F.filter(F.transform(ends, measured), lambda x: x["less"] <= -threshold))
                return _let(best, lambda x: F.when(x.isNotNull(), F.struct(x["fewer"].alias("fewer"), x["less"].alias("less"), t["name"].alias("template"), i.alias("first"), x["last"].alias("last"))))

            at = F.filter(F.transform(own, lambda x, i: F.when(F.array_contains(t["grams"], x), i)), lambda i: i.isNotNull())
            return _let(at, lambda hits: F.array_compact(F.transform(hits, lambda i: from_start(hits, i))))

        near = _let(F.array_distinct(own), lambda every: F.filter(F.array(*fields), lambda t: F.size(F.array_intersect(every, t["grams"])) >= t["lo"]))
        return F.flatten(F.transform(near, against))

    def apart(found: Column) -> Column:
        clear = lambda taken, x: ~F.exists(taken, lambda y: (y["first"] < x["last"]) & (x["first"] < y["last"]))
        return F.aggregate(found, F.filter(found, lambda x: F.lit(False)), lambda taken, x: F.when(clear(taken, x), F.array_append(taken, x)).otherwise(taken))

    own = F.transform(F.slice(w, 2, F.greatest(F.size(w) - 1, F.lit(0))), lambda x, i: F.concat_ws(" ", F.element_at(w, i + 1), x))
    return _let(F.array_sort(_let(own, of)), apart)


def beyond(w: Column, held: Column, templates: dict[str, str], threshold: float) -> Column:
    """(less, template) of the runs beyond the units that matched, held: (best, unit)."""
    pad = lambda c: F.concat(F.lit(" "), c, F.lit(" "))

    def new(x: Column) -> Column:
        text = pad(F.array_join(F.slice(w, x["first"] + 1, x["last"] - x["first"]), " "))
        return _let(text, lambda run: ~F.exists(held, lambda h: F.contains(pad(h["unit"]), run) | ((h["best"]["template"] == x["template"]) & F.contains(run, pad(h["unit"])))))

    return F.transform(F.filter(runs(w, templates, threshold), new), lambda x: F.struct(F.round(x["less"], 6).alias("less"), x["template"].alias("template")))


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """One row for each row of ``docs`` (doc_id, text): matched units and runs, the licences' names joined by commas, the best coefficient (0 without a match)."""
    templates = templates or TEMPLATES
    words = key_words(templates, threshold)
    low = docs.select("doc_id", F.lower(F.coalesce("text", F.lit(""))).alias("low"))
    units = F.array_distinct(F.transform(F.concat(F.array("low"), F.split("low", r"\n[\x20\t]*\n", -1), F.split("low", "\n", -1)), lambda u: F.trim(u)))
    # by substring first, which is cheap, then by word
    holds = holds_key_word(F.col("low"), words)
    some = low.select("doc_id", F.when(holds, normalised(F.col("low"))).alias("words"), F.when(holds, F.filter(units, lambda u: holds_key_word(u, words))).alias("units"))
    split = F.filter(F.transform("units", lambda u: F.split(normalised(u), " ")), lambda w: F.arrays_overlap(w, _words(words)))
    both = F.filter(F.transform(split, lambda w: F.struct(best_template(w, templates, threshold).alias("best"), F.concat_ws(" ", w).alias("unit"))), lambda x: x["best"].isNotNull())
    held = some.select("doc_id", F.split("words", " ").alias("w"), both.alias("both"))
    more = _let(F.col("w"), lambda w: _let(F.col("both"), lambda held: beyond(w, held, templates, threshold)))
    found = held.select("doc_id", F.concat(F.transform("both", lambda x: x["best"]), more).alias("found"))
    return found.select(
        "doc_id",
        F.when(F.col("found").isNull(), 0).otherwise(F.size("found")).cast("bigint").alias("n_matches"),
        F.coalesce(F.array_join(F.array_sort(F.array_distinct(F.transform("found", lambda x: x["template"]))), ","), F.lit("")).alias("licenses"),
        F.coalesce(F.array_max(F.transform("found", lambda x: -x["less"])), F.lit(0.0)).alias("best_dice"),
    )


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def oracle() -> str:
    """DuckDB SQL for op4: every unit (whole text, paragraph, line) against every template by its definition, without bounds and key words. Runs of words beyond the units are not in it; tests hold them against brute force."""
    values = ", ".join("('{}', [{}], {})".format(k, ", ".join(f"'{g}'" for g in bigrams(v)), len(bigrams(v))) for k, v in TEMPLATES.items())
    return rf"""
WITH t(template, grams, n) AS (VALUES {values}),
u0 AS (
  SELECT doc_id, rn, list_distinct(list_transform(list_concat(list_concat([x], regexp_split_to_array(x, '\n[ \t]*\n')), string_split(x, chr(10))), lambda v: trim(v, ' '))) AS units
  FROM (SELECT doc_id, row_number() OVER () AS rn, lower(coalesce(text, '')) AS x FROM documents)),
u AS (SELECT rn, unnest(units) AS unit FROM u0),
w AS (SELECT rn, string_split(trim(regexp_replace(unit, '[^\p{{L}}\p{{N}}]+', ' ', 'g'), ' '), ' ') AS w FROM u),
g AS (SELECT rn, row_number() OVER () AS un, list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS g FROM w WHERE len(w) > 1),
d AS (SELECT rn, un, template, round(2.0 * len(list_intersect(g, grams)) / (len(g) + n), 6) AS dice,
             2.0 * len(list_intersect(g, grams)) / (len(g) + n) AS exact FROM g, t),
b AS (SELECT rn, un, template, dice, row_number() OVER (PARTITION BY un ORDER BY dice DESC, template) AS r FROM d WHERE exact >= {THRESHOLD})
SELECT u0.doc_id, CAST(count(b.un) AS BIGINT) AS n_matches,
       coalesce(string_agg(DISTINCT b.template, ',' ORDER BY b.template), '') AS licenses,
       coalesce(max(b.dice), 0.0) AS best_dice
FROM u0 LEFT JOIN b ON u0.rn = b.rn AND b.r = 1
GROUP BY u0.rn, u0.doc_id
"""
