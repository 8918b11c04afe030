"""License scans: an exact set-similarity join of text blocks with license templates, beside phrase places.

Blocks are the lines and, for notices wrapped over lines, every run of words as long as a template may be stretched.

The tokens of all templates are ordered by their counts in the whole corpus, rarest first. A block that holds at
least the threshold share of a template's tokens holds one of the template's first |T| - c + 1 tokens (prefix
filter, c = least common tokens), has c template tokens or more (length filter), and from their first common token on
both have c tokens left in that order (positional filter): the template by the token's place in it, the block by how
many of its tokens are rarer. Pairs that pass are verified. Built-in functions only.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, table

BREAK = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Phrases that name a license; one-sentence notices; whole public license notices.
PHRASES = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}
SENTENCES = {
    "mit": ["released under the mit license", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"],
    "apache-2": ["licensed under the apache license version 2 0", "you may not use this file except in compliance with the license you may obtain a copy of the license at"],
    "cc-by-nc": ["licensed under cc by nc 4 0"],
    "gpl-3": ["this work is licensed under the gnu general public license version 3", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license"],
    "bsd": ["redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"],
    "cc-by-sa": ["this work is licensed under a creative commons attribution sharealike 4 0 international license"],
}
NOTICES = {
    "mit": """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated
documentation files (the "Software"), to deal in the Software without restriction, including without limitation the
rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit
persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and
this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED
"AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF
MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS
BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,
OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "isc": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby
granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS
PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF
MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL
DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT,
NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "apache-2": """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in
compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless
required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS"
BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language
governing permissions and limitations under the License.""",
    "bsd": """Redistribution and use in source and binary forms, with or without modification, are permitted provided that
the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of
conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice,
this list of conditions and the following disclaimer in the documentation and/or other materials provided with the
distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED
WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE
ARE DISCLAIMED.""",
    "gpl-3": """This program is free software: you can redistribute it and/or modify it under the terms of the GNU General
Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any
later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the
implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more
details. You should have received a copy of the GNU General Public License along with this program. If not, see
https://www.gnu.org/licenses/.""",
}


def as_words(notice: str) -> str:
    return " ".join(re.findall("[0-9a-z]+", notice.lower()))


TEMPLATES = {label: SENTENCES.get(label, []) + ([as_words(NOTICES[label])] if label in NOTICES else []) for label in sorted({*SENTENCES, *NOTICES})}
#: Templates up to so many words are searched in short windows, so that a long notice does not widen theirs.
SHORT_SPAN = 48
THRESHOLD = 0.8


def _words(text: Column) -> Column:
    """The words with one space before and after each: ' a b c '; a single space without words."""
    return F.concat(F.lit(" "), F.btrim(F.regexp_replace(text, BREAK, " ")), F.lit(" "))


def _spaces(x: Column) -> Column:
    return F.char_length(x) - F.char_length(F.replace(x, F.lit(" "), F.lit("")))


def scan_blocks(docs: DataFrame, templates: dict[str, list[str]]) -> DataFrame:
    """One row per document: id, figures of the phrases, and the distinct template tokens of each line that has some."""
    vocabulary = sorted({w for texts in templates.values() for t in texts for w in t.split()})
    text = F.translate(F.coalesce(F.col("text").cast("string"), F.lit("")), UPPER, LOWER)
    low = docs.select("doc_id", text.alias("low")).withColumn("s", _words(F.col("low")))
    low = low.withColumn("s", F.when(F.col("s") == "  ", F.lit(" ")).otherwise(F.col("s")))
    places, first, last, named = F.lit(0), [], [], []
    for phrase, label in PHRASES.items():
        here = f" {phrase} "
        n = F.regexp_count("s", F.lit(f" {phrase}(?= )"))
        places = places + n
        at = F.instr("s", here)
        back = F.instr(F.reverse("s"), here[::-1])
        held = at > 0
        first.append(F.when(held, _spaces(F.substr(F.col("s"), F.lit(1), at)) - 1))
        last.append(F.when(held, _spaces(F.substr(F.col("s"), F.lit(1), F.char_length("s") - back - len(here) + 2)) - 1))
        named.append(F.when(held, F.lit(label)))
    # a run within one line adds nothing to that line's block
    marked = F.transform(F.split(F.btrim("s"), " "), lambda w: F.when(w.isin(*vocabulary), w).otherwise(""))
    lines = F.transform(
        F.split("low", "\n", -1),
        lambda line: F.array_distinct(F.filter(F.split(_words(line), " "), lambda w: w.isin(*vocabulary))),
    )
    return low.select(
        "doc_id",
        F.greatest(_spaces(F.col("s")) - 1, F.lit(0)).cast("long").alias("n_words"),
        places.cast("long").alias("n_base"),
        F.least(*first).cast("long").alias("first_word"),
        F.greatest(*last).cast("long").alias("last_word"),
        F.array_sort(F.array_distinct(F.filter(F.array(*named), lambda x: x.isNotNull()))).alias("base"),
        F.filter(lines, lambda b: F.size(b) > 0).alias("blocks"),
        F.when(F.contains("low", F.lit("\n")), marked).alias("marked"),
        F.expr("uuid()").alias("row"),
    )


def _run_length(template: str, threshold: float) -> int:
    """Words of a run that is searched for a template: its own, stretched by the share that may be foreign."""
    return math.ceil(len(template.split()) / threshold - 1e-9)


def word_windows(scanned: DataFrame, longest: int) -> DataFrame:
    """row, run, block: windows of 2 * longest words, each longest words further, and their distinct template tokens.

    Every run of `longest` words stands whole in one window.
    """
    starts = F.sequence(F.lit(1), F.greatest(F.size("marked") - longest, F.lit(1)), F.lit(longest))
    cut = scanned.where("marked IS NOT NULL").select("row", F.explode(F.transform(starts, lambda i: F.slice("marked", i, F.lit(2 * longest)))).alias("run"))
    return cut.withColumn("block", F.array_distinct(F.filter("run", lambda w: w != "")))


def _listed(templates: dict[str, list[str]], order: list[str], threshold: float) -> list[tuple]:
    """A row for each prefix token of each template, by the given order of tokens."""
    rank, out = {w: k for k, w in enumerate(order)}, []
    for label, texts in templates.items():
        for i, t in enumerate(texts):
            tokens = sorted(set(t.split()), key=rank.__getitem__)
            least = math.ceil(threshold * len(tokens) - 1e-9)
            out += [(label, i, w, k, least, _run_length(t, threshold), tokens, order[: rank[w]]) for k, w in enumerate(tokens[: len(tokens) - least + 1])]
    return out


LISTED = "label string, part int, token string, place int, least int, span int, tokens array<string>, rarer array<string>"


def block_joins(blocks: DataFrame, listed: list[tuple]) -> DataFrame:
    """row, label, containment of blocks (row, run, block) that hold enough of a template's distinct tokens.

    run: the words of a window, of which the best stretch as long as the template may be counts; null for a line.
    """
    prefix = blocks.sparkSession.createDataFrame(listed, LISTED)
    rare, shortest = sorted({x[2] for x in listed}), min(x[4] for x in listed)
    in_line = F.size(F.array_intersect("block", "tokens"))
    starts = F.sequence(F.lit(1), F.greatest(F.size("run") - F.col("span") + 1, F.lit(1)))
    in_run = F.array_max(F.transform(starts, lambda i: F.size(F.array_intersect(F.slice("run", i, F.col("span")), "tokens"))))
    # right at the pair's first common token; a later one may pass or not and adds nothing
    left = F.least(F.size("tokens") - F.col("place"), F.size("block") - F.size(F.array_intersect("block", "rarer")))
    found = (
        blocks.where(F.size("block") >= shortest)
        .withColumn("token", F.explode(F.filter("block", lambda w: w.isin(*rare))))
        .join(F.broadcast(prefix), "token")  # as many rows as the templates have prefix tokens
        .where((F.size("block") >= F.col("least")) & (left >= F.col("least")))
        .where(in_line >= F.col("least"))
        .withColumn("common", F.when(F.col("run").isNull(), in_line).otherwise(in_run))
        .where(F.col("common") >= F.col("least"))
    )
    return found.select("row", "label", (F.col("common") / F.size("tokens")).alias("containment"))


def template_joins(scanned: DataFrame, templates: dict[str, list[str]], threshold: float) -> DataFrame:
    """row, label, containment of every block that holds at least `threshold` of a template's distinct tokens."""
    lines = scanned.select("row", F.explode("blocks").alias("block"))
    vocabulary = {w for texts in templates.values() for t in texts for w in t.split()}
    # at most one row for each token of the templates comes to the driver
    counts = {r["t"]: r["n"] for r in lines.select(F.explode("block").alias("t")).groupBy("t").agg(F.count("*").alias("n")).collect()}
    order = sorted(vocabulary, key=lambda w: (counts.get(w, 0), w))
    listed = _listed(templates, order, threshold)
    found = block_joins(lines.withColumn("run", F.lit(None).cast("array<string>")), listed)
    for some in ([x for x in listed if x[5] <= SHORT_SPAN], [x for x in listed if x[5] > SHORT_SPAN]):
        if some:
            found = found.unionByName(block_joins(word_windows(scanned, max(x[5] for x in some)), some))
    return found.groupBy("row", "label").agg(F.max("containment").alias("containment"))


def license_scan(docs: DataFrame, templates: dict[str, list[str]] | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """One row per row of docs (doc_id, text): words, phrase places, labels of phrases and of matching blocks, score.

    Null or empty texts have no words, places or labels, and score 0. Repeated rows stay; an empty table gives no
    rows; other columns are ignored. The score is the largest containment of a template, 1 where a phrase stands.
    """
    templates = templates or TEMPLATES
    scanned = materialise(scan_blocks(docs, templates))
    found = template_joins(scanned, templates, threshold).groupBy("row").agg(F.collect_set("label").alias("more"), F.max("containment").alias("containment"))
    none = F.array().cast("array<string>")
    joined = scanned.drop("blocks", "marked").join(found, "row", "left")
    return joined.select(
        "doc_id",
        "n_words",
        "n_base",
        "first_word",
        "last_word",
        F.array_join("base", ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union("base", F.coalesce("more", none))), ",").alias("labels"),
        F.greatest(F.coalesce("containment", F.lit(0.0)), F.when(F.col("n_base") > 0, 1.0).otherwise(0.0)).alias("score"),
    )


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """License labels of every document."""
    return license_scan(table(spark, sf_dir, "documents"))
