"""License scans: sparse TF-IDF cosine to templates, then inheritance from the nearest directory. DataFrame functions only.

The candidates of every file are its lines, headers of two to ``HEADER`` short lines in a row, the blocks between blank lines and
the whole text. Their terms, weighted by inverse frequency over the candidates of the corpus that hold a licence word and the templates, are
compared with each template by cosine; the best one at or above ``threshold`` names the candidate's licence. A header
counts unless a part of it names the same licence as well; a line has the best licence of what covers it. Each statement is a template of its own, so one that stands alone has cosine 1 in any corpus;
some licences have their full text as a template, too. A file all whose words are in such lines, or most of them, is a licence file: it declares
a licence for its directory. A file without a licence of its own takes that of the nearest directory above it which has one.

Scale: only candidates whose cosine may reach the threshold by a bound leave the scan, and equal ones are compared once; templates are fixed and broadcast; declarations are one row a directory, summed before
the shuffle; the join of files with their directories is by equality on each level of the path, so its size is files x depth.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored, table, word_count

# Usual statements of widespread licences.
TEMPLATES = {
    "Apache-2.0": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License.",
    "Apache-2.0 ": "Licensed under the Apache License, Version 2.0.",
    "MIT": "Released under the MIT License.",
    "MIT ": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files",
    "MIT  ": "MIT License Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "ISC": "ISC License Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS.",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-2.0": "This work is licensed under the GNU General Public License, version 2.",
    "LGPL-3.0": "This work is licensed under the GNU Lesser General Public License, version 3.",
    "BSD-3-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted.",
    "BSD-3-Clause ": "Licensed under the BSD 3-Clause License.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "CC-BY-4.0": "Licensed under CC BY 4.0.",
    "CC-BY-4.0 ": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-SA-4.0": "Licensed under CC BY-SA 4.0.",
    "CC-BY-SA-4.0 ": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "CC0-1.0": "Dedicated to the public domain under the CC0 1.0 Universal Public Domain Dedication.",
    "Proprietary": "All rights reserved.",
    "Proprietary ": "Unauthorized copying of this file is prohibited.",
    "Proprietary  ": "Copyright. All rights reserved. Unauthorized copying of this file is prohibited.",
}
#: Candidates with one of these say how frequent a term is in licence statements; others are compared as well.
CUE = r"(?i)licen[sc]e|copyright|public domain|spdx|redistribut|permission is|all rights reserved"
TERM = r"[A-Za-z0-9]+(?:[.-][A-Za-z0-9]+)*"
TERMS = "regexp_extract_all(lower({}), r'(" + TERM.replace("{", "{{") + ")', 1)"
THRESHOLD = 0.6
#: What stands between two blocks.
BLOCKS = r"\n[^\S\n]*\n"
#: Lines of a header at most, and characters of a line that can be one of several: a statement is wrapped into short lines.
HEADER, WRAPPED = 4, 200
#: A file is a licence file when at least this share of its words is in licence lines.
WHOLE = 0.5


def terms(text) -> F.Column:
    return F.regexp_extract_all(F.lower(text), F.lit(f"({TERM})"), F.lit(1))


def vectors(lines: DataFrame, key: str, idf: DataFrame, unseen: float = 0.0) -> DataFrame:
    """``key, terms`` -> key, term, weight of unit length; a term that ``idf`` does not hold has the weight ``unseen``."""
    tf = lines.select(key, F.explode("terms").alias("term")).groupBy(key, "term").agg(F.count("*").alias("tf"))
    weighed = tf.join(idf, "term", "left").select(key, "term", ((1.0 + F.log("tf")) * F.coalesce("idf", F.lit(unseen))).alias("w"))
    norm = weighed.groupBy(key).agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    return weighed.join(norm, key).select(key, "term", (F.col("w") / F.col("norm")).alias("w"))


def headers(lines: F.Column) -> F.Column:
    """(first line, number of lines, text) of every header among the lines of a block, one line at least."""
    size = F.size(lines)
    return F.flatten(F.transform(F.sequence(F.lit(1), F.lit(HEADER)), lambda k: F.transform(
        F.filter(F.sequence(F.lit(1), size), lambda i: (i + k - 1 <= size) & ((k == 1) | F.forall(F.slice(lines, i, k), lambda x: F.length(x) <= WRAPPED))),
        lambda i: F.struct(i.alias("first"), k.alias("length"), F.array_join(F.slice(lines, i, k), "\n").alias("part")),
    )))


class Sieve:
    """Bounds of a text's cosine to the templates, from the weights of the templates' terms (``template, term, v, idf``). They only let
    go what is surely below the threshold.

    A cosine is at most the length of the template's vector over the terms that the text has, too. What a part of a text shares with a template the text
    shares as well, so this bound of a file or block holds for all in it (``may_hold``). A text's own length is at least that over
    the templates' terms and 1 for each other term, since no term weighs less (``may_match``).
    """

    def __init__(self, weights: list, threshold: float) -> None:
        least, names = threshold - 1e-6, sorted({r["term"] for r in weights})
        idf, at = {r["term"]: float(r["idf"]) for r in weights}, {k: i for i, k in enumerate(sorted({r["template"] for r in weights}))}
        table = {t: [0.0] * len(at) for t in names}
        for r in weights:
            table[r["term"]][at[r["template"]]] = float(r["v"])
        array = lambda values: "array(" + ", ".join(values) + ")"
        double = lambda values: array(f"{v!r}D" for v in values)
        known, rows, zeros = array(f"'{t}'" for t in names), array(double(table[t]) for t in names), double([0.0] * len(at))
        row = f"element_at({rows}, cast(array_position({known}, t) as int))"
        weight = f"(1 + ln(size(x) - size(array_remove(x, t)))) * element_at({double(idf[t] for t in names)}, cast(array_position({known}, t) as int))"
        # One element in an array gives its value a name, so that it is made once a row.
        self._hold = f"exists(array({{x}}), x -> array_max(aggregate(array_intersect(x, {known}), {zeros}, (a, t) -> zip_with(a, {row}, (p, v) -> p + v * v))) >= {least**2!r}D)"
        self._match = (
            f"exists(array({{x}}), x -> exists(array(transform(array_intersect(x, {known}), t -> named_struct('r', {row}, 'w', {weight}))), "
            f"k -> size(k) > 0 and array_max(aggregate(k, {zeros}, (a, s) -> zip_with(a, s.r, (p, v) -> p + s.w * v))) >= {least!r}D * sqrt(size(array_distinct(x)) - size(k) + aggregate(k, 0D, (a, s) -> a + s.w * s.w))))"
        )

    def may_hold(self, text: str) -> F.Column:
        return F.expr(self._hold.format(x=TERMS.format(text)))

    def may_match(self, text: str) -> F.Column:
        return F.expr(self._match.format(x=TERMS.format(text)))


def line_matches(files: DataFrame, threshold: float = THRESHOLD) -> tuple[DataFrame, DataFrame]:
    """``path, text`` -> path, n_words, license, score of each line that matches a template, by itself or as a part of a header, block or
    file; and path, words of the files with such a line."""
    spark = files.sparkSession
    lines = F.split("block", "\n")
    in_blocks = lambda df: df.select("path", F.md5("text").alias("of_text"), F.posexplode(F.split("text", BLOCKS)).alias("block_no", "block"))
    # Terms are weighed by their frequency in what has a licence word, equal candidates counted as often as they occur.
    cue = in_blocks(files.filter(F.col("text").rlike(CUE))).filter(F.col("block").rlike(CUE)).withColumn("lines", lines)
    cue = cue.select(F.explode(F.concat(F.transform(F.filter(headers(F.col("lines")), lambda x: x["part"].rlike(CUE)), lambda x: x["part"]), F.array("block"))).alias("part"))
    cue = cue.unionByName(files.filter(F.col("text").rlike(CUE)).select(F.col("text").alias("part")))
    cue = stored(cue.groupBy(F.md5("part").alias("digest")).agg(terms(F.first("part")).alias("terms"), F.count("*").alias("times")).select("times", "terms"))
    known = spark.createDataFrame([(k.strip() + "|" + str(i), v) for i, (k, v) in enumerate(TEMPLATES.items())], "template string, text string").select("template", terms(F.col("text")).alias("terms"))
    n = (cue.agg(F.coalesce(F.sum("times"), F.lit(0))).first()[0] or 0) + len(TEMPLATES)
    df = cue.select("times", F.explode(F.array_distinct("terms")).alias("term")).groupBy("term").agg(F.sum("times").alias("df"))
    own = known.select(F.lit(1).cast("long").alias("times"), F.explode(F.array_distinct("terms")).alias("term")).groupBy("term").agg(F.sum("times").alias("df"))
    # Half of the frequency's logarithm: statements that are common in the corpus must still tell licences apart.
    idf = df.unionByName(own).groupBy("term").agg(F.sum("df").alias("df")).select("term", (1.0 + 0.5 * F.log((1.0 + n) / (1.0 + F.col("df")))).alias("idf"))
    idf = stored(idf)
    template = stored(vectors(known, "template", idf).select("template", "term", F.col("w").alias("v")))
    sieve = Sieve(template.join(idf, "term").collect(), threshold)  # the terms of the templates
    # Of all texts, what may match by the bounds, licence word or not. Equal candidates are scored once, however many files hold them.
    likely = files.filter(sieve.may_hold("text"))
    # The whole text goes as the block -1, which has no headers, so that one scan finds the candidates.
    both = likely.select("path", F.md5("text").alias("of_text"), F.posexplode(F.concat(F.array("text"), F.split("text", BLOCKS))).alias("pos", "block"))
    both = both.select("path", "of_text", (F.col("pos") - 1).alias("block_no"), "block").filter(sieve.may_hold("block"))
    own = F.array(F.struct(F.lit(0).alias("first"), F.lit(0).alias("length"), F.col("block").alias("part")))
    both = both.select("path", "of_text", "block_no", F.explode(F.when(F.col("block_no") < 0, own).otherwise(F.concat(headers(lines), own))).alias("h"))
    cue = both.filter(sieve.may_match("h.part")).withColumn("terms", terms(F.col("h.part")))
    cue = stored(cue.select("path", "of_text", "block_no", "h.first", "h.length", F.md5("h.part").alias("digest"), "terms"))
    distinct = cue.groupBy("digest").agg(F.first("terms").alias("terms"))
    unseen = 1.0 + 0.5 * math.log(1.0 + n)
    dot = vectors(distinct, "digest", idf, unseen).join(F.broadcast(template), "term").groupBy("digest", "template").agg(F.round(F.sum(F.col("w") * F.col("v")), 9).alias("score"))  # the order of a sum shows in its last digits
    best = dot.filter(F.col("score") >= threshold).groupBy("digest").agg(F.max(F.struct("score", F.split("template", r"\|")[0].alias("license"))).alias("b"))
    best = stored(best)
    # The files with a match, in blocks: of a line its number of words goes on, no text is moved. A text that no bound lets through has no line with a match.
    matched = stored(cue.join(best.select("digest"), "digest", "left_semi").select("path").distinct())
    some = in_blocks(likely).select("path", "of_text", "block_no", F.md5("block").alias("of_block"), F.transform(lines, word_count).alias("words"))
    some = stored(some.join(matched, "path", "left_semi"))
    # Matching headers, without those of which a part has the same licence at no lower score.
    found = cue.filter("length > 0").drop("terms").join(best, "digest").select("path", "of_text", "block_no", "first", "length", "b").distinct()
    found = stored(found)
    inner = F.explode(F.flatten(F.transform(F.sequence(F.lit(1), F.col("length") - 1), lambda k: F.transform(F.sequence(F.col("first"), F.col("first") + F.col("length") - k), lambda i: F.struct(i.alias("i"), k.alias("k"))))))
    longer = found.filter("length > 1").select("path", "of_text", "block_no", "first", "length", "b", inner.alias("x")).select(*[F.col(c).alias("w_" + c) for c in ("path", "of_text", "block_no", "first", "length", "b")], F.col("x.i").alias("i"), F.col("x.k").alias("k"))
    at = (F.col("path") == F.col("w_path")) & (F.col("of_text") == F.col("w_of_text")) & (F.col("block_no") == F.col("w_block_no"))
    part = (F.col("first") == F.col("i")) & (F.col("length") == F.col("k")) & (F.col("b.license") == F.col("w_b.license")) & (F.col("b.score") >= F.col("w_b.score"))
    weak = longer.join(found, at & part).select("w_path", "w_of_text", "w_block_no", "w_first", "w_length").distinct()
    strong = found.join(weak, at & (F.col("first") == F.col("w_first")) & (F.col("length") == F.col("w_length")), "left_anti")
    covered = strong.select("path", "of_text", "block_no", F.explode(F.sequence(F.col("first"), F.col("first") + F.col("length") - 1)).alias("line_no"), "b")
    covered = covered.groupBy("path", "of_text", "block_no", "line_no").agg(F.max("b").alias("of_header"))
    # Every line of a file with a match, with what its block and its file match; the words of a file are in its lines.
    whole = some.select("path", "of_text", "block_no", "of_block", F.posexplode("words").alias("at", "n_words")).select("path", "of_text", "block_no", "of_block", (F.col("at") + 1).alias("line_no"), "n_words")
    sizes = files.select("path", word_count(F.col("text")).alias("n_words")).join(matched, "path", "left_semi").groupBy("path").agg(F.sum("n_words").alias("words"))
    whole = whole.join(covered, ["path", "of_text", "block_no", "line_no"], "left")
    for c in ("block", "text"):
        whole = whole.join(best.select(F.col("digest").alias("of_" + c), F.col("b").alias("b_" + c)), "of_" + c, "left")
    return whole.withColumn("b", F.greatest("of_header", "b_block", "b_text")).filter("b is not null").select("path", "n_words", "b.license", "b.score"), sizes


def parents(path) -> F.Column:
    """The directories above a path, nearest first, as (directory, distance)."""
    parts = F.split(path, "/")
    return F.transform(
        F.sequence(F.lit(1), F.greatest(F.size(parts) - 1, F.lit(1))),
        lambda k: F.struct(F.array_join(F.slice(parts, 1, F.size(parts) - k), "/").alias("directory"), k.alias("distance")),
    )


def scanned(files: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """``id, path, text`` -> id, path, license, score, origin, inherited_from.

    origin: ``header`` (the file has a statement), ``file`` (it is a licence file), ``inherited`` or ``none``. Of several statements
    the best score counts, then the greater name. Null texts have none, a null path neither gives nor takes; rows that share a path
    are one file with several texts. An empty table gives an empty result, extra columns are ignored.
    """
    rows = files.select("id", "path", "text")
    found, sizes = line_matches(rows.select("path", "text").filter("path is not null"), threshold)
    found = stored(found)
    per_file = found.groupBy("path").agg(F.max(F.struct("score", "license")).alias("best"), F.sum("n_words").alias("covered"))
    own = per_file.join(sizes, "path").select("path", F.col("best.license").alias("license"), F.col("best.score").alias("score"), (F.col("covered") >= WHOLE * F.col("words")).alias("whole"))
    own = stored(own)
    here = F.element_at(parents(F.col("path")), 1)["directory"]
    declared = own.filter("whole").select(here.alias("directory"), "license", "score").groupBy("directory").agg(F.max(F.struct("score", "license")).alias("d"))
    declared = stored(declared.select("directory", F.col("d.license").alias("given")))
    # Files share few directories: the nearest declaration is found once a directory, then joined by path.
    leaf = rows.filter("path is not null").select(here.alias("leaf")).distinct()
    above = leaf.select("leaf", F.explode(F.concat(F.array(F.struct(F.col("leaf").alias("directory"), F.lit(0).alias("distance"))), F.filter(parents(F.col("leaf")), lambda x: F.col("leaf").contains("/")))).alias("x"))
    nearest = above.select("leaf", "x.*").join(declared, "directory").groupBy("leaf").agg(F.min(F.struct("distance", "directory", "given")).alias("n"))
    nearest = stored(nearest.select("leaf", F.col("n.directory").alias("directory"), F.col("n.given").alias("given")))
    out = rows.select("id", "path", here.alias("leaf")).join(own.withColumnRenamed("path", "p"), F.col("path") == F.col("p"), "left").join(nearest, "leaf", "left")
    inherits = F.col("license").isNull() & F.col("given").isNotNull()
    origin = F.when(F.col("whole"), "file").when(F.col("license").isNotNull(), "header").when(inherits, "inherited").otherwise("none")
    return out.select("id", "path", F.coalesce("license", "given").alias("license"), F.coalesce("score", F.lit(0.0)).alias("score"), origin.alias("origin"), F.when(inherits, F.col("directory")).alias("inherited_from"))


def op5(spark, sf_dir: str) -> DataFrame:
    """One row a document, taken as a file in the directory source/lang."""
    docs = table(spark, sf_dir, "documents")
    path = F.concat_ws("/", F.coalesce("source", F.lit("-")), F.coalesce("lang", F.lit("-")), F.coalesce(F.col("doc_id").cast("string"), F.lit("-")))
    return scanned(docs.select(F.col("doc_id").alias("id"), path.alias("path"), "text")).withColumnRenamed("id", "doc_id")
