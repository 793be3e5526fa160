"""Licence notices and texts in documents, by the Dice coefficient over word bigrams.

Lines, blocks of lines between blank ones, and runs of blocks are compared with
templates.
Dice over multisets is 2 s / (n + t) with s shared bigrams, so a segment of n
bigrams can only reach d with a template whose t lies in [n d / (2 - d),
n (2 - d) / d]; other templates are pruned before anything is counted.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Names and texts of common notices and licences.
TEMPLATES = (
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "This project is licensed under the terms of the MIT license."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0"),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("BSD-2-Clause", "Released under the BSD 2-Clause License."),
    ("BSD-3-Clause", "Released under the BSD 3-Clause License."),
    ("BSD-2-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0"),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0"),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0"),
    ("CC-BY-ND-4.0", "Licensed under CC BY-ND 4.0"),
    ("CC-BY-NC-SA-4.0", "Licensed under CC BY-NC-SA 4.0"),
    ("CC-BY-NC-ND-4.0", "Licensed under CC BY-NC-ND 4.0"),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related rights to this work."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
)
THRESHOLD = 0.8
BLANK_LINE = r"\n\s*\n"


def normal_words(text: Column) -> Column:
    """Lower-cased runs of letters and digits; all beyond ASCII counts as letters."""
    return F.array_remove(F.split(F.lower(text), r"[^a-z0-9\x{80}-\x{10FFFF}]+"), "")


def templates_frame(spark: SparkSession, templates: tuple = TEMPLATES) -> DataFrame:
    return spark.createDataFrame([(k, *t) for k, t in enumerate(templates)], "template int, license string, text string")


def template_bigrams(templates: DataFrame) -> DataFrame:
    """``(bigram, template, template_count, template_size)``."""
    words = templates.select("template", normal_words(F.col("text")).alias("w")).where(F.size("w") > 1)
    spots = words.select("template", (F.size("w") - 1).alias("template_size"), "w", F.posexplode("w").alias("k", "word")).where(F.col("k") < F.col("template_size"))
    pair = F.xxhash64("word", F.get("w", F.col("k") + 1))
    return spots.groupBy(pair.alias("bigram"), "template", "template_size").agg(F.count("*").alias("template_count"))


def segments(docs: DataFrame, longest: int, id_col: str, text_col: str) -> DataFrame:
    """``(doc_id, level, part, text_no, words)``: lines, and blocks of several lines no longer than templates allow."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).alias("doc_id"), text.alias("body"), F.xxhash64(text).alias("text_no"))
    lines = rows.select("doc_id", "text_no", F.lit("line").alias("level"), F.posexplode(F.split("body", "[\r\n]+")).alias("part", "segment"))
    # a text without a blank line is one block; blocks are judged by their words alone, however they are laid out
    paragraphs = F.filter(F.when(F.contains("body", F.lit("\n\n")), F.split("body", "\n\n+")).otherwise(F.array("body")), lambda p: F.contains(p, F.lit("\n")))
    short = F.filter(F.transform(paragraphs, normal_words), lambda w: (F.size(w) > 1) & (F.size(w) <= longest + 1))
    blocks = rows.select("doc_id", "text_no", F.lit("block").alias("level"), F.posexplode(short).alias("part", "words"))
    lines = lines.where(F.length("segment") > 2).withColumn("words", normal_words(F.col("segment"))).drop("segment")
    return lines.where((F.size("words") > 1) & (F.size("words") <= longest + 1)).unionByName(blocks)


def block_runs(docs: DataFrame, bigrams: DataFrame, threshold: float, id_col: str, text_col: str) -> DataFrame:
    """``(doc_id, level, part, last, text_no, words)``: runs of two blocks or more, from block ``part`` to block ``last``.

    A run reaches the threshold only with a template of which it, and so its
    text, holds d / (2 - d) of the bigrams. All runs of a text that does are
    taken, up to the longest that such a template allows.
    """
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).alias("doc_id"), text.alias("body"), F.xxhash64(text).alias("text_no")).where(F.col("body").rlike(BLANK_LINE))
    spots = rows.select("doc_id", "text_no", normal_words(F.col("body")).alias("w")).select("doc_id", "text_no", "w", F.posexplode("w").alias("k", "word"))
    pairs = spots.select("doc_id", "text_no", F.xxhash64("word", F.get("w", F.col("k") + 1)).alias("bigram"))
    held = pairs.join(F.broadcast(bigrams), "bigram").groupBy("doc_id", "text_no", "template", "template_size", "bigram", "template_count").agg(F.count("*").alias("n"))
    held = held.groupBy("doc_id", "text_no", "template", "template_size").agg(F.sum(F.least("n", "template_count")).alias("s"))
    may = held.where(F.col("s") * (2 - threshold) >= F.col("template_size") * threshold - 1e-9).groupBy("text_no").agg(F.floor(F.max("template_size") * (2 - threshold) / threshold + 2).cast("int").alias("most"))
    blocks = F.filter(F.transform(F.split("body", BLANK_LINE), normal_words), lambda w: F.size(w) > 0)
    cut = rows.join(may, "text_no").select("doc_id", "text_no", "most", blocks.alias("blocks")).withColumn("sizes", F.transform("blocks", F.size))
    starts = cut.select("*", F.posexplode("sizes").alias("part", "size")).where((F.col("size") < F.col("most")) & (F.col("part") + 1 < F.size("sizes")))
    # each block has a word at least, so no run is longer than the words allowed
    near = starts.withColumn("blocks", F.slice("blocks", F.col("part") + 1, F.col("most"))).withColumn("sizes", F.slice("sizes", F.col("part") + 1, F.col("most")))
    runs = near.select("doc_id", "text_no", "most", "part", "blocks", "sizes", F.explode(F.sequence(F.lit(2), F.size("sizes"))).alias("n"))
    runs = runs.where(F.aggregate(F.slice("sizes", F.lit(1), F.col("n")), F.lit(0), lambda total, x: total + x) <= F.col("most"))
    words = F.flatten(F.slice("blocks", F.lit(1), F.col("n")))
    return runs.select("doc_id", F.lit("run").alias("level"), "part", (F.col("part") + F.col("n") - 1).alias("last"), "text_no", words.alias("words"))


def license_matches(docs: DataFrame, templates: DataFrame, threshold: float = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, license, dice, level, n_segments``: for each document and licence the best segment, and how many reach the threshold.

    A segment counts for the template it resembles most (ties: the earlier
    template); runs of blocks that begin at the same block count once. Null and blank texts and segments of under two words match
    nothing; repeated rows count once for an id and text; null ids stay null.
    Empty tables give no rows; other columns are not looked at. Templates are
    broadcast: their table is checked to be at most 20,000 rows.
    """
    if templates.limit(20_001).count() > 20_000:
        raise ValueError("more than 20,000 templates cannot be broadcast")
    bigrams = template_bigrams(templates)
    longest = int((bigrams.agg(F.max("template_size")).first()[0] or 0) * (2 - threshold) / threshold) + 1
    cut = segments(docs, longest, id_col, text_col).withColumn("last", F.col("part"))
    cut = cut.unionByName(block_runs(docs, bigrams, threshold, id_col, text_col)).withColumn("size", F.size("words") - 1)
    spots = cut.select("doc_id", "text_no", "level", "part", "last", "size", "words", F.posexplode("words").alias("k", "word")).where(F.col("k") < F.col("size"))
    found = spots.withColumn("bigram", F.xxhash64("word", F.get("words", F.col("k") + 1))).drop("words", "word", "k")
    may = (F.col("template_size") * threshold <= F.col("size") * (2 - threshold) + 1e-9) & (F.col("size") * threshold <= F.col("template_size") * (2 - threshold) + 1e-9)
    key = ["doc_id", "text_no", "level", "part", "last", "size"]
    shared = found.join(F.broadcast(bigrams), "bigram").where(may).groupBy(*key, "template", "template_size", "bigram", "template_count").agg(F.count("*").alias("n"))
    dice = shared.groupBy(*key, "template", "template_size").agg((2 * F.sum(F.least("n", "template_count")) / (F.col("size") + F.col("template_size"))).alias("dice")).where(F.col("dice") >= threshold)
    best = dice.groupBy(*key).agg(F.max(F.struct("dice", (-F.col("template")).alias("back"))).alias("b")).select("doc_id", "text_no", "level", "part", F.col("b.dice").alias("dice"), (-F.col("b.back")).alias("template"))
    named = best.join(F.broadcast(templates.select("template", "license")), "template")
    return named.groupBy("doc_id", "license").agg(
        F.max("dice").alias("dice"), F.max_by("level", F.struct("dice", "level")).alias("level"), F.countDistinct("text_no", "level", "part").alias("n_segments")
    )


def op6_licenses(spark, sf_dir: str) -> DataFrame:
    """Every licence found in every document, at a Dice coefficient of 0.8."""
    return license_matches(spark.read.parquet(f"{sf_dir}/documents.parquet"), templates_frame(spark))
