"""Licence scan with DataFrame functions only: sparse TF-IDF cosine to templates, then inheritance by directory.

Units of a text are compared with licence templates - one-line notices, headers and full texts: both are TF-IDF vectors
(1 + ln tf) with the templates' own inverse document frequencies (words of no template weigh as much as the rarest).
Segments are the lines and sentences of a text. A unit is a segment, or a run of words as long as some template that
starts at a segment, whatever lines it is wrapped over; of a licence file (by its name, or no longer than twice the
longest template) also the whole text. Units start at segments that hold a word of TRIGGER, and at those before them; each
template has such a word in its first sentence. Equal units are compared once. A row's licence is that of its best unit. A licence file - by
name, or because the best unit makes up half of its words or more - speaks for its directory; rows without a licence
of their own inherit from the nearest ancestor directory that has one, by a join on paths.

Defined results: null or empty text has no licence of its own; equal scores go to the longer unit, then to the licence
that sorts first; several licence files of one directory: the best score, then the smallest licence id; a null path has
no ancestors; repeated rows are repeated; whole texts are read.
"""

from __future__ import annotations

import math
import re
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecrag.llm.common import checkpointed

LEAST = 0.7
#: Matching units (under 100 bytes each) that may be broadcast.
BROADCAST = 100_000
#: Licence notices by SPDX identifier (fixed values).
TEMPLATES = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License."),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("BSD-3-Clause", "Released under the 3-Clause BSD License."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC0-1.0", "Dedicated to the public domain under CC0 1.0 Universal."),
    ("ISC", "Released under the ISC License."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
    ("GPL-3.0", "GNU General Public License Version 3, 29 June 2007"),
    ("GPL-2.0", "GNU General Public License Version 2, June 1991"),
    # headers
    (
        "Apache-2.0",
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at "
        "http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, "
        "WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    ),
    (
        "GPL-3.0",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, "
        "either version 3 of the License, or (at your option) any later version.",
    ),
    (
        "GPL-2.0",
        "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; "
        "either version 2 of the License, or (at your option) any later version.",
    ),
    (
        "MPL-2.0",
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.",
    ),
    # full texts
    (
        "MIT",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, "
        "including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is "
        "furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. "
        "THE SOFTWARE IS PROVIDED AS IS, WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND "
        "NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, "
        "OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    ),
    (
        "ISC",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice "
        "appear in all copies. THE SOFTWARE IS PROVIDED AS IS AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. "
        "IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN "
        "ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    ),
    (
        "BSD-3-Clause",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain "
        "the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and "
        "the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be "
        "used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS AS IS AND ANY "
        "EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED.",
    ),
    *((name, f"SPDX-License-Identifier: {name}") for name in ("Apache-2.0", "MIT", "GPL-3.0", "GPL-2.0", "LGPL-3.0", "AGPL-3.0", "BSD-3-Clause", "MPL-2.0", "ISC", "Unlicense")),
)
TOKEN = r"[a-z0-9]+(?:\.[0-9]+)*"
FILE_NAME = r"(?i)(?:^|/)(?:licen[sc]e|copying|notice)[^/]*$"


def vectors(templates=TEMPLATES) -> tuple[dict[str, float], list[tuple[str, dict[str, float]]]]:
    """Inverse document frequencies and the unit TF-IDF vector of each template."""
    counts = [(name, Counter(re.findall(TOKEN, text.lower()))) for name, text in templates]
    df = Counter(t for _, c in counts for t in c)
    idf = {t: math.log((1 + len(counts)) / (1 + n)) + 1 for t, n in df.items()}
    out = []
    for name, c in counts:
        w = {t: (1 + math.log(n)) * idf[t] for t, n in c.items()}
        norm = math.sqrt(sum(x * x for x in w.values()))
        out.append((name, {t: x / norm for t, x in w.items()}))
    return idf, out


#: What a segment must hold for units to be made around it (fixed value): words that licence notices are made of.
TRIGGER = r"(?<![a-z0-9])(?:licen[sc]e[sd]?|copyright|permission|redistribut(?:e|ion)|spdx|unencumbered|domain|mpl|cc0)(?![a-z0-9])"


def lengths(templates=TEMPLATES) -> list[int]:
    """Words of the templates, each length once."""
    return sorted({len(re.findall(TOKEN, text.lower())) for _, text in templates})


def _words(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(f"({TOKEN})"))


def _segments(text: Column) -> Column:
    """Lower-cased lines and sentences that hold a word; null for a text without a trigger, which most texts are."""
    lowered = F.lower(F.coalesce(text.cast("string"), F.lit("")))
    return F.when(F.rlike(lowered, F.lit(TRIGGER)), F.filter(F.split(lowered, r"[\n\r]+|(?<=[.!?;:])\s+"), lambda x: F.rlike(x, F.lit("[a-z0-9]"))))


def _starts(templates) -> Column:
    """Of the columns segments, joined and whole: the words from each segment that has a trigger, or stands before one that
    has, on: (tokens, own), where own is the segment's own number of words and tokens holds as many more as the longest
    template. A row that is compared as a whole has all its words as one entry more.
    """
    most = lengths(templates)[-1]
    hits = F.filter(F.transform("segments", lambda x, i: F.when(F.rlike(x, F.lit(TRIGGER)), i)), lambda i: i.isNotNull())
    at = F.array_distinct(F.filter(F.flatten(F.transform(hits, lambda i: F.array(i - 1, i))), lambda i: i >= 0))
    entry = lambda i: F.struct(F.slice(_words(F.array_join(F.slice("segments", i + 1, F.lit(most)), " ")), 1, most).alias("tokens"), F.size(_words(F.get("segments", i))).alias("own"))
    runs = F.transform(at, entry)
    return F.when(F.col("whole"), F.concat(runs, F.array(F.struct(_words(F.col("joined")).alias("tokens"), F.size(_words(F.col("joined"))).alias("own"))))).otherwise(runs)


def _units(row_starts: DataFrame, row: list[str], templates) -> DataFrame:
    """(row, unit, size): the distinct units of every row's entries."""
    own = F.col("s.own")
    sizes = F.array_distinct(F.filter(F.concat(F.array(own), *(F.array(F.lit(n)) for n in lengths(templates))), lambda n: (n > 0) & (n <= F.size("s.tokens"))))
    each = row_starts.select(*row, F.explode("starts").alias("s")).select(*row, "s", F.explode(sizes).alias("size"))
    return each.select(*row, F.array_join(F.slice("s.tokens", F.lit(1), F.col("size")), " ").alias("unit"), "size").distinct()


def compare(units: DataFrame, templates=TEMPLATES, least: float = LEAST) -> DataFrame:
    """(key, license, score): licence and score (6 places) of each distinct unit (key, unit) that reaches the threshold."""
    spark = units.sparkSession
    idf, weights = vectors(templates)
    rare = math.log(1 + len(templates)) + 1
    known = spark.createDataFrame([(t, x) for t, x in idf.items()], "token string, idf double")
    postings = spark.createDataFrame([(t, k, name, x) for k, (name, w) in enumerate(weights) for t, x in w.items()], "token string, template int, license string, unit double")
    tokens = units.select("key", F.explode(F.split("unit", " ")).alias("token"))
    tf = tokens.groupBy("key", "token").agg(F.count("*").alias("tf"))
    # the templates are fixed values of the code, so their tables are broadcast
    weighted = tf.join(F.broadcast(known), "token", "left").withColumn("w", (1 + F.log("tf")) * F.coalesce("idf", F.lit(rare)))
    parts = weighted.join(F.broadcast(postings), "token", "left").select("key", "template", "license", (F.col("w") * F.col("unit")).alias("dot"))
    norms = weighted.groupBy("key").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    dots = parts.where("template is not null").groupBy("key", "template", "license").agg(F.sum("dot").alias("dot"))
    scored = dots.join(norms, "key").withColumn("score", F.round(F.col("dot") / F.col("norm"), 6)).where(F.col("score") >= least)
    best = scored.groupBy("key").agg(F.min(F.struct((-F.col("score")).alias("low"), "license")).alias("b"))
    return best.select("key", F.col("b.license").alias("license"), (-F.col("b.low")).alias("score"))


def scan(df: DataFrame, path: Column, doc_id: str = "doc_id", text: str = "text", templates=TEMPLATES, least: float = LEAST) -> DataFrame:
    """doc_id, path, license, score, origin (`own`, `inherited` or null) and from_dir of every row."""
    file = F.coalesce(path.cast("string").rlike(FILE_NAME), F.lit(False))
    whole = file | F.coalesce(F.length(F.col(text)) <= 2 * max(len(t) for _, t in templates), F.lit(False))
    base = df.select(F.col(doc_id).alias("doc_id"), path.cast("string").alias("path"), F.xxhash64(F.col(text)).alias("body"), file.alias("file"), whole.alias("whole"), _segments(F.col(text)).alias("segments"))
    base = checkpointed(base)  # one scan of the texts; most rows have no segments left
    row = ["doc_id", "path", "body"]
    some = base.where("segments is not null").groupBy(*row, "file", "whole").agg(F.first("segments").alias("segments"))  # equal rows once
    some = some.withColumn("joined", F.array_join("segments", " "))
    some = checkpointed(some.select(*row, "file", F.size(_words(F.col("joined"))).alias("words"), _starts(templates).alias("starts")))
    units = checkpointed(_units(some, [*row, "file", "words"], templates).withColumn("key", F.md5("unit")))
    names = compare(units.groupBy("key").agg(F.first("unit").alias("unit")), templates, least)
    names = checkpointed(names)
    small = F.broadcast if names.count() <= BROADCAST else lambda table: table
    told = units.drop("unit").join(small(names), "key")
    pick = F.min(F.struct((-F.col("score")).alias("low"), (-F.col("size")).alias("shorter"), "license")).alias("b")
    own = told.groupBy(*row, "file", "words").agg(pick)
    own = own.select(*row, F.col("b.license").alias("license"), (-F.col("b.low")).alias("score"), (F.col("file") | (-2 * F.col("b.shorter") >= F.col("words"))).alias("speaks"))
    base = base.drop("segments", "whole", "file")
    same = [base[c].eqNullSafe(own[c]) for c in row]
    own = base.join(own, same[0] & same[1] & same[2], "left").select(*(base[c] for c in row), "license", "score", F.coalesce("speaks", F.lit(False)).alias("speaks"))
    own = checkpointed(own)
    folder = F.regexp_replace(F.col("path"), r"/?[^/]*$", "")
    spoken = own.where("license is not null and speaks and path is not null").groupBy(folder.alias("dir")).agg(F.min(F.struct((-F.col("score")).alias("low"), "license")).alias("d"))
    spoken = spoken.select("dir", F.col("d.license").alias("dir_license"), (-F.col("d.low")).alias("dir_score"))
    pieces = F.split(folder, "/")
    ancestors = F.transform(F.sequence(F.lit(0), F.size(pieces)), lambda n: F.struct(n.alias("depth"), F.array_join(F.slice(pieces, 1, n), "/").alias("dir")))
    # of a path only: the rows of one directory share its ancestors, so they are resolved once
    folders = own.where("license is null and path is not null").select(folder.alias("folder"), F.explode(ancestors).alias("up")).distinct()
    near = folders.join(spoken, folders["up.dir"] == spoken["dir"]).groupBy("folder").agg(F.max(F.struct("up.depth", "dir", "dir_license", "dir_score")).alias("near"))
    near = near.select(F.col("folder"), F.col("near.dir").alias("from_dir"), F.col("near.dir_license").alias("dir_license"), F.col("near.dir_score").alias("dir_score"))
    out = own.withColumn("folder", F.when(F.col("license").isNull(), folder)).join(near, "folder", "left")
    return out.select(
        "doc_id", "path", F.coalesce("license", "dir_license").alias("license"), F.coalesce("score", "dir_score").alias("score"),
        F.when(F.col("license").isNotNull(), "own").when(F.col("dir_license").isNotNull(), "inherited").alias("origin"),
        F.when(F.col("license").isNull(), F.col("from_dir")).alias("from_dir"),
    )
