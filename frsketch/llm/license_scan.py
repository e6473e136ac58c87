"""Licence scan: sparse TF-IDF cosine to templates, then inheritance along directories.

Every line of every text is compared with every template. Weights are term counts times
``ln((1 + N) / (1 + df)) + 1``, df over all documents; terms that no template has weigh as if no
document had them. A line whose cosine to a template reaches ``least`` carries that licence.

A line can only reach ``least`` if it has one of a template's heaviest terms: those that must be taken
away until the rest's norm is below ``least`` of the whole. Lines without such a term are dropped before
anything is exploded, which loses nothing. Templates are a small fixed list, broadcast as literals.

Every run of terms of a template's length is compared as well, with the same templates and with ``BLOCKS``,
the full wording of licences and headers: notices wrapped over lines or inside a longer line, licence
files and the heads of those too long to list. Here terms have the weights of all templates together. A run
can only reach ``least`` in a text whose terms hold that share of a template's norm; other texts are
dropped before, which loses nothing. A run counts where it is closer than the text's best line. SPDX
identifiers of a listed licence count as cosine 1.

A licence file speaks for its directory. A document without a licence of its own takes that of the
nearest directory at or above its own that has one. DataFrame functions only.

Null texts and paths: no licence of their own, and the root directory. Ties: the first template name.
Repeated rows keep a row each. An empty table gives an empty one; no further columns are read.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frsketch.llm.shared import stored

LEAST = 0.7
# fixed values: notices as they are published
TEMPLATES = {
    "Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "BSD-3-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted under the BSD 3-Clause License.",
    "CC-BY-4.0": "Licensed under CC BY 4.0.",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "CC-BY-SA-4.0": "Licensed under CC BY-SA 4.0.",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "ISC": "Permission to use, copy, modify, and distribute this software for any purpose with or without fee is hereby granted under the ISC License.",
    "LGPL-3.0": "This work is licensed under the GNU Lesser General Public License, version 3.",
    "MIT": "Released under the MIT License.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "Unlicense": "This is free and unencumbered software released into the public domain.",
}
GRANT = "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"
NO_WARRANTY = "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE."
BSD = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."
#: (licence, wording): full texts, headers and heads of files
BLOCKS = [
    ("MIT", GRANT),
    ("MIT", GRANT + " The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("BSD-2-Clause", BSD),
    ("BSD-3-Clause", BSD + " 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("Apache-2.0", "Apache License Version 2.0, January 2004 http://www.apache.org/licenses/ TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION"),
    *[
        (name, f"This {what} is free software: you can redistribute it and/or modify it under the terms of the GNU {title} as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. " + NO_WARRANTY + f" See the GNU {title} for more details.")
        for name, what, title in (("GPL-3.0", "program", "General Public License"), ("LGPL-3.0", "library", "Lesser General Public License"), ("AGPL-3.0", "program", "Affero General Public License"))
    ],
    *[(name, f"GNU {title} Version 3, {day} 2007") for name, title, day in (("GPL-3.0", "GENERAL PUBLIC LICENSE", "29 June"), ("LGPL-3.0", "LESSER GENERAL PUBLIC LICENSE", "29 June"), ("AGPL-3.0", "AFFERO GENERAL PUBLIC LICENSE", "19 November"))],
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."),
    ("MPL-2.0", "Mozilla Public License Version 2.0 1. Definitions"),
    ("Unlicense", "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."),
    *[(name, f"This work is licensed under a Creative Commons {title} 4.0 International License.") for name, title in (("CC-BY-4.0", "Attribution"), ("CC-BY-NC-4.0", "Attribution-NonCommercial"), ("CC-BY-SA-4.0", "Attribution-ShareAlike"))],
]
SPLIT = r"[^\p{L}\p{N}.-]+"


def terms_of(text: Column) -> Column:
    """Terms: lower case; full stops only inside."""
    parts = F.transform(F.split(F.lower(text), SPLIT), lambda t: F.trim(t, F.lit(".-")))
    return F.array_remove(parts, "")


def _terms(text: str) -> list[str]:
    import regex

    return [t for t in (p.strip(".-") for p in regex.split(SPLIT, text.lower())) if t]


def weights(templates: dict[str, str], df: dict[str, int], n: int) -> dict[str, dict[str, float]]:
    out = {}
    for name, text in templates.items():
        w: dict[str, float] = {}
        for t in _terms(text):
            w[t] = w.get(t, 0.0) + math.log((1 + n) / (1 + df.get(t, 0))) + 1
        norm = math.sqrt(sum(x * x for x in w.values()))
        out[name] = {t: x / norm for t, x in w.items()}
    return out


def heavy_terms(vectors: dict[str, dict[str, float]], least: float) -> list[str]:
    """Terms of which a line must have one to reach ``least``."""
    out = set()
    for w in vectors.values():
        rest = 1.0
        for t, x in sorted(w.items(), key=lambda p: (-p[1], p[0])):
            if rest < least * least:
                break
            out.add(t)
            rest -= x * x
    return sorted(out)


def least_terms(vector: dict[str, float], least: float) -> int:
    """How many of its terms a text must have at the least to reach ``least``."""
    rest = least * least - 1e-9
    for k, x in enumerate(sorted(vector.values(), reverse=True), 1):
        rest -= x * x
        if rest <= 0:
            return k
    return len(vector)


def block_hits(rows: DataFrame, forms: list[tuple[str, str]], df: dict[str, int], n: int, least: float) -> DataFrame:
    """row, run (cosine, name, n terms, lines): each text's run of terms closest to one of the forms."""
    vectors = weights({str(k): text for k, (_, text) in enumerate(forms)}, df, n)
    rare = math.log(1 + n) + 1
    vocab = sorted({t for w in vectors.values() for t in w})
    idf = {t: math.log((1 + n) / (1 + df.get(t, 0))) + 1 for t in vocab}
    cells = [(k, name, len(_terms(text)), vectors[str(k)], {t: x * idf[t] for t, x in vectors[str(k)].items()}, {t: idf[t] for t in vectors[str(k)]}) for k, (name, text) in enumerate(forms)]
    table = F.broadcast(rows.sparkSession.createDataFrame(cells, "k int, name string, len int, weight map<string,double>, part map<string,double>, idf map<string,double>"))
    base = rows.select("row", F.transform(F.split("text", "\n"), terms_of).alias("lines"))
    base = base.select("row", F.flatten("lines").alias("t"), F.flatten(F.transform("lines", lambda x, i: F.array_repeat(i, F.size(x)))).alias("at"))
    base = base.withColumn("have", F.array_intersect("t", strings(vocab)))
    fit = F.array_compact(F.array(*[F.when(F.size(F.array_intersect("have", strings(sorted(vectors[str(k)])))) >= least_terms(vectors[str(k)], least), F.lit(k)) for k in range(len(forms))]))
    got = base.withColumn("k", F.explode(fit)).join(table, "k")
    held = F.aggregate(F.array_intersect("have", F.map_keys("weight")), F.lit(0.0), lambda a, t: a + F.element_at("weight", t) * F.element_at("weight", t))
    got = got.where(held >= least * least - 1e-9)
    # terms outside all forms weigh as if no document had them
    every = F.map_from_arrays(strings(vocab), F.array(*[F.lit(idf[t]) for t in vocab]))
    got = got.withColumn("dots", F.transform("t", lambda t: F.coalesce(F.try_element_at("part", t), F.lit(0.0))))
    got = got.withColumn("idfs", F.transform("t", lambda t: F.coalesce(F.try_element_at("idf", t), F.try_element_at(every, t), F.lit(rare))))

    def total(a):
        return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)

    def bound(s):
        dot = total(F.slice("dots", s, F.col("len")))
        return (dot > 0) & (dot + 1e-9 >= least * F.sqrt(F.aggregate(F.slice("idfs", s, F.col("len")), F.lit(0.0), lambda a, x: a + x * x)))

    starts = F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("t") - F.col("len") + 1))
    got = got.withColumn("s", F.explode(F.filter(starts, bound)))
    got = got.select("row", "name", F.slice("t", F.col("s"), F.col("len")).alias("t"), F.slice("at", F.col("s"), F.col("len")).alias("at"), F.slice("idfs", F.col("s"), F.col("len")).alias("w"), total(F.slice("dots", F.col("s"), F.col("len"))).alias("dot"))
    # the square of a count is that count once for each occurrence
    square = total(F.zip_with("t", "w", lambda t, w: w * w * F.size(F.filter("t", lambda x: x == t))))
    got = got.withColumn("cosine", F.round(F.col("dot") / F.sqrt(square), 9)).where(F.col("cosine") >= least)
    run = F.struct("cosine", "name", F.size("t").alias("n"), (F.array_max("at") - F.array_min("at") + 1).cast("long").alias("lines"))
    return got.groupBy("row").agg(F.min_by(run, F.struct(-F.col("cosine"), F.col("name"), -F.size("t"))).alias("run"))


def spdx_hits(rows: DataFrame, names: list[str]) -> DataFrame:
    """row, run as in ``block_hits``: the first identifier of a listed licence."""
    ids = F.regexp_extract_all("text", F.lit(r"SPDX-License-Identifier:[ \t]*([A-Za-z0-9.-]*[A-Za-z0-9])"), 1)
    bare = F.filter(F.transform(ids, lambda x: F.regexp_replace(x, r"-(only|or-later)$", "")), lambda x: F.array_contains(strings(names), x))
    run = F.struct(F.lit(1.0).alias("cosine"), F.get(bare, F.lit(0)).alias("name"), F.lit(2).alias("n"), F.lit(1).cast("long").alias("lines"))
    return rows.where(F.contains("text", F.lit("SPDX-License-Identifier:"))).select("row", run.alias("run")).where("run.name is not null")


def strings(values: list[str]) -> Column:
    return F.array(*[F.lit(v) for v in values])


def scan_licences(docs: DataFrame, path: Column, licence_file: Column | None = None, templates: dict[str, str] | None = None, least: float = LEAST, id_col: str = "doc_id", text_col: str = "text", blocks: list[tuple[str, str]] | None = None) -> DataFrame:
    """id, path, own (licence in the text, or null), cosine, n_lines (licence lines), licence (own or
    inherited), from_dir (the directory it was inherited from, or null).

    licence_file: which rows speak for their directory; it may use ``share``, the part of the text's
    terms that stand in licence lines. Default: a base name of LICENSE, LICENCE, COPYING or NOTICE."""
    blocks = blocks if blocks is not None else BLOCKS if templates is None else []
    templates = TEMPLATES if templates is None else templates
    forms = sorted(templates.items()) + list(blocks)
    rows = docs.select(F.col(id_col).alias("_id"), F.coalesce(path, F.lit("")).alias("path"), F.coalesce(text_col, F.lit("")).alias("text"))
    vocab = sorted({t for x in templates.values() for t in _terms(x)})
    asked = sorted({t for _, x in forms for t in _terms(x)})
    seen = rows.select(F.explode(F.array_intersect(terms_of(F.col("text")), strings(asked))).alias("t")).groupBy("t").count()
    df = {r["t"]: r["count"] for r in seen.collect()}  # one row a template term
    n = rows.count()
    vectors = weights(templates, df, n)
    heavy = strings(heavy_terms(vectors, least))
    idf = {t: math.log((1 + n) / (1 + df.get(t, 0))) + 1 for t in vocab}
    spark = docs.sparkSession
    cells = [(name, t, x) for name, w in sorted(vectors.items()) for t, x in w.items()]
    table = F.broadcast(spark.createDataFrame(cells, "name string, term string, weight double"))
    idfs = F.broadcast(spark.createDataFrame(list(idf.items()), "term string, idf double"))
    rare = math.log(1 + n) + 1
    rows = rows.withColumn("row", F.monotonically_increasing_id()).withColumn("dir", F.regexp_extract("path", "^(.*)/[^/]*$", 1))
    lines = rows.select("row", F.posexplode(F.split("text", "\n")).alias("line", "text"))
    lines = lines.select("row", "line", terms_of(F.col("text")).alias("terms")).where(F.arrays_overlap("terms", heavy))
    tf = lines.select("row", "line", F.size("terms").alias("n"), F.explode("terms").alias("term")).groupBy("row", "line", "n", "term").agg(F.count("*").alias("tf"))
    tf = tf.join(idfs, "term", "left").withColumn("w", F.col("tf") * F.coalesce("idf", F.lit(rare)))
    norm = tf.groupBy("row", "line", "n").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    dot = tf.join(table, "term").groupBy("row", "line", "name").agg(F.sum(F.col("w") * F.col("weight")).alias("dot"))
    hit = dot.join(norm, ["row", "line"]).withColumn("cosine", F.round(F.col("dot") / F.col("norm"), 9)).where(F.col("cosine") >= least)
    line = hit.groupBy("row", "line", "n").agg(F.max("cosine").alias("cosine"), F.min_by("name", F.struct(-F.col("cosine"), F.col("name"))).alias("name"))
    own = line.groupBy("row").agg(F.min_by("name", F.struct(-F.col("cosine"), F.col("name"))).alias("own"), F.max("cosine").alias("cosine"), F.count("*").alias("n_lines"), F.sum("n").alias("terms_in"))
    got = rows.select("row", "_id", "path", "dir", F.size(terms_of(F.col("text"))).alias("terms")).join(own, "row", "left")
    runs = block_hits(rows, forms, df, n, least).unionByName(spdx_hits(rows, sorted({name for name, _ in forms})))
    runs = runs.groupBy("row").agg(F.min_by("run", F.struct(-F.col("run.cosine"), F.col("run.name"), -F.col("run.n"))).alias("run"))
    nearer = F.col("run").isNotNull() & (F.col("run.cosine") > F.coalesce("cosine", F.lit(0.0)))
    got = got.join(runs, "row", "left").withColumn("nearer", nearer)
    got = got.select("row", "_id", "path", "dir", "terms", *[F.when(F.col("nearer"), new).otherwise(F.col(c)).alias(c) for c, new in (("own", F.col("run.name")), ("cosine", F.col("run.cosine")), ("n_lines", F.greatest("n_lines", "run.lines")), ("terms_in", F.greatest("terms_in", "run.n")))])
    got = got.withColumn("share", F.when(F.col("terms") > 0, F.coalesce("terms_in", F.lit(0)) / F.col("terms")).otherwise(0.0))
    if licence_file is None:
        licence_file = F.regexp_extract("path", "([^/]*)$", 1).rlike(r"(?i)^(licen[sc]e|copying|notice)(\..*)?$")
    got = stored(got.withColumn("speaks", licence_file & F.col("own").isNotNull()), "licences")
    speaks = got.where("speaks").groupBy("dir").agg(F.min_by("own", F.struct(-F.col("cosine"), F.col("own"))).alias("said"))
    # each directory once, then its ancestors
    dirs = got.select("dir").distinct()
    parts = F.filter(F.split("dir", "/"), lambda p: p != "")
    up = dirs.withColumn("parts", parts).select("dir", F.explode(F.sequence(F.lit(0), F.size("parts"))).alias("depth"), "parts")
    up = up.select("dir", "depth", F.concat(F.when(F.startswith("dir", F.lit("/")), "/").otherwise(""), F.array_join(F.slice("parts", 1, F.col("depth")), "/")).alias("above"))
    near = up.join(speaks.withColumnRenamed("dir", "above"), "above").groupBy("dir").agg(F.max_by("said", "depth").alias("said"), F.max_by("above", "depth").alias("from_dir"))
    out = got.join(near, "dir", "left")
    alone = F.col("own").isNull()
    return out.select(F.col("_id").alias(id_col), "path", "own", "cosine", F.coalesce("n_lines", F.lit(0)).alias("n_lines"), F.coalesce("own", "said").alias("licence"), F.when(alone, F.col("from_dir")).alias("from_dir"))
