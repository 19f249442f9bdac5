"""Licence scans: TF-IDF cosine of passages to licence templates, inheritance along directories."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from semjoin.llm.common import materialize, small

#: Licence notices, several to a licence; short licences in full are FULL_TEXTS.
TEMPLATES = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License."),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or any later version."),
    ("GPL-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License, version 2."),
    ("LGPL-3.0", "Licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "Licensed under the GNU Affero General Public License, version 3."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related rights to this work."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
    ("ISC", "Permission to use, copy, modify, and distribute this software for any purpose with or without fee is hereby granted."),
)
_MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:
The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.
THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
_ISC = """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.
THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""
_BSD = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:
1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.
2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.
%sTHIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
_THIRD = "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.\n"
#: Licences in full.
FULL_TEXTS = (("MIT", _MIT), ("ISC", _ISC), ("BSD-2-Clause", _BSD % ""), ("BSD-3-Clause", _BSD % _THIRD))
_FILE_NAME = r"(?i)(^|/)(licen[cs]e|copying|unlicense|notice)(\.[a-z]+)?$"
_SENTENCE_END = "([.!?;])[ \t]+"
#: What parts paragraphs: a line without letters and digits, blank or a mark of comments alone.
_PARAGRAPH_END = r"\r?\n(?:[^\p{L}\p{N}\n]*\n)+"
_NOT_TERM = "[^a-z0-9]+"


def terms_of(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), _NOT_TERM), lambda x: x != "")


def passages_of(text: Column) -> Column:
    """What is compared: each line and sentence, each paragraph (a notice wrapped over lines is one), and the whole text."""
    lines = F.split(F.regexp_replace(text, _SENTENCE_END, "$1\n"), "\n")
    return F.array_distinct(F.concat(lines, F.split(text, _PARAGRAPH_END), F.array(text)))


def template_terms(spark: SparkSession, notices: tuple = TEMPLATES, full: tuple = FULL_TEXTS) -> DataFrame:
    """(template, licence, whole, term, tf) of the notices, and of the licences in full, whose `whole` is true."""
    every = [(*x, False) for x in notices] + [(*x, True) for x in full]
    rows = F.array(*[F.struct(F.lit(i).alias("template"), F.lit(name).alias("licence"), F.lit(whole).alias("whole"), F.lit(text).alias("text")) for i, (name, text, whole) in enumerate(every)])
    each = spark.range(1).select(F.explode(rows).alias("x")).select("x.template", "x.licence", "x.whole", F.explode(terms_of(F.col("x.text"))).alias("term"))
    return each.groupBy("template", "licence", "whole", "term").agg(F.count(F.lit(1)).alias("tf"))


def weight(tf: Column, df: Column, n: Column) -> Column:
    return (1 + F.log(tf)) * (F.log((n + 1) / (df + 1)) + 1)


def passages_with_licence(docs: DataFrame, min_cosine: float = 0.8, notices: tuple = TEMPLATES, full: tuple = FULL_TEXTS) -> DataFrame:
    """(k1, k2, licence, cosine, file): the best licence of each text of docs (k1, k2, text) that has a
    passage (passages_of) with a cosine of min_cosine or more to a template; file tells that the whole text has it to a
    licence in full.

    Document frequencies of the templates' terms are counted over all of docs; other terms weigh as unseen.
    A passage can reach min_cosine only if it has one of a template's heaviest terms, those whose rest weighs
    less than min_cosine of the template; only such passages are scored, which loses none.
    """
    spark = docs.sparkSession
    tf = materialize(template_terms(spark, notices, full), "notices")
    vocabulary = sorted(r["term"] for r in tf.select("term").distinct().collect())
    n_docs = docs.agg(F.count(F.lit(1)).alias("n")).first()["n"]
    vocab = F.array(*[F.lit(t) for t in vocabulary])
    df = docs.select(F.explode(F.array_intersect(terms_of(F.col("text")), vocab)).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    n = F.lit(float(n_docs))
    weighted = tf.join(F.broadcast(df), "term", "left").select("template", "licence", "whole", "term", weight(F.col("tf"), F.coalesce("df", F.lit(0)), n).alias("w"), F.coalesce("df", F.lit(0)).alias("df"))
    rest = Window.partitionBy("template").orderBy("w", "term").rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy("template")
    weighted = materialize(weighted.select("*", F.sqrt(F.sum(F.col("w") ** 2).over(whole)).alias("norm"), F.sqrt(F.sum(F.col("w") ** 2).over(rest)).alias("rest")), "weights")
    # The terms whose rest still reaches min_cosine are heavy, and one more, as sums of doubles are not exact.
    heavy = sorted(r["term"] for r in weighted.where(F.col("rest") >= (min_cosine - 1e-6) * F.col("norm")).select("term").distinct().collect())
    heavy_terms = F.array(*[F.lit(t) for t in heavy]).cast("array<string>")

    texts = docs.where(F.arrays_overlap(terms_of(F.col("text")), heavy_terms)).dropDuplicates(["k1", "k2"])
    cut = texts.select("k1", "k2", F.length("text").alias("size"), F.posexplode(passages_of(F.col("text"))).alias("at", "passage"))
    cut = cut.select("k1", "k2", "at", (F.length("passage") == F.col("size")).alias("all"), terms_of(F.col("passage")).alias("terms")).where(F.arrays_overlap("terms", heavy_terms))
    each = cut.select("k1", "k2", "at", "all", F.explode("terms").alias("term"))
    counted = each.groupBy("k1", "k2", "at", "all", "term").agg(F.count(F.lit(1)).alias("tf"))
    known = weighted.select("term", "df").distinct()
    own = counted.join(F.broadcast(known), "term", "left").withColumn("w", weight(F.col("tf"), F.coalesce("df", F.lit(0)), n)).drop("df", "tf")
    key = ["k1", "k2", "at", "all"]
    norms = own.groupBy(*key).agg(F.sum(F.col("w") ** 2).alias("n2"))
    dots = own.join(F.broadcast(weighted.select("template", "licence", "whole", "term", F.col("w").alias("tw"), "norm")), "term").groupBy(*key, "template", "licence", "whole", "norm").agg(F.sum(F.col("w") * F.col("tw")).alias("dot"))
    cos = dots.join(norms, key).select(*key, "template", "licence", "whole", F.round(F.col("dot") / (F.col("norm") * F.sqrt("n2")), 6).alias("cosine")).where(F.col("cosine") >= min_cosine)
    best = cos.groupBy("k1", "k2").agg(F.max(F.struct("cosine", -F.col("template"), "licence")).alias("b"), F.bool_or(F.col("all") & F.col("whole")).alias("file"))
    return best.select("k1", "k2", "b.licence", "b.cosine", "file")


def licences(docs: DataFrame, path: Column, min_cosine: float = 0.8, id_col: str = "doc_id", text_col: str = "text", **templates) -> DataFrame:
    """One row per row of docs: doc_id, path, licence, cosine, how (own, inherited, none), from_dir.

    A document has its own licence if a passage of it is a notice (see passages_with_licence). A document with a
    licence is a licence file if its name says so or all of it is a licence in full; the best one of a
    directory (highest cosine, then the smallest id) licenses the directory. A document without a licence of its own
    inherits that of its nearest ancestor directory. Ancestors are formed for distinct directories, not
    for documents. A document without a path (null) is in no directory: it neither gives nor inherits. Null texts are
    empty; equal rows get equal results; extra columns are not read.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    keyed = docs.select(F.col(id_col).alias("doc_id"), path.alias("path"), text.alias("text"), F.xxhash64(text).alias("k1"), F.xxhash64(text, F.lit("second")).alias("k2"))
    found = materialize(passages_with_licence(keyed.select("k1", "k2", "text"), min_cosine, **templates), "found")
    folder = F.when(F.col("path").contains("/"), F.regexp_replace("path", "/[^/]*$", "")).when(F.col("path").isNotNull(), F.lit(""))
    rows = materialize(keyed.select("doc_id", "path", "k1", "k2", folder.alias("dir")), "paths")
    own = rows.join(small(found, 200_000), ["k1", "k2"], "left")
    files = own.where(F.col("licence").isNotNull() & F.col("dir").isNotNull() & (F.col("path").rlike(_FILE_NAME) | F.col("file")))
    dirs = files.groupBy("dir").agg(F.max_by(F.struct("licence", "cosine"), F.struct("cosine", -F.coalesce("doc_id", F.lit(2**62)), "licence")).alias("f")).select(F.col("dir").alias("from_dir"), F.col("f.licence").alias("f_licence"), F.col("f.cosine").alias("f_cosine"))
    parts = F.split("dir", "/")
    ups = rows.where("dir is not null").select("dir").distinct().select("dir", F.explode(F.transform(F.sequence(F.lit(0), F.size(parts)), lambda i: F.array_join(F.slice(parts, F.lit(1), i), "/"))).alias("from_dir")).distinct()
    nearest = ups.join(dirs, "from_dir").groupBy("dir").agg(F.max_by(F.struct("from_dir", "f_licence", "f_cosine"), F.length("from_dir")).alias("f"))
    nearest = materialize(nearest, "dirs")
    out = own.join(small(nearest, 200_000), "dir", "left")
    mine = F.col("licence").isNotNull()
    return out.select(
        "doc_id", "path", F.coalesce("licence", "f.f_licence").alias("licence"), F.coalesce("cosine", "f.f_cosine").alias("cosine"),
        F.when(mine, "own").when(F.col("f").isNotNull(), "inherited").otherwise("none").alias("how"), F.when(mine, F.col("dir")).otherwise(F.col("f.from_dir")).alias("from_dir"))
