"""Licence scans with DataFrame functions only.

Texts are compared with licence notices and licence texts by the cosine of their sparse TF-IDF vectors; document
frequencies of all terms come from all documents.  Three kinds of segments are compared: lines and sentences, and
blocks of lines joined (headers are wrapped) with notices, and whole texts with full licence texts.  A file without a
licence of its own inherits that of the nearest ancestor directory that holds a licence file.

The search is exact and in two steps.  A segment that reaches a cosine shares one of the template's heaviest terms,
so segments without any of them are passed over; the rest is bounded from above by sums that need no vector
norms, and only segments whose bound reaches the threshold get their exact norm, with the corpus frequency of each
of their terms.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from dataclasses import dataclass
from importlib import resources

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from framepatterns.llm.scratch import Scratch

#: Licence notices: fixed values, short forms in common use.
TEMPLATES = (
    ("MIT", "Released under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction."),
    ("MIT", "SPDX-License-Identifier: MIT"),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License."),
    ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License, either version 3 of the License, or any later version."),
    ("GPL-3.0", "SPDX-License-Identifier: GPL-3.0-only"),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met."),
    ("BSD-3-Clause", "SPDX-License-Identifier: BSD-3-Clause"),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related rights to this work. Public domain dedication."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("proprietary", "Copyright. All rights reserved. No part of this work may be reproduced without written permission."),
    ("proprietary", "All rights reserved."),
    # licences and versions that are told apart from the above by one term
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("GPL-2.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License, either version 2 of the License, or any later version."),
    ("GPL-2.0", "SPDX-License-Identifier: GPL-2.0-only"),
    ("LGPL-2.1", "This work is licensed under the GNU Lesser General Public License, version 2.1."),
    ("LGPL-2.1", "SPDX-License-Identifier: LGPL-2.1-only"),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("LGPL-3.0", "SPDX-License-Identifier: LGPL-3.0-only"),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("AGPL-3.0", "SPDX-License-Identifier: AGPL-3.0-only"),
    ("BSD-2-Clause", "SPDX-License-Identifier: BSD-2-Clause"),
    ("MPL-2.0", "SPDX-License-Identifier: MPL-2.0"),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
)
#: A notice that names its licence by one of these groups of terms is only found where all of the group's terms are.
NAMES = {
    "MIT": ("mit",), "Apache-2.0": ("apache",), "MPL-2.0": ("mozilla 2", "mpl 2"), "BSD-3-Clause": ("bsd 3",), "BSD-2-Clause": ("bsd 2",),
    "GPL-2.0": ("gnu general public 2", "gpl 2"), "GPL-3.0": ("gnu general public 3", "gpl 3"), "AGPL-3.0": ("affero 3", "agpl 3"),
    "LGPL-2.1": ("lesser 2 1", "lgpl 2 1"), "LGPL-3.0": ("lesser 3", "lgpl 3"),
    "CC-BY-4.0": ("cc by", "creative commons attribution"), "CC-BY-SA-4.0": ("cc by sa", "sharealike"), "CC-BY-NC-4.0": ("cc by nc", "noncommercial"),
}
#: Kinds of segments.
LINE, HEADER, TEXT = 0, 1, 2
#: Lines that are empty but for comment marks part blocks.
BLOCK = r"\n[ \t\r#*/;%!>-]*\n"
#: Least cosine of a whole text with a full licence text.
WHOLE = 0.8
FILE_NAME = r"(?i)(^|/)(un)?(licen[cs]e|copying)[^/]*$"
#: Ends of lines and sentences; what follows a colon belongs to it.
BREAK = r"\n|(?<=[.!?])[ \t]+(?=[A-Z\"'(])"
SALTS = 16


def terms_of(text: str) -> list[str]:
    """Lower-case runs of letters and digits."""
    out, word = [], ""
    for c in text.lower() + " ":
        if c.isascii() and c.isalnum():
            word += c
        elif word:
            out.append(word)
            word = ""
    return out


VOCABULARY = sorted({t for _, text in TEMPLATES for t in terms_of(text)})


def _full_texts() -> dict[str, str]:
    """Full licence texts; the two without a file differ from a neighbour by a clause and by a name."""
    folder = resources.files("framepatterns.llm") / "license_texts"
    texts = {f.name.removesuffix(".txt"): f.read_text() for f in sorted(folder.iterdir(), key=lambda f: f.name) if f.name.endswith(".txt")}
    texts["BSD-2-Clause"] = re.sub(r"(?s)\n3\. Neither.*?\n\n", "\n\n", texts["BSD-3-Clause"])
    texts["AGPL-3.0"] = re.sub(r"(?i)general\s+public", "Affero General Public", texts["GPL-3.0"])
    return texts


FULL_TEXTS = _full_texts()
FULL_VOCABULARY = sorted({t for text in FULL_TEXTS.values() for t in terms_of(text)})


def _terms(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), "[^a-z0-9]+"), lambda t: t != "")


def term_frequencies(docs: DataFrame) -> DataFrame:
    """(t, n): in how many documents each term occurs; the empty term counts all documents."""
    own = F.array_distinct(F.split(F.lower(F.coalesce("text", F.lit(""))), "[^a-z0-9]+"))
    return docs.select(F.explode(F.concat(F.array(F.lit("")), F.filter(own, lambda t: t != ""))).alias("t")).groupBy("t").agg(F.count("*").alias("n"))


def inverse_frequency(n, total: float):
    """Smoothed inverse document frequency, 1 at least."""
    if isinstance(n, Column):
        return F.ln((1.0 + total) / (1.0 + n)) + 1
    return math.log((1 + total) / (1 + n)) + 1


@dataclass(frozen=True)
class Templates:
    """Unit vectors of the templates of one kind, with the terms that a segment must share."""

    least: float
    vectors: list  # (template, license, term, weight, bit of a term that the template requires)
    required: list  # per template: all bits
    idf: dict
    prefix: list  # a segment without any of these terms reaches ``least`` with no template

    @classmethod
    def weighted(cls, texts: list[tuple[str, str]], idf: dict[str, float], least: float, names: dict | None = None) -> Templates:
        vectors, required, prefix = [], [], set()
        for k, (name, text) in enumerate(texts):
            w = {t: n * idf[t] for t, n in Counter(terms_of(text)).items()}
            norm = math.sqrt(sum(v * v for v in w.values()))
            groups = [g.split() for g in (names or {}).get(name, ()) if set(g.split()) <= set(w)]
            must = groups[0] if groups else []
            vectors += [(k, name, t, v / norm, 1 << must.index(t) if t in must else 0) for t, v in sorted(w.items())]
            required.append((1 << len(must)) - 1)
            rest = 1.0
            for t, v in sorted(w.items(), key=lambda x: (-x[1], x[0])):
                if rest < least * least - 1e-9:
                    break
                prefix.add(t)
                rest -= (v / norm) ** 2
        return cls(least, vectors, required, {t: idf[t] for _, _, t, _, _ in vectors}, sorted(prefix))


def _any_of(terms: list[str]) -> str:
    """A pattern for a text in lower case that has one of the terms as a whole term; branches by first letter."""
    by: dict[str, list[str]] = {}
    for t in terms:
        by.setdefault(t[0], []).append(t[1:])
    branches = "|".join(f"{c}(?:{'|'.join(sorted(rest))})" for c, rest in sorted(by.items()))
    return f"(?<![a-z0-9])(?:{branches})(?![a-z0-9])" if terms else "(?!)"


def _segments(docs: DataFrame, kinds: dict[int, Templates]) -> DataFrame:
    """(doc_id, v, kind, k, terms, words) of the segments that share a prefix term with a template of their kind; v is a hash of the text."""
    low = F.lower(F.col("text"))
    cut = {LINE: lambda: F.split("text", BREAK), HEADER: lambda: F.split("text", BLOCK), TEXT: lambda: F.array("text")}
    every = sorted({t for m in kinds.values() for t in m.prefix})
    found = docs.where(F.regexp(low, F.lit(_any_of(every)))).select("doc_id", "text", F.xxhash64("text").alias("v"), F.size(_terms(F.col("text"))).alias("words"))
    named = lambda kind: lambda s, i: F.struct(F.lit(kind).alias("kind"), i.alias("k"), F.lower(s).alias("s"))
    parts = F.concat(*[F.transform(cut[kind](), named(kind)) for kind in kinds])
    out = found.select("doc_id", "v", "words", F.inline(parts))
    wanted = F.lit(False)
    for kind, m in kinds.items():
        wanted = wanted | ((F.col("kind") == kind) & F.regexp("s", F.lit(_any_of(m.prefix))))
    return out.where(wanted).select("doc_id", "v", "kind", "k", _terms(F.col("s")).alias("terms"), "words")


_SEGMENT = ["doc_id", "v", "kind", "k"]


def similar_segments(docs: DataFrame, scratch: Scratch, notice: float = 0.6, whole: float = WHOLE) -> DataFrame:
    """(doc_id, v, kind, k, n, words, license, score): segments and the templates that they reach the threshold with.

    n is the number of terms in the segment, words that in the document.  A template counts only if the segment
    has the terms that name its licence.
    """
    spark = docs.sparkSession
    frequencies = scratch.save(term_frequencies(docs))
    seen = dict(frequencies.where(F.col("t").isin([*VOCABULARY, *FULL_VOCABULARY, ""])).collect())  # one row a term of the templates at most
    total = seen.get("", 0)
    idf = {t: inverse_frequency(seen.get(t, 0), total) for t in {*VOCABULARY, *FULL_VOCABULARY}}
    kinds = {LINE: Templates.weighted(list(TEMPLATES), idf, notice, NAMES)}
    kinds |= {HEADER: kinds[LINE], TEXT: Templates.weighted(list(FULL_TEXTS.items()), idf, whole)}

    # templates travel to every task; their size is fixed
    rows = [(kind, t, idf[t], k, name, w, bit, kinds[kind].required[k]) for kind in kinds for k, name, t, w, bit in kinds[kind].vectors]
    templates = F.broadcast(spark.createDataFrame(rows, "kind int, t string, idf double, template int, license string, wt double, bit long, required long"))
    limits = F.element_at(F.array(*[F.lit(kinds[k].least) for k in sorted(kinds)]), F.col("kind") + 1)

    tokens = _segments(docs, kinds).select(*_SEGMENT, "words", F.size("terms").alias("n"), F.explode("terms").alias("t"))
    shared = tokens.join(templates, ["kind", "t"]).groupBy(*_SEGMENT, "template", "license", "required", "n", "words").agg(F.sum(F.col("idf") * F.col("wt")).alias("dot"), F.sum(F.col("idf") * F.col("idf") - 1).alias("more"), F.bit_or("bit").alias("bits"))
    # a term that comes tf times adds (tf * idf) ** 2 >= tf * idf ** 2 to the squared norm, and idf >= 1
    bound = F.col("dot") / F.sqrt(F.col("n") + F.col("more"))
    close = scratch.save(shared.where((F.col("bits") == F.col("required")) & (bound >= limits - 1e-9)).select(*_SEGMENT, "template", "license", "n", "words", "dot"))

    renamed = {c: f"_{c}" for c in _SEGMENT}
    same = F.col("doc_id").eqNullSafe(F.col("_doc_id")) & (F.col("v") == F.col("_v")) & (F.col("kind") == F.col("_kind")) & (F.col("k") == F.col("_k"))
    mine = close.select(*_SEGMENT).distinct().withColumnsRenamed(renamed)
    tf = _segments(docs, kinds).join(mine, same, "left_semi").select(*_SEGMENT, F.explode("terms").alias("t")).groupBy(*_SEGMENT, "t").agg(F.count("*").alias("c"))
    weighed = tf.join(frequencies.withColumnRenamed("n", "df"), "t").withColumn("w", F.col("c") * inverse_frequency(F.col("df").cast("double"), float(total)))
    norms = weighed.groupBy(*_SEGMENT).agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    out = close.join(norms.withColumnsRenamed(renamed), same)
    # rows of one id and one text were added up in dot and in norm alike
    out = out.withColumn("score", F.round(F.col("dot") / F.col("norm"), 6)).where(F.col("score") >= limits)
    return out.select(*_SEGMENT, F.col("n").cast("long").alias("n"), F.col("words").cast("long").alias("words"), "license", "score")


def own_licenses(docs: DataFrame, scratch: Scratch, notice: float = 0.6, whole: float = WHOLE) -> DataFrame:
    """(doc_id, v, license, score, share) for each document text with a licence of its own.

    The full text that it is as a whole, or else its best notice; licences of equal score are all named, in
    order, with " OR " between them.  share is the part of its words in notices, 1 for a full text.
    """
    found = scratch.save(similar_segments(docs, scratch, notice, whole).withColumn("text", F.col("kind") == TEXT))
    best = found.groupBy("doc_id", "v").agg(F.max(F.struct("text", "score")).alias("b")).select(F.col("doc_id").alias("_d"), F.col("v").alias("_v"), F.col("b.text").alias("_text"), F.col("b.score").alias("_score"))
    same = F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("v") == F.col("_v"))
    top = found.join(best, same & (F.col("text") == F.col("_text")) & (F.col("score") == F.col("_score")))
    names = top.groupBy("doc_id", "v").agg(F.array_join(F.array_sort(F.collect_set("license")), " OR ").alias("license"), F.max("score").alias("score"))
    covered = found.groupBy("doc_id", "v", "kind", "k", "n", "words").agg(F.max("score")).groupBy("doc_id", "v", "kind").agg((F.sum("n") / F.greatest(F.max("words"), F.lit(1))).alias("part"))
    shares = covered.groupBy(F.col("doc_id").alias("_d"), F.col("v").alias("_v")).agg(F.least(F.max("part"), F.lit(1.0)).alias("share"))
    return names.join(shares, same).select("doc_id", "v", "license", "score", "share")


def parent(path: Column) -> Column:
    return F.when(F.locate("/", path) > 0, F.regexp_replace(path, "/[^/]*$", "")).otherwise(F.lit(""))


def ancestors(folder: Column) -> Column:
    """The folder and all folders above it, the root ("") included."""
    parts = F.filter(F.split(folder, "/"), lambda x: x != "")
    return F.transform(F.sequence(F.lit(0), F.size(parts)), lambda n: F.struct(n.alias("depth"), F.array_join(F.slice(parts, 1, n), "/").alias("folder")))


def nearest_holders(folders: DataFrame, held: DataFrame) -> DataFrame:
    """(folder, inherited_from, from_license): the nearest folder at or above each folder that ``held`` (folder, from_license) has.

    Every folder looks up all folders above it.  The root and other folders near it are above many, so look-ups
    are salted by the folder that asks.
    """
    salt = F.pmod(F.xxhash64("folder"), F.lit(SALTS))
    asked = folders.select(F.col("folder").alias("at"), salt.alias("salt"), F.inline(ancestors(F.col("folder"))))
    copies = held.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    found = asked.join(copies, ["folder", "salt"]).groupBy("at").agg(F.max(F.struct("depth", "folder", "from_license")).alias("b"))
    return found.select(F.col("at").alias("folder"), F.col("b.folder").alias("inherited_from"), F.col("b.from_license").alias("from_license"))


def license_scan(files: DataFrame, least: float = 0.6, file_share: float = 0.2) -> DataFrame:
    """(doc_id, path, own_license, score, license, inherited_from) for every row of ``files`` (doc_id, path, text).

    A file's own licence is the full text that it is as a whole, or else its best notice on a line, in a
    sentence or in a block of lines (see ``own_licenses``).  It is a licence file of its folder if it is a full
    text, if notices fill ``file_share`` of its words or more, or if it has a licence and the name of a licence
    file; of several in one folder the best score counts, then the last name.  license is the file's own
    licence, or else that of the nearest folder at or above its own with a licence file, or null.

    Null and empty texts have no licence of their own; a null path is the root.  Texts are read whole, however
    long.  Rows that repeat a doc_id come back each, with the licence of their own text; a null doc_id is an id
    like others.  An empty table gives an empty result; other columns are ignored.
    """
    docs = files.select("doc_id", F.coalesce("path", F.lit("")).alias("path"), F.col("text").cast("string").alias("text"))
    scratch = Scratch(files.sparkSession, "licenses")
    own = scratch.save(own_licenses(docs, scratch, least)).withColumnsRenamed({"doc_id": "_doc_id", "v": "_v"})
    thin = docs.select("doc_id", "path", F.xxhash64("text").alias("v"), parent(F.col("path")).alias("folder"))
    own_of = F.col("doc_id").eqNullSafe(F.col("_doc_id")) & (F.col("v") == F.col("_v"))
    holders = thin.join(own, own_of).where((F.col("share") >= file_share) | F.regexp("path", F.lit(FILE_NAME)))
    held = scratch.save(holders.groupBy("folder").agg(F.max(F.struct("score", "license")).alias("b")).select("folder", F.col("b.license").alias("from_license")))
    nearest = nearest_holders(thin.select("folder").distinct(), held)
    out = thin.join(own, own_of, "left").join(nearest, "folder", "left")
    has = F.col("license").isNotNull()
    return out.select("doc_id", "path", F.col("license").alias("own_license"), "score", F.coalesce("license", "from_license").alias("license"), F.when(~has, F.col("inherited_from")).alias("inherited_from"))


def document_paths(docs: DataFrame, per_folder: int = 50) -> DataFrame:
    """Documents as files: source / language / shelf of ``per_folder`` neighbours / doc_id."""
    shelf = F.floor(F.col("doc_id") / per_folder).cast("string")
    return docs.select("doc_id", F.concat_ws("/", F.coalesce("source", F.lit("unknown")), F.coalesce("lang", F.lit("unknown")), shelf, F.col("doc_id").cast("string")).alias("path"), "text")
