"""Licence scans: MinHash bands over overlapping text windows retrieve templates, exact containment verifies.

Words are runs of letters and digits, lower-cased; shingles are five words. A template with n shingles
belongs to the class of the least power of two S that is not under n. Texts are cut into windows of 2 S
shingles every S, so that every occurrence lies whole in one window; at a containment of 0.8 or more
the Jaccard similarity of template and window is then at least 0.18, and 48 bands of one MinHash value
miss such a pair with a chance under 1e-4 (under 1e-6 for a whole copy). Candidates are verified by the
share of the template's distinct shingles that the window has.

Only windows with an anchor can match: from each template the longest words are taken as anchors until
less than the asked share of its shingles is without one, so whatever reaches that share has an anchor.
That loses nothing and keeps the MinHash work off texts without a word of any licence.

Defined results: a row for each doc_id and template that reaches the threshold; a null or empty text has
none; rows of one doc_id, a null one too, count together; other columns are ignored. Templates of fewer
than five words are refused. Only DataFrame functions are used, the templates being literals.
"""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SHINGLE, THRESHOLD, BANDS = 5, 0.8, 48

#: Wordings of published licences and notices.
TEMPLATES = {
    "apache-2.0-line": "Licensed under the Apache License, Version 2.0.",
    "apache-2.0-notice": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0',
    "mit-line": "Released under the MIT License.",
    "mit-grant": 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software',
    "gpl-3.0-line": "This work is licensed under the GNU General Public License, version 3.",
    "gpl-3.0-notice": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "cc-by-nc-4.0-line": "Licensed under CC BY-NC 4.0.",
    "cc-by-4.0-notice": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "bsd-3-clause-grant": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "mpl-2.0-notice": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "isc-grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "unlicense-grant": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software",
}


def template_words(text: str) -> list[str]:
    return re.sub(r"[^a-z0-9]+", " ", text.lower()).split()


def anchors(templates: dict[str, str], threshold: float = THRESHOLD) -> list[str]:
    """Words of which every text that contains ``threshold`` of a template has at least one."""
    found: set[str] = set()
    for text in templates.values():
        words = template_words(text)
        if len(words) < SHINGLE:
            raise ValueError("a template has five words at least")
        shingles = {tuple(words[i : i + SHINGLE]) for i in range(len(words) - SHINGLE + 1)}
        for word in sorted(set(words), key=lambda w: (w not in found, -len(w), w)):
            if sum(not found.intersection(s) for s in shingles) < threshold * len(shingles):
                break
            found.add(word)
    return sorted(found)


def _words(text: str) -> Column:
    return F.filter(F.split(F.regexp_replace(F.lower(F.col(text)), r"[^\p{L}\p{N}]+", " "), " "), lambda w: w != "")


def _shingles(words: Column) -> Column:
    """Hashes of the shingles of a word array with at least five words; none for fewer."""
    starts = F.when(F.size(words) >= SHINGLE, F.sequence(F.lit(1), F.size(words) - (SHINGLE - 1))).otherwise(F.array().cast("array<int>"))
    return F.array_distinct(F.transform(starts, lambda i: F.xxhash64(F.concat_ws(" ", F.slice(words, i, SHINGLE)))))


def _signature(shingles: Column) -> Column:
    """(band, least hash) packed as one hash, for each band."""

    def band(j: int) -> Column:
        return F.xxhash64(F.lit(j), F.array_min(F.transform(shingles, lambda x: F.xxhash64(x, F.lit(j)))))

    return F.array(*map(band, range(BANDS)))


def scan(docs: DataFrame, templates: dict[str, str] | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, template_id, containment, word_at (first word of the best window) and windows (how many reach the threshold)."""
    templates = TEMPLATES if templates is None else templates
    spark = docs.sparkSession
    marks = anchors(templates, threshold)
    size = {}
    for key, text in templates.items():
        words = template_words(text)
        n = len({tuple(words[i : i + SHINGLE]) for i in range(len(words) - SHINGLE + 1)})
        size[key] = 1 << (n - 1).bit_length()

    rows = F.array(*[F.struct(F.lit(k).alias("template_id"), F.lit(size[k]).alias("span"), F.lit(t).alias("text")) for k, t in sorted(templates.items())])
    wanted = spark.range(1).select(F.explode(rows).alias("t")).select("t.*").withColumn("template", _shingles(_words("text")))
    bands = wanted.select("template_id", "span", "template", F.explode(_signature(F.col("template"))).alias("band"))

    lowered = F.lower(F.col("text"))
    marked = docs.select("doc_id", "text").where(reduce(lambda a, b: a | b, [F.contains(lowered, F.lit(m)) for m in marks]))
    held = marked.select("doc_id", _words("text").alias("words"))
    spots = F.filter(F.transform("words", lambda w, i: F.when(w.isin(marks), i).otherwise(-1)), lambda i: i >= 0)
    held = held.withColumn("spots", spots).where(F.size("spots") > 0)

    def windows(span: int) -> Column:
        near = lambda i: F.sequence(F.greatest(F.lit(0), F.floor((i - (SHINGLE - 1)) / span) - 1), F.floor(i / span))
        return F.transform(F.array_distinct(F.flatten(F.transform("spots", near))), lambda w: F.struct(F.lit(span).alias("span"), (w * span).cast("int").alias("word_at")))

    each = F.explode(F.concat(*[windows(s) for s in sorted(set(size.values()))]))
    cut = held.select("doc_id", "words", each.alias("w")).select("doc_id", F.col("w.span").alias("span"), F.col("w.word_at").alias("word_at"), F.slice("words", F.col("w.word_at") + 1, 2 * F.col("w.span") + (SHINGLE - 1)).alias("part"))
    cut = cut.select("doc_id", "span", "word_at", _shingles(F.col("part")).alias("shingles")).where(F.size("shingles") > 0)
    keyed = cut.select("doc_id", "span", "word_at", "shingles", F.explode(_signature(F.col("shingles"))).alias("band"))
    met = keyed.join(F.broadcast(bands), ["span", "band"])
    share = F.size(F.array_intersect("template", "shingles")) / F.size("template")
    found = met.select("doc_id", "template_id", "word_at", share.alias("containment")).where(F.col("containment") >= threshold)
    best = F.max(F.struct("containment", (-F.col("word_at")).alias("before")))
    out = found.groupBy("doc_id", "template_id").agg(best.alias("best"), F.count_distinct("word_at").alias("windows"))
    return out.select("doc_id", "template_id", F.col("best.containment").alias("containment"), (-F.col("best.before")).alias("word_at"), "windows")
