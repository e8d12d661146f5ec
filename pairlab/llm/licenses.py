"""License scans in DataFrame functions: MinHash bands retrieve templates, shingle containment verifies them.

Words are runs of a-z and 0-9 in the lower-cased text; shingles are ``shingle`` of them in a row.  Templates fall
into size classes; a class reads a text in windows of twice its size, each starting half a window
after the last, so a passage as long as a template lies whole in one of them.  A window's MinHash values, one
per band of one row, meet the templates' values; with Jaccard similarity s the chance to miss is
(1 - s) ^ bands, under 10^-7 for a template of one shingle in a window of twelve with the default 192 bands.  Candidates are verified: the share of the
template's shingles in the window must reach ``percent``.  A window without any shingle of any template can
meet none, so only the others are hashed.  A template of fewer words than a shingle is one shingle of all its
words, and is met by runs of as many words.

Defined results: null or empty text has no match; rows that repeat get equal results; extra columns are
ignored; an empty table gives an empty result; very long texts cost in proportion to their words.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Notices of common public licenses, in their usual words.
TEMPLATES = {
    "mit_notice": "Released under the MIT License.",
    "mit": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction",
    "apache_notice": "Licensed under the Apache License, Version 2.0.",
    "apache": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License.",
    "gpl3_notice": "This work is licensed under the GNU General Public License, version 3.",
    "gpl": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
    "cc_by_nc_notice": "Licensed under CC BY-NC 4.0.",
    "cc_by": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "bsd": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted",
    "mpl": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "rights_reserved": "All rights reserved. No part of this publication may be reproduced",
}

#: Notices that stand alone in a line, shorter than a shingle.
NOTICES = {"rights_reserved_notice": "All rights reserved."}


def words_of(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), "[^a-z0-9]+"), lambda w: w != "")


def _let(value: Column, body) -> Column:
    """body(value) with value evaluated once, whatever the optimizer moves."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _shingles(words: Column, shingle: int) -> Column:
    """Their hashes; of too few words none."""
    runs = F.sequence(F.lit(1), F.size(words) - (shingle - 1))
    return F.when(F.size(words) < shingle, F.array().cast("array<bigint>")).otherwise(F.transform(runs, lambda i: F.xxhash64(*(F.element_at(words, i + k) for k in range(shingle)))))


def template_table(spark: SparkSession, templates: dict[str, str], shingle: int = 5, bands: int = 192) -> tuple[DataFrame, DataFrame]:
    """template, c (size class), g (words in a shingle), t (shingles); and these with m (MinHash values). A template without words is an error."""
    words = {k: re.findall("[a-z0-9]+", v.lower()) for k, v in templates.items()}
    empty = [k for k, w in words.items() if not w]
    if empty:
        raise ValueError(f"templates without words: {empty}")
    size = {k: min(shingle, len(w)) for k, w in words.items()}
    rows = [(k, math.ceil(math.log2(len(w))), size[k], w[i : i + size[k]]) for k, w in words.items() for i in range(len(w) - size[k] + 1)]
    runs = spark.createDataFrame(rows, "template string, c int, g int, w array<string>").distinct()
    # the hash passes over the nulls after a short one
    hashed = runs.select("template", "c", "g", F.xxhash64(*(F.get("w", F.lit(k)) for k in range(shingle))).alias("x"))
    known: dict[tuple, set] = {}
    for r in hashed.collect():  # as many as the templates have words
        known.setdefault((r["template"], r["c"], r["g"]), set()).add(r["x"])
    table = spark.createDataFrame([(*k, sorted(x)) for k, x in sorted(known.items())], "template string, c int, g int, t array<long>")
    m = F.transform(F.sequence(F.lit(1), F.lit(bands)), lambda b: F.array_min(F.transform("t", lambda x: F.xxhash64(x, b))))
    return table, table.withColumn("m", m)


def scan(docs: DataFrame, templates: dict[str, str] | None = None, percent: int = 80, shingle: int = 5, bands: int = 192, group: int = 500) -> DataFrame:
    """doc_id, template, start (word), percent: the verified matches, one row per document, template and window. Texts are read once for
    each group templates."""
    spark = docs.sparkSession
    templates = TEMPLATES if templates is None else templates
    if len(templates) > group:  # the shingles of a group stand in the plan, and its band table is broadcast
        names, out = sorted(templates), None
        for k in range(0, len(names), group):
            one = scan(docs, {n: templates[n] for n in names[k : k + group]}, percent, shingle, bands, group)
            out = one if out is None else out.union(one)
        return out
    plain, table = template_table(spark, templates, shingle, bands)
    known = plain.collect()  # group templates at most
    sizes = sorted({r["g"] for r in known})
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")

    def windows(words: Column, size: int) -> Column:
        """All windows with a template's shingle of size words: struct<c, g, start, s (shingles)>; class c has 2 * 2^c words from multiples of 2^c."""
        universe = sorted({x for r in known if r["g"] == size for x in r["t"]})
        classes = sorted({r["c"] for r in known if r["g"] == size})

        def around(x: Column) -> Column:
            parts = []
            for c in classes:
                step = 2**c
                blocks = F.array_distinct(F.flatten(F.transform(x["hits"], lambda i: F.array(F.floor(i / step), F.floor(i / step) - 1))))
                parts.append(F.transform(F.filter(blocks, lambda k: k >= 0), lambda k: F.struct(F.lit(c).alias("c"), F.lit(size).alias("g"), (k * step).cast("int").alias("start"), F.array_distinct(F.slice(x["all"], (k * step).cast("int") + 1, 2 * step - size + 1)).alias("s"))))
            return F.concat(*parts)

        def hits(all: Column) -> Column:
            places = F.filter(F.transform(all, lambda h, i: F.when(h.isin(universe), i)), lambda i: i.isNotNull())
            return F.struct(all.alias("all"), places.alias("hits"))

        return _let(_let(_shingles(words, size), hits), around)

    found = _let(words_of(F.coalesce("text", F.lit(""))), lambda w: F.concat(*(windows(w, g) for g in sizes)))
    # an outer explode: for an inner one the optimizer would test, and so compute, the windows beforehand
    rows = slim.select("doc_id", F.monotonically_increasing_id().alias("rid"), F.explode_outer(found).alias("x")).filter("x is not null").select("doc_id", "rid", "x.*")
    # bands meet: an equi-join of (class, band, value), then each window and template once
    bands_of = lambda df, *keys: df.select(*keys, F.posexplode(F.col("m")).alias("band", "value"))
    hashed = F.transform(F.sequence(F.lit(1), F.lit(bands)), lambda b: F.array_min(F.transform("s", lambda x: F.xxhash64(x, b))))
    met = bands_of(rows.withColumn("m", hashed), "doc_id", "rid", "c", "g", "start", "s").join(F.broadcast(bands_of(table, "c", "g", "template")), ["c", "g", "band", "value"])
    met = met.groupBy("rid", "c", "g", "start", "template").agg(F.first("doc_id").alias("doc_id"), F.first("s").alias("s"))
    pairs = met.join(F.broadcast(plain.select("template", "t")), "template")
    share = 100 * F.size(F.array_intersect("s", "t")) / F.size("t")
    return pairs.select("doc_id", "template", "start", share.alias("percent")).filter(F.col("percent") >= percent)


def summary(docs: DataFrame, **options) -> DataFrame:
    """doc_id, template, n_windows, best (percent) of every document and template that match."""
    return scan(docs, **options).groupBy("doc_id", "template").agg(F.count("*").alias("n_windows"), F.max("percent").alias("best"))
