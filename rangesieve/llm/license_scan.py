"""License scan with MinHash bands over overlapping text windows, on DataFrame functions alone.

A template of n shingles is looked for in windows of 2n shingles that start every n, so any run of n shingles lies
whole in a window and the window's similarity to a template that it holds is 1/2, or 2/5 where a fifth of the shingles
was changed. BANDS bands of one least hash each collide with probability 1 - (1 - 2/5)^BANDS at least, which is
0.999995 for 24. A window that collides in a band is verified: the share of the template's distinct shingles that it
contains must reach CONTAINED.

A window collides only if it holds a template's least shingle of some band, and those shingles are a fixed list; so
the first pass over the text is a search for that list, and windows are formed only around its hits. Shingles have
five words (fewer only for templates of fewer words).

Defined cases: null and empty texts have no windows; a text shorter than a window is one window; repeated rows are
scanned alike and yield rows of their own count; equally good windows count once, the first by position; extra
columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rangesieve.llm.common import SHINGLE_WORDS, own

BANDS = 24
CONTAINED = 0.8

#: Notices as public licenses word them.
TEMPLATES = {
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0.", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0'],
    "MIT": ["Released under the MIT License.", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction"],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3.", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "CC-BY-4.0": ["This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "BSD-3-Clause": ["Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"],
    "ISC": ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."],
}


def _words(text: str) -> list[str]:
    import re

    return re.findall(r"[^\W_]+", text.lower())


def _shingles(text: str) -> list[str]:
    w = _words(text)
    return [" ".join(w[i : i + SHINGLE_WORDS]) for i in range(max(1, len(w) - SHINGLE_WORDS + 1))]


def template_rows() -> list[tuple[str, int, str, list[str]]]:
    """(license, number, text, shingles) of every template."""
    return [(name, i, t, _shingles(t)) for name, texts in TEMPLATES.items() for i, t in enumerate(texts)]


def _band_hashes(shingles: Column) -> Column:
    """The least hash of each band over an array of shingles."""

    def least(band: int) -> Column:
        return F.array_min(F.transform(shingles, lambda s: F.xxhash64(s, F.lit(band))))

    return F.array(*[least(b) for b in range(BANDS)])


def template_bands(spark: SparkSession) -> DataFrame:
    """license, number, n (shingles), shingles, bands: as many rows as there are templates."""
    rows = spark.createDataFrame([(k, i, len(s), s) for k, i, _, s in template_rows()], "license string, number int, n int, shingles array<string>")
    return rows.select("license", "number", "n", F.array_distinct("shingles").alias("shingles"), _band_hashes(F.col("shingles")).alias("bands"))


def _least_shingles(bands: DataFrame) -> list[str]:
    """The shingles that are some template's least one in some band."""
    least = bands.select(F.explode("shingles").alias("s"), "bands").select("s", F.posexplode("bands").alias("b", "h")).where(F.col("h") == F.xxhash64("s", "b"))
    return sorted(r.s for r in least.select("s").distinct().collect())  # at most templates times BANDS


def scan_licenses(docs: DataFrame) -> DataFrame:
    """One row for each document and license found: doc_id, license, contained (best share), first_word (of the window), times (windows that hold it)."""
    spark = docs.sparkSession
    bands = template_bands(spark).cache()
    hits = _least_shingles(bands)
    sizes = sorted({len(s) for _, _, _, s in template_rows()})
    text = F.regexp_replace(F.lower("text"), r"[^\p{L}\p{N}]+", " ")
    plain = own(docs, "doc_id", "text").where("text is not null").select("doc_id", F.concat(F.lit(" "), text, F.lit(" ")).alias("plain"))
    some = plain.where(F.col("plain").rlike(" (?:" + "|".join(hits) + ") "))
    worded = some.select("doc_id", F.filter(F.split("plain", " "), lambda w: w != "").alias("w"))
    shingled = worded.select("doc_id", F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - SHINGLE_WORDS + 1, F.lit(1))), lambda i: F.array_join(F.slice(F.col("w"), i, SHINGLE_WORDS), " ")).alias("s"))
    wanted = F.array(*[F.lit(h) for h in hits])
    at = F.filter(F.transform("s", lambda x, i: F.when(F.array_contains(wanted, x), i)), lambda i: i.isNotNull())
    # Windows of each size around the hits: number k covers the shingles from k * n on, 2n of them.
    around = F.array_distinct(F.flatten(F.transform(F.array(*[F.lit(n) for n in sizes]), lambda n: F.flatten(F.transform(F.col("at"), lambda i: F.filter(F.array(F.struct(n.alias("n"), (i / n).cast("int").alias("k")), F.struct(n.alias("n"), ((i / n).cast("int") - 1).alias("k"))), lambda x: x.k >= 0))))))
    windows = shingled.withColumn("at", at).withColumn("row", F.monotonically_increasing_id()).withColumn("x", F.explode(around))
    cut = windows.select("row", "doc_id", F.col("x.n").alias("n"), F.col("x.k").alias("k"), F.slice("s", F.col("x.k") * F.col("x.n") + 1, 2 * F.col("x.n")).alias("held"))
    banded = cut.withColumn("mine", _band_hashes(F.col("held")))
    t = bands.select("license", "number", F.col("n").alias("t_n"), F.col("shingles").alias("wants"), F.col("bands").alias("theirs"))
    # The templates are a fixed list of a few rows.
    met = banded.join(F.broadcast(t), F.col("n") == F.col("t_n")).where(F.exists(F.zip_with("mine", "theirs", lambda a, b: a == b), lambda x: x))
    share = F.size(F.array_intersect("held", "wants")) / F.size("wants")
    found = met.select("row", "doc_id", "license", share.alias("contained"), (F.col("k") * F.col("n")).cast("long").alias("first_word")).where(F.col("contained") >= CONTAINED)
    best = found.groupBy("row", "doc_id", "license").agg(F.max("contained").alias("contained"), F.min("first_word").alias("first_word"), F.count_distinct("first_word").alias("times"))
    return best.select("doc_id", "license", "contained", "first_word", "times")


def _literal(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def oracle() -> str:
    """The same result by containment in every window, without hashes."""
    rows = ", ".join(f"({_literal(k)}, {i}, {_literal(s)}, {len(sh)}, {len(set(sh))})" for k, i, _, sh in template_rows() for s in sorted(set(sh)))
    return rf"""
WITH t(license, number, s, n, n_distinct) AS (VALUES {rows}),
toks AS (SELECT doc_id, row_number() OVER () AS r, regexp_extract_all(lower(text), '[\p{{L}}\p{{N}}]+') AS w FROM documents),
sh AS (
  SELECT r, doc_id, i - 1 AS p, array_to_string(w[i : i + {SHINGLE_WORDS - 1}], ' ') AS s
  FROM (SELECT r, doc_id, w, unnest(range(1, greatest(len(w) - {SHINGLE_WORDS - 2}, 2))) AS i FROM toks)),
hit AS (SELECT r, doc_id, license, number, n, n_distinct, p, sh.s FROM sh JOIN t ON sh.s = t.s),
win AS (
  SELECT r, doc_id, license, number, n, n_distinct, k, count(DISTINCT s) AS c
  FROM (SELECT *, p // n AS k FROM hit UNION ALL SELECT *, p // n - 1 AS k FROM hit WHERE p >= n)
  GROUP BY ALL)
SELECT doc_id, license, max(c::DOUBLE / n_distinct) AS contained, min(k * n)::BIGINT AS first_word, count(DISTINCT k * n) AS times
FROM win WHERE c::DOUBLE / n_distinct >= {CONTAINED} GROUP BY r, doc_id, license
"""
