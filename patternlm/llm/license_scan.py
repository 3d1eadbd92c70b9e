"""License scan by MinHash bands over overlapping text windows, then exact shingle containment (built-in functions only).

Words are runs of letters and digits, lower-cased (A-Z); a shingle is the 64-bit hash of five words. Texts are covered by windows of 1, 2, 4 and 8
shingles that start every half window (windows of a document) or at every shingle (windows of a template). A band is one MinHash value of a
window: the minimum of its shingles under one random xor mask; a window that shares 6 of 8 shingles (similarity 0.6) collides in one of
`bands(0.6, 0.005)` bands with probability 0.995. Every template is retrieved by the windows of one width, the widest for which a text that contains
enough of it has a window inside an untouched run (`width_of`): such a window equals one of the template's and collides for certain. A
statement of five words is one shingle, which is its own window and MinHash. A retrieved template is verified against the whole document: the
share of its distinct shingles found there.

Everything is one projection per row: no shuffle, and only the template table (driver-side, a parameter) is shipped. Templates need five words at
least (ValueError). Null, empty and short texts have no shingle and match nothing; repeated rows match each by itself; an empty table or template
list gives no rows; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import math
import random
import re
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from patternlm.llm.common import ascii_lower, column, let

WORDS = 5
LEAST = 0.8
WIDTHS = (1, 2, 4, 8)

# Public license statements.
TEMPLATES = {
    "MIT": "Released under the MIT License.",
    "Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "MIT-grant": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "ISC-grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "Apache-2.0-notice": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
    "BSD-conditions": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "MPL-2.0-notice": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at",
    "CC-BY-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "Unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "LGPL-2.1-notice": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.",
    "GPL-3.0-notice": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
}
NOT_WORD = r"[^\p{L}\p{N}]+"


def bands(similarity: float, miss: float) -> int:
    """The least number of one-row bands that miss a pair of this similarity with at most this probability."""
    return math.ceil(math.log(miss) / math.log(1 - similarity))


BANDS = bands(0.6, 0.005)
_RANDOM = random.Random(7)
MASKS = [_RANDOM.getrandbits(64) - (1 << 63) for _ in range(BANDS)]


def scan_words(text: Column) -> Column:
    """Words without the empty strings that separators at either end leave."""

    def trimmed(w: Column) -> Column:
        skip = F.when(F.get(w, F.lit(0)) == "", 1).otherwise(0)
        last = F.when((F.size(w) > 1) & (F.get(w, F.size(w) - 1) == ""), 1).otherwise(0)
        return F.slice(w, skip + 1, F.greatest(F.size(w) - skip - last, F.lit(0)))

    return let(F.split(ascii_lower(F.coalesce(text, F.lit(""))), NOT_WORD), trimmed)


def _joined(a: Column, b: Column, skip: int) -> Column:
    """Hashes of a[i] with b[i + skip], as far as both go."""
    n = F.greatest(F.size(b) - skip, F.lit(0))
    return F.zip_with(F.slice(a, 1, n), F.slice(b, skip + 1, n), lambda x, y: F.xxhash64(x, y))


def shingles(w: Column) -> Column:
    """Hashes of all runs of five words, in order."""

    def of_hashes(h: Column) -> Column:
        fours = let(let(h, lambda a: _joined(a, a, 1)), lambda two: _joined(two, two, 2))
        return let(fours, lambda f: _joined(f, h, WORDS - 1))

    return let(F.transform(w, lambda x: F.xxhash64(x)), of_hashes)


def width_of(shingles_: int, least: float) -> int:
    """The widest windows that retrieve a template of so many shingles for certain.

    With `least` of them found at most `lost` are not; a change inside the text costs at least four in a row, so the rest lies in few runs, and a
    window of w shingles, starting every half window, lies within a run of w + w/2 - 1.
    """
    lost = shingles_ - math.ceil(least * shingles_ - 1e-9)
    run = -(-(shingles_ - lost) // (lost // 4 + 1))
    return max(w for w in WIDTHS if w == 1 or w + w // 2 - 1 <= run)


def window_bands(s: Column, widths: Sequence[int], keys: dict[int, Column]) -> Column:
    """The band values of windows of s that are among keys[width]: minima of neighbours, doubled from width to width."""

    def one(mask: int) -> Column:
        def pairs(a: Column) -> Column:
            n = F.greatest(F.size(a) - 1, F.lit(0))
            return F.zip_with(F.slice(a, 1, n), F.slice(a, 2, n), lambda x, y: F.least(x, y))

        def doubled(a: Column) -> Column:
            """Windows 0, 2, 4, ... of a, each with the one that begins where it ends."""
            last = F.floor((F.size(a) - 3) / 2).cast("int")
            return F.when(last >= 0, F.transform(F.sequence(F.lit(0), F.greatest(last, F.lit(0))), lambda k: F.least(F.get(a, 2 * k), F.get(a, 2 * k + 2)))).otherwise(F.array().cast("array<bigint>"))

        def hits(width: int, a: Column) -> Column:
            found = F.array_intersect(a, keys[width]) if width in widths else F.array().cast("array<bigint>")
            if width >= max(widths):
                return found
            return F.concat(found, let(pairs(a) if width == 1 else doubled(a), lambda b: hits(2 * width, b)))

        return let(F.transform(s, lambda x: x.bitwiseXOR(F.lit(mask))), lambda a: hits(1, a))

    return F.concat(*map(one, MASKS))


def compile_templates(spark: SparkSession, templates: dict[str, str], least: float = LEAST) -> list[tuple[str, int, list[int], list[int]]]:
    """(license, width, retrieval keys, distinct shingles) of each template, hashed by the same expressions as the documents."""
    rows = spark.createDataFrame(list(templates.items()), "license string, text string").select("license", shingles(scan_words(F.col("text"))).alias("s")).collect() if templates else []
    out = []
    for license_, s in rows:
        if not s:
            raise ValueError(f"template {license_!r} has fewer than {WORDS} words")
        w = width_of(len(s), least)
        keys = {min(x ^ m for x in s[i : i + w]) for i in range(len(s) - w + 1) for m in MASKS}
        out.append((license_, w, sorted(keys), list(dict.fromkeys(s))))
    return out


def _longs(values: list[int]) -> Column:
    return F.array(*map(F.lit, values)).cast("array<bigint>") if values else F.array().cast("array<bigint>")


def license_scan(docs: DataFrame, templates: dict[str, str] | None = None, least: float = LEAST, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row for each document and template it contains: doc_id, license, found, of, containment, first_word (from 0)."""
    known = compile_templates(docs.sparkSession, TEMPLATES if templates is None else templates, least)
    table = F.array(*(F.struct(F.lit(i).alias("license"), _longs(k).alias("keys"), _longs(s).alias("shingles")) for i, _, k, s in known)) if known else F.array().cast("array<struct<license:string,keys:array<bigint>,shingles:array<bigint>>>")
    widths = sorted({w for _, w, _, _ in known}) or [1]
    keys = {w: _longs(sorted({k for _, v, own, _ in known if v == w for k in own})) for w in widths}
    hashed = docs.select(column(id_col).cast("long").alias("doc_id"), shingles(scan_words(column(text_col))).alias("s"))
    retrieved = let(window_bands(F.col("s"), widths, keys), lambda h: F.when(F.size(h) > 0, F.filter(table, lambda t: F.arrays_overlap(t["keys"], h))))
    # explode_outer, so that no filter on the array's size is inferred and pushed below, which would compute it twice
    met = hashed.select("doc_id", "s", F.explode_outer(retrieved).alias("t")).where("t IS NOT NULL")
    found = met.select("doc_id", "s", "t", F.size(F.array_intersect(F.col("t.shingles"), F.col("s"))).cast("long").alias("found"), F.size("t.shingles").cast("long").alias("of"))
    first = F.array_position(F.transform("s", lambda x: F.array_contains(F.col("t.shingles"), x)), True) - 1
    return found.where(F.col("found") >= F.lit(least) * F.col("of")).select("doc_id", F.col("t.license").alias("license"), "found", "of", F.round(F.col("found") / F.col("of"), 6).alias("containment"), first.alias("first_word"))


def sql(templates: dict[str, str] | None = None, least: float = LEAST) -> str:
    """Brute force in DuckDB: every document's shingles as text against every template's."""
    values = ", ".join(f"('{i}', '{t.replace(chr(39), chr(39) * 2)}')" for i, t in (templates or TEMPLATES).items())
    low = "translate(coalesce({0}, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    cut = "list_filter(regexp_split_to_array(" + low + r", '[^\p{{L}}\p{{N}}]+'), lambda x: x <> '')"
    runs = f"[array_to_string(w[i : i + {WORDS - 1}], ' ') for i in range(1, len(w) - {WORDS - 2})]"
    return f"""
WITH t AS (SELECT license, {cut.format('body')} AS w FROM (VALUES {values}) AS v(license, body)),
ts AS (SELECT license, unnest(list_distinct({runs})) AS sh FROM t),
tn AS (SELECT license, CAST(count(*) AS BIGINT) AS n FROM ts GROUP BY license),
d AS (SELECT doc_id, {cut.format('text')} AS w FROM documents),
ds AS (SELECT doc_id, unnest({runs}) AS sh, unnest(range(0, greatest(len(w) - {WORDS - 1}, 0))) AS pos FROM d),
m AS (SELECT doc_id, license, count(DISTINCT ds.sh) AS found, min(pos) AS first_word FROM ds JOIN ts USING (sh) GROUP BY doc_id, license)
SELECT doc_id, license, CAST(found AS BIGINT) AS found, n AS "of", round(found / n, 6) AS containment, CAST(first_word AS BIGINT) AS first_word
FROM m JOIN tn USING (license) WHERE found >= {least} * n"""


def plain_words(text: str) -> list[str]:
    """scan_words in Python, for tests."""
    import regex

    low = re.sub("[A-Z]", lambda m: m.group().lower(), text)
    return [x for x in regex.split(NOT_WORD, low) if x]
