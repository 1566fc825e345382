"""License notices found by patience alignment.

A template is sought around each place where one of its telling words stands: so many of its rarest words that a notice
which keeps the least coverage must hold one of them. There the template's words are aligned with the text. The words that occur once in both are matched, the longest run of these that rises in both is kept, and the gaps between them, where
other words have become unique, are aligned in the same way; words next to a matched one are matched while they agree. The
share of the template's words that found a place is its coverage.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from floorcount.llm.scratch import free_name, must_be_free, tidy

#: Notices and openings of public licenses.
TEMPLATES = {
    "apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "apache-2.0-notice": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
    "mit": "Released under the MIT License.",
    "mit-text": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction",
    "gpl-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "gpl-notice": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
    "bsd": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted",
    "mpl-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "cc-by-nc-4.0": "Licensed under CC BY-NC 4.0.",
    "cc-by-4.0": "Licensed under CC BY 4.0.",
    "cc-by-sa-4.0": "Licensed under CC BY-SA 4.0.",
    "all-rights-reserved": "All rights reserved.",
}
LEAST_COVERAGE = 0.8
WORD = re.compile(rb"[0-9a-z\x80-\xff]+")
LOWER = bytes(range(256)).lower()
HITS = T.ArrayType(T.StructType([T.StructField("license", T.StringType()), T.StructField("coverage", T.DoubleType()), T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType())]))


def rising(places: list[int]) -> list[int]:
    """Indexes of a longest strictly rising subsequence."""
    tails: list[int] = []
    ends: list[int] = []
    before: list[int] = []
    for i, x in enumerate(places):
        k = bisect_left(tails, x)
        before.append(ends[k - 1] if k else -1)
        if k == len(tails):
            tails.append(x)
            ends.append(i)
        else:
            tails[k], ends[k] = x, i
    out, at = [], ends[-1] if ends else -1
    while at >= 0:
        out.append(at)
        at = before[at]
    return out[::-1]


def align(text: list, template: list) -> list[tuple[int, int]]:
    """Pairs of places (in text, in template) that patience alignment matches, rising in both."""
    out: list[tuple[int, int]] = []
    gaps = [(0, len(text), 0, len(template))]
    while gaps:
        a, b, c, d = gaps.pop()
        while a < b and c < d and text[a] == template[c]:
            out.append((a, c))
            a, c = a + 1, c + 1
        while a < b and c < d and text[b - 1] == template[d - 1]:
            b, d = b - 1, d - 1
            out.append((b, d))
        if a == b or c == d:
            continue
        wanted = Counter(template[c:d])
        seen = Counter(w for w in text[a:b] if w in wanted)
        at = {text[i]: i for i in range(a, b) if seen.get(text[i]) == 1 and wanted[text[i]] == 1}
        both = [(at[template[j]], j) for j in range(c, d) if template[j] in at]
        anchors = [both[k] for k in rising([i for i, _ in both])]
        if not anchors:
            continue
        edges = [(a - 1, c - 1), *anchors, (b, d)]
        out += anchors
        gaps += [(i + 1, k, j + 1, m) for (i, j), (k, m) in zip(edges, edges[1:])]
    return sorted(out)


class Scanner:
    def __init__(self, templates: dict[str, str] = TEMPLATES):
        self.words = {k: WORD.findall(t.encode().translate(LOWER)) for k, t in templates.items()}
        common = Counter(w for words in self.words.values() for w in set(words))
        # of n places in a template, n - least of any others can go unmatched: one more place than that must be found
        self.least = {k: math.ceil(LEAST_COVERAGE * len(words) - 1e-9) for k, words in self.words.items()}
        self.telling = {k: set(sorted(words, key=lambda w: (common[w], -len(w), w))[: len(words) - self.least[k] + 1]) for k, words in self.words.items()}
        self.needles = {w for ws in self.telling.values() for w in ws}
        self.own = {k: frozenset(words) for k, words in self.words.items()}

    def _width(self, name: str) -> float:
        """Words between the first and the last matched one of a notice are fewer."""
        return 1.5 * len(self.words[name]) + 1

    def _stretches(self, name: str, words: list[bytes], where: dict[bytes, list[int]]) -> set[tuple[int, int]]:
        """Stretches of the text around each telling word that hold enough of the template's words: as wide as an edited notice can
        be, cut where the telling word stands again, as another notice may stand there, and not cut."""
        out: set[tuple[int, int]] = set()
        width, own, least = int(self._width(name)) + 1, self.own[name], self.least[name]
        for needle in self.telling[name]:
            here = where.get(needle, [])
            for k, at in enumerate(here):
                lo, hi = max(at - width, 0), min(at + width + 1, len(words))
                cut = max(lo, here[k - 1] + 1 if k else 0), min(hi, here[k + 1] if k + 1 < len(here) else len(words))
                # a text may repeat a telling word without end, so a stretch that holds too few of the words isn't aligned
                out |= {(a, b) for a, b in {cut, (lo, at + 1), (at, hi), (lo, hi)} if sum(w in own for w in words[a:b]) >= least}
        return out

    def scan(self, text: bytes | None) -> list[tuple[str, float, int, int]]:
        """(license, coverage, first and last character) of each notice; of those that overlap, the one with most words."""
        low = (text or b"").translate(LOWER)
        words = WORD.findall(low)
        there = self.needles.intersection(words)
        if not there:
            return []
        where: dict[bytes, list[int]] = {}
        for i, w in enumerate(words):
            if w in there:
                where.setdefault(w, []).append(i)
        found = []
        for name, template in self.words.items():
            for lo, hi in self._stretches(name, words, where):
                pairs = align(words[lo:hi], template)
                if len(pairs) >= self.least[name] and pairs[-1][0] - pairs[0][0] < self._width(name):
                    found.append((len(pairs), len(pairs) / len(template), name, lo + pairs[0][0], lo + pairs[-1][0]))
        if not found:
            return []
        spans = [m.span() for m in WORD.finditer(low)]
        out: list[tuple[str, float, int, int]] = []
        taken: list[tuple[int, int]] = []
        for _, coverage, name, a, b in sorted(found, key=lambda x: (-x[0], -x[1], x[4] - x[3], x[2], x[3])):
            if all(b < c or a > d for c, d in taken):
                taken.append((a, b))
                out.append((name, coverage, len(text[: spans[a][0]].decode("utf-8", "replace")), len(text[: spans[b][1]].decode("utf-8", "replace"))))
        return sorted(out, key=lambda x: x[2])


_scanner: list[Scanner] = []


def scan(df: DataFrame, text: str = "text", to: str = "licenses") -> DataFrame:
    """df without the text, with an array `to` of (license, coverage, start, end), in the text's order.

    Null and empty texts have none; repeated rows are scanned alike; an empty table gives an empty one. A column of that
    name must not be there.
    """
    must_be_free(df, to)
    rest = [f for f in df.schema.fields if f.name != text]
    schema = T.StructType([*rest, T.StructField(to, HITS)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not _scanner:
            _scanner.append(Scanner())
        kind = pa.list_(pa.struct([("license", pa.string()), ("coverage", pa.float64()), ("start", pa.int32()), ("end", pa.int32())]))
        for batch in batches:
            found = [[dict(zip(("license", "coverage", "start", "end"), x)) for x in _scanner[0].scan(t)] for t in batch.column(batch.num_columns - 1).cast(pa.binary()).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(found, kind)], names=schema.names)

    return df.select(*[F.col(f"`{f.name}`") for f in rest], F.col(f"`{text}`").cast("string").alias(free_name(df, "_text"))).mapInArrow(tidy(run), schema)
