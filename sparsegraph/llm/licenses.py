"""License scans by conditional compression.

Candidate blocks come from the templates themselves. A template of which at most k words may be edited is cut into k + 1 runs
of words; k edits leave at least one run whole, so every stretch within the allowed edits holds one. All runs of all templates
are searched at once, in the text as lower-cased words, whatever lines, paragraphs or comment marks it runs over; each opens a
window of a template length on either side. In a window that holds enough of a template's words, the stretch that is the
fewest word edits away from the template is aligned with it, and must be within the allowed number of edits. The stretch,
without the text around it, which would drown its saving, is compressed alone and with the template as zstandard raw
dictionary; the share of its bytes that the template saves must reach a least value and ranks the templates. Reported are the
byte offsets of the stretch, the saving and the exact differences.

Null and empty texts have no windows. Ties between templates go to more words explained (equal ones less edits), then to the
larger saving, then to the longer template, then to the name; of overlapping notices only those go that a better one covers, all
others are reported, each with its own stretch. Repeated rows are scanned each for itself. Very long texts are
scanned whole. Other columns stay as they are."""

from __future__ import annotations

import re
from array import array
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows, schema_of

LEVEL = 3

# Public license notices and grants, by SPDX identifier.
TEMPLATES = {
    "MIT": [
        "Released under the MIT License.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    ],
    "Apache-2.0": [
        "Licensed under the Apache License, Version 2.0.",
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
    ],
    "GPL-3.0": [
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    ],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "CC-BY-4.0": ["Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "CC-BY-SA-4.0": ["Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."],
    "BSD-3-Clause": ["Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."],
    "ISC": ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."],
    "Unlicense": ["This is free and unencumbered software released into the public domain."],
}
WORD = re.compile(rb"[0-9a-z]+(?:[.-][0-9a-z]+)*")
#: Where a text may be cut without cutting a word.
GAP = re.compile(rb"[^0-9a-z.-]")
#: Bytes of a text that are words in memory at once.
BLOCK = 1 << 20


def words(text: bytes) -> list[bytes]:
    """Lower-cased words; version numbers and hyphenated names are one word."""
    return WORD.findall(text.lower())


def runs(want: list[bytes], most: int) -> list[list[bytes]]:
    """The words cut into most + 1 runs (no more than there are words), of which `most` edits leave one whole."""
    n = min(most + 1, len(want))
    return [want[i * len(want) // n : (i + 1) * len(want) // n] for i in range(n)]


class Scanner:
    def __init__(self, templates: dict[str, list[str]], min_saving: float = 0.25, max_difference: float = 0.15):
        import ahocorasick
        import zstandard

        self.min_saving, self.max_difference = min_saving, max_difference

        plain = zstandard.ZstdCompressor(level=LEVEL, write_content_size=False, write_checksum=False, write_dict_id=False)
        frame = len(plain.compress(b""))
        self.alone = lambda text: len(plain.compress(text)) - frame
        self.templates = []
        for name in sorted(templates):
            for text in templates[name]:
                want = words(text.encode())
                if not want:
                    continue
                raw = b" ".join(want)
                # A raw dictionary must have 8 bytes at least.
                pack = zstandard.ZstdCompressionDict(raw.ljust(8), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
                given = zstandard.ZstdCompressor(level=LEVEL, dict_data=pack, write_content_size=False, write_checksum=False, write_dict_id=False)
                self.templates.append((name, want, Counter(want), lambda text, c=given: len(c.compress(text)) - frame))

        owners: dict[str, set[int]] = {}
        for k, (_, want, *_) in enumerate(self.templates):
            for run in runs(want, self.most(k)):
                owners.setdefault(f" {b' '.join(run).decode()} ", set()).add(k)
        self.longest = max((key.count(" ") - 1 for key in owners), default=0)
        self.automaton = ahocorasick.Automaton()
        for key, ks in owners.items():
            self.automaton.add_word(key, (len(key), tuple(sorted(ks))))
        if owners:
            self.automaton.make_automaton()

    def most(self, k: int) -> int:
        """Word edits that template k may have."""
        return int(self.max_difference * len(self.templates[k][1]))

    def anchors(self, low: bytes) -> dict[int, list[int]]:
        """For each template of which a run occurs in the lower-cased text, the numbers of the words where one begins."""
        import numpy as np

        out: dict[int, set[int]] = {}
        tail: list[bytes] = []
        at = before = 0
        while self.longest and at < len(low):
            cut = GAP.search(low, at + BLOCK)
            to = cut.start() if cut else len(low)
            own = tail + WORD.findall(low, at, to)
            line = f" {b' '.join(own).decode()} "
            hits = list(self.automaton.iter(line))
            if hits:
                spaces = np.flatnonzero(np.frombuffer(line.encode(), np.uint8) == 32)
                first = np.searchsorted(spaces, [end - size + 1 for end, (size, _) in hits]) + (before - len(tail))
                for word, (_, (_, ks)) in zip(first.tolist(), hits, strict=True):
                    for k in ks:
                        out.setdefault(k, set()).add(word)
            before += len(own) - len(tail)
            tail = own[len(own) - min(self.longest - 1, len(own)) :]
            at = to
        return {k: sorted(out[k]) for k in sorted(out)}

    def matches(self, k: int, own: list[bytes], min_saving: float, max_difference: float) -> list[dict]:
        """Disjoint stretches of the words `own` that hold template k, each with the positions of its equal words."""
        name, want, counts, given = self.templates[k]
        most = int(max_difference * len(want))
        held = Counter(own)
        if sum(min(n, held[w]) for w, n in counts.items()) < len(want) - most:
            return []
        out, open_ = [], [(0, len(own))]
        while open_:
            lo, hi = open_.pop()
            found = differences(want, own[lo:hi])
            if not found or found["edits"] > most:
                continue
            at = [lo + i for i in found.pop("at")]
            part = b" ".join(own[at[0] : at[-1] + 1])
            saving = 1 - given(part) / self.alone(part)
            if saving >= min_saving:
                out.append({"license": name, "template": k, "saving": saving, "at": at, **found})
            open_ += [(lo, at[0]), (at[-1] + 1, hi)]
        return out


def differences(want: list[bytes], own: list[bytes]) -> dict | None:
    """The stretch of `own` with the fewest word edits from `want` (the first of several): positions of its equal words;
    words of the template that it lacks; words between its first and last equal word that are not the template's; edits,
    where a word in place of another is one; and both kinds of words as text."""
    rows = [[0] * (len(own) + 1)]
    for i, w in enumerate(want, 1):
        up, row = rows[-1], [i]
        left = i
        for j, o in enumerate(own):
            left = min(up[j] + (w != o), up[j + 1] + 1, left + 1)
            row.append(left)
        rows.append(row)
    i, j = len(want), rows[-1].index(min(rows[-1]))
    edits = rows[i][j]
    steps: list[tuple[int | None, int | None]] = []
    while i:
        if j and rows[i][j] == rows[i - 1][j - 1] + (want[i - 1] != own[j - 1]):
            i, j = i - 1, j - 1
            steps.append((i, j))
        elif rows[i][j] == rows[i - 1][j] + 1:
            i -= 1
            steps.append((i, None))
        else:
            j -= 1
            steps.append((None, j))
    steps.reverse()
    at = [b for a, b in steps if a is not None and b is not None and want[a] == own[b]]
    if not at:
        return None
    changes: list[str] = []
    added = 0
    less: list[str] = []
    more: list[str] = []
    for a, b in [*steps, (None, None)]:
        if (a is None and b is None) or (b is not None and a is not None and want[a] == own[b]):
            changes += less + more
            less, more = [], []
            continue
        if a is not None:
            less.append(f"-{want[a].decode()}")
        if b is not None and at[0] < b < at[-1]:
            more.append(f"+{own[b].decode()}")
            added += 1
    return {"at": at, "missing": len(want) - len(at), "added": added, "edits": edits, "differences": changes}


def windows(hits: list[int], reach: int, n: int) -> Iterator[tuple[int, int]]:
    """(from, to) in words: each of the sorted words `hits` has `reach` words on either side in one window at least, and no
    window is longer than three times that."""
    at = 0
    while at < len(hits):
        to = bisect_right(hits, hits[at] + reach) - 1
        yield max(0, hits[at] - reach), min(n, hits[to] + reach + 1)
        at = to + 1


def notices(text: bytes, scanner: Scanner, seen: dict) -> list[dict]:
    """Confirmed notices of one text in order of their start."""
    low = text.lower()
    anchors = scanner.anchors(low)
    if not anchors:
        return []
    starts, ends = array("q"), array("q")
    for m in WORD.finditer(low):
        starts.append(m.start())
        ends.append(m.end())
    found = []
    for k, hits in anchors.items():
        for lo, hi in windows(hits, len(scanner.templates[k][1]) + scanner.most(k), len(starts)):
            part = low[starts[lo] : ends[hi - 1]]
            if (k, part) not in seen:
                seen[k, part] = scanner.matches(k, words(part), scanner.min_saving, scanner.max_difference)
            found += [{**f, "at": [lo + i for i in f["at"]], "start": starts[lo + f["at"][0]], "end": ends[lo + f["at"][-1]]} for f in seen[k, part]]
    found.sort(key=lambda f: (f["edits"] - len(f["at"]), -f["saving"], -len(scanner.templates[f["template"]][1]), f["license"], f["start"]))
    return sorted(chosen(found), key=lambda f: (f["start"], f["end"]))


def chosen(found: list[dict]) -> list[dict]:
    """Of matches in order of merit, those that no better one covers. A better one covers what lies within its stretch
    and has most of its equal words in common with it, or any if of the same template (as seen from another window)."""
    owners: dict[int, list[dict]] = {}
    out = []
    for f in found:
        better = {id(g): g for i in f["at"] for g in owners.get(i, ())}
        common = Counter(id(g) for i in f["at"] for g in owners.get(i, ()))
        if any(g["template"] == f["template"] or (g["start"] <= f["start"] and f["end"] <= g["end"] and 2 * common[i] > len(f["at"])) for i, g in better.items()):
            continue
        out.append(f)
        for i in f["at"]:
            owners.setdefault(i, []).append(f)
    return out


FIELDS = ("license", "start", "end", "saving", "missing", "added", "differences")
HITS = "array<struct<license:string,start:int,end:int,saving:double,missing:int,added:int,differences:array<string>>>"


def scan(docs: DataFrame, *, templates: dict[str, list[str]] | None = None, min_saving: float = 0.25, max_difference: float = 0.15, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """docs (or its columns `keep`) plus `licenses`: for each confirmed notice the license, its byte offsets, the saving and
    the exact wording differences."""
    docs = docs.drop("licenses")
    kept = keep or docs.columns
    texts = templates or TEMPLATES
    held: dict[str, Scanner] = {}

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        if not held:
            held["scanner"] = Scanner(texts, min_saving, max_difference)
        scanner = held["scanner"]
        seen: dict[tuple[int, bytes], list[dict]] = {}
        column = []
        for text in batch.column(text_col).cast(pa.binary()).to_pylist():
            found = notices(text, scanner, seen) if text else []
            column.append([{c: f[c] for c in FIELDS} for f in found])
        kind = pa.list_(pa.struct([("license", pa.string()), ("start", pa.int32()), ("end", pa.int32()), ("saving", pa.float64()), ("missing", pa.int32()), ("added", pa.int32()), ("differences", pa.list_(pa.string()))]))
        return pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(column, kind)], names=[*kept, "licenses"])

    return map_rows(docs, run, schema_of(docs.select(*kept), f"licenses {HITS}"))


def by_document(docs: DataFrame) -> DataFrame:
    """(doc_id, n_licenses, licenses, n_differences, best_saving) for every document."""
    s = scan(docs.select("doc_id", "text"), keep=["doc_id"])
    return s.select(
        "doc_id",
        F.size("licenses").cast("long").alias("n_licenses"),
        F.array_join(F.array_sort(F.array_distinct("licenses.license")), ",").alias("licenses"),
        F.aggregate("licenses", F.lit(0).cast("long"), lambda a, x: a + x["missing"] + x["added"]).alias("n_differences"),
        F.round(F.array_max("licenses.saving"), 6).alias("best_saving"),
    )
