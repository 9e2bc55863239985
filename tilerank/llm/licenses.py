"""License scan by conditional compression.

A line is a candidate if it has a cue, or if most of its words stand in templates; candidate lines that follow each other, with at
least one cue among them, are a block. Cues come from the templates: of each, so many of its longest words that a match, which may
lack no more than 1 - CONFIRM of the template's words, must hold one of them. No block that could be confirmed lacks a cue.

A block is compressed alone and with each template as a raw zstandard dictionary, and the templates are ranked by the share of the
block that they save. All that a bag-of-words bound admits are then compared word by word in the order of that rank: a template is confirmed
in a stretch of the block, at most SLACK as long as itself, that holds at least CONFIRM of its words in order. The
one that covers its wording best wins (ties go to the better rank), what differs is reported (``exact`` if nothing does but blanks
and case), and the words before, between and after the winner's stretches are judged again until nothing is confirmed; so a
block may hold any number of licenses.

Each text is scanned whole, in one pass without a shuffle. Defined cases: null and empty texts have no blocks; templates that
tie in coverage and rank go by their order; a template's words may be split over lines in any way, with comment marks around
them; repeated rows get a row each; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame

# Fixed wording of public license notices.
NOTICES = {
    "Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "MIT": "Released under the MIT License.",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-2.0": "This work is licensed under the GNU General Public License, version 2.",
    "LGPL-2.1": "This work is licensed under the GNU Lesser General Public License, version 2.1.",
    "AGPL-3.0": "This work is licensed under the GNU Affero General Public License, version 3.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "BSD-3-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.",
    "MIT-grant": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction.",
    "CC-BY-4.0": "Licensed under CC BY 4.0.",
    "CC-BY-SA-4.0": "Licensed under CC BY-SA 4.0.",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "CC-BY-ND-4.0": "Licensed under CC BY-ND 4.0.",
    "CC0-1.0": "To the extent possible under law, the author has waived all copyright under CC0 1.0.",
}
#: Wordings by license: its notice, and the tag that names it.
TEMPLATES = {k: [t, f"SPDX-License-Identifier: {k}"] for k, t in NOTICES.items()}
WORD = re.compile(r"[^\W_]+(?:[.-][^\W_]+)*")
CONFIRM, SLACK, SHARED, LEVEL = 0.7, 1.5, 0.6, 3


@dataclass
class Template:
    license: str
    words: list[str]
    bag: Counter
    least: int
    primed: zstandard.ZstdCompressor


def longest_common(a: list[str], b: list[str]) -> tuple[int, list[tuple[int, int]]]:
    """Length of the longest common subsequence, and the places in ``a`` and ``b`` of one (the last places that do)."""
    rows = [[0] * (len(b) + 1)]
    for x in a:
        before, row = rows[-1], [0]
        for j, y in enumerate(b):
            row.append(before[j] + 1 if x == y else max(before[j + 1], row[j]))
        rows.append(row)
    i, j, places = len(a), len(b), []
    while i and j:
        if a[i - 1] == b[j - 1] and rows[i][j] == rows[i - 1][j - 1] + 1:
            i, j = i - 1, j - 1
            places.append((i, j))
        elif rows[i - 1][j] >= rows[i][j - 1]:
            i -= 1
        else:
            j -= 1
    return rows[-1][-1], places[::-1]


class Scanner:
    def __init__(self, templates: dict[str, list[str]]):
        self.templates: list[Template] = []
        for k, wordings in templates.items():
            for t in wordings:
                words = [w.lower() for w in WORD.findall(t)]
                dictionary = zstandard.ZstdCompressionDict(t.encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
                primed = zstandard.ZstdCompressor(level=LEVEL, write_content_size=False, write_dict_id=False, dict_data=dictionary)
                self.templates.append(Template(k, words, Counter(words), next(n for n in range(len(words) + 1) if n >= CONFIRM * len(words)), primed))
        self.vocabulary = {w for t in self.templates for w in t.words}
        self.plain = zstandard.ZstdCompressor(level=LEVEL, write_content_size=False)
        cues = set()
        for t in self.templates:
            # a match lacks len - least words at most; of one more of them, one is there
            cues.update(sorted(t.words, key=lambda w: (w not in cues, -len(w), w))[: len(t.words) - t.least + 1])
        self.cue = re.compile(r"(?<![^\W_])(?:" + "|".join(re.escape(w) for w in sorted(cues, key=lambda w: (-len(w), w))) + r")(?![^\W_])", re.IGNORECASE)

    def fits(self, line: str) -> bool:
        words = WORD.findall(line)
        return bool(words) and sum(w.lower() in self.vocabulary for w in words) >= SHARED * len(words)

    def blocks(self, text: str | None) -> list[tuple[int, int]]:
        """Spans of candidate blocks, in code points."""
        found, at, done, text = [], 0, 0, text or ""
        while m := self.cue.search(text, at):
            start = max(text.rfind("\n", 0, m.start()) + 1, done)
            while start > done:
                before = max(text.rfind("\n", 0, start - 1) + 1, done)
                if not self.fits(text[before:start]):
                    break
                start = before
            end = text.find("\n", m.end())
            end = len(text) if end < 0 else end
            while end < len(text):
                stop = text.find("\n", end + 1)
                stop = len(text) if stop < 0 else stop
                line = text[end:stop]
                if not (self.cue.search(line) or self.fits(line)):
                    break
                end = stop
            found.append((start, end))
            at = done = end
        return found

    def rank(self, block: str, among: list[Template]) -> list[tuple[Template, float]]:
        """Templates by the share of the compressed size that they save."""
        raw = block.encode("utf-8", "surrogatepass")
        alone = len(self.plain.compress(raw))
        saved = [(t, 1 - len(t.primed.compress(raw)) / alone) for t in among]
        return sorted(saved, key=lambda x: -x[1])

    def stretches(self, t: Template, words: list[str], least: int, once: bool) -> list[tuple[int, int, int, int, int]]:
        """Stretches with ``least`` common words or more: (common, first, last, template's words lacking before, and after). ``once``: the best alone, the first of those with most; else
        all from left to right that don't overlap."""
        width, have, bag, found = int(SLACK * len(t.words)), 0, Counter(), []
        hits = [i for i, w in enumerate(words) if w in t.bag]
        lo = 0
        for hi, i in enumerate(hits):
            w = words[i]
            bag[w] += 1
            have += bag[w] <= t.bag[w]
            while hits[lo] <= i - width:
                out = words[hits[lo]]
                have -= bag[out] <= t.bag[out]
                bag[out] -= 1
                lo += 1
            if have < least:
                continue
            common, places = longest_common(t.words, [words[x] for x in hits[lo : hi + 1]])
            if common < least:
                continue
            (head, a), (tail, b) = places[0], places[-1]
            got = (common, hits[lo + a], hits[lo + b], head, len(t.words) - 1 - tail)
            if once:
                found, least = [got], common + 1
                if common == len(t.words):
                    break
            else:
                found.append(got)
                have, lo = 0, hi + 1
                bag.clear()
        return found

    def judge(self, words: list[str], places: list[tuple[int, int]], block: str) -> list[dict]:
        """Confirmed licenses of a block's words, in order; ``places`` are their spans in ``block``."""
        out, open_ = [], [(0, len(words))]
        while open_:
            lo, hi = open_.pop()
            part = words[lo:hi]
            bag = Counter(part)
            among = [t for t in self.templates if sum((bag & t.bag).values()) >= t.least]
            best = None
            for t, saved in self.rank(block[places[lo][0] : places[hi - 1][1]], among) if among else ():
                for common, first, last, _, _ in self.stretches(t, part, t.least, True):
                    score = (common / len(t.words), -(len(t.words) + last - first + 1 - 2 * common))
                    if best is None or score > best[0]:
                        best = (score, t, saved, common)
            if best is None:
                continue
            score, t, saved, least = best
            done = 0
            for common, first, last, head, tail in self.stretches(t, part, least, False):
                size = last - first + 1
                if (common / len(t.words), -(len(t.words) + size - 2 * common)) < score:
                    continue
                a, b = lo + first, lo + last
                # words of the same line that stand where the template's first or last ones are lacking differ too
                before = sum("\n" not in block[places[x][1] : places[a][0]] for x in range(max(lo + done, a - head), a))
                after = sum("\n" not in block[places[b][1] : places[x][0]] for x in range(b + 1, min(hi, b + 1 + tail)))
                same = {"missing": len(t.words) - common, "extra": size - common + before + after, "exact": common == len(t.words) == size}
                out.append({"license": t.license, "start": places[a][0], "end": places[b][1], "saved": saved} | same)
                open_.append((lo + done, a))
                done = last + 1
            open_.append((lo + done, hi))
        return sorted(out, key=lambda f: f["start"])

    def scan(self, text: str | None) -> list[dict]:
        out = []
        for a, b in self.blocks(text):
            block = text[a:b]
            found = list(WORD.finditer(block))
            mine = self.judge([m[0].lower() for m in found], [m.span() for m in found], block)
            out += [f | {"start": a + f["start"], "end": a + f["end"]} for f in mine]
        return out


FOUND = pa.struct([("license", pa.string()), ("start", pa.int32()), ("end", pa.int32()), ("saved", pa.float64()), ("missing", pa.int32()), ("extra", pa.int32()), ("exact", pa.bool_())])


def license_blocks(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", templates: dict[str, list[str]] = TEMPLATES) -> DataFrame:
    """-> ``id_col``, ``blocks``: confirmed license notices of each document, in order of place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(templates)
        for batch in batches:
            found = [scanner.scan(t.as_py()) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.list_(FOUND))], names=[id_col, "blocks"])

    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"`{id_col}` {kind}, blocks array<struct<license:string,start:int,end:int,saved:double,missing:int,extra:int,exact:boolean>>"
    return docs.select(id_col, text_col).mapInArrow(run, schema)
