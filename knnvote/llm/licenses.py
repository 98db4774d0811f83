"""License scans by conditional compression: how much shorter a block gets when a template is the dictionary.

Blocks of a document that may be about a license are compressed on their own and once with each template as
a raw zstandard dictionary. Templates are ranked by the share of bytes saved, and the winners are confirmed
by the exact differences in wording.
"""

from __future__ import annotations

import re
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from difflib import SequenceMatcher
from functools import lru_cache

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import small_batches

#: License notices by SPDX identifier, several wordings each.
TEMPLATES: dict[str, tuple[str, ...]] = {
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0.",
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0',
    ),
    "MIT": (
        "Released under the MIT License.",
        'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software',
    ),
    "GPL-3.0-only": (
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    ),
    "GPL-2.0-only": (
        "This work is licensed under the GNU General Public License, version 2.",
        "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    ),
    "BSD-3-Clause": (
        "Released under the 3-Clause BSD License.",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    ),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",),
    "CC-BY-4.0": ("Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    "CC-BY-SA-4.0": ("Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    "CC0-1.0": ("To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",),
}

#: Words that make a paragraph a candidate.
CUES = re.compile(r"licen[sc]|copyright|public domain|permission is|redistribut|all rights|warrant|spdx|creative commons|waived", re.I)

HINTS = re.compile(r"licen[sc]|copyright|public|permission|redistribut|rights|warrant|spdx|creative|waived", re.I)  # a cue has one of these, wherever lines break
MARKS = re.compile(r"^\s*(?:/\*+|\*+/?|//+|#+|--+|;+|%+|<!--|(?:rem|dnl)\b)|(?:\*+/|-->)\s*$", re.I)  # of comments
WORDS = re.compile(r"[^\W_]+(?:(?:[.\-]|-[ \t\r]*\n\s*)[^\W_]+)*")  # a hyphen also joins over a line's end
LIKE = 0.8  # share of a block's and a template's words that must agree
BLOCK = 2_000  # characters of a candidate block; longer paragraphs are taken in overlapping blocks
LEVEL = 19


@dataclass(frozen=True)
class Found:
    begin: int  # characters of the document
    end: int
    license: str
    saved: float  # share of the compressed bytes that the template saves
    agreement: float
    missing: tuple[str, ...]  # words of the template that the block lacks
    added: tuple[str, ...]


def _words(text: str) -> list[str]:
    return WORDS.findall(text.lower())


class Scanner:
    def __init__(self, templates: dict[str, tuple[str, ...]] = TEMPLATES):
        self.named = [(name, t) for name, ts in sorted(templates.items()) for t in ts]
        self.plain = zstandard.ZstdCompressor(level=LEVEL, write_content_size=False)
        self.primed = [
            zstandard.ZstdCompressor(level=LEVEL, write_content_size=False, dict_data=zstandard.ZstdCompressionDict(t.lower().encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT))
            for _, t in self.named
        ]
        self.words = [_words(t) for _, t in self.named]
        self.counts = [Counter(w) for w in self.words]
        self.judge = lru_cache(maxsize=50_000)(self._judge)

    def savings(self, block: str) -> list[tuple[float, int]]:
        """(share saved, template) for every template, the best first."""
        raw = block.lower().encode()
        alone = len(self.plain.compress(raw))
        return sorted(((1 - len(c.compress(raw)) / alone, i) for i, c in enumerate(self.primed)), key=lambda x: (-x[0], x[1]))

    def _judge(self, block: str) -> tuple:
        """Every template that the wording confirms, none over the words of a better one: the best, then those of the words beside it."""
        spots = [(m.start(), m.end(), "".join(m.group().lower().split())) for m in WORDS.finditer(block)]
        out, todo = [], [(0, len(spots))]
        while todo:
            lo, hi = todo.pop()
            best = self._best(block[spots[lo][0] : spots[hi - 1][1]] if lo or hi < len(spots) else block, [w for _, _, w in spots[lo:hi]]) if lo < hi else None
            if best:
                _, share, saved, i, missing, added, a, b = best
                out.append((share, saved, i, missing, added, spots[lo + a][0], spots[lo + b - 1][1]))
                todo += [(lo, lo + a), (lo + b, hi)]
        return tuple(out)

    def _best(self, block: str, words: list[str]) -> tuple | None:
        """The template of most agreeing words among those that save bytes and that the wording confirms, or none."""
        held = Counter(words)
        able = {i for i, c in enumerate(self.counts) if _enough((c & held).total(), c.total())}
        best = None
        for saved, i in self.savings(" ".join(block.split())) if able else ():
            if saved <= 0:
                break
            if i not in able:
                continue
            theirs = self.words[i]
            for same in _alignments(theirs, self.counts[i], words):
                agree = sum(m[2] for m in same)
                lo, hi = same[0][1], same[-1][1] + same[-1][2]
                share = 2 * agree / (len(theirs) + hi - lo)
                if share >= LIKE and (best is None or (agree, share, saved) > best[:3]):
                    a_hit = {j for x, _, n in same for j in range(x, x + n)}
                    b_hit = {j for _, x, n in same for j in range(x, x + n)}
                    best = (agree, share, saved, i, tuple(w for j, w in enumerate(theirs) if j not in a_hit), tuple(words[j] for j in range(lo, hi) if j not in b_hit), lo, hi)
        return best

    def scan(self, text: str | None) -> list[Found]:
        """Confirmed licenses of a text, by place; of two that overlap, the longer one."""
        out = []
        for begin, block in blocks(text or ""):
            for share, saved, i, missing, added, lo, hi in self.judge(block):
                out.append(Found(begin + lo, begin + hi, self.named[i][0], round(saved, 6), round(share, 6), missing, added))
        kept: list[Found] = []
        for x in sorted(out, key=lambda x: (x.begin - x.end, -x.agreement, x.begin, -x.saved)):
            if all(x.end <= y.begin or y.end <= x.begin for y in kept):
                kept.append(x)
        return sorted(kept, key=lambda x: x.begin)


def _enough(agree: int, theirs: int) -> bool:
    """Whether so many words in common can reach LIKE: the words of the text are no fewer than those."""
    return 2 * agree >= LIKE * (theirs + agree)


def _alignments(theirs: list[str], counts: Counter, words: list[str]) -> Iterator[list[tuple[int, int, int]]]:
    """Runs of equal words (place in the template, place in the block, length), the best stretch of every window that has enough of them.

    A stretch that agrees is at most 2 / LIKE - 1 times as long as the template, so it lies in one window whole.
    """
    most = int(len(theirs) * (2 / LIKE - 1)) + 1
    step = max(1, len(theirs) // 2)
    for at in range(0, max(1, len(words) - most + step), step):
        part = words[at : at + most + step]
        if not _enough((Counter(part) & counts).total(), len(theirs)):
            continue
        same = [(m.a, at + m.b, m.size) for m in SequenceMatcher(None, theirs, part, autojunk=False).get_matching_blocks() if m.size]
        stretch = lambda lo, hi: 2 * sum(m[2] for m in same[lo:hi]) / (len(theirs) + same[hi - 1][1] + same[hi - 1][2] - same[lo][1])
        if same:
            lo, hi = max(((lo, hi) for lo in range(len(same)) for hi in range(lo + 1, len(same) + 1)), key=lambda x: (stretch(*x), x[1] - x[0]))
            yield same[lo:hi]


def blocks(text: str) -> Iterator[tuple[int, str]]:
    """(begin, block): paragraphs with a cue, comment marks blanked out; long ones in pieces that overlap by half.

    A paragraph ends at a line without words. Blanks keep every word at its place.
    """
    if not HINTS.search(text):
        return
    at, begin, held = 0, 0, []
    for line in [*text.split("\n"), ""]:
        plain = MARKS.sub(lambda m: " " * len(m.group()), line)
        if WORDS.search(plain):
            begin = begin if held else at
            held.append(plain)
        elif held:
            whole, held = "\n".join(held), []
            if CUES.search(" ".join(whole.split())):
                yield from ((begin + lo, piece) for lo, piece in _pieces(whole))
        at += len(line) + 1


def _pieces(block: str) -> Iterator[tuple[int, str]]:
    """Pieces of about BLOCK characters without those between the words, cut between words."""
    if len(block) <= BLOCK:
        yield 0, block
        return
    spots, size = [m.span() for m in WORDS.finditer(block)], [0]
    for lo, hi in spots:
        size.append(size[-1] + hi - lo + 1)
    first = 0
    while True:
        last = max(first + 1, bisect_right(size, size[first] + BLOCK) - 1)
        yield spots[first][0], block[spots[first][0] : spots[last - 1][1]]
        if last == len(spots):
            return
        first = max(first + 1, bisect_right(size, size[last] - BLOCK // 2) - 1)


def scan_documents(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", templates: dict[str, tuple[str, ...]] = TEMPLATES) -> DataFrame:
    """(doc_id, n_blocks, licenses, saved, agreement, spans) for every row of docs.

    licenses: distinct identifiers, sorted; saved and agreement: those of the best confirmed block (null without
    one); spans: every confirmed notice with its license and its differences in wording. Null and empty texts
    have no blocks. Equal blocks are judged once by each worker. Repeated rows each keep their row. Further
    columns are ignored.
    """
    small_batches(docs.sparkSession)
    span = pa.struct([("begin", pa.int64()), ("end", pa.int64()), ("license", pa.string()), ("saved", pa.float64()), ("agreement", pa.float64()), ("missing", pa.list_(pa.string())), ("added", pa.list_(pa.string()))])

    def run(batches):
        scanner = Scanner(templates)
        for b in batches:
            found = [scanner.scan(t) for t in b.column(1).to_pylist()]
            best = [max(f, key=lambda x: (x.agreement, x.saved), default=None) for f in found]
            yield pa.record_batch(
                [
                    b.column(0),
                    pa.array([len(f) for f in found], pa.int64()),
                    pa.array([sorted({x.license for x in f}) for f in found], pa.list_(pa.string())),
                    pa.array([x and x.saved for x in best], pa.float64()),
                    pa.array([x and x.agreement for x in best], pa.float64()),
                    pa.array([[{**vars(x), "missing": list(x.missing), "added": list(x.added)} for x in f] for f in found], pa.list_(span)),
                ],
                names=["doc_id", "n_blocks", "licenses", "saved", "agreement", "spans"],
            )

    kind = "doc_id long, n_blocks long, licenses array<string>, saved double, agreement double, spans array<struct<begin:long,end:long,license:string,saved:double,agreement:double,missing:array<string>,added:array<string>>>"
    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("t")).mapInArrow(run, kind)
