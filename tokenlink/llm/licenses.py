"""License notices, exact and with small errors.

Every text is lowered (ASCII letters only) and cut into words.  Base phrases are looked for word by word.
Short notices are then searched with errors: a notice for which e errors are allowed is split into e + 1
pieces, one of which must occur exactly (the pigeonhole principle).  One automaton finds all pieces of all
notices; around each hit a window that holds every possible match goes to the ``regex`` library, whose
bounded-error matching confirms it and gives span and errors.

The notices cover name lines, opening and body sentences of common licenses, and SPDX identifier lines, whose
identifier itself must be exact; callers may pass their own table.

Defined results.  A null text is empty: no words, no labels, score 0.  Overlapping places all count for the
base; of a notice's fuzzy matches the leftmost non-overlapping ones count, each improved to its best fit.  Spans
are word positions.  Null ids, ties and repeated rows are rows like any other; an empty table gives none.  Time
is linear in a text's words.  Further columns pass through; a column named ``found`` is replaced by :func:`scan`.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_WORD = regex.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")

#: Base phrases and their labels.
BASE = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}

# Short notices: label, words, errors allowed, words that must follow exactly.
NOTICES = (
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy", 6, ""),
    ("mit", "the above copyright notice and this permission notice shall be included in all copies", 6, ""),
    ("mit", "licensed under the mit license", 2, ""),
    ("apache", "licensed under the apache license version", 3, ""),
    ("apache", "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis", 8, ""),
    ("gpl", "licensed under the gnu general public license", 3, ""),
    ("gpl", "free software you can redistribute it and or modify it under the terms of the gnu general public license", 8, ""),
    ("gpl", "gnu general public license", 2, ""),
    ("lgpl", "gnu lesser general public license", 2, ""),
    ("lgpl", "gnu library general public license", 2, ""),
    ("agpl", "gnu affero general public license", 2, ""),
    ("gfdl", "gnu free documentation license", 2, ""),
    ("bsd", "redistribution and use in source and binary forms with or without modification", 6, ""),
    ("bsd", "may be used to endorse or promote products derived from this software without specific prior written permission", 8, ""),
    ("bsd", "licensed under the bsd license", 2, ""),
    ("isc", "permission to use copy modify and or distribute this software for any purpose", 6, ""),
    ("mpl", "mozilla public license", 2, ""),
    ("epl", "eclipse public license", 2, ""),
    ("cddl", "common development and distribution license", 3, ""),
    ("boost", "boost software license", 2, ""),
    ("zlib", "altered source versions must be plainly marked as such and must not be misrepresented as being the original software", 8, ""),
    ("artistic", "artistic license", 1, ""),
    ("cc0", "creative commons zero", 1, ""),
    ("cc0", "cc0 1 0 universal", 1, ""),
    ("cc", "licensed under cc by", 1, ""),
    ("cc", "creative commons attribution", 2, ""),
    ("unlicense", "free and unencumbered software released into the public domain", 4, ""),
    *((label, "spdx license identifier", 2, name) for label, name in (
        ("mit", "mit"), ("apache", "apache 2 0"), ("gpl", "gpl 2 0"), ("gpl", "gpl 3 0"), ("lgpl", "lgpl 2 1"), ("lgpl", "lgpl 3 0"), ("agpl", "agpl 3 0"), ("bsd", "bsd 2 clause"), ("bsd", "bsd 3 clause"),
        ("isc", "isc"), ("mpl", "mpl 2 0"), ("epl", "epl 2 0"), ("cddl", "cddl 1 0"), ("boost", "bsl 1 0"), ("zlib", "zlib"), ("artistic", "artistic 2 0"), ("cc0", "cc0 1 0"), ("unlicense", "unlicense"),
    )),
)


@dataclass(frozen=True)
class Notice:
    label: str
    text: str
    errors: int
    exact: str = ""

    @property
    def pieces(self) -> list[str]:
        n, k = len(self.text), self.errors + 1
        return [self.text[n * i // k : n * (i + 1) // k] for i in range(k)]

    @property
    def size(self) -> int:
        return len(self.text) + (len(self.exact) + 1 if self.exact else 0)

    @property
    def pattern(self) -> regex.Pattern:
        # a match begins and ends with a word; each is improved to the best fit where it stands
        tail = " " + regex.escape(self.exact, special_only=True) if self.exact else ""
        return regex.compile(rf"(?e)(?<![^ ])(?:{regex.escape(self.text, special_only=True)}){{e<={self.errors}}}{tail}(?![^ ])")


def _merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for start, stop in sorted(spans):
        if out and start <= out[-1][1]:
            out[-1] = out[-1][0], max(stop, out[-1][1])
        else:
            out.append((start, stop))
    return out


class Scanner:
    def __init__(self, notices: tuple = NOTICES):
        import ahocorasick

        self.notices = [Notice(*x) for x in notices]
        self.patterns = [x.pattern for x in self.notices]
        self.base = {tuple(k.split()): v for k, v in BASE.items()}
        owners: dict[str, list[tuple[int, int]]] = {}
        for i, x in enumerate(self.notices):
            at = 0
            for piece in x.pieces:
                owners.setdefault(piece, []).append((i, at))
                at += len(piece)
        self.seeds = ahocorasick.Automaton()
        for piece, own in owners.items():
            self.seeds.add_word(piece, (len(piece), own))
        self.seeds.make_automaton()

    def base_places(self, words: list[str]) -> list[tuple[int, str]]:
        found = []
        for phrase, label in self.base.items():
            last, at = phrase[-1], -1
            while True:
                try:
                    at = words.index(last, at + 1)
                except ValueError:
                    break
                start = at - len(phrase) + 1
                if start >= 0 and tuple(words[start : at + 1]) == phrase:
                    found.append((start, label))
        return sorted(found)

    def fuzzy(self, words: list[str]) -> list[tuple[int, int, str, float]]:
        """(first word, word after the last, label, score) of each confirmed notice."""
        joined = " ".join(words)
        windows: dict[int, list[tuple[int, int]]] = {}
        for end, (length, own) in self.seeds.iter(joined):
            for i, at in own:
                x = self.notices[i]
                start = max(0, end - length + 1 - at - x.errors)
                windows.setdefault(i, []).append((start, min(len(joined), start + x.size + 2 * x.errors + 1)))
        if not windows:
            return []
        starts = np.cumsum([0, *(len(w) + 1 for w in words)])
        found = set()
        for i, spans in windows.items():
            x = self.notices[i]
            for start, stop in _merged(spans):
                start = joined.rfind(" ", 0, start) + 1  # whole words
                stop = joined.find(" ", stop) if joined.find(" ", stop) >= 0 else len(joined)
                for m in self.patterns[i].finditer(joined, start, stop):
                    # an error at an end may take in the blank there
                    first, last = np.searchsorted(starts, (m.start() + (joined[m.start()] == " "), m.end() - (joined[m.end() - 1] == " ")), "right")
                    found.add((int(first) - 1, int(last), x.label, 1 - sum(m.fuzzy_counts) / x.size))
        return sorted(found)

    def scan(self, text: str | None) -> tuple[int, list[tuple[int, str]], list[tuple[int, int, str, float]]]:
        words = _WORD.findall((text or "").translate(_LOWER))
        if not words:
            return 0, [], []
        return len(words), self.base_places(words), self.fuzzy(words)


_SCHEMA = "n_words long, base array<struct<at:long,label:string>>, notices array<struct<first:long,last:long,label:string,score:double>>"


def scan(docs: DataFrame, text_col: str = "text", notices: tuple = NOTICES) -> DataFrame:
    """``docs`` with ``found``: n_words, base places and confirmed notices with word spans and scores."""

    @F.pandas_udf(_SCHEMA)
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        scanner = Scanner(notices)
        for texts in batches:
            rows = [scanner.scan(t) for t in texts]
            yield pd.DataFrame({
                "n_words": [n for n, _, _ in rows],
                "base": [[{"at": a, "label": x} for a, x in b] for _, b, _ in rows],
                "notices": [[{"first": a, "last": b, "label": x, "score": s} for a, b, x, s in f] for _, _, f in rows],
            })

    return docs.withColumn("found", run(F.col(text_col)))


def digest(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    found = scan(docs.select(id_col, text_col), text_col).select(id_col, "found.*")
    names = lambda *cols: F.array_join(F.array_sort(F.array_distinct(F.concat(*cols))), ",")
    base, more = F.col("base.label"), F.col("notices.label")
    return found.select(
        id_col,
        "n_words",
        F.size("base").cast("long").alias("n_base"),
        F.array_min("base.at").alias("first_word"),
        F.array_max("base.at").alias("last_word"),
        names(base).alias("base_labels"),
        names(base, more).alias("labels"),
        F.coalesce(F.when(F.size("base") > 0, F.lit(1.0)), F.array_max("notices.score"), F.lit(0.0)).alias("score"),
    )
