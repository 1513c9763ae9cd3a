"""Phonetic codes: Soundex is built in; Metaphone and a two-code variant run as Arrow-batched functions.

The Metaphone rules follow the published description of the algorithm (English initial and context rules).
The two-code variant follows the published description of its successor, which reads letters in context of
their word's origin and gives a second code where a name is also read another way.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

_VOWELS = frozenset("AEIOU")
_FRONT = frozenset("EIY")
_SILENT_FIRST = ("AE", "GN", "KN", "PN", "WR")


def soundex(c: Column) -> Column:
    return F.soundex(c)


def metaphone_code(word: str | None) -> str | None:
    """The Metaphone code of an upper-case ASCII word."""
    if not word:
        return None
    w = "".join(ch for ch in word.upper() if "A" <= ch <= "Z")
    if not w:
        return None
    if w[:2] in _SILENT_FIRST:
        w = w[1:]
    elif w[0] == "X":
        w = "S" + w[1:]
    elif w[:2] == "WH":
        w = "W" + w[2:]
    out: list[str] = []
    n = len(w)
    at = lambda k: w[k] if 0 <= k < n else ""
    i = 0
    while i < n:
        c, prev, nxt, after = w[i], at(i - 1), at(i + 1), at(i + 2)
        if c == prev and c != "C":
            i += 1
            continue
        if c in _VOWELS:
            if i == 0:
                out.append(c)
        elif c == "B":
            if not (i == n - 1 and prev == "M"):
                out.append("B")
        elif c == "C":
            if nxt == "I" and after == "A":
                out.append("X")
            elif nxt == "H":
                out.append("K" if prev == "S" else "X")
            elif nxt in _FRONT:
                if prev != "S":
                    out.append("S")
            else:
                out.append("K")
        elif c == "D":
            out.append("J" if nxt == "G" and after in _FRONT else "T")
        elif c == "G":
            silent_gh = nxt == "H" and i + 2 < n and after not in _VOWELS
            silent_gn = nxt == "N" and (i + 2 == n or w[i + 1 :] == "NED")
            after_dg = prev == "D" and nxt in _FRONT
            if not (silent_gh or silent_gn or after_dg or (nxt == "H" and i + 2 == n)):
                out.append("J" if nxt in _FRONT and prev != "G" else "K")
        elif c == "H":
            if nxt in _VOWELS and prev not in frozenset("CSPTG"):
                out.append("H")
        elif c == "K":
            if prev != "C":
                out.append("K")
        elif c == "P":
            out.append("F" if nxt == "H" else "P")
        elif c == "Q":
            out.append("K")
        elif c == "S":
            if nxt == "H" or (nxt == "I" and after in ("O", "A")):
                out.append("X")
            else:
                out.append("S")
        elif c == "T":
            if nxt == "I" and after in ("O", "A"):
                out.append("X")
            elif nxt == "H":
                out.append("0")
            elif not (nxt == "C" and after == "H"):
                out.append("T")
        elif c == "V":
            out.append("F")
        elif c in ("W", "Y"):
            if nxt in _VOWELS:
                out.append(c)
        elif c == "X":
            out.append("KS")
        elif c == "Z":
            out.append("S")
        else:
            out.append(c)
        i += 1
    return "".join(out)


class _Reading:
    """A word under the two-code algorithm: it reads letters in context and writes a main and an alternate code."""

    def __init__(self, word: str):
        self.w, self.n = word, len(word)
        self.main: list[str] = []
        self.other: list[str] = []
        self.slavic_or_german = any(x in word for x in ("W", "K", "CZ", "WITZ"))

    def at(self, k: int, *options: str) -> bool:
        """Whether one of the options stands at place ``k``."""
        return k >= 0 and any(self.w.startswith(x, k) for x in options)

    def letter(self, k: int) -> str:
        return self.w[k] if 0 <= k < self.n else ""

    def vowel(self, k: int) -> bool:
        return self.letter(k) in _WIDE_VOWELS and 0 <= k < self.n

    def write(self, main: str, other: str | None = None) -> None:
        self.main.append(main)
        self.other.append(main if other is None else other)

    def read(self) -> tuple[str, str]:
        k = 1 if self.at(0, "GN", "KN", "PN", "WR", "PS") else 0
        if self.at(0, "X"):
            self.write("S")
            k = 1
        while k < self.n:
            c = self.letter(k)
            if c in _WIDE_VOWELS:
                if k == 0:
                    self.write("A")
                k += 1
            elif c in _PLAIN:
                self.write(_PLAIN[c])
                k += 2 if self.letter(k + 1) == c or (c == "P" and self.letter(k + 1) == "B") or (c == "M" and self._silent_b(k)) else 1
            else:
                k = getattr(self, "_" + c.lower())(k) if c.isalpha() and hasattr(self, "_" + c.lower()) else k + 1
        return "".join(self.main), "".join(self.other)

    def _silent_b(self, k: int) -> bool:
        return self.at(k - 1, "UMB") and (k + 1 == self.n - 1 or self.at(k + 2, "ER"))

    def _p(self, k: int) -> int:
        if self.letter(k + 1) == "H":
            self.write("F")
            return k + 2
        self.write("P")
        return k + (2 if self.at(k + 1, "P", "B") else 1)

    def _c(self, k: int) -> int:
        if k > 1 and not self.vowel(k - 2) and self.at(k - 1, "ACH") and self.letter(k + 2) != "I" and (self.letter(k + 2) != "E" or self.at(k - 2, "BACHER", "MACHER")):
            self.write("K")
            return k + 2
        if k == 0 and self.at(0, "CAESAR"):
            self.write("S")
            return k + 2
        if self.at(k, "CHIA"):
            self.write("K")
            return k + 2
        if self.at(k, "CH"):
            return self._ch(k)
        if self.at(k, "CZ") and not self.at(k - 2, "WICZ"):
            self.write("S", "X")
            return k + 2
        if self.at(k + 1, "CIA"):
            self.write("X")
            return k + 3
        if self.at(k, "CC") and not (k == 1 and self.letter(0) == "M"):
            if self.at(k + 2, "I", "E", "H") and not self.at(k + 2, "HU"):
                hard = (k == 1 and self.letter(0) == "A") or self.at(k - 1, "UCCEE", "UCCES")
                self.write("KS" if hard else "X")
                return k + 3
            self.write("K")
            return k + 2
        if self.at(k, "CK", "CG", "CQ"):
            self.write("K")
            return k + 2
        if self.at(k, "CI", "CE", "CY"):
            self.write(*(("S", "X") if self.at(k, "CIO", "CIE", "CIA") else ("S",)))
            return k + 2
        self.write("K")
        if self.at(k + 1, " C", " Q", " G"):
            return k + 3
        return k + (2 if self.at(k + 1, "C", "K", "Q") and not self.at(k + 1, "CE", "CI") else 1)

    def _ch(self, k: int) -> int:
        if k > 0 and self.at(k, "CHAE"):
            self.write("K", "X")
        elif k == 0 and (self.at(1, "HARAC", "HARIS") or self.at(1, "HOR", "HYM", "HIA", "HEM")) and not self.at(0, "CHORE"):
            self.write("K")
        elif (
            self.at(0, "VAN ", "VON ", "SCH")
            or self.at(k - 2, "ORCHES", "ARCHIT", "ORCHID")
            or self.at(k + 2, "T", "S")
            or ((k == 0 or self.at(k - 1, "A", "O", "U", "E")) and (k + 2 >= self.n or self.at(k + 2, "L", "R", "N", "M", "B", "H", "F", "V", "W", " ")))
        ):
            self.write("K")
        elif k > 0:
            self.write(*(("K",) if self.at(0, "MC") else ("X", "K")))
        else:
            self.write("X")
        return k + 2

    def _d(self, k: int) -> int:
        if self.at(k, "DG"):
            soft = self.at(k + 2, "I", "E", "Y")
            self.write("J" if soft else "TK")
            return k + (3 if soft else 2)
        self.write("T")
        return k + (2 if self.at(k, "DT", "DD") else 1)

    def _g(self, k: int) -> int:
        nxt = self.letter(k + 1)
        if nxt == "H":
            return self._gh(k)
        if nxt == "N":
            if k == 1 and self.vowel(0) and not self.slavic_or_german:
                self.write("KN", "N")
            elif not self.at(k + 2, "EY") and not self.slavic_or_german:
                self.write("N", "KN")
            else:
                self.write("KN")
            return k + 2
        if self.at(k + 1, "LI") and not self.slavic_or_german:
            self.write("KL", "L")
            return k + 2
        if k == 0 and (nxt == "Y" or self.at(1, "ES", "EP", "EB", "EL", "EY", "IB", "IL", "IN", "IE", "EI", "ER")):
            self.write("K", "J")
            return k + 2
        if (self.at(k + 1, "ER") or nxt == "Y") and not self.at(0, "DANGER", "RANGER", "MANGER") and not self.at(k - 1, "E", "I") and not self.at(k - 1, "RGY", "OGY"):
            self.write("K", "J")
            return k + 2
        if nxt in ("E", "I", "Y") and nxt or self.at(k - 1, "AGGI", "OGGI"):
            if self.at(0, "VAN ", "VON ", "SCH") or self.at(k + 1, "ET"):
                self.write("K")
            elif self.at(k + 1, "IER") and k + 4 >= self.n:
                self.write("J")
            else:
                self.write("J", "K")
            return k + 2
        self.write("K")
        return k + (2 if nxt == "G" else 1)

    def _gh(self, k: int) -> int:
        if k > 0 and not self.vowel(k - 1):
            self.write("K")
        elif k == 0:
            self.write("J" if self.letter(2) == "I" else "K")
        elif self.at(k - 2, "B", "H", "D") or self.at(k - 3, "B", "H", "D") or self.at(k - 4, "B", "H"):
            pass
        elif k > 2 and self.letter(k - 1) == "U" and self.at(k - 3, "C", "G", "L", "R", "T"):
            self.write("F")
        elif self.letter(k - 1) != "I":
            self.write("K")
        return k + 2

    def _h(self, k: int) -> int:
        if (k == 0 or self.vowel(k - 1)) and self.vowel(k + 1):
            self.write("H")
            return k + 2
        return k + 1

    def _j(self, k: int) -> int:
        if self.at(k, "JOSE") or self.at(0, "SAN "):
            whole = self.at(0, "SAN ") or (k == 0 and (self.n == 4 or self.letter(4) == " "))
            self.write(*(("H",) if whole else ("J", "H")))
            return k + 1
        if k == 0:
            self.write("J", "A")
        elif self.vowel(k - 1) and not self.slavic_or_german and self.at(k + 1, "A", "O"):
            self.write("J", "H")
        elif k == self.n - 1:
            self.write("J", "")
        elif not self.at(k + 1, "L", "T", "K", "S", "N", "M", "B", "Z") and not self.at(k - 1, "S", "K", "L"):
            self.write("J")
        return k + (2 if self.letter(k + 1) == "J" else 1)

    def _l(self, k: int) -> int:
        if self.letter(k + 1) != "L":
            self.write("L")
            return k + 1
        spanish = (k == self.n - 3 and self.at(k - 1, "ILLO", "ILLA", "ALLE")) or (k > 0 and (self.w.endswith(("AS", "OS")) or self.w.endswith(("A", "O"))) and self.at(k - 1, "ALLE"))
        self.write("L", "" if spanish else None)
        return k + 2

    def _r(self, k: int) -> int:
        silent = k == self.n - 1 and not self.slavic_or_german and self.at(k - 2, "IE") and not self.at(k - 4, "ME", "MA")
        self.write("" if silent else "R", "R")
        return k + (2 if self.letter(k + 1) == "R" else 1)

    def _s(self, k: int) -> int:
        if self.at(k - 1, "ISL", "YSL"):
            return k + 1
        if k == 0 and self.at(0, "SUGAR"):
            self.write("X", "S")
            return k + 1
        if self.at(k, "SH"):
            self.write("S" if self.at(k + 1, "HEIM", "HOEK", "HOLM", "HOLZ") else "X")
            return k + 2
        if self.at(k, "SIO", "SIA"):
            self.write("S", None if self.slavic_or_german else "X")
            return k + 3
        if (k == 0 and self.at(1, "M", "N", "L", "W")) or self.at(k + 1, "Z"):
            self.write("S", "X")
            return k + (2 if self.at(k + 1, "Z") else 1)
        if self.at(k, "SC"):
            return self._sc(k)
        silent = k == self.n - 1 and self.at(k - 2, "AI", "OI")
        self.write("" if silent else "S", "S")
        return k + (2 if self.at(k + 1, "S", "Z") else 1)

    def _sc(self, k: int) -> int:
        if self.letter(k + 2) == "H":
            if self.at(k + 3, "ER", "EN"):
                self.write("X", "SK")
            elif self.at(k + 3, "OO", "UY", "ED", "EM"):
                self.write("SK")
            elif k == 0 and not self.vowel(3) and self.letter(3) != "W":
                self.write("X", "S")
            else:
                self.write("X")
        else:
            self.write("S" if self.at(k + 2, "I", "E", "Y") else "SK")
        return k + 3

    def _t(self, k: int) -> int:
        if self.at(k, "TION", "TIA", "TCH"):
            self.write("X")
            return k + 3
        if self.at(k, "TH", "TTH"):
            hard = self.at(k + 2, "OM", "AM") or self.at(0, "VAN ", "VON ", "SCH")
            self.write("T" if hard else "0", "T")
            return k + 2
        self.write("T")
        return k + (2 if self.at(k + 1, "T", "D") else 1)

    def _w(self, k: int) -> int:
        if self.at(k, "WR"):
            self.write("R")
            return k + 2
        if k == 0 and (self.vowel(1) or self.at(0, "WH")):
            self.write("A", "F" if self.vowel(1) else None)
        elif (k == self.n - 1 and self.vowel(k - 1)) or self.at(k - 1, "EWSKI", "EWSKY", "OWSKI", "OWSKY") or self.at(0, "SCH"):
            self.write("", "F")
        elif self.at(k, "WICZ", "WITZ"):
            self.write("TS", "FX")
            return k + 4
        return k + 1

    def _x(self, k: int) -> int:
        if not (k == self.n - 1 and (self.at(k - 3, "IAU", "EAU") or self.at(k - 2, "AU", "OU"))):
            self.write("KS")
        return k + (2 if self.at(k + 1, "C", "X") else 1)

    def _z(self, k: int) -> int:
        if self.letter(k + 1) == "H":
            self.write("J")
            return k + 2
        between = self.at(k + 1, "ZO", "ZI", "ZA") or (self.slavic_or_german and k > 0 and self.letter(k - 1) != "T")
        self.write("S", "TS" if between else None)
        return k + (2 if self.letter(k + 1) == "Z" else 1)


_WIDE_VOWELS = frozenset("AEIOUY")
#: Letters with one reading, doubled or not.
_PLAIN = {"B": "P", "F": "F", "K": "K", "M": "M", "N": "N", "Q": "K", "V": "F"}


def double_metaphone_codes(word: str | None, length: int = 4) -> tuple[str | None, str | None]:
    """The main and the alternate code of a word, of at most ``length`` letters; equal where there is one reading."""
    w = "".join(ch for ch in (word or "").upper() if "A" <= ch <= "Z" or ch == " ").strip()
    if not w:
        return None, None
    main, other = _Reading(w).read()
    return main[:length], other[:length]


def metaphone(c: Column) -> Column:
    @F.pandas_udf("string")
    def code(words: pd.Series) -> pd.Series:
        return words.map(metaphone_code)

    return code(c)


def double_metaphone(c: Column) -> Column:
    @F.pandas_udf("primary string, alternate string")
    def codes(words: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([double_metaphone_codes(w) for w in words], columns=["primary", "alternate"])

    return codes(c)
