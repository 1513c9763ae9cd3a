"""Rules: ordered lists of key parts, compiled to Catalyst expressions or to SQL text.

A rule is written as part codes: S ssn, L last, M middle, F first, B birth date, Y year of birth, G gender,
Z zip, A address; a digit takes a prefix (of S the last digits), ``~`` the Soundex code, ``^`` the Metaphone code and
``^^`` the main double Metaphone code (Arrow-batched functions; the others are Catalyst expressions).
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.phonetic import double_metaphone, metaphone

_FIELDS = {"S": "ssn", "L": "last_name", "M": "middle_name", "F": "first_name", "B": "birth_date", "Y": "birth_date", "G": "gender", "Z": "zip", "A": "address"}

_PHONETIC = {"~": "soundex", "^": "metaphone", "^^": "double_metaphone"}


@dataclass(frozen=True)
class Part:
    field: str
    transform: str = "whole"  # whole, prefix, last, soundex, metaphone, double_metaphone
    n: int = 0

    @classmethod
    def parse(cls, code: str) -> Part:
        m = re.fullmatch(r"([A-Z])(~|\^\^?|\d+)?", code)
        if not m or m[1] not in _FIELDS:
            raise ValueError(f"unknown key part {code!r}")
        field, how = _FIELDS[m[1]], m[2]
        if m[1] == "Y":
            return cls(field, "prefix", 4)
        if how is None or how == "5" and m[1] == "Z":
            return cls(field)
        if how in _PHONETIC:
            return cls(field, _PHONETIC[how])
        return cls(field, "last" if m[1] == "S" else "prefix", int(how))

    @property
    def column(self) -> Column:
        c = F.col(self.field)
        if self.transform == "prefix":
            return F.substring(c, 1, self.n)
        if self.transform == "last":
            return F.right(c, F.lit(self.n))
        if self.transform == "double_metaphone":
            return double_metaphone(c).getField("primary")
        return {"soundex": F.soundex, "metaphone": metaphone}[self.transform](c) if self.transform in _PHONETIC.values() else c

    def determines(self, other: Part) -> bool:
        """Whether the other part is a function of this one."""
        if self.field != other.field:
            return False
        if self == other or self.transform == "whole":
            return True
        first_letter = other.transform == "prefix" and other.n == 1
        return (self.transform == other.transform == "prefix" and self.n >= other.n) or (self.transform == other.transform == "last" and self.n >= other.n) or (self.transform == "soundex" and first_letter)


@dataclass(frozen=True)
class Rule:
    id: int
    codes: str
    name: str = ""

    @property
    def parts(self) -> tuple[Part, ...]:
        return tuple(map(Part.parse, self.codes.split()))

    @property
    def fields(self) -> frozenset[str]:
        return frozenset(p.field for p in self.parts)

    @property
    def kind(self) -> str:
        how = {p.transform for p in self.parts}
        return "phonetic" if how & set(_PHONETIC.values()) else "partial" if how - {"whole"} else "exact"

    def token(self, sep: str = "") -> Column:
        """The key; null if any part is (``concat`` propagates nulls, ``concat_ws`` would not)."""
        cols = [p.column for p in self.parts]
        if sep:
            cols = [x for c in cols for x in (F.lit(sep), c)][1:]
        return F.concat(*cols)

    def refines(self, other: Rule) -> bool:
        """Equal keys under this rule imply equal keys under the other."""
        return all(any(mine.determines(theirs) for mine in self.parts) for theirs in other.parts)


@dataclass(frozen=True)
class RuleSet:
    rules: tuple[Rule, ...]

    @classmethod
    def of(cls, *codes: str, prefix: str = "") -> RuleSet:
        return cls(tuple(Rule(i, c, f"{prefix}.{i}" if prefix else str(i)) for i, c in enumerate(codes, 1)))

    def __iter__(self) -> Iterator[Rule]:
        return iter(self.rules)

    def __len__(self) -> int:
        return len(self.rules)

    def with_rule(self, codes: str) -> RuleSet:
        n = max((r.id for r in self.rules), default=0) + 1
        return RuleSet((*self.rules, Rule(n, codes, str(n))))

    def coarser_than(self, rule: Rule) -> list[Rule]:
        return [r for r in self.rules if r.id != rule.id and rule.refines(r)]


# The twenty evaluated rules, by id.
EVALUATED = RuleSet.of(
    "S L M F B", "S L F B", "S B", "S Y F L", "S L M F", "S", "S4 L M F B", "S4 B", "L M F B", "L M F Y",
    "L F B", "L M1 F", "L F3 B", "L F1 B", "L~ M~ F~ B", "L~ M~ F~ Y", "L~ F~ B", "L", "F", "B",
)

#: Keys of the twenty's phonetic rules under the codes planned to follow Soundex.
PHONETIC = RuleSet.of("L^ M^ F^ B", "L^ M^ F^ Y", "L^ F^ B", "L^^ M^^ F^^ B", "L^^ M^^ F^^ Y", "L^^ F^^ B", prefix="phonetic")

# Rule sets of earlier systems.
LEGACY = RuleSet.of("S B", "S F L Y", prefix="legacy")
METRO = RuleSet.of("F L B", "B S", "L S", "F3 L3 F~ L~ B S", prefix="metro")
REGISTRY = RuleSet.of("F L B G", prefix="registry")
STATE = RuleSet.of("S", "F3 L3 B", "F~ L~ B", prefix="state")
VENDOR = RuleSet.of(
    "L F1 G B", "L~ F~ G B", "L F B Z3", "L F G B", "S G B", "L F3 G B Z3", "L F3 G B", "L F3 G Z5", "L A",
    "L F3 G Z3", "L F G Z3", "L F G Z5", "L M1 F G Z3", "A Z5 B", "A Z5 B G", prefix="vendor",
)
BASELINES = {"legacy": LEGACY, "metro": METRO, "registry": REGISTRY, "state": STATE, "vendor15": VENDOR}
