"""Cleaning and validation of identifying fields.  All functions are Catalyst expressions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

# Accents and the letters they fold to, applied before upper-casing.
ACCENTS = "ÀÁÂÃÄÅÇÈÉÊËÌÍÎÏÑÒÓÔÕÖÙÚÛÜÝàáâãäåçèéêëìíîïñòóôõöùúûüýÿß"
PLAIN = "AAAAAACEEEEIIIINOOOOOUUUUYaaaaaaceeeeiiiinooooouuuuyys"

# Placeholder numbers that are never a person's.
DEFAULT_DENY = (
    "999999999", "888888888", "123456789", "012345678", "000000000", "001010001", "111111111",
    "090909090", "333333333", "444444444", "555555555", "666666666", "777777777",
)


@dataclass(frozen=True)
class CleaningPolicy:
    """One policy object cleans both files, so that equal raw values always give equal clean values."""

    accents: str = "fold"
    first_chars: int = 15
    middle_chars: int = 15
    last_chars: int = 20
    min_year: int = 1850
    max_year: int = 2022
    calendar: bool = False
    deny: tuple[str, ...] = DEFAULT_DENY


def digits_only(c: Column) -> Column:
    return F.regexp_replace(c, "[^0-9]", "")


def letters_only(c: Column, accents: str = "fold") -> Column:
    """Upper-case letters; accented ones are folded, or dropped with the rest."""
    folded = F.translate(c, ACCENTS, PLAIN) if accents == "fold" else c
    # other letters could become ASCII by upper-casing, so what is not ASCII goes first
    return F.upper(F.regexp_replace(folded, "[^A-Za-z]", ""))


def truncated(c: Column, n: int) -> Column:
    return F.substring(c, 1, n)


def null_if_blank(c: Column) -> Column:
    return F.when(F.trim(c) != "", c)


def clean_name(c: Column, n: int, accents: str = "fold") -> Column:
    return null_if_blank(truncated(letters_only(c, accents), n))


def to_ymd(c: Column, layout: str = "ymd") -> Column:
    """Eight digits, year first, from year-first (``ymd``) or month-first (``mdy``) text with any separators."""
    if layout == "ymd":
        return digits_only(c)
    part = lambda i: F.regexp_extract(c, r"^\s*([0-9]{1,2})[^0-9]([0-9]{1,2})[^0-9]([0-9]{4})\s*$", i)
    return F.when(part(3) != "", F.concat(part(3), F.lpad(part(1), 2, "0"), F.lpad(part(2), 2, "0")))


def valid_date(ymd: Column, lo: int = 1850, hi: int = 2022, calendar: bool = False) -> Column:
    """The date if it has eight digits and a year in the window, both ends included; else null."""
    ok = (F.length(ymd) == 8) & F.substring(ymd, 1, 4).between(str(lo), str(hi))
    if calendar:
        ok = ok & F.try_to_date(ymd, "yyyyMMdd").isNotNull()
    return F.when(ok, ymd)


def valid_ssn(c: Column, deny: tuple[str, ...] = DEFAULT_DENY) -> Column:
    """The nine digits, or null for an impossible area, group or serial, a placeholder, or another length."""
    d = digits_only(c)
    area, group, serial = F.substring(d, 1, 3), F.substring(d, 4, 2), F.substring(d, 6, 4)
    bad = area.isin("000", "666") | (F.substring(d, 1, 1) == "9") | (group == "00") | (serial == "0000") | d.isin(*deny)
    return F.when((F.length(d) == 9) & ~bad, d)


def ssn_defect(c: Column) -> Column:
    """What is wrong with a present number, whole-value placeholders first; null for valid or missing ones."""
    d = digits_only(c)
    area, group, serial = F.substring(d, 1, 3), F.substring(d, 4, 2), F.substring(d, 6, 4)
    return (
        F.when(d == "", F.lit(None).cast("string"))
        .when(d.isin(*DEFAULT_DENY), d)
        .when(F.length(d) != 9, "bad-length")
        .when(F.substring(d, 1, 1) == "9", "area-9xx")
        .when(group == "00", "group-00")
        .when(area == "666", "area-666")
        .when(area == "000", "area-000")
        .when(serial == "0000", "serial-0000")
    )


def adjacent_swaps(c: Column) -> Column:
    """Every text that exchanging two neighbouring letters or digits makes of a text; an empty array for a null."""
    turned = lambda i: F.concat(F.substring(c, F.lit(1), i - 1), F.substring(c, i + 1, F.lit(1)), F.substring(c, i, F.lit(1)), F.substring(c, i + 2, F.length(c)))
    differ = lambda i: F.substring(c, i, F.lit(1)) != F.substring(c, i + 1, F.lit(1))
    none = F.array().cast("array<string>")
    return F.when(F.length(c) > 1, F.transform(F.filter(F.sequence(F.lit(1), F.length(c) - 1), differ), turned)).otherwise(none)


def agreeing_digits(a: Column, b: Column, n: int = 9) -> Column:
    """Positions at which two numbers hold the same digit."""
    same = [F.when(F.substring(a, i, 1) == F.substring(b, i, 1), 1).otherwise(0) for i in range(1, n + 1)]
    return sum(same[1:], same[0])


def clean_gender(c: Column) -> Column:
    g = F.upper(F.substring(F.trim(c), 1, 1))
    return F.when(g.isin("F", "M"), g)


def clean_address(c: Column) -> Column:
    return null_if_blank(F.regexp_replace(F.upper(F.regexp_replace(F.translate(c, ACCENTS, PLAIN), "[^A-Za-z0-9]", "")), "[^A-Z0-9]", ""))


def clean_zip(c: Column) -> Column:
    d = digits_only(c)
    return F.when(F.length(d) == 5, d)
