"""Standardized person records."""

from __future__ import annotations

from functools import partial

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.cleaning import CleaningPolicy, adjacent_swaps, clean_address, clean_gender, clean_name, clean_zip, to_ymd, valid_date, valid_ssn

#: Bits of ``valid_mask``.
MASK = ("ssn", "last_name", "middle_name", "first_name", "birth_date")


def cleaned(policy: CleaningPolicy = CleaningPolicy()) -> dict[str, Column]:
    return {
        "first_name": clean_name(F.col("first_name_raw"), policy.first_chars, policy.accents),
        "middle_name": clean_name(F.col("middle_name_raw"), policy.middle_chars, policy.accents),
        "last_name": clean_name(F.col("last_name_raw"), policy.last_chars, policy.accents),
        "birth_date": valid_date(to_ymd(F.col("birth_raw")), policy.min_year, policy.max_year, policy.calendar),
        "ssn": valid_ssn(F.col("ssn_raw"), policy.deny),
    }


def standardize(raw: DataFrame, id_col: str, policy: CleaningPolicy = CleaningPolicy(), extra: tuple[str, ...] = ("gender", "zip", "address")) -> DataFrame:
    """One projection over a raw file: clean fields (null if not valid), death date, validity bits, extension fields."""
    fields = cleaned(policy)
    more = {"gender": clean_gender, "zip": clean_zip, "address": clean_address}
    parts = raw.select(F.col(id_col).alias("rec_id"), "true_person", *[c.alias(k) for k, c in fields.items()], F.col("dod").alias("death_date"), *[more[x](F.col(f"{x}_raw")).alias(x) for x in extra])
    bits = [F.when(F.col(f).isNotNull(), 1 << i).otherwise(0) for i, f in enumerate(MASK)]
    return parts.withColumn("valid_mask", sum(bits[1:], bits[0]))


def explode_names(raw: DataFrame, names: Column) -> DataFrame:
    """One raw row for each known name; ``names`` is an array of (first, last, kind)."""
    rows = raw.withColumn("__n", F.explode(names))
    return rows.withColumn("first_name_raw", F.col("__n.first")).withColumn("last_name_raw", F.col("__n.last")).withColumn("name_kind", F.col("__n.kind")).drop("__n")


#: Variants by exchange of neighbouring letters or digits: kind and field.
ADJACENT = {"first_letters": "first_name", "last_letters": "last_name", "ssn_digits": "ssn", "birth_digits": "birth_date"}


def swap_variants(std: DataFrame, kinds: tuple[str, ...] = ("names", "month_day", *ADJACENT)) -> DataFrame:
    """The records and their variants: first and last name, or month and day of birth, exchanged; and, for each place
    in a field, two neighbouring letters or digits exchanged."""
    fields = ("first_name", "last_name", "birth_date", "ssn")

    def made(kind: str, **changed: Column) -> Column:
        return F.struct(F.lit(kind).alias("kind"), *[changed.get(f, F.col(f)).alias(f) for f in fields])

    def changed(kind: str, field: str, x: Column) -> Column:
        return made(kind, **{field: x})

    month_day = F.concat(F.substring("birth_date", 1, 4), F.substring("birth_date", 7, 2), F.substring("birth_date", 5, 2))
    variants = [F.array(made("as_is"))]
    if "names" in kinds:
        variants.append(F.array(made("names", first_name=F.col("last_name"), last_name=F.col("first_name"))))
    if "month_day" in kinds:
        variants.append(F.array(made("month_day", birth_date=month_day)))
    variants += [F.transform(adjacent_swaps(F.col(f)), partial(changed, kind, f)) for kind, f in ADJACENT.items() if kind in kinds]
    rows = std.withColumn("__v", F.explode(F.concat(*variants)))
    return rows.withColumns({"variant": F.col("__v.kind"), **{f: F.col(f"__v.{f}") for f in fields}}).drop("__v")
