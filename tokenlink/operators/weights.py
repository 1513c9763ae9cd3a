"""Frequency weights, agreement classes and the choice among candidates; m/u estimation by EM."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.cleaning import agreeing_digits

WEIGHTED = ("first_name", "middle_name", "last_name", "birth_date")
#: Weights are kept in millionths, so that sums do not depend on the order of addition.
UNIT = 1_000_000


def value_weights(ref: DataFrame, fields: tuple[str, ...] = WEIGHTED) -> DataFrame:
    """(field, value, n, weight): log2(1 / relative frequency) among present values, in millionths."""
    spread = [x for f in fields for x in (F.lit(f), F.col(f))]
    long = ref.select(F.stack(F.lit(len(fields)), *spread).alias("field", "value")).where("value is not null")
    counts = long.groupBy("field", "value").agg(F.count("*").alias("n"))
    totals = counts.groupBy("field").agg(F.sum("n").alias("total"))
    weight = F.round(F.log2(F.col("total").cast("double") / F.col("n").cast("double")) * UNIT).cast("long")
    return counts.join(F.broadcast(totals), "field").select("field", "value", "n", weight.alias("weight"))  # a row a field


def score_pairs(pairs: DataFrame, a: DataFrame, b: DataFrame, weights: DataFrame, fields: tuple[str, ...] = WEIGHTED, disagreement: int = 0) -> DataFrame:
    """(clinic_id, reg_id, score): weights of the fields that agree; a disagreement adds ``disagreement``."""
    mine = a.select(F.col("rec_id").alias("clinic_id"), *[F.col(f).alias(f"a_{f}") for f in fields])
    theirs = b.select(F.col("rec_id").alias("reg_id"), *[F.col(f).alias(f"b_{f}") for f in fields])
    both = pairs.select("clinic_id", "reg_id").join(mine, "clinic_id").join(theirs, "reg_id")
    spread = [x for f in fields for x in (F.lit(f), F.when(F.col(f"a_{f}") == F.col(f"b_{f}"), F.col(f"a_{f}")), F.col(f"a_{f}") != F.col(f"b_{f}"))]
    long = both.select("clinic_id", "reg_id", F.stack(F.lit(len(fields)), *spread).alias("field", "value", "differs"))
    agreed = long.where("value is not null").join(weights.select("field", "value", "weight"), ["field", "value"]).select("clinic_id", "reg_id", "weight")
    rest = long.where("value is null").select("clinic_id", "reg_id", F.when(F.col("differs"), disagreement).otherwise(0).cast("long").alias("weight"))
    return agreed.unionByName(rest).groupBy("clinic_id", "reg_id").agg(F.sum("weight").alias("score"))


def agreement_class(a: str = "a", b: str = "b") -> Column:
    """The class of a pair whose two records stand in structs ``a`` and ``b``; exactly one of 1 to 5.

    1: at least eight digits and first name, middle initial (both may be blank), last name, birth year within three,
    birth month, sex and state of birth agree; 2: number present, at least seven digits, not class 1; 3: number
    unknown, eight or more of eleven items agree, each present and equal: first name, middle initial, last name,
    father's surname (of women), day, month and year of birth, sex, race, marital status, state of birth; 4: number
    unknown otherwise; 5: number present, under seven digits.
    """
    x, y = lambda f: F.col(f"{a}.{f}"), lambda f: F.col(f"{b}.{f}")
    eq = lambda f: F.coalesce(x(f) == y(f), F.lit(False))
    known = x("ssn").isNotNull() & y("ssn").isNotNull()
    digits = F.when(known, agreeing_digits(x("ssn"), y("ssn")))
    initials = F.substring(x("middle_name"), 1, 1), F.substring(y("middle_name"), 1, 1)
    born = lambda r, at, n: F.substring(r("birth_date"), at, n)
    years = F.coalesce(F.abs(born(x, 1, 4).cast("int") - born(y, 1, 4).cast("int")) <= 3, F.lit(False))
    year, months, days = (F.coalesce(born(x, at, n) == born(y, at, n), F.lit(False)) for at, n in ((1, 4), (5, 2), (7, 2)))
    first = (digits >= 8) & eq("first_name") & initials[0].eqNullSafe(initials[1]) & eq("last_name") & years & months & eq("gender") & eq("birth_state")
    father = F.coalesce((x("gender") == "F") & (x("father_surname") == y("father_surname")), F.lit(False))
    initial = F.coalesce(initials[0] == initials[1], F.lit(False))
    items = [eq("first_name"), initial, eq("last_name"), father, days, months, year, eq("gender"), eq("race"), eq("marital"), eq("birth_state")]
    agreeing = sum((c.cast("int") for c in items[1:]), items[0].cast("int"))
    return F.when(known & first, 1).when(known & (digits >= 7), 2).when(known, 5).when(agreeing >= 8, 3).otherwise(4)


CLASS_FIELDS = ("ssn", "first_name", "middle_name", "last_name", "birth_date", "gender", "birth_state", "race", "marital", "father_surname")


def classified(pairs: DataFrame, a: DataFrame, b: DataFrame) -> DataFrame:
    """(clinic_id, reg_id, class); both files carry ``CLASS_FIELDS``."""
    mine = a.select(F.col("rec_id").alias("clinic_id"), F.struct(*CLASS_FIELDS).alias("a"))
    theirs = b.select(F.col("rec_id").alias("reg_id"), F.struct(*CLASS_FIELDS).alias("b"))
    return pairs.select("clinic_id", "reg_id").join(mine, "clinic_id").join(theirs, "reg_id").select("clinic_id", "reg_id", agreement_class().alias("class"))


def select_best(scored: DataFrame) -> DataFrame:
    """Each patient's candidates of the lowest class and then largest score; several are left for review."""
    w = Window.partitionBy("clinic_id").orderBy("class", F.col("score").desc())
    top = scored.withColumn("r", F.rank().over(w)).where("r = 1").drop("r")
    return top.withColumn("needs_review", F.count("*").over(Window.partitionBy("clinic_id")) > 1)


def patterns(pairs: DataFrame, a: DataFrame, b: DataFrame, fields: tuple[str, ...] = WEIGHTED) -> DataFrame:
    """(pattern, n): agreement bits of candidate pairs, at most 2^fields rows."""
    mine = a.select(F.col("rec_id").alias("clinic_id"), *[F.col(f).alias(f"a_{f}") for f in fields])
    theirs = b.select(F.col("rec_id").alias("reg_id"), *[F.col(f).alias(f"b_{f}") for f in fields])
    both = pairs.join(mine, "clinic_id").join(theirs, "reg_id")
    bits = [F.when(F.col(f"a_{f}") == F.col(f"b_{f}"), 1 << i).otherwise(0) for i, f in enumerate(fields)]
    return both.groupBy(sum(bits[1:], bits[0]).alias("pattern")).agg(F.count("*").alias("n"))


def estimate_mu(counts: DataFrame, n_fields: int, iterations: int = 100) -> dict[str, np.ndarray | float]:
    """m and u probabilities and the share of matches, by EM over the pattern counts (which are few)."""
    rows = counts.collect()
    bits = np.array([[r["pattern"] >> i & 1 for i in range(n_fields)] for r in rows], float)
    n = np.array([r["n"] for r in rows], float)
    m, u, share = np.full(n_fields, 0.9), np.full(n_fields, 0.1), 0.1
    for _ in range(iterations):
        like = lambda p: np.prod(np.where(bits == 1, p, 1 - p), axis=1)
        a, b = share * like(m), (1 - share) * like(u)
        w = n * a / np.maximum(a + b, 1e-300)
        share = w.sum() / n.sum()
        m = np.clip((w @ bits) / max(w.sum(), 1e-12), 1e-6, 1 - 1e-6)
        u = np.clip(((n - w) @ bits) / max((n - w).sum(), 1e-12), 1e-6, 1 - 1e-6)
    return {"m": m, "u": u, "share": float(share)}
