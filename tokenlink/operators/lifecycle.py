"""Deliveries, register variants, release policy and plausibility."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def latest(rows: DataFrame, key: str, order: tuple[str, ...], keep: tuple[str, ...]) -> DataFrame:
    """The newest row of each key, by partial aggregation."""
    return rows.groupBy(key).agg(F.max_by(F.struct(*keep), F.struct(*order)).alias("x")).select(key, "x.*")


def public_file(register: DataFrame, as_of: str, months: int = 36) -> DataFrame:
    """Without deaths of the last three years."""
    return register.where(F.col("dod") < F.add_months(F.lit(as_of).cast("date"), -months))


def without_state(register: DataFrame, since: str | None = None) -> DataFrame:
    """Without records reported by states, of all times or of deaths since a date."""
    state = F.col("source") == "state"
    return register.where(~(state & (F.col("dod") >= F.lit(since).cast("date")) if since else state))


def coverage_by_year(register: DataFrame) -> DataFrame:
    """Deaths by year and their change from the year before."""
    per = register.where("dod is not null").groupBy(F.year("dod").alias("year")).agg(F.count("*").alias("n_deaths"))
    return per.select("year", "n_deaths", (F.col("n_deaths") - F.lag("n_deaths").over(Window.orderBy("year"))).alias("change"))


def released(dod: Column, clinic_dod: Column, as_of: str, mode: str = "anniversary") -> Column:
    """The register's date if it may be shown: three years old (to the day, or by the end of the year), or confirmed by the clinic."""
    day = F.lit(as_of).cast("date")
    old = F.add_months(dod, 36) <= day if mode == "anniversary" else F.year(dod) + 3 < F.year(day)
    return F.when(old | F.coalesce(dod == clinic_dod, F.lit(False)), dod)


def release(presented: DataFrame, as_of: str, mode: str = "anniversary") -> DataFrame:
    """(patient, deceased, clinic_dod, register_dod): the flag stays where the date is withheld."""
    dod = F.col("register.dod")
    return presented.select("patient", (F.col("clinic_dod").isNotNull() | dod.isNotNull()).alias("deceased"), "clinic_dod", released(dod, F.col("clinic_dod"), as_of, mode).alias("register_dod"))


def refute_by_encounter(presented: DataFrame, encounters: DataFrame, kinds: tuple[str, ...], grace_days: int = 0) -> DataFrame:
    """Patients seen after their linked death.  Encounters shrink to the last one of a patient, so the join is an equi-join."""
    last = encounters.where(F.col("kind").isin(*kinds)).groupBy("patient").agg(F.max("day").alias("last_seen"))
    dod = F.col("register.dod")
    return presented.join(last, "patient").where(F.col("last_seen") > F.date_add(dod, grace_days)).select("patient", dod.alias("register_dod"), "last_seen", F.datediff("last_seen", dod).alias("days_after"))


def vital_status(presented: DataFrame) -> DataFrame:
    """Deceased or unknown; absence from a death file never means alive."""
    dead = F.col("clinic_dod").isNotNull() | F.col("register.dod").isNotNull()
    return presented.select("patient", F.when(dead, "deceased").otherwise("unknown").alias("status"))


def research_filter(rows: DataFrame, predicate: Column | str) -> DataFrame:
    return rows.where(predicate)
