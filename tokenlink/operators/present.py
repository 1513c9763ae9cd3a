"""Confidence categories and the date published for each patient."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def category(rate: Column, cuts: tuple[float, float] = (80.0, 50.0)) -> Column:
    """1 above the upper cut, 3 below the lower one, 2 between them with both ends; null without a rate."""
    pct = rate * 100.0
    return F.when(pct > cuts[0], 1).when(pct >= cuts[1], 2).when(pct < cuts[1], 3)


def categorize(scores: DataFrame, cuts: tuple[float, float] = (80.0, 50.0)) -> DataFrame:
    return scores.withColumn("category", category(F.col("match_rate"), cuts))


def rule_priority(scores: DataFrame) -> DataFrame:
    """Rules with a rate, ranked by it unrounded, ties by id; a handful of rows."""
    w = Window.orderBy(F.col("match_rate").desc(), "rule_id")
    return categorize(scores).where("match_rate is not null").select("rule_id", "match_rate", "category", F.row_number().over(w).alias("priority"))


def best_link(found: DataFrame, priority: DataFrame) -> DataFrame:
    """The link of each patient's best rule: an aggregate, cheaper than a window."""
    ranked = found.join(F.broadcast(priority.select("rule_id", "category", "priority")), "rule_id")  # one row a rule
    best = F.min_by(F.struct("rule_id", "category", "priority", "reg_id", "reg_dod"), "priority").alias("best")
    return ranked.groupBy("clinic_id").agg(best).select("clinic_id", "best.*")


def present(clinic: DataFrame, best: DataFrame) -> DataFrame:
    """Every patient with the clinic's own date and, from the register, date, category and rule as one struct."""
    got = best.select(F.col("clinic_id").alias("__id"), F.struct(F.col("reg_dod").alias("dod"), "category", "rule_id").alias("register"))
    return clinic.select(F.col("rec_id").alias("patient"), F.col("death_date").alias("clinic_dod")).join(got, F.col("patient") == F.col("__id"), "left").drop("__id")


def present_sources(clinic: DataFrame, sources: dict[str, DataFrame]) -> DataFrame:
    """One best link for each source, as an array sorted by source."""
    rows = None
    for name, best in sources.items():
        own = best.select(F.col("clinic_id").alias("__id"), F.struct(F.lit(name).alias("source"), F.col("reg_dod").alias("dod"), "category", "rule_id").alias("s"))
        rows = own if rows is None else rows.unionByName(own)
    gathered = rows.groupBy("__id").agg(F.array_sort(F.collect_list("s")).alias("sources"))  # one a source
    return clinic.select(F.col("rec_id").alias("patient"), F.col("death_date").alias("clinic_dod")).join(gathered, F.col("patient") == F.col("__id"), "left").drop("__id")


def conflicts(found: DataFrame) -> DataFrame:
    """Patients whose rules point at different register records or dates."""
    targets = found.groupBy("clinic_id", "reg_id").agg(F.count("*").alias("n"), F.min("reg_dod").alias("dod"))
    per = targets.groupBy("clinic_id").agg(F.sum("n").alias("n_links"), F.count("*").alias("n_targets"), F.min("dod").alias("min_dod"), F.max("dod").alias("max_dod"))
    return per.where("n_targets > 1")


def shared_targets(found: DataFrame) -> DataFrame:
    """Register records that several patients are linked to."""
    pairs = found.groupBy("reg_id", "clinic_id").agg(F.count("*").alias("n"))
    return pairs.groupBy("reg_id").agg(F.count("*").alias("n_patients"), F.min("clinic_id").alias("first_patient")).where("n_patients > 1")


def refresh_diff(old: DataFrame, new: DataFrame) -> DataFrame:
    """Patients by what a refresh does to their published date: appears, vanishes, changes, stays."""
    a = old.select(F.col("clinic_id").alias("a_id"), F.col("reg_dod").alias("a_dod"))
    b = new.select(F.col("clinic_id").alias("b_id"), F.col("reg_dod").alias("b_dod"))
    what = F.when(F.col("a_id").isNull(), "appears").when(F.col("b_id").isNull(), "vanishes").when(F.col("a_dod").eqNullSafe(F.col("b_dod")), "stays").otherwise("changes")
    return a.join(b, F.col("a_id") == F.col("b_id"), "full_outer").select(F.coalesce("a_id", "b_id").alias("patient"), what.alias("change"))


def sensitivity(visits: DataFrame, presented: DataFrame, days: int = 30) -> DataFrame:
    """Return within ``days`` of a visit under five treatments of deaths.

    visits: (patient, day).  A treatment leaves out visits whose patient had died by the end of the period,
    counting as deaths: none, the clinic's, and register dates of category 1, up to 2, up to 3.
    """
    w = Window.partitionBy("patient").orderBy("day", "visit_id")
    flagged = visits.withColumn("next_day", F.lead("day").over(w)).join(presented, "patient", "left")
    returned = F.coalesce(F.datediff("next_day", "day") <= days, F.lit(False))
    steps = [F.struct(F.lit(0).alias("step"), F.lit("none").alias("deaths"), F.lit(None).cast("date").alias("dod")), F.struct(F.lit(1).alias("step"), F.lit("clinic").alias("deaths"), F.col("clinic_dod").alias("dod"))]
    for c in (1, 2, 3):
        dod = F.coalesce("clinic_dod", F.when(F.col("register.category") <= c, F.col("register.dod")))
        steps.append(F.struct(F.lit(c + 1).alias("step"), F.lit(f"category_{c}").alias("deaths"), dod.alias("dod")))
    rows = flagged.withColumn("returned", returned).select("day", "returned", F.inline(F.array(*steps)))
    alive = F.col("dod").isNull() | (F.col("dod") > F.date_add("day", days))
    counted = rows.where(alive).groupBy("step", "deaths").agg(F.count("*").alias("n_visits"), F.count_if("returned").alias("n_returns"))
    return counted.withColumn("return_rate", F.col("n_returns").cast("double") / F.col("n_visits").cast("double"))


def quality_report(fields: DataFrame, tokens: DataFrame, scores: DataFrame, path: str | None = None) -> dict[str, DataFrame]:
    """What to publish with a linkage: field profile, key profile, categorized scorecard; optionally written."""
    report = {"fields": fields, "tokens": tokens, "rules": categorize(scores)}
    if path:
        for name, df in report.items():
            df.write.mode("overwrite").parquet(f"{path}/{name}.parquet")
            df.coalesce(1).write.mode("overwrite").option("header", True).csv(f"{path}/{name}.csv")  # tens of rows
            df.coalesce(1).write.mode("overwrite").json(f"{path}/{name}.json")
    return report
