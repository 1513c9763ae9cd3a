"""Agreement on the date of death, which no rule uses, as the measure of a rule."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .rules import EVALUATED, RuleSet


def rule_list(spark: SparkSession, rules: RuleSet) -> DataFrame:
    return spark.range(1).select(F.explode(F.array(*[F.lit(r.id) for r in rules])).alias("rule_id"))


def agreement(tolerance_days: int = 0) -> Column:
    """True, false, or null where the register has no date."""
    return F.abs(F.datediff("reg_dod", "clinic_dod")) <= tolerance_days


def scorecard(pairs: DataFrame, rules: RuleSet = EVALUATED, tolerance_days: int = 0) -> DataFrame:
    """(rule_id, n_one_to_one, n_match, n_nonmatch, match_rate) of every rule; pairs without a register date are left out."""
    ok = agreement(tolerance_days)
    counts = pairs.groupBy("rule_id").agg(F.count(ok).alias("n_one_to_one"), F.count_if(ok).alias("n_match"))
    full = rule_list(pairs.sparkSession, rules).join(counts, "rule_id", "left").na.fill(0, ["n_one_to_one", "n_match"])
    n, k = F.col("n_one_to_one"), F.col("n_match")
    return full.select("rule_id", "n_one_to_one", "n_match", (n - k).alias("n_nonmatch"), F.when(n > 0, k.cast("double") / n.cast("double")).alias("match_rate"))


def wilson(k: Column, n: Column, z: float = 1.959963984540054) -> tuple[Column, Column]:
    """The score interval of a proportion."""
    n, k = n.cast("double"), k.cast("double")
    p, zz = k / n, z * z
    mid, half = (p + zz / (n * 2.0)) / (zz / n + 1.0), F.sqrt(p * (F.lit(1.0) - p) / n + zz / (n * n * 4.0)) * z / (zz / n + 1.0)
    return mid - half, mid + half


def dod_gaps(pairs: DataFrame) -> DataFrame:
    gap = F.datediff("reg_dod", "clinic_dod").alias("gap_days")
    return pairs.where("reg_dod is not null").select("rule_id", gap).groupBy("rule_id", "gap_days").agg(F.count("*").alias("n_pairs"))


def confusion(pairs: DataFrame, clinic: DataFrame, register: DataFrame, rules: RuleSet = EVALUATED) -> DataFrame:
    """Against the hidden truth: tp, fp, fn, tn of each rule over the validation subset, precision, recall, specificity, F1."""
    subset = clinic.where("death_date is not null").select(F.col("rec_id").alias("clinic_id"), F.col("true_person").alias("clinic_true"))
    reg = register.select(F.col("rec_id").alias("reg_id"), F.col("true_person").alias("reg_true"))
    known = subset.join(reg.select(F.col("reg_true").alias("clinic_true")).distinct(), "clinic_true", "left_semi").select("clinic_id", F.lit(True).alias("in_register"))
    people = subset.join(known, "clinic_id", "left")
    totals = people.agg(F.count("*").alias("people"), F.count("in_register").alias("known"))
    judged = pairs.select("rule_id", "clinic_id", "reg_id").join(people, "clinic_id").join(reg, "reg_id")
    right = F.col("clinic_true") == F.col("reg_true")
    per = judged.groupBy("rule_id").agg(F.count_if(right).alias("tp"), F.count_if(~right).alias("fp"), F.count_if(~right & F.col("in_register").isNull()).alias("fp_unknown"))
    full = rule_list(pairs.sparkSession, rules).join(per, "rule_id", "left").na.fill(0).crossJoin(F.broadcast(totals))  # one row
    fn = F.col("known") - F.col("tp")
    tn = F.col("people") - F.col("known") - F.col("fp_unknown")
    d = lambda a, b: F.when(b > 0, a.cast("double") / b.cast("double"))
    tp, fp = F.col("tp"), F.col("fp")
    return full.select(
        "rule_id", "tp", "fp", fn.alias("fn"), tn.alias("tn"), d(tp, tp + fp).alias("precision"), d(tp, tp + fn).alias("recall"), d(tn, tn + fp).alias("specificity"), d(tp * 2, tp * 2 + fp + fn).alias("f1")
    )


def frontier(scores: DataFrame, profile: DataFrame) -> DataFrame:
    """Rules by falling rate with the best coverage so far; ``on_frontier`` where a rule raises it."""
    w = Window.orderBy(F.col("match_rate").desc(), "rule_id").rowsBetween(Window.unboundedPreceding, -1)
    joined = scores.where("match_rate is not null").join(profile.select("rule_id", "n_complete"), "rule_id")
    best = F.coalesce(F.max("n_complete").over(w), F.lit(-1))
    return joined.select("rule_id", "match_rate", "n_complete", (F.col("n_complete") > best).alias("on_frontier"))


def ranking_shift(a: DataFrame, b: DataFrame) -> DataFrame:
    """Ranks of the same rules on two pairs of files."""

    def ranked(s: DataFrame, name: str) -> DataFrame:
        w = Window.orderBy(F.col("match_rate").desc(), "rule_id")
        return s.where("match_rate is not null").select("rule_id", F.row_number().over(w).alias(name))

    both = ranked(a, "rank_a").join(ranked(b, "rank_b"), "rule_id", "full_outer")
    return both.select("rule_id", "rank_a", "rank_b", (F.col("rank_b") - F.col("rank_a")).alias("shift"))


def deceased_overlap(clinic: DataFrame, found: DataFrame) -> DataFrame:
    """Patients deceased by the clinic only, by the register only, by both, and in all."""
    linked = found.select(F.col("clinic_id").alias("rec_id")).distinct().withColumn("there", F.lit(True))
    here, there = F.col("death_date").isNotNull(), F.col("there").isNotNull()
    return clinic.join(linked, "rec_id", "left").agg(
        F.count_if(here & ~there).alias("clinic_only"), F.count_if(~here & there).alias("register_only"), F.count_if(here & there).alias("both"), F.count_if(here | there).alias("total")
    )
