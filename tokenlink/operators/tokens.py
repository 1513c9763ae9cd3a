"""Match keys of standardized records."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .rules import EVALUATED, Rule, RuleSet


def tokens_wide(std: DataFrame, rules: RuleSet = EVALUATED, sep: str = "") -> DataFrame:
    """rec_id and one column ``t<id>`` for each rule."""
    return std.select("rec_id", *[r.token(sep).alias(f"t{r.id}") for r in rules])


def tokens_long(std: DataFrame, rules: RuleSet = EVALUATED, sep: str = "", keep: tuple[str, ...] = ()) -> DataFrame:
    """(rec_id, kept columns, rule_id, token), one row for each key that exists; a narrow step within the scan's stage."""
    pairs = [x for r in rules for x in (F.lit(r.id), r.token(sep))]
    return std.select("rec_id", *keep, F.stack(F.lit(len(rules)), *pairs).alias("rule_id", "token")).where("token is not null")


def hashed(token: Column, rule: Column | Rule, salt: str) -> Column:
    """A keyed digest for exchange between organisations; null where the key is, so the receiver sees the rule is unusable."""
    rule_id = F.lit(rule.id) if isinstance(rule, Rule) else rule
    return F.sha2(F.concat(F.lit(salt), F.lit("|"), rule_id.cast("string"), F.lit("|"), token), 256)


def hash_tokens(long: DataFrame, salt: str) -> DataFrame:
    return long.withColumn("token", hashed(F.col("token"), F.col("rule_id"), salt))


def compact(long: DataFrame) -> DataFrame:
    """Keys as two 64-bit hashes, to shuffle 16 bytes instead of the text; for internal use, not for privacy."""
    return long.withColumn("token", F.concat(F.hex(F.xxhash64("rule_id", "token")), F.hex(F.xxhash64(F.lit(7), "token", "rule_id"))))


def key_sample(long: DataFrame, one_in: int) -> DataFrame:
    """All records of a share of the keys: multiplicities stay whole, so distinct and singleton counts scale without bias."""
    return long.where(F.pmod(F.xxhash64("rule_id", "token"), F.lit(one_in)) == 0)


def boundary_collisions(std: DataFrame, rules: RuleSet = EVALUATED) -> DataFrame:
    """Per rule: distinct keys with and without a separator; fewer without one means parts ran together."""
    pairs = [x for r in rules for x in (F.lit(r.id), r.token(""), r.token("|"))]
    long = std.select(F.stack(F.lit(len(rules)), *pairs).alias("rule_id", "bare", "apart")).where("bare is not null")
    # one grouping by both keys, then counts on what is left: no Expand of two distinct counts
    kinds = long.groupBy("rule_id", "apart").agg(F.min("bare").alias("bare"))
    per_bare = kinds.groupBy("rule_id", "bare").agg(F.count("*").alias("n"))
    out = per_bare.groupBy("rule_id").agg(F.count("*").alias("bare"), F.sum("n").alias("separated"))
    return out.select("rule_id", "bare", "separated", (F.col("separated") - F.col("bare")).alias("collisions"))
