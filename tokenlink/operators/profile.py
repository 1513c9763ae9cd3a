"""Completeness, distinctness and validity of fields and keys."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .evaluate import rule_list
from .rules import EVALUATED, RuleSet
from .standardize import MASK, cleaned
from .tokens import tokens_long

RAW = {"ssn": "ssn_raw", "last_name": "last_name_raw", "first_name": "first_name_raw", "middle_name": "middle_name_raw", "birth_date": "birth_raw", "death_date": "dod"}


def profile_fields(raw: DataFrame, blank_is_complete: bool = True) -> DataFrame:
    """(field, n_rows, n_complete, n_distinct, n_invalid, n_invalid_nonblank, null_rate, invalid_rate).

    Every row is spread to (field, value, valid) and grouped by value once, so distinct counts need no Expand.
    """
    clean = cleaned()
    valid = {f: clean[f].isNotNull() if f in clean else F.col(RAW[f]).isNotNull() for f in RAW}
    spread = [x for f, c in RAW.items() for x in (F.lit(f), F.col(c).cast("string"), valid[f])]
    long = raw.select(F.stack(F.lit(len(RAW)), *spread).alias("field", "value", "ok"))
    if not blank_is_complete:
        long = long.withColumn("value", F.when(F.trim("value") != "", F.col("value")))
    values = long.groupBy("field", "value").agg(F.count("*").alias("n"), F.count_if("ok").alias("n_ok"))
    has, blank = F.col("value").isNotNull(), F.trim("value") == ""
    amount = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("n") - F.col("n_ok"))), F.lit(0))
    out = values.groupBy("field").agg(
        F.sum("n").alias("n_rows"),
        F.coalesce(F.sum(F.when(has, F.col("n"))), F.lit(0)).alias("n_complete"),
        F.count("value").alias("n_distinct"),
        amount(has).alias("n_invalid"),
        amount(has & ~blank).alias("n_invalid_nonblank"),
    )
    rate = lambda c: c.cast("double") / F.col("n_rows").cast("double")
    return out.withColumn("null_rate", rate(F.col("n_rows") - F.col("n_complete"))).withColumn("invalid_rate", rate(F.col("n_invalid")))


def profile_tokens(db: DataFrame, n_rows: int, rules: RuleSet = EVALUATED) -> DataFrame:
    """(rule_id, n_complete, n_distinct, complete_rate, distinct_rate) from a token database."""
    per = db.groupBy("rule_id").agg(F.sum("n_records").alias("n_complete"), F.count("*").alias("n_distinct"))
    full = rule_list(db.sparkSession, rules).join(per, "rule_id", "left").na.fill(0)
    rate = lambda c: F.col(c).cast("double") / F.lit(float(n_rows))
    return full.select("rule_id", "n_complete", "n_distinct", rate("n_complete").alias("complete_rate"), rate("n_distinct").alias("distinct_rate"))


def profile_tokens_approx(std: DataFrame, rules: RuleSet = EVALUATED, rsd: float = 0.02) -> DataFrame:
    """Completeness exactly, distinct keys by HyperLogLog++: kilobytes are shuffled instead of keys."""
    return tokens_long(std, rules).groupBy("rule_id").agg(F.count("*").alias("n_complete"), F.approx_count_distinct("token", rsd).alias("n_distinct"))


def token_sketches(std: DataFrame, rules: RuleSet = EVALUATED) -> DataFrame:
    """(rule_id, sketch): mergeable by ``hll_union_agg`` as deliveries arrive."""
    return tokens_long(std, rules).groupBy("rule_id").agg(F.hll_sketch_agg("token").alias("sketch"))


def merged_sketches(*parts: DataFrame) -> DataFrame:
    """(rule_id, n_distinct) over several deliveries from their sketches."""
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return whole.groupBy("rule_id").agg(F.hll_union_agg("sketch").alias("sketch")).select("rule_id", F.hll_sketch_estimate("sketch").alias("n_distinct"))


def heavy_keys(long: DataFrame, least: int, eps: float = 1e-4, confidence: float = 0.999, seed: int = 1) -> DataFrame:
    """(rule_id, token, n_records) of the keys of ``least`` records or more, exactly.

    A count-min sketch never counts a key short, so only keys whose sketched count suffices are counted exactly, and
    the exchange carries few others.  The sketch has a fixed size, whatever the file's.
    """
    code = F.xxhash64("rule_id", "token")
    data = bytes(long.select(code.alias("k")).agg(F.count_min_sketch("k", F.lit(eps), F.lit(confidence), F.lit(seed)).alias("s")).first()["s"])
    # as Spark writes it: version, total, depth, width, a multiplier for each row, the rows
    depth, width = (int(x) for x in np.frombuffer(data, ">i4", 2, 12))
    factors = np.frombuffer(data, ">i8", depth, 20).astype(np.int64)
    table = np.frombuffer(data, ">i8", depth * width, 20 + 8 * depth).astype(np.int64).reshape(depth, width)

    @F.pandas_udf("long")
    def sketched(keys: pd.Series) -> pd.Series:
        k, counts = keys.to_numpy(np.int64), []
        for factor, row in zip(factors, table, strict=True):
            with np.errstate(over="ignore"):
                h = factor * k
                h = (h + (h >> 32)) & np.int64((1 << 31) - 1)
            counts.append(row[h % width])
        return pd.Series(np.min(counts, axis=0))

    return long.where(sketched(code) >= least).groupBy("rule_id", "token").agg(F.count("*").alias("n_records")).where(F.col("n_records") >= least)


def completeness_by_mask(std: DataFrame, rules: RuleSet = EVALUATED) -> DataFrame:
    """Completeness of every rule from the validity bits alone: at most 32 groups, and no key is built."""
    rows = []
    for r in rules:
        if r.fields <= set(MASK):
            rows.append(F.struct(F.lit(r.id).alias("rule_id"), F.lit(sum(1 << MASK.index(f) for f in r.fields)).alias("need")))
    needs = std.sparkSession.range(1).select(F.inline(F.array(*rows)))
    masks = std.groupBy("valid_mask").agg(F.count("*").alias("n"))
    held = F.sum(F.when(F.col("valid_mask").bitwiseAND(F.col("need")) == F.col("need"), F.col("n")).otherwise(0))
    return needs.join(F.broadcast(masks)).groupBy("rule_id").agg(held.alias("n_complete"))  # 32 rows at most


def multiplicity(db: DataFrame) -> DataFrame:
    return db.groupBy("rule_id", "n_records").agg(F.count("*").alias("n_tokens"))


def rate_by(std: DataFrame, group: Column, field: str = "ssn") -> DataFrame:
    """Share of valid values of a field by a group."""
    n, k = F.count("*"), F.count(field)
    return std.groupBy(group.alias("grp")).agg(n.alias("n_rows"), k.alias("n_valid"), (k.cast("double") / n.cast("double")).alias("valid_rate"))


def reconcile(fields: DataFrame, tokens: DataFrame) -> DataFrame:
    """Complete minus invalid of a field against the completeness of the rule made of that field alone."""
    pairs = (("ssn", 6), ("last_name", 18), ("first_name", 19), ("birth_date", 20))
    rows = F.array(*[F.struct(F.lit(f).alias("field"), F.lit(r).alias("rule_id")) for f, r in pairs])
    single = fields.sparkSession.range(1).select(F.inline(rows))
    joined = single.join(fields, "field").join(tokens.select("rule_id", F.col("n_complete").alias("n_tokens")), "rule_id")
    expected = F.col("n_complete") - F.col("n_invalid")
    return joined.select("field", "rule_id", expected.alias("n_expected"), "n_tokens", (F.col("n_tokens") - expected).alias("difference"))
