"""Token databases and one-to-one links.

The token database of a file counts the records of each key.  Building it is the one large exchange of the
engine; partial aggregation before it collapses frequent keys, and everything after it joins on keys that are
unique on both sides, so no join can blow up or run hot.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.written import is_short, materialize
from .rules import EVALUATED, RuleSet
from .tokens import tokens_long

KEY = ["rule_id", "token"]
#: Register records of a key beyond which it is cut into shares.
HEAVY = 10_000


def token_db(long: DataFrame) -> DataFrame:
    """(rule_id, token, n_records, n_dod, min_dod, max_dod, min_rec_id) from keys with ``death_date``."""
    return long.groupBy(*KEY).agg(
        F.count("*").alias("n_records"),
        F.count("death_date").alias("n_dod"),
        F.min("death_date").alias("min_dod"),
        F.max("death_date").alias("max_dod"),
        F.min("rec_id").alias("min_rec_id"),
    )


def file_db(std: DataFrame, rules: RuleSet = EVALUATED, sep: str = "") -> DataFrame:
    return token_db(tokens_long(std, rules, sep, ("death_date",)))


def merge_token_db(*parts: DataFrame) -> DataFrame:
    """The database of the union of disjoint files from their databases."""
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return whole.groupBy(*KEY).agg(
        F.sum("n_records").alias("n_records"), F.sum("n_dod").alias("n_dod"), F.min("min_dod").alias("min_dod"), F.max("max_dod").alias("max_dod"), F.min("min_rec_id").alias("min_rec_id")
    )


def retire(db: DataFrame, gone: DataFrame, current: DataFrame) -> DataFrame:
    """The database after records leave: only keys that ``gone`` touches are recounted, from the ``current`` keys."""
    touched = gone.select(*KEY).distinct()
    recounted = token_db(current.join(touched, KEY, "left_semi"))
    return db.join(touched, KEY, "left_anti").unionByName(recounted)


def validation_subset(std: DataFrame) -> DataFrame:
    return std.where(F.col("death_date").isNotNull())


def semi_reduce(long: DataFrame, keys: DataFrame) -> DataFrame:
    """The keys that also occur in ``keys``: uniqueness of a key needs only the records that carry it."""
    return reduce_to(long, materialize(keys.select(*KEY).distinct()))


def reduce_to(long: DataFrame, db: DataFrame) -> DataFrame:
    """:func:`semi_reduce` to the keys of a written table, which are measured: broadcast up to a fixed size, beyond
    which the join shuffles."""
    wanted = db.select(*KEY)
    return long.join(F.broadcast(wanted) if is_short(wanted, F.octet_length("token") + 16) else wanted, KEY, "left_semi")


def one_to_one(a_db: DataFrame, b_db: DataFrame, unique: str = "record") -> DataFrame:
    """Keys with a single record in ``a`` and, in ``b``, a single record or (``date``) a single date of death."""
    a = a_db.where("n_records = 1").select(*KEY, F.col("min_rec_id").alias("clinic_id"), F.col("min_dod").alias("clinic_dod"))
    alone = F.col("n_records") == 1 if unique == "record" else F.col("min_dod") == F.col("max_dod")
    b = b_db.where(alone).select(*KEY, F.col("min_rec_id").alias("reg_id"), F.col("min_dod").alias("reg_dod"))
    return a.join(b, KEY)


def subset_pairs(clinic: DataFrame, register: DataFrame, rules: RuleSet = EVALUATED, unique: str = "record", reduce: bool = True, sep: str = "") -> DataFrame:
    """One-to-one pairs between the validation subset and the register."""
    subset = materialize(file_db(validation_subset(clinic), rules, sep).where("n_records = 1"))
    long = tokens_long(register, rules, sep, ("death_date",))
    return one_to_one(subset, token_db(reduce_to(long, subset) if reduce else long), unique)


def link_outcomes(clinic: DataFrame, register: DataFrame, rules: RuleSet = EVALUATED) -> DataFrame:
    """What becomes of the subset's keys: counts by rule and outcome."""
    a = file_db(validation_subset(clinic), rules).select(*KEY, F.col("n_records").alias("here"))
    there = token_db(semi_reduce(tokens_long(register, rules, keep=("death_date",)), a)).select(*KEY, F.col("n_records").alias("there"))
    outcome = F.when(F.col("here") > 1, "repeated_in_subset").when(F.col("there").isNull(), "absent_in_register").when(F.col("there") > 1, "repeated_in_register").otherwise("one_to_one")
    return a.join(there, KEY, "left").withColumn("outcome", outcome).groupBy("rule_id", "outcome").agg(F.count("*").alias("n_keys"))


def links(clinic: DataFrame, register: DataFrame, rules: RuleSet = EVALUATED, sep: str = "") -> DataFrame:
    """(rule_id, clinic_id, reg_id, clinic_dod, reg_dod) for keys unique in both whole files."""
    mine = materialize(file_db(clinic, rules, sep).where("n_records = 1"))
    theirs = token_db(reduce_to(tokens_long(register, rules, sep, ("death_date",)), mine))
    return one_to_one(mine, theirs).drop("token")


def link_any(found: DataFrame) -> DataFrame:
    """Patients linked by at least one rule, with the number of rules and of distinct register records."""
    per = found.groupBy("clinic_id", "reg_id").agg(F.count("*").alias("n"))
    return per.groupBy("clinic_id").agg(F.sum("n").alias("n_rules"), F.count("*").alias("n_targets"), F.min("reg_id").alias("min_reg_id"))


def link_cascade(found: DataFrame, order: dict[int, int]) -> DataFrame:
    """The link of each patient's first rule in ``order`` (rule id to rank); a single pass instead of one per tier."""
    rank = F.element_at(F.create_map(*[F.lit(x) for kv in order.items() for x in kv]), F.col("rule_id"))
    best = F.min_by(F.struct("rule_id", "reg_id", "clinic_dod", "reg_dod"), F.struct(rank, F.col("rule_id"))).alias("best")
    return found.where(F.col("rule_id").isin(*order)).groupBy("clinic_id").agg(best).select("clinic_id", "best.*")


def shared_keys(mine: DataFrame, theirs: DataFrame, heavy: int = HEAVY) -> DataFrame:
    """(clinic_id, reg_id) of records that share a key, once a pair.

    A key that more than ``heavy`` register records carry is cut into shares of about that many; the clinic's records
    of the key meet each share, so that no task holds a heavy key.
    """
    counts = materialize(theirs.groupBy(*KEY).agg(F.ceil(F.count("*") / heavy).cast("int").alias("shares")).where("shares > 1"))
    if counts.isEmpty():
        return mine.join(theirs, KEY).select("clinic_id", "reg_id").distinct()
    few = F.broadcast(counts) if is_short(counts, F.octet_length("token") + 16) else counts
    shares = F.coalesce("shares", F.lit(1))
    cut = theirs.join(few, KEY, "left").withColumn("share", F.pmod(F.xxhash64("reg_id"), shares).cast("int")).drop("shares")
    met = mine.join(few, KEY, "left").withColumn("share", F.explode(F.sequence(F.lit(0), shares - 1))).drop("shares")
    return met.join(cut, [*KEY, "share"]).select("clinic_id", "reg_id").distinct()


def candidates(clinic: DataFrame, register: DataFrame, rules: RuleSet) -> DataFrame:
    """(clinic_id, reg_id) sharing a key of a loose rule."""
    mine = tokens_long(clinic, rules).withColumnRenamed("rec_id", "clinic_id")
    theirs = semi_reduce(tokens_long(register, rules), mine).withColumnRenamed("rec_id", "reg_id")
    return shared_keys(mine, theirs)


def deletions(c: Column, edits: int) -> Column:
    """What is left of a text after up to ``edits`` letters are taken out; texts within so many edits share one."""
    out = F.array(c)
    for _ in range(edits):
        fewer = lambda x: F.when(F.length(x) > 0, F.transform(F.sequence(F.lit(1), F.length(x)), lambda i: F.concat(F.substring(x, F.lit(1), i - 1), F.substring(x, i + 1, F.length(x))))).otherwise(F.array().cast("array<string>"))
        out = F.array_distinct(F.concat(out, F.flatten(F.transform(out, fewer))))
    return out


def link_fuzzy(clinic: DataFrame, register: DataFrame, edits: int = 1) -> DataFrame:
    """Pairs of the same birth date whose first and last names differ by at most ``edits`` letters each, or are exchanged.

    Texts within k edits share a text left by k deletions, so the birth date with such a remnant of the clinic's first
    name is a key that loses no pair; a birth date that many records share by default does not make all of them meet.
    """

    def keyed(std: DataFrame, side: str, *names: str) -> DataFrame:
        left = F.array_distinct(F.flatten(F.array(*[F.when(F.col(n).isNotNull(), deletions(F.col(n), edits)).otherwise(F.array().cast("array<string>")) for n in names])))
        rows = std.where("birth_date is not null").select(F.col("rec_id").alias(side), "birth_date", F.explode(left).alias("left"))
        return rows.select(side, F.lit(0).alias("rule_id"), F.concat_ws("|", "birth_date", "left").alias("token"))

    mine = keyed(clinic, "clinic_id", "first_name")
    theirs = semi_reduce(keyed(register, "reg_id", "first_name", "last_name"), mine)
    names = lambda std, side: std.select(F.col("rec_id").alias(side), *[F.col(c).alias(f"{side}_{c}") for c in ("first_name", "last_name")])
    pairs = shared_keys(mine, theirs).join(names(clinic, "clinic_id"), "clinic_id").join(names(register, "reg_id"), "reg_id")
    near = lambda a, b: F.levenshtein(F.col(a), F.col(b)) <= edits
    straight = near("clinic_id_first_name", "reg_id_first_name") & near("clinic_id_last_name", "reg_id_last_name")
    crossed = near("clinic_id_first_name", "reg_id_last_name") & near("clinic_id_last_name", "reg_id_first_name")
    return pairs.where(straight | crossed).select("clinic_id", "reg_id", F.when(straight, "straight").otherwise("crossed").alias("how"))
