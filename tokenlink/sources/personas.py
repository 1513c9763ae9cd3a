"""Person files derived from the given tables by closed formulas.

The register has a person for each order, the clinic a record for each customer.  Names are words of
documents; numbers and dates are arithmetic of the keys; half of the clinic's patients are in the register.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .tables import Tables


def ssn9(p: Column) -> Column:
    return (F.lit(100000000) + p * 7919 % 59999 * 10000 + p * 69621 % 2147483647 % 101 + 1).cast("string")


def birth(p: Column, shift: int = 0, days: int = 2991, first: str = "1910-01-01", factor: int = 48271) -> Column:
    return F.date_add(F.lit(first).cast("date"), ((p * factor + shift) % 2147483647 % days).cast("int"))


def _with_words(people: DataFrame, t: Tables) -> DataFrame:
    """Add ``w``, the first words of the document that person ``p`` borrows names from, and ``g``."""
    nd = t.size("documents")
    words = t.documents.select(F.col("doc_id").alias("__doc"), F.split("text", " ", 14).alias("w"))
    people = people.withColumn("__at", F.col("p") % nd).withColumn("g", (F.floor(F.col("p") / nd) % 4).cast("int"))
    return people.join(words, F.col("__at") == F.col("__doc")).drop("__at", "__doc")


def word(i: int | Column) -> Column:
    """The i-th word, counted from one, or the empty string."""
    return F.coalesce(F.get("w", (i if isinstance(i, Column) else F.lit(i)) - 1), F.lit(""))


def register_raw(t: Tables) -> DataFrame:
    o = t.orders.select(F.col("o_orderkey").alias("p"), F.col("o_orderdate").cast("date").alias("dod"))
    p, g = F.col("p"), F.col("g")
    return _with_words(o, t).select(
        p.alias("reg_id"),
        p.alias("true_person"),
        word(g + 1).alias("first_name_raw"),
        F.when(p % 17 < 8, word(11)).otherwise("").alias("middle_name_raw"),
        word(g + 6).alias("last_name_raw"),
        F.replace(birth(p).cast("string"), F.lit("-"), F.lit("/")).alias("birth_raw"),
        ssn9(p).alias("ssn_raw"),
        "dod",
        F.when(p % 2 == 0, "F").otherwise("M").alias("gender_raw"),
        (F.lit(90000) + p % 250).cast("string").alias("zip_raw"),
        F.concat((p % 300 + 1).cast("string"), F.lit(" "), word(12)).alias("address_raw"),
        (p % 25).cast("int").alias("birth_state"),
        F.when(p % 5 < 3, "state").otherwise("other").alias("source"),
        (p % 5).cast("int").alias("race"),
        (p % 4).cast("int").alias("marital"),
        word(13).alias("father_surname"),
        (p % 25).cast("int").alias("residence_state"),
    )


def clinic_raw(t: Tables) -> DataFrame:
    no = t.size("orders")
    k = F.col("c_custkey")
    p = F.when(k % 20 == 17, (k - 1) * 10 + 3).when(k % 4 > 1, k + no).otherwise(k * 10 + 3)
    people = t.customer.select(k, p.alias("p")).withColumn("__order", F.col("p") % no)
    orders = t.orders.select(F.col("o_orderkey").alias("__key"), F.col("o_orderdate").cast("date").alias("order_date"))
    people = people.join(orders, F.col("__order") == F.col("__key"), "left")
    p, g, m = F.col("p"), F.col("g"), k % 100
    hyphened = F.concat_ws("-", F.substring(ssn9(p), 1, 3), F.substring(ssn9(p), 4, 2), F.substring(ssn9(p), 6, 4))
    # Placeholders and impossible numbers, by the upper end of m they hold for
    fixed = ((20, "999-99-9999"), (33, "888-88-8888"), (36, "000-00-0000"), (37, "912-34-5678"), (38, "123-00-4567"), (39, "666-12-3456"), (40, "000-12-3456"), (41, "123-45-6789"), (42, "111-11-1111"))
    ssn = F.when(m < fixed[0][0], fixed[0][1])
    for below, value in fixed[1:]:
        ssn = ssn.when(m < below, value)
    return _with_words(people, t).select(
        k.alias("clinic_id"),
        p.alias("true_person"),
        F.when(k % 11 == 5, F.substring(word(g + 1), 1, 3)).when(k % 29 == 7, "%^3").otherwise(word(g + 1)).alias("first_name_raw"),
        F.when(k % 9 < 3, word(11)).alias("middle_name_raw"),
        F.when(k % 13 == 6, F.concat(word(g + 6), F.lit("e"))).otherwise(word(g + 6)).alias("last_name_raw"),
        F.when(k % 97 == 9, "1803-02-01").when(k % 23 == 4, birth(p, 1).cast("string")).otherwise(birth(p).cast("string")).alias("birth_raw"),
        ssn.when(m >= 57, hyphened).alias("ssn_raw"),
        F.when(k % 5 < 2, F.date_add("order_date", F.when(k % 7 == 0, 4).otherwise(0))).alias("dod"),
        F.when(k % 31 != 3, F.when(p % 2 == 0, "F").otherwise("M")).alias("gender_raw"),
        F.when(k % 6 == 1, "94305").otherwise((F.lit(90000) + p % 250).cast("string")).alias("zip_raw"),
        F.concat((p % 300 + 1).cast("string"), F.lit(" "), word(12)).alias("address_raw"),
        (p % 25).cast("int").alias("birth_state"),
        F.when(k % 8 != 2, (p % 5).cast("int")).alias("race"),
        F.when(k % 9 == 4, (p + 1) % 4).otherwise(p % 4).cast("int").alias("marital"),
        word(13).alias("father_surname"),
        F.when(k % 10 == 3, (p + 1) % 25).otherwise(p % 25).cast("int").alias("residence_state"),
    )


def deliveries(t: Tables) -> DataFrame:
    return t.lineitem.select(F.col("l_orderkey").alias("person"), F.col("l_linenumber").alias("version"), F.col("l_shipdate").cast("date").alias("dod"))


def encounters(t: Tables) -> DataFrame:
    back = (F.lit(8400) + F.col("user_id") * 17 % 2000).cast("int")
    return t.events.select("event_id", F.col("user_id").alias("patient"), F.date_sub(F.col("ts").cast("date"), back).alias("day"), F.col("event_type").alias("kind"))


def register_dup_raw(t: Tables) -> DataFrame:
    """The register with some deaths reported twice, under another id."""
    r = register_raw(t)
    return r.unionByName(r.where("true_person % 25 = 3").withColumn("reg_id", F.col("reg_id") + t.size("orders")))


def second_pair(t: Tables) -> tuple[DataFrame, DataFrame]:
    """Another register (parts) and clinic (suppliers), with few names and no middle names."""

    def person(frame: DataFrame, key: str, p: Column) -> DataFrame:
        parts = F.split("p_name", " ")
        return frame.select(
            key,
            p.alias("true_person"),
            F.coalesce(F.get(parts, F.lit(0)), F.lit("")).alias("first_name_raw"),
            F.lit(None).cast("string").alias("middle_name_raw"),
            F.coalesce(F.get(parts, F.lit(1)), F.lit("")).alias("last_name_raw"),
            birth(p, 0, 401, "1930-01-01").cast("string").alias("birth_raw"),
            ssn9(p).alias("ssn_raw"),
            birth(p, 0, 2400, "1995-01-01", 69621).alias("dod"),
            *[F.lit(None).cast("string").alias(c) for c in ("gender_raw", "zip_raw", "address_raw")],
        )

    reg = person(t.part.withColumn("reg_id", F.col("p_partkey")), "reg_id", F.col("p_partkey"))
    copied = t.supplier.withColumn("p_partkey", F.col("s_suppkey") * 20 + 1).join(t.part.select("p_partkey", "p_name"), "p_partkey").withColumnRenamed("s_suppkey", "clinic_id")
    s = F.col("clinic_id")
    clinic = person(copied, "clinic_id", F.col("p_partkey")).withColumn("ssn_raw", F.when(s % 3 != 0, F.col("ssn_raw"))).withColumn("dod", F.date_add("dod", F.when(s % 9 == 1, 4).otherwise(0)))
    return reg, clinic
