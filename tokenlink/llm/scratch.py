"""Tables that cut lineage, kept in the folder every executor shares, and joins with tables of a measured size."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.written import materialize, shared_dir  # noqa: F401


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Bytes of a table that may be broadcast, and shares that a key is cut into beyond them.
BROADCAST_BYTES, SALTS = 64 << 20, 64


def attach(rows: DataFrame, short: DataFrame, key: str, short_key: str, row_bytes: int | Column) -> DataFrame:
    """``rows`` left-joined to ``short``, which holds a key once (nulls are equal).

    The short table is written and measured (``row_bytes`` a row).  Up to ``BROADCAST_BYTES`` it is broadcast, so
    that rows stay where they are; beyond, both sides are shuffled with every key cut into ``SALTS`` shares.
    """
    short = materialize(short)
    size = short.agg(F.sum(row_bytes if isinstance(row_bytes, Column) else F.lit(row_bytes)).cast("long")).first()[0] or 0
    same = F.col(key).eqNullSafe(F.col(short_key))
    if size <= BROADCAST_BYTES:
        return rows.join(F.broadcast(short), same, "left").drop(short_key)
    salted = rows.withColumn("__salt", F.pmod(F.xxhash64(*[F.col(f"`{c}`") for c, t in rows.dtypes if "map<" not in t]), F.lit(SALTS)))
    spread = short.withColumn("__part", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return salted.join(spread, same & (F.col("__salt") == F.col("__part")), "left").drop(short_key, "__salt", "__part")


def without(rows: DataFrame, key: Column, keys: DataFrame) -> DataFrame:
    """``rows`` whose key is not among the one column of ``keys``, which is written and measured: broadcast up to
    ``BROADCAST_BYTES``, so that rows stay where they are, and shuffled beyond."""
    name = keys.columns[0]
    keys = materialize(keys.distinct())
    short = 16 * keys.count() <= BROADCAST_BYTES
    return rows.join(F.broadcast(keys) if short else keys, key == F.col(name), "left_anti")
