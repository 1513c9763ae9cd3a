"""Two-pass external shuffle into shards.

Pass one scatters rows uniformly into buckets by a seeded hash and writes them.  Pass two puts every bucket
through a seeded Fisher-Yates shuffle and numbers the rows through.  Row number modulo the shard count is the
shard, the quotient the slot, so shard sizes differ by at most one row (law ``rows``).

Every draw is a hash of the seed, the bucket and the step, and buckets start from a canonical order, so the
permutation depends on the rows and the seed alone: not on partitions, tasks or the order of arrival.  Buckets
are cut into chunks of bounded rows and bytes, which bounds what a task gathers, whatever the hash gives.

Equal rows are counted before the shuffle and numbered as copies, block by block, and copies scatter like
other rows: a row that makes up a third of the table meets no task as a whole.

Defined results.  A null text has no bytes and checksum 0.  Null ids are ids like any other; repeated rows each
get a place.  A very long text takes a chunk of its own where rows carry texts.  An empty table gives no rows.
Columns named ``shard`` or ``slot`` in the input are replaced by :func:`write_shards`; no other name clashes.
"""

from __future__ import annotations

from math import ceil

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .scratch import materialize

#: Buckets whose offsets are summed by one task, and copies of a row that are numbered by one.
_GROUP, _COPIES = 1024, 4096


def _shuffled(size: Column, *seeds: Column) -> Column:
    """A Fisher-Yates permutation of 0..size-1, grown from the left: step i swaps i with a draw from 0..i."""
    steps = F.transform(F.sequence(F.lit(0), size - 1), lambda i: F.struct(i.alias("i"), F.pmod(F.xxhash64(*seeds, i), i + 1).cast("int").alias("j")))

    def swap(done: Column, x: Column) -> Column:
        moved = F.concat(F.slice(done, F.lit(1), x["j"]), F.array(x["i"]), F.slice(done, x["j"] + 2, x["i"] - x["j"] - 1), F.slice(done, x["j"] + 1, F.lit(1)))
        return F.when(x["i"] == x["j"], F.concat(done, F.array(x["i"]))).otherwise(moved)

    return F.aggregate(steps, F.expr("cast(array() as array<int>)"), swap)


def _copies(rows: DataFrame) -> DataFrame:
    """Rows of (row struct) with ``copy``, which numbers equal rows."""
    counted = rows.groupBy("row").agg(F.count("*").alias("n"))
    blocks = counted.withColumn("block", F.explode(F.sequence(F.lit(0), F.floor((F.col("n") - 1) / _COPIES))))
    last = F.least(F.col("n"), (F.col("block") + 1) * _COPIES) - 1
    return blocks.repartition(F.xxhash64("row", "block")).withColumn("copy", F.explode(F.sequence(F.col("block") * _COPIES, last))).select("row", "copy")


def scattered(rows: DataFrame, n_rows: int, bucket_rows: int, seed: int) -> DataFrame:
    """Pass one, written: (bucket, lot, row, copy)."""
    n_buckets = max(1, ceil(n_rows / bucket_rows))
    lot = lambda k: F.xxhash64(F.lit(seed + k), "row", "copy")
    return materialize(_copies(rows).select(F.pmod(lot(0), F.lit(n_buckets)).alias("bucket"), lot(1).alias("lot"), "row", "copy"))


def _positions(rows: DataFrame, n_rows: int, bucket_rows: int, seed: int, weight: Column, chunk_bytes: int) -> DataFrame:
    """Add ``position``, a random permutation of 0..n-1, to rows of (row struct); ``weight``: bytes of a row."""
    thrown = scattered(rows, n_rows, bucket_rows, seed)
    counts = thrown.groupBy("bucket").agg(F.count("*").alias("n")).withColumn("band", F.floor(F.col("bucket") / _GROUP))
    bands = counts.groupBy("band").agg(F.sum("n").alias("band_n"))
    before = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    band_start = bands.select("band", F.coalesce(F.sum("band_n").over(before(Window.orderBy("band"))), F.lit(0)).alias("band_start"))
    starts = counts.join(band_start, "band").select(
        "bucket",
        (F.col("band_start") + F.coalesce(F.sum("n").over(before(Window.partitionBy("band").orderBy("bucket"))), F.lit(0))).alias("start"),
    )

    order = Window.partitionBy("bucket").orderBy("lot", "copy", "row")
    ahead = F.coalesce(F.sum(weight).over(before(order)), F.lit(0))
    placed = thrown.withColumn("at", F.row_number().over(order) - 1).withColumn("chunk", F.floor(F.col("at") / (2 * bucket_rows)) + F.floor(ahead / chunk_bytes))
    chunks = placed.groupBy("bucket", "chunk").agg(F.min("at").alias("first"), F.sort_array(F.collect_list(F.struct("at", "row"))).alias("rows")).join(starts, "bucket")
    drawn = chunks.withColumn("drawn", _shuffled(F.size("rows"), F.lit(seed + 2), F.col("bucket"), F.col("chunk")))
    return drawn.select("start", "first", F.posexplode(F.transform("drawn", lambda k: F.get("rows", k))).alias("k", "item")).select(
        F.col("item.row").alias("row"), (F.col("start") + F.col("first") + F.col("k")).alias("position")
    )


def assign_shards(docs: DataFrame, n_shards: int = 16, seed: int = 17, bucket_rows: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, size (UTF-8 bytes plus 1), text_crc32, law, shard, slot, grown_shard (null under this law)."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.struct(F.col(id_col).alias("id"), (F.octet_length(text).cast("long") + 1).alias("size"), F.crc32(text.cast("binary")).alias("crc")).alias("row"))
    placed = _positions(rows, docs.count(), bucket_rows, seed, F.lit(32), 1 << 30)
    return placed.select(
        F.col("row.id").alias(id_col),
        F.col("row.size").alias("size"),
        F.col("row.crc").alias("text_crc32"),
        F.lit("rows").alias("law"),
        F.pmod("position", F.lit(n_shards)).cast("int").alias("shard"),
        F.floor(F.col("position") / n_shards).cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )


def write_shards(docs: DataFrame, path: str, n_shards: int = 16, seed: int = 17, bucket_bytes: int = 8 << 20, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Write whole rows in shuffled order below ``path``/shard=k, each shard sorted by slot.

    A bucket holds about ``bucket_bytes`` by the mean row, and no chunk of one more than that and a row.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    n, size = docs.agg(F.count("*"), F.coalesce(F.sum(F.octet_length(text).cast("long")), F.lit(0))).first()
    bucket_rows = max(16, min(2048, int(bucket_bytes / max(1, size / max(1, n)))))
    keep = [c for c in docs.columns if c not in ("shard", "slot")]
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in keep]).alias("row"))
    weight = F.coalesce(F.octet_length(F.col("row").getField(text_col)).cast("long"), F.lit(0))
    placed = _positions(rows, n, bucket_rows, seed, weight, bucket_bytes).select(
        "row.*", F.pmod("position", F.lit(n_shards)).cast("int").alias("shard"), F.floor(F.col("position") / n_shards).cast("long").alias("slot")
    )
    placed.repartitionByRange(n_shards * max(1, ceil(size / n_shards / (1 << 30))), "shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
