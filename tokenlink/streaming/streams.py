"""Streams of person records, deliveries and encounters.

Stateless steps reuse the batch functions.  Links are not monotone (a new record can destroy one), so counts
are kept and published by upsert in ``update`` mode; nothing is appended that may have to be taken back.
"""

from __future__ import annotations

import json
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import DataStreamWriter

from ..operators.linkage import KEY, one_to_one, token_db
from ..operators.rules import EVALUATED, RuleSet
from ..operators.standardize import standardize
from ..operators.tokens import tokens_long


def file_stream(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def event_stream(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """Events with ``ts`` as an instant, which watermarks need."""
    return file_stream(spark, path, schema).withColumn("ts", F.col("ts").cast("timestamp"))


def tokenized(raw: DataFrame, id_col: str, rules: RuleSet = EVALUATED) -> DataFrame:
    """Standardize and tokenize arriving records; stateless."""
    return tokens_long(standardize(raw, id_col), rules, keep=("death_date",))


def running_counts(long: DataFrame) -> DataFrame:
    """Records of each key so far, for ``update`` mode: a key that reaches two is no longer unique."""
    return long.groupBy(*KEY).agg(F.count("*").alias("n_records"), F.min("death_date").alias("min_dod"), F.max("death_date").alias("max_dod"), F.min("rec_id").alias("min_rec_id"))


def new_patient_links(arriving: DataFrame, register_db: DataFrame) -> Callable[[DataFrame, int], DataFrame]:
    """A batch function: patients that arrive, linked to a static register database."""

    def link(batch: DataFrame, batch_id: int) -> DataFrame:
        return one_to_one(token_db(batch), register_db).withColumn("batch_id", F.lit(batch_id))

    return link


def upsert_latest(table: str, key: str, order: tuple[str, ...]) -> Callable[[DataFrame, int], None]:
    """For ``foreachBatch``: keep the newest row of each key in Parquet parts below ``table``.

    A batch is reduced to its newest rows and written as a part of its own.  Parts are merged while the one before is
    not more than twice as large, so that a row is rewritten about log(table / batch) times, and not at every batch.
    A pointer file names the parts and the batch that made the last, so a batch that is replayed after a restart is
    recognized and changes nothing; parts that the pointer before last named are deleted.  Pointer and parts go
    through Hadoop's file system, which every table path has.
    """

    def put(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        state = _pointer(spark, table)
        if batch_id <= state["batch"]:
            return
        parts = [*state["parts"], _part(spark, _newest(batch, key, order), f"{table}/v{batch_id}")]
        made = list(parts)
        while len(parts) > 1 and parts[-2]["rows"] <= 2 * parts[-1]["rows"]:
            both = spark.read.schema(batch.schema).parquet(*[x["path"] for x in parts[-2:]])
            parts[-2:] = [_part(spark, _newest(both, key, order), f"{table}/m{batch_id}-{len(parts) - 1}")]
            made.append(parts[-1])
        named = {x["path"] for x in parts}
        gone = [x["path"] for x in made if x["path"] not in named]
        _set_pointer(spark, table, {"batch": batch_id, "key": key, "order": list(order), "parts": parts, "gone": gone})
        for path in state["gone"]:
            _delete(spark, path)

    return put


def _newest(rows: DataFrame, key: str, order: tuple[str, ...] | list[str]) -> DataFrame:
    w = Window.partitionBy(key).orderBy(*[F.col(c).desc() for c in order])
    return rows.withColumn("__rn", F.row_number().over(w)).where("__rn = 1").drop("__rn")


def _part(spark: SparkSession, rows: DataFrame, path: str) -> dict:
    rows.write.mode("overwrite").parquet(path)
    return {"path": path, "rows": spark.read.parquet(path).count()}


def current(spark: SparkSession, table: str) -> DataFrame:
    """The newest row of each key over the parts."""
    state = _pointer(spark, table)
    return _newest(spark.read.parquet(*[x["path"] for x in state["parts"]]), state["key"], state["order"])


def _delete(spark: SparkSession, path: str) -> None:
    gone = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    gone.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(gone, True)


def _path(spark: SparkSession, table: str):  # noqa: ANN202  a Java object
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(f"{table}/_current.json")
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), path


def _pointer(spark: SparkSession, table: str) -> dict:
    fs, path = _path(spark, table)
    if not fs.exists(path):
        return {"batch": -1, "parts": [], "gone": []}
    stream = fs.open(path)
    try:
        return json.loads(bytes(stream.readAllBytes()).decode())
    finally:
        stream.close()


def _set_pointer(spark: SparkSession, table: str, state: dict) -> None:
    fs, path = _path(spark, table)
    stream = fs.create(path, True)
    try:
        stream.write(bytearray(json.dumps(state).encode()))
    finally:
        stream.close()


def start(df: DataFrame, checkpoint: str | Path, mode: str = "append", name: str | None = None) -> DataStreamWriter:
    """A writer that drains what is available and stops; the checkpoint makes a restart go on where it left."""
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", str(checkpoint)).trigger(availableNow=True)
    return writer.queryName(name) if name else writer


def deduplicated(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events once each, however often they are delivered within the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])
