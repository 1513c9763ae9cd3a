"""Deliveries in their raw formats: fixed width, delimited, JSON lines, and a paged remote source."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

Layout = tuple[tuple[str, int, str], ...]


def to_fixed_width(df: DataFrame, layout: Layout) -> DataFrame:
    """One text column ``value``; fields are padded, and cut where too long."""
    return df.select(F.concat(*[F.rpad(F.coalesce(F.col(c).cast("string"), F.lit("")), n, " ") for c, n, _ in layout]).alias("value"))


def from_fixed_width(lines: DataFrame, layout: Layout) -> DataFrame:
    """Typed columns from ``value``; blanks become null, except in strings, which are only trimmed at the right."""
    out, at = [], 1
    for c, n, kind in layout:
        raw = F.rtrim(F.substring("value", at, n))
        out.append((raw if kind == "string" else F.when(raw != "", raw).try_cast(kind)).alias(c))
        at += n
    return lines.select(*out)


def read_quarantined(spark: SparkSession, path: str, schema: str, fmt: str = "csv", **options: str) -> tuple[DataFrame, DataFrame]:
    """Good rows, and rows that do not parse with their text."""
    reader = spark.read.schema(f"{schema}, _corrupt string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt").options(**options)
    rows = reader.format(fmt).load(path)
    return rows.where("_corrupt is null").drop("_corrupt"), rows.where("_corrupt is not null")


def write_tokens(long: DataFrame, table: str, buckets: int = 64) -> None:
    """Keys partitioned by rule and bucketed by key, so that repeated joins need no exchange."""
    long.write.mode("overwrite").partitionBy("rule_id").bucketBy(buckets, "token").sortBy("token").saveAsTable(table)


class _Page(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _PagedReader(DataSourceReader):
    def __init__(self, total: int, page: int):
        self.total, self.page = total, page

    def partitions(self) -> list[InputPartition]:
        return [_Page(a, min(a + self.page, self.total)) for a in range(0, self.total, self.page)] or [_Page(0, 0)]

    def read(self, partition: _Page) -> Iterator[tuple]:
        for i in range(partition.first, partition.last):
            yield i, f"{100000000 + i * 7919 % 59999 * 10000 + 1}", f"{1910 + i % 90}0101"


class PagedDelivery(DataSource):
    """A delivery fetched page by page, one task a page; here the pages are generated."""

    @classmethod
    def name(cls) -> str:
        return "paged_delivery"

    def schema(self) -> str:
        return "person long, ssn string, birth_date string"

    def reader(self, schema: object) -> DataSourceReader:
        return _PagedReader(int(self.options.get("total", 1000)), int(self.options.get("page", 100)))
