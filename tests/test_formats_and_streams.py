from __future__ import annotations

from pyspark.sql import functions as F

from tokenlink.operators import lifecycle, linkage, present, profile
from tokenlink.operators.rules import RuleSet
from tokenlink.operators.standardize import standardize
from tokenlink.operators.tokens import tokens_long
from tokenlink.plans.context import Context
from tokenlink.sources import delivery
from tokenlink.streaming import streams, windows


def test_formats(spark, data, tmp_path):
    rows = Context(spark, data).register_raw.select("reg_id", "first_name_raw", "ssn_raw", "dod").where("first_name_raw <> '' and not contains(first_name_raw, '\n')")
    for fmt in ("csv", "json", "orc"):
        rows.write.format(fmt).option("header", False).save(f"{tmp_path}/{fmt}")
        back = spark.read.schema(rows.schema).format(fmt).load(f"{tmp_path}/{fmt}")
        assert back.exceptAll(rows).count() == 0 and back.count() == rows.count()


def test_quarantine(spark, tmp_path):
    (tmp_path / "x.csv").write_text("1,1999-01-01\nnot a number,1999-01-01\n2,1999-01-02\n")
    good, bad = delivery.read_quarantined(spark, str(tmp_path / "x.csv"), "id long, day date")
    assert {r["id"] for r in good.collect()} == {1, 2}
    assert [r["_corrupt"] for r in bad.collect()] == ["not a number,1999-01-01"]


def test_paged_source(spark):
    spark.dataSource.register(delivery.PagedDelivery)
    df = spark.read.format("paged_delivery").option("total", 250).option("page", 100).load()
    assert df.count() == 250 and df.rdd.getNumPartitions() == 3


def test_bucketed_tokens(spark, data):
    long = tokens_long(Context(spark, data).clinic, RuleSet.of("S B", "L F B"))
    spark.sql("DROP TABLE IF EXISTS clinic_keys")
    delivery.write_tokens(long, "clinic_keys", 4)
    assert spark.table("clinic_keys").count() == long.count()
    spark.sql("DROP TABLE clinic_keys")


def test_quality_report(spark, data, tmp_path):
    c = Context(spark, data)
    report = present.quality_report(profile.profile_fields(c.clinic_raw), profile.profile_tokens(linkage.file_db(c.clinic), 150), c.scores, str(tmp_path))
    assert spark.read.parquet(f"{tmp_path}/rules.parquet").count() == report["rules"].count() == 20


def test_stream_equals_batch(spark, data, tmp_path):
    """Arriving records are tokenized, counted and linked like a batch."""
    c = Context(spark, data)
    raw = c.clinic_raw
    raw.repartition(3).write.parquet(f"{tmp_path}/in")
    schema = ", ".join(f"{n} {t}" for n, t in raw.dtypes)
    stream = streams.tokenized(streams.file_stream(spark, f"{tmp_path}/in", schema), "clinic_id")
    streams.start(streams.running_counts(stream), f"{tmp_path}/ck", "complete", "key_counts").format("memory").start().awaitTermination(120)
    expected = linkage.file_db(standardize(raw, "clinic_id")).select("rule_id", "token", "n_records")
    got = spark.table("key_counts").select("rule_id", "token", "n_records")
    assert got.exceptAll(expected).count() == 0 and expected.exceptAll(got).count() == 0

    found: list = []
    link = streams.new_patient_links(stream, linkage.file_db(c.register).cache())
    one = raw.coalesce(1)
    one.write.parquet(f"{tmp_path}/in1")
    whole = streams.tokenized(streams.file_stream(spark, f"{tmp_path}/in1", schema), "clinic_id")
    streams.start(whole, f"{tmp_path}/ck1").foreachBatch(lambda b, i: found.extend(link(b, i).select("rule_id", "clinic_id", "reg_id").collect())).start().awaitTermination(120)
    assert sorted(map(tuple, found)) == sorted(map(tuple, c.links.select("rule_id", "clinic_id", "reg_id").collect()))


def test_latest_wins_and_replay(spark, data, tmp_path):
    rows = Context(spark, data).t.lineitem.select(F.col("l_orderkey").alias("person"), F.col("l_linenumber").alias("version"), F.col("l_shipdate").cast("date").alias("dod"))
    rows.repartition(4).write.parquet(f"{tmp_path}/in")
    put = streams.upsert_latest(f"{tmp_path}/table", "person", ("version", "dod"))
    stream = streams.file_stream(spark, f"{tmp_path}/in", "person long, version int, dod date")
    for _ in range(2):  # the second start finds nothing new
        streams.start(stream, f"{tmp_path}/ck").foreachBatch(put).start().awaitTermination(120)
    expected = lifecycle.latest(rows, "person", ("version", "dod"), ("version", "dod"))
    before = streams.current(spark, f"{tmp_path}/table")
    assert before.exceptAll(expected).count() == 0 and before.count() == expected.count()
    put(rows.limit(5).withColumn("version", F.lit(999)), 0)  # a replayed batch
    assert streams.current(spark, f"{tmp_path}/table").where("version = 999").count() == 0


def test_upserts_cost_what_is_delivered(spark, tmp_path):
    """Many small deliveries after a large one leave it alone, parts stay few, and old parts go."""
    table, n = f"{tmp_path}/t", 40
    put = streams.upsert_latest(table, "person", ("version",))
    put(spark.range(2000).selectExpr("id AS person", "0 AS version"), 0)
    for b in range(1, n):
        put(spark.range(5).selectExpr(f"id * 7 % 11 + {b} AS person", f"{b} AS version"), b)
    state = streams._pointer(spark, table)
    assert state["parts"][0] == {"path": f"{table}/v0", "rows": 2000} and len(state["parts"]) < 8
    on_disk = {x.name for x in (tmp_path / "t").iterdir() if x.is_dir()}
    assert on_disk == {x["path"].rsplit("/", 1)[1] for x in state["parts"]} | {x.rsplit("/", 1)[1] for x in state["gone"]}
    expected = dict.fromkeys(range(2000), 0)
    for b in range(1, n):
        expected |= {i * 7 % 11 + b: b for i in range(5)}
    assert {r["person"]: r["version"] for r in streams.current(spark, table).collect()} == expected


def test_windows_late_and_repeated(spark, data, tmp_path):
    events = Context(spark, data).t.events
    schema = ", ".join(f"{n} {t}" for n, t in events.dtypes)
    events.unionByName(events).orderBy("ts").coalesce(1).write.parquet(f"{tmp_path}/in")
    stream = streams.event_stream(spark, f"{tmp_path}/in", schema)
    once = streams.deduplicated(stream, "10 days")
    streams.start(once, f"{tmp_path}/d", "append", "once").format("memory").start().awaitTermination(120)
    assert spark.table("once").count() == events.count()
    daily = windows.tumbling(stream.withWatermark("ts", "1 hour"))
    streams.start(daily, f"{tmp_path}/w", "complete", "daily").format("memory").start().awaitTermination(120)
    expected = {(r["start"], r["event_type"]): 2 * r["n"] for r in windows.tumbling(events).collect()}
    assert {(r["start"], r["event_type"]): r["n"] for r in spark.table("daily").collect()} == expected


def test_late_rows_are_counted(spark, tmp_path):
    late = spark.createDataFrame([(1, "2024-01-01 00:00:00"), (2, "2024-01-20 00:00:00")], "event_id long, t string").select("event_id", F.col("t").cast("timestamp").alias("ts"), F.lit("view").alias("event_type"))
    late.coalesce(1).write.parquet(f"{tmp_path}/in")
    stream = streams.file_stream(spark, f"{tmp_path}/in", "event_id long, ts timestamp, event_type string")
    counts = windows.tumbling(stream.withWatermark("ts", "1 day"))
    streams.start(counts, f"{tmp_path}/ck", "update", "upd").format("memory").start().awaitTermination(60)
    late.where("event_id = 1").withColumn("event_id", F.lit(3).cast("long")).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    q = streams.start(counts, f"{tmp_path}/ck", "update").format("noop").start()
    q.awaitTermination(60)
    dropped = sum(o["numRowsDroppedByWatermark"] for p in q.recentProgress for o in p["stateOperators"])
    assert dropped == 1


def test_interval_join_stream(spark, data, tmp_path):
    events = Context(spark, data).t.events
    schema = ", ".join(f"{n} {t}" for n, t in events.dtypes)
    events.coalesce(1).write.parquet(f"{tmp_path}/in")
    s = lambda: streams.event_stream(spark, f"{tmp_path}/in", schema)
    joined = windows.notice_then_encounter(windows.notices(s()).withWatermark("notice_ts", "1 hour"), windows.seen(s()).withWatermark("encounter_ts", "1 hour"))
    streams.start(joined, f"{tmp_path}/ck", "append", "pairs").format("memory").start().awaitTermination(120)
    expected = windows.notice_then_encounter(windows.notices(events), windows.seen(events))
    assert spark.table("pairs").count() == expected.count()


def test_entry(spark, data):
    import __spark_entry__ as e

    q, o = e.queries(), e.oracle_sql()
    assert set(o) <= set(q) and len(q) > 110
    assert e.entry(spark).count() == 20
