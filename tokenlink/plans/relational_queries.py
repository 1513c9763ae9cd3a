"""Queries over the relational surface: scans, predicates, joins, aggregates, windows, set operations, functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import lifecycle, linkage, present, tokens
from ..operators.rules import EVALUATED, RuleSet
from ..sources import delivery, personas
from ..sources.tables import NAMES
from ..streaming import windows

from .context import Context
from .linkage_queries import register
from .oracle_views import query

# --- scans and formats ------------------------------------------------------------------------------------

register("q_scan_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in NAMES))(lambda c: _scans(c))


def _scans(c: Context) -> DataFrame:
    out = None
    for t in NAMES:
        one = getattr(c.t, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.unionByName(one)
    return out


register("q_fixed_width_roundtrip", query("SELECT rec_id AS reg_id, first_name, death_date AS dod FROM register"))(lambda c: _fixed_width(c))


def _fixed_width(c: Context) -> DataFrame:
    layout = (("reg_id", 12, "long"), ("first_name", 15, "string"), ("dod", 10, "date"))
    rows = c.register.select(F.col("rec_id").alias("reg_id"), "first_name", F.col("death_date").alias("dod"))
    back = delivery.from_fixed_width(delivery.to_fixed_width(rows, layout), layout)
    return back.withColumn("first_name", F.nullif("first_name", F.lit("")))


# --- predicates -------------------------------------------------------------------------------------------

register("q_filter_invalid_any", query("SELECT rec_id, valid_mask FROM clinic WHERE ssn IS NULL OR NOT (birth_date IS NOT NULL AND last_name IS NOT NULL)"))(
    lambda c: c.clinic.where("ssn is null or not (birth_date is not null and last_name is not null)").select("rec_id", "valid_mask")
)
register(
    "q_null_safe_compare",
    query("SELECT a.rec_id, a.middle_name IS NOT DISTINCT FROM b.middle_name AS same_or_both_missing, a.middle_name = b.middle_name AS same FROM clinic a JOIN register b ON a.true_person = b.rec_id"),
)(lambda c: _null_safe(c))


def _null_safe(c: Context) -> DataFrame:
    theirs = c.register.select(F.col("rec_id").alias("p"), F.col("middle_name").alias("m"))
    joined = c.clinic.join(theirs, F.col("true_person") == F.col("p"))
    return joined.select("rec_id", F.col("middle_name").eqNullSafe(F.col("m")).alias("same_or_both_missing"), (F.col("middle_name") == F.col("m")).alias("same"))


register("q_mask_filter", query("SELECT rec_id, valid_mask FROM register WHERE valid_mask & 25 = 25"))(lambda c: c.register.where(F.col("valid_mask").bitwiseAND(25) == 25).select("rec_id", "valid_mask"))
register("q_like_names", query("SELECT rec_id, last_name FROM register WHERE last_name LIKE 'A%E' OR regexp_matches(last_name, '^(S|T)H.*N$')"))(
    lambda c: c.register.where(F.col("last_name").like("A%E") | F.col("last_name").rlike("^(S|T)H.*N$")).select("rec_id", "last_name")
)
register("q_dedup_rows", query("SELECT DISTINCT first_name, last_name FROM register"))(lambda c: c.register.select("first_name", "last_name").distinct())

# --- joins ------------------------------------------------------------------------------------------------

_S = RuleSet.of("S B")
_JOINED = query("SELECT a.rec_id AS clinic_id, b.rec_id AS reg_id FROM clinic a JOIN register b ON a.ssn = b.ssn AND a.birth_date = b.birth_date")


def _by_hint(c: Context, hint: str) -> DataFrame:
    a = c.clinic.select(F.col("rec_id").alias("clinic_id"), "ssn", "birth_date")
    b = c.register.select(F.col("rec_id").alias("reg_id"), "ssn", "birth_date")
    return b.join(a.hint(hint), ["ssn", "birth_date"]).select("clinic_id", "reg_id")


for _hint in ("broadcast", "merge", "shuffle_hash"):
    # the broadcast here is the clinic's key columns, on a machine that holds them; linkage counts keys first
    register(f"q_join_{_hint}", _JOINED)(lambda c, hint=_hint: _by_hint(c, hint))
register("q_join_semi", query("SELECT rec_id FROM register WHERE EXISTS (SELECT 1 FROM subset_tokens s WHERE s.rule_id = 6 AND s.token = ssn)"))(
    lambda c: linkage.semi_reduce(tokens.tokens_long(c.register, RuleSet.of("S")), tokens.tokens_long(linkage.validation_subset(c.clinic), RuleSet.of("S"))).select("rec_id")
)
register("q_join_anti_unlinked", query("SELECT rec_id FROM clinic WHERE rec_id NOT IN (SELECT clinic_id FROM links)"))(
    lambda c: c.clinic.select("rec_id").join(c.links.select(F.col("clinic_id").alias("rec_id")), "rec_id", "left_anti")
)
register(
    "q_join_range_birth",
    query(
        """SELECT a.rec_id AS clinic_id, b.rec_id AS reg_id FROM clinic a JOIN register b ON a.last_name = b.last_name AND a.first_name = b.first_name
AND abs(CAST(substr(a.birth_date, 1, 4) AS INT) - CAST(substr(b.birth_date, 1, 4) AS INT)) <= 3"""
    ),
)(lambda c: _near_birth(c))


def _near_birth(c: Context, years: int = 3) -> DataFrame:
    """Birth years within a band: bins as wide as the band, each row of one side in its bin and both neighbours."""
    year = F.substring("birth_date", 1, 4).cast("int")
    a = c.clinic.select(F.col("rec_id").alias("clinic_id"), "first_name", "last_name", year.alias("ya")).withColumn("bin", F.floor(F.col("ya") / years))
    b = c.register.select(F.col("rec_id").alias("reg_id"), "first_name", "last_name", year.alias("yb")).withColumn("at", F.floor(F.col("yb") / years))
    b = b.withColumn("bin", F.explode(F.array(F.col("at") - 1, F.col("at"), F.col("at") + 1)))
    return a.join(b, ["first_name", "last_name", "bin"]).where(F.abs(F.col("ya") - F.col("yb")) <= years).select("clinic_id", "reg_id")


_DAYS = "SELECT o_orderkey AS id, o_custkey AS patient, CAST(o_orderdate AS DATE) AS day FROM orders"
register("q_join_interval_30d", query("SELECT a.id, b.id AS later_id FROM days a JOIN days b ON a.patient = b.patient AND b.day > a.day AND b.day <= a.day + 30", days=_DAYS))(lambda c: _within_30(c))


def _visits(c: Context) -> DataFrame:
    return c.t.orders.select(F.col("o_orderkey").alias("id"), F.col("o_custkey").alias("patient"), F.col("o_orderdate").cast("date").alias("day"))


def _within_30(c: Context) -> DataFrame:
    a = _visits(c)
    b = a.select(F.col("id").alias("later_id"), F.col("patient").alias("p"), F.col("day").alias("later"))
    return a.join(b, (F.col("patient") == F.col("p")) & (F.col("later") > F.col("day")) & (F.col("later") <= F.date_add("day", 30))).select("id", "later_id")


register(
    "q_join_asof_last_encounter",
    query(
        """SELECT p.patient, register_dod, (SELECT max(day) FROM encounters e WHERE e.patient = p.patient AND e.day <= p.register_dod) AS last_before FROM presented p WHERE register_dod IS NOT NULL"""
    ),
)(lambda c: _asof(c))


def _asof(c: Context) -> DataFrame:
    """Deaths and encounters in one stream by patient and day; the last encounter's day is carried forward."""
    deaths = c.presented.where("register.dod is not null").select("patient", F.col("register.dod").alias("day"), F.lit(1).alias("is_death"), F.lit(None).cast("date").alias("seen"))
    seen = c.encounters.select("patient", "day", F.lit(0).alias("is_death"), F.col("day").alias("seen"))
    w = Window.partitionBy("patient").orderBy("day", "is_death").rowsBetween(Window.unboundedPreceding, 0)
    carried = deaths.unionByName(seen).withColumn("last_before", F.last("seen", ignorenulls=True).over(w))
    return carried.where("is_death = 1").select("patient", F.col("day").alias("register_dod"), "last_before")


register("q_self_duplicates", query("SELECT DISTINCT a.rec_id AS a, b.rec_id AS b FROM clinic_tokens a JOIN clinic_tokens b ON a.rule_id = b.rule_id AND a.token = b.token AND a.rec_id < b.rec_id WHERE a.rule_id = 3"))(lambda c: _self(c))


def _self(c: Context) -> DataFrame:
    long = tokens.tokens_long(c.clinic, _S)
    other = long.select(F.col("rec_id").alias("b"), F.col("token").alias("t"))
    return long.join(other, (F.col("token") == F.col("t")) & (F.col("rec_id") < F.col("b"))).select(F.col("rec_id").alias("a"), "b")


register(
    "q_lateral_topk",
    query(
        "SELECT clinic_id, reg_id, score FROM (SELECT *, row_number() OVER (PARTITION BY clinic_id ORDER BY score DESC, reg_id) AS rn FROM pair_scores) WHERE rn <= 3"
    ),
)(lambda c: _topk(c))


def _topk(c: Context) -> DataFrame:
    c.pair_scores.createOrReplaceTempView("tokenlink_pair_scores")
    return c.spark.sql(
        """SELECT p.clinic_id, k.reg_id, k.score FROM (SELECT clinic_id, array_sort(collect_list(struct(-score AS s, reg_id))) AS best FROM tokenlink_pair_scores GROUP BY clinic_id) p,
           LATERAL (SELECT x.reg_id, -x.s AS score FROM (SELECT explode(slice(p.best, 1, 3)) AS x)) k"""
    )


# --- aggregates -------------------------------------------------------------------------------------------

register(
    "q_rollup_region_nation",
    query(
        """SELECT r_name, n_name, CAST(grouping(r_name, n_name) AS BIGINT) AS grouping_id, count(*) AS n, count(ssn) AS n_ssn FROM clinic JOIN customer ON rec_id = c_custkey
JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)"""
    ),
)(
    lambda c: c.clinic.join(c.t.customer, F.col("rec_id") == F.col("c_custkey")).join(c.t.nation, F.col("c_nationkey") == F.col("n_nationkey")).join(c.t.region, F.col("n_regionkey") == F.col("r_regionkey"))
    .rollup("r_name", "n_name").agg(F.grouping_id().alias("grouping_id"), F.count("*").alias("n"), F.count("ssn").alias("n_ssn"))
)
register(
    "q_grouping_sets_rules",
    query("SELECT rule_id, n_records, count(*) AS n_tokens, CAST(sum(n_dod) AS BIGINT) AS n_dod FROM clinic_db GROUP BY GROUPING SETS ((rule_id), (n_records), ())"),
)(lambda c: linkage.file_db(c.clinic).groupingSets([["rule_id"], ["n_records"], []], "rule_id", "n_records").agg(F.count("*").alias("n_tokens"), F.sum("n_dod").alias("n_dod")))
register(
    "q_pivot_categories",
    query("SELECT category, CAST(sum(n_match) AS BIGINT) AS n_match, CAST(count(*) FILTER (WHERE s.rule_id <= 10) AS BIGINT) AS first_ten, CAST(count(*) FILTER (WHERE s.rule_id > 10) AS BIGINT) AS second_ten FROM scorecard s JOIN priority p ON s.rule_id = p.rule_id GROUP BY category"),
)(lambda c: _pivoted(c))


def _pivoted(c: Context) -> DataFrame:
    rows = present.categorize(c.scores).where("category is not null").withColumn("half", F.when(F.col("rule_id") <= 10, "first_ten").otherwise("second_ten"))
    counts = rows.groupBy("category").pivot("half", ["first_ten", "second_ten"]).agg(F.count(F.lit(1))).na.fill(0)
    return counts.join(rows.groupBy("category").agg(F.sum("n_match").alias("n_match")), "category").select("category", "n_match", "first_ten", "second_ten")


register(
    "q_unpivot_profile",
    query("SELECT rule_id, u.measure, u.n FROM (SELECT rule_id, unnest([struct_pack(measure := 'complete', n := c), struct_pack(measure := 'distinct', n := d)]) AS u FROM (SELECT rule_id, count(*) AS c, count(DISTINCT token) AS d FROM clinic_tokens GROUP BY rule_id))"),
)(
    lambda c: linkage.file_db(c.clinic).groupBy("rule_id").agg(F.sum("n_records").alias("complete"), F.count("*").alias("distinct"))
    .unpivot("rule_id", ["complete", "distinct"], "measure", "n")
)
register(
    "q_gap_percentiles",
    query("SELECT rule_id, round(quantile_cont(g, 0.5), 6) AS median_gap, round(quantile_cont(g, 0.9), 6) AS p90_gap, max(abs(g)) AS largest FROM (SELECT rule_id, CAST(date_diff('day', clinic_dod, reg_dod) AS INTEGER) AS g FROM subset_pairs) GROUP BY rule_id"),
)(
    lambda c: c.pairs.withColumn("g", F.datediff("reg_dod", "clinic_dod")).groupBy("rule_id").agg(F.round(F.percentile("g", F.lit(0.5)), 6).alias("median_gap"), F.round(F.percentile("g", F.lit(0.9)), 6).alias("p90_gap"), F.max(F.abs("g")).alias("largest"))
)

register(
    "q_gap_percentiles_approx",
    query("SELECT rule_id, quantile_disc(g, 0.5) AS median_gap, quantile_disc(g, 0.9) AS p90_gap FROM (SELECT rule_id, CAST(date_diff('day', clinic_dod, reg_dod) AS INTEGER) AS g FROM subset_pairs) GROUP BY rule_id"),
)(
    # a summary of bounded size a group; exact while a group has fewer values than the accuracy
    lambda c: c.pairs.withColumn("g", F.datediff("reg_dod", "clinic_dod")).groupBy("rule_id").agg(F.approx_percentile("g", 0.5, 10_000).alias("median_gap"), F.approx_percentile("g", 0.9, 10_000).alias("p90_gap"))
)

# --- windows, order, sets ---------------------------------------------------------------------------------

register(
    "q_rank_rules",
    query(
        """SELECT rule_id, CAST(rank() OVER w AS INTEGER) AS rnk, CAST(dense_rank() OVER w AS INTEGER) AS dense, CAST(row_number() OVER (ORDER BY match_rate DESC, rule_id) AS INTEGER) AS rn,
  percent_rank() OVER w AS pct, CAST(ntile(4) OVER (ORDER BY match_rate DESC, rule_id) AS INTEGER) AS quarter FROM scorecard WHERE match_rate IS NOT NULL WINDOW w AS (ORDER BY match_rate DESC)"""
    ),
)(lambda c: _ranks(c))


def _ranks(c: Context) -> DataFrame:
    w, total = Window.orderBy(F.col("match_rate").desc()), Window.orderBy(F.col("match_rate").desc(), "rule_id")  # twenty rows
    s = c.scores.where("match_rate is not null")
    return s.select("rule_id", F.rank().over(w).alias("rnk"), F.dense_rank().over(w).alias("dense"), F.row_number().over(total).alias("rn"), F.percent_rank().over(w).alias("pct"), F.ntile(4).over(total).alias("quarter"))


register(
    "q_encounter_gaps",
    query(
        """SELECT event_id, CAST(date_diff('day', lag(day) OVER w, day) AS INTEGER) AS since_last, CAST(date_diff('day', day, lead(day) OVER w) AS INTEGER) AS to_next FROM encounters WINDOW w AS (PARTITION BY patient ORDER BY day, event_id)"""
    ),
)(lambda c: _gaps(c))


def _gaps(c: Context) -> DataFrame:
    w = Window.partitionBy("patient").orderBy("day", "event_id")
    return c.encounters.select("event_id", F.datediff("day", F.lag("day").over(w)).alias("since_last"), F.datediff(F.lead("day").over(w), "day").alias("to_next"))


register(
    "q_cumulative_coverage",
    query("SELECT priority, n_patients, CAST(sum(n_patients) OVER (ORDER BY priority) AS BIGINT) AS covered FROM (SELECT priority, count(*) AS n_patients FROM best GROUP BY priority)"),
)(lambda c: c.best.groupBy("priority").agg(F.count("*").alias("n_patients")).withColumn("covered", F.sum("n_patients").over(Window.orderBy("priority").rowsBetween(Window.unboundedPreceding, 0))))
_DEATHS = "SELECT dod, count(*) AS n FROM register_raw GROUP BY dod"
register(
    "q_deaths_trailing_90d",
    query("SELECT dod, n, CAST(sum(n) OVER (ORDER BY dod RANGE BETWEEN INTERVAL 90 DAY PRECEDING AND CURRENT ROW) AS BIGINT) AS trailing FROM (" + _DEATHS + ")"),
)(lambda c: _trailing(c))


def _trailing(c: Context) -> DataFrame:
    days = c.register_raw.groupBy("dod").agg(F.count("*").alias("n")).withColumn("d", F.datediff("dod", F.lit("1970-01-01").cast("date")))
    return days.withColumn("trailing", F.sum("n").over(Window.orderBy("d").rangeBetween(-90, 0))).drop("d")  # one row a day


register(
    "q_first_last_delivery",
    query(
        """SELECT DISTINCT person, first_value(dod) OVER w AS first_dod, last_value(dod) OVER w AS last_dod, nth_value(dod, 2) OVER w AS second_dod FROM deliveries
WINDOW w AS (PARTITION BY person ORDER BY version, dod ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"""
    ),
)(lambda c: _first_last(c))


def _first_last(c: Context) -> DataFrame:
    w = Window.partitionBy("person").orderBy("version", "dod").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    d = personas.deliveries(c.t)
    return d.select("person", F.first_value("dod").over(w).alias("first_dod"), F.last_value("dod").over(w).alias("last_dod"), F.nth_value("dod", 2).over(w).alias("second_dod")).distinct()


register("q_top_heavy_tokens", query("SELECT rule_id, token, n_records FROM register_db ORDER BY n_records DESC, rule_id, token LIMIT 25"))(
    lambda c: linkage.file_db(c.register).select("rule_id", "token", "n_records").orderBy(F.col("n_records").desc(), "rule_id", "token").limit(25)
)
for _op, _sql in (("intersect", "INTERSECT"), ("except", "EXCEPT"), ("union", "UNION")):
    register(f"q_linked_{_op}", query(f"SELECT clinic_id FROM links WHERE rule_id = 3 {_sql} SELECT clinic_id FROM links WHERE rule_id = 13"))(lambda c, op=_op: _linked(c, op))


def _linked(c: Context, op: str) -> DataFrame:
    two = RuleSet(tuple(r for r in EVALUATED if r.id in (3, 13)))
    found = linkage.links(c.clinic, c.register, two)
    a, b = (found.where(F.col("rule_id") == r).select("clinic_id") for r in (3, 13))
    return a.intersect(b) if op == "intersect" else a.subtract(b) if op == "except" else a.union(b).distinct()


register("q_delivery_except_all", query("SELECT person, dod FROM deliveries EXCEPT ALL SELECT person, dod FROM corrected"))(lambda c: personas.deliveries(c.t).select("person", "dod").exceptAll(c.corrected.select("person", "dod")))

# --- functions --------------------------------------------------------------------------------------------

register(
    "q_string_suite",
    """SELECT c_custkey, lower(c_name) AS lo, trim('  ' || c_name || ' ') AS tr, lpad(CAST(c_custkey AS VARCHAR), 12, '0') AS lp, rpad(c_mktsegment, 12, '.') AS rp, reverse(c_name) AS rv, left(c_name, 4) AS l4, right(c_name, 4) AS r4,
  length(c_name) AS len, split_part(c_name, '#', 2) AS part, CAST(strpos(c_name, '#') AS INTEGER) AS pos, translate(c_mktsegment, 'AEIOU', '12345') AS tl, CAST(levenshtein(c_mktsegment, 'BUILDING') AS INTEGER) AS lev,
  regexp_extract(c_name, '([0-9]+)', 1) AS num, concat_ws('/', c_mktsegment, c_name) AS cw, CAST(len(regexp_extract_all(c_name, '0')) AS INTEGER) AS zeros FROM customer""",
)(
    lambda c: c.t.customer.selectExpr(
        "c_custkey", "lower(c_name) lo", "trim('  ' || c_name || ' ') tr", "lpad(c_custkey, 12, '0') lp", "rpad(c_mktsegment, 12, '.') rp", "reverse(c_name) rv", "left(c_name, 4) l4", "right(c_name, 4) r4",
        "cast(length(c_name) as bigint) len", "split_part(c_name, '#', 2) part", "instr(c_name, '#') pos", "translate(c_mktsegment, 'AEIOU', '12345') tl", "levenshtein(c_mktsegment, 'BUILDING') lev",
        "regexp_extract(c_name, '([0-9]+)', 1) num", "concat_ws('/', c_mktsegment, c_name) cw", "regexp_count(c_name, '0') zeros",
    )
)
register(
    "q_date_suite",
    """SELECT o_orderkey, year(d) AS y, month(d) AS m, day(d) AS dd, CAST(date_diff('day', DATE '1995-01-01', d) AS INTEGER) AS since, d + 10 AS plus, CAST(d + INTERVAL 3 MONTH AS DATE) AS later, last_day(d) AS ld, CAST(date_trunc('month', d) AS DATE) AS tm,
  make_date(year(d), 1, 1) AS ny FROM (SELECT o_orderkey, CAST(o_orderdate AS DATE) AS d FROM orders)""",
)(
    lambda c: c.t.orders.selectExpr("o_orderkey", "cast(o_orderdate as date) d").selectExpr(
        "o_orderkey", "cast(year(d) as bigint) y", "cast(month(d) as bigint) m", "cast(dayofmonth(d) as bigint) dd", "datediff(d, date'1995-01-01') since", "date_add(d, 10) plus", "add_months(d, 3) later", "last_day(d) ld",
        "cast(trunc(d, 'month') as date) tm", "make_date(year(d), 1, 1) ny",
    )
)
register(
    "q_math_suite",
    """SELECT p_partkey, sqrt(p_retailprice) AS sq, floor(p_retailprice / 7) AS fl, abs(p_size - 25) AS ab, greatest(p_size, 10) AS gr, least(p_size, 10) AS le, CAST(bit_count(p_partkey) AS INTEGER) AS bc, p_partkey & 12 AS an,
  ((p_size - 30) % 7 + 7) % 7 AS pm FROM part""",
)(
    lambda c: c.t.part.selectExpr("p_partkey", "sqrt(p_retailprice) sq", "cast(floor(p_retailprice / 7) as double) fl", "abs(p_size - 25) ab", "greatest(p_size, 10) gr", "least(p_size, 10) le", "bit_count(p_partkey) bc", "p_partkey & 12 an", "pmod(p_size - 30, 7) pm")
)
register(
    "q_array_suite",
    """SELECT p_partkey, len(w) AS n, array_to_string(list_transform(w, lambda x: upper(x)), '|') AS up, len(list_filter(w, lambda x: length(x) > 4)) AS long_ones, list_sort(w)[1] AS first_one, list_contains(w, 'red') AS has_red
FROM (SELECT p_partkey, string_split(p_name, ' ') AS w FROM part)""",
)(
    lambda c: c.t.part.selectExpr("p_partkey", "split(p_name, ' ') w").selectExpr(
        "p_partkey", "cast(size(w) as bigint) n", "array_join(transform(w, x -> upper(x)), '|') up", "cast(size(filter(w, x -> length(x) > 4)) as bigint) long_ones", "element_at(array_sort(w), 1) first_one", "array_contains(w, 'red') has_red"
    )
)
register("q_json_props", "SELECT event_type, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1, 2")(
    lambda c: c.t.events.select("event_type", F.from_json("props", "k int")["k"].alias("k")).groupBy("event_type", "k").agg(F.count("*").alias("n"))
)
register("q_hash_suite", query("SELECT rec_id, md5(ssn) AS m, sha256(ssn) AS s FROM clinic"))(lambda c: c.clinic.select("rec_id", F.md5("ssn").alias("m"), F.sha2("ssn", 256).alias("s")))

# --- batch twins of the streams ---------------------------------------------------------------------------

register("q_win_tumbling", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")(lambda c: windows.tumbling(c.t.events))
register(
    "q_win_sliding",
    "SELECT s AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 6 HOUR, ts), time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR]) AS s FROM events) GROUP BY 1, 2",
)(lambda c: windows.sliding(c.t.events))
register(
    "q_win_session",
    """SELECT user_id, min(ts) AS start, max(ts) AS last, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (
SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""",
)(lambda c: windows.sessions(c.t.events))
register(
    "q_interval_join_events",
    "SELECT a.event_id AS notice_id, b.event_id AS encounter_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type <> 'error' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 DAY",
)(lambda c: windows.notice_then_encounter(windows.notices(c.t.events), windows.seen(c.t.events)))
register("q_research_filter", query("SELECT event_id, patient, day, kind FROM encounters WHERE kind <> 'error' AND day >= DATE '1996-01-01'"))(
    lambda c: lifecycle.research_filter(c.encounters, "kind <> 'error' and day >= date'1996-01-01'")
)
_REFINES = [(a.id, b.id) for a in EVALUATED for b in EVALUATED if a.id != b.id and a.refines(b)]
register("q_refinement_lattice", query("SELECT f.fine, f.coarse, a.n <= b.n AS completeness_holds FROM (VALUES " + ", ".join(map(str, _REFINES)) + ") f(fine, coarse) JOIN (SELECT rule_id, count(*) AS n FROM register_tokens GROUP BY 1) a ON a.rule_id = f.fine JOIN (SELECT rule_id, count(*) AS n FROM register_tokens GROUP BY 1) b ON b.rule_id = f.coarse"))(lambda c: _lattice(c))


def _lattice(c: Context) -> DataFrame:
    n = tokens.tokens_long(c.register).groupBy("rule_id").agg(F.count("*").alias("n"))
    pairs = c.spark.range(1).select(F.inline(F.array(*[F.struct(F.lit(a).alias("fine"), F.lit(b).alias("coarse")) for a, b in _REFINES])))
    fine, coarse = n.select(F.col("rule_id").alias("fine"), F.col("n").alias("nf")), n.select(F.col("rule_id").alias("coarse"), F.col("n").alias("nc"))
    return pairs.join(fine, "fine").join(coarse, "coarse").select("fine", "coarse", (F.col("nf") <= F.col("nc")).alias("completeness_holds"))


