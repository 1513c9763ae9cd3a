"""Queries over the linkage methods, each with its DuckDB oracle."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import cleaning, phonetic
from ..operators import evaluate, lifecycle, linkage, present, profile, tokens, weights
from ..operators.rules import BASELINES, EVALUATED, PHONETIC, RuleSet
from ..operators.standardize import ADJACENT, explode_names, standardize, swap_variants
from ..sources import personas
from . import oracle_views as V
from .context import Context
from .oracle_views import query

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

STD = ["rec_id", "true_person", "first_name", "middle_name", "last_name", "birth_date", "ssn", "death_date", "valid_mask"]
SALT = "example-salt"
AS_OF = "2001-08-01"


def register(name: str, sql: str | None) -> Callable:
    def add(f: Callable[[Context], DataFrame]) -> Callable[[Context], DataFrame]:
        QUERIES[name] = lambda spark, path: f(Context(spark, path))
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


# --- cleaning ---------------------------------------------------------------------------------------------

register("q_clean_digits", query(f"SELECT clinic_id, {V.digits('ssn_raw')} AS ssn_digits, {V.digits('birth_raw')} AS birth_digits FROM clinic_raw"))(
    lambda c: c.clinic_raw.select("clinic_id", cleaning.digits_only(F.col("ssn_raw")).alias("ssn_digits"), cleaning.digits_only(F.col("birth_raw")).alias("birth_digits"))
)
for _how in ("fold", "drop"):
    register(f"q_clean_names_{_how}", query(f"SELECT reg_id, {V.letters('first_name_raw', _how)} AS first_name, {V.letters('last_name_raw', _how)} AS last_name FROM register_raw"))(
        lambda c, how=_how: c.register_raw.select("reg_id", cleaning.letters_only(F.col("first_name_raw"), how).alias("first_name"), cleaning.letters_only(F.col("last_name_raw"), how).alias("last_name"))
    )
register("q_clean_truncate", query(f"SELECT reg_id, substr({V.letters('address_raw')}, 1, 3) AS three, substr({V.letters('last_name_raw')}, 1, 20) AS twenty FROM register_raw"))(
    lambda c: c.register_raw.select("reg_id", cleaning.truncated(cleaning.letters_only(F.col("address_raw")), 3).alias("three"), cleaning.truncated(cleaning.letters_only(F.col("last_name_raw")), 20).alias("twenty"))
)
register("q_valid_dates", query(f"SELECT clinic_id, {V.date8('birth_raw')} AS birth_date, ({V.date8('birth_raw')}) IS NOT NULL AND try_strptime({V.date8('birth_raw')}, '%Y%m%d') IS NOT NULL AS on_calendar FROM clinic_raw"))(
    lambda c: c.clinic_raw.select(
        "clinic_id",
        cleaning.valid_date(cleaning.to_ymd(F.col("birth_raw"))).alias("birth_date"),
        cleaning.valid_date(cleaning.to_ymd(F.col("birth_raw")), calendar=True).isNotNull().alias("on_calendar"),
    )
)
register(
    "q_date_layouts",
    """
SELECT o_orderkey, strftime(o_orderdate, '%Y%m%d') AS from_dashes, strftime(o_orderdate, '%Y%m%d') AS from_slashes, strftime(o_orderdate, '%Y%m%d') AS from_month_first FROM orders""",
)(
    lambda c: c.t.orders.select(
        "o_orderkey",
        cleaning.to_ymd(F.date_format("o_orderdate", "yyyy-MM-dd")).alias("from_dashes"),
        cleaning.to_ymd(F.date_format("o_orderdate", "yyyy/MM/dd")).alias("from_slashes"),
        cleaning.to_ymd(F.date_format("o_orderdate", "M/d/yyyy"), "mdy").alias("from_month_first"),
    )
)
register("q_valid_ssn", query(f"SELECT clinic_id, {V.ssn('ssn_raw')} AS ssn FROM clinic_raw"))(lambda c: c.clinic_raw.select("clinic_id", cleaning.valid_ssn(F.col("ssn_raw")).alias("ssn")))
register("q_ssn_defects", query(f"SELECT defect, count(*) AS n FROM (SELECT {V.defect('ssn_raw')} AS defect FROM clinic_raw) WHERE defect IS NOT NULL GROUP BY defect"))(
    lambda c: c.clinic_raw.select(cleaning.ssn_defect(F.col("ssn_raw")).alias("defect")).where("defect is not null").groupBy("defect").agg(F.count("*").alias("n"))
)
register("q_std_register", query(f"SELECT {', '.join(STD)} FROM register"))(lambda c: c.register.select(STD))
register("q_std_clinic", query(f"SELECT {', '.join(STD)} FROM clinic"))(lambda c: c.clinic.select(STD))
register(
    "q_alt_names",
    query(
        f"""SELECT reg_id AS rec_id, u.kind AS name_kind, {V.name('u.f', 15)} AS first_name, {V.name('u.l', 20)} AS last_name FROM (
  SELECT p AS reg_id, unnest([struct_pack(kind := 'current', f := {V.w(1)}, l := {V.w(6)}), struct_pack(kind := 'previous', f := {V.w(2)}, l := {V.w(7)})]) AS u FROM register_p)"""
    ),
)(lambda c: _alternates(c))


def _alternates(c: Context) -> DataFrame:
    people = personas._with_words(c.t.orders.select(F.col("o_orderkey").alias("p")), c.t).withColumnRenamed("p", "reg_id")
    known = [F.struct(personas.word(i).alias("first"), personas.word(i + 5).alias("last"), F.lit(kind).alias("kind")) for i, kind in ((1, "current"), (2, "previous"))]
    rows = explode_names(people, F.array(*known))
    return rows.select(F.col("reg_id").alias("rec_id"), "name_kind", cleaning.clean_name(F.col("first_name_raw"), 15).alias("first_name"), cleaning.clean_name(F.col("last_name_raw"), 20).alias("last_name"))


_OTHERS = {"first_name": "first_name", "last_name": "last_name", "birth_date": "birth_date", "ssn": "ssn"}


def _variant_sql(kind: str, **changed: str) -> str:
    return f"SELECT rec_id, '{kind}' AS variant, " + ", ".join(f"{changed.get(f, f)} AS {f}" for f in _OTHERS) + " FROM clinic"


def _swapped_sql(kind: str, field: str) -> str:
    turned = f"substr({field}, 1, i - 1) || substr({field}, i + 1, 1) || substr({field}, i, 1) || substr({field}, i + 2)"
    places = f"(SELECT *, unnest(range(1, length({field}))) AS i FROM clinic WHERE {field} IS NOT NULL)"
    return _variant_sql(kind, **{field: turned}).replace("FROM clinic", f"FROM {places} WHERE substr({field}, i, 1) <> substr({field}, i + 1, 1)")


_MONTH_DAY = "substr(birth_date, 1, 4) || substr(birth_date, 7, 2) || substr(birth_date, 5, 2)"
register(
    "q_swap_variants",
    query(" UNION ALL ".join([_variant_sql("as_is"), _variant_sql("names", first_name="last_name", last_name="first_name"), _variant_sql("month_day", birth_date=_MONTH_DAY), *[_swapped_sql(*x) for x in ADJACENT.items()]])),
)(lambda c: swap_variants(c.clinic).select("rec_id", "variant", *_OTHERS))
register(
    "q_swap_links",
    query(
        "SELECT DISTINCT v.rec_id AS clinic_id, r.rec_id AS reg_id, v.variant FROM variants v JOIN register r ON v.ssn || v.last_name || v.birth_date = r.ssn || r.last_name || r.birth_date",
        variants=" UNION ALL ".join([_variant_sql("as_is"), _variant_sql("month_day", birth_date=_MONTH_DAY), *[_swapped_sql(k, f) for k, f in ADJACENT.items() if f != "first_name"]]),
    ),
)(lambda c: _swap_links(c))


def _swap_links(c: Context) -> DataFrame:
    """Whom the clinic's records and their variants meet under a strict key."""
    rules = RuleSet.of("S L B")
    variants = swap_variants(c.clinic, ("month_day", "last_letters", "ssn_digits", "birth_digits"))
    mine = tokens.tokens_long(variants, rules, keep=("variant",)).withColumnRenamed("rec_id", "clinic_id")
    theirs = linkage.semi_reduce(tokens.tokens_long(c.register, rules), mine).withColumnRenamed("rec_id", "reg_id")
    return mine.join(theirs, linkage.KEY).select("clinic_id", "reg_id", "variant").distinct()


# --- keys -------------------------------------------------------------------------------------------------

for _side in ("register", "clinic"):
    _cols = ", ".join(f"{' || '.join(map(V.part, r.parts))} AS t{r.id}" for r in EVALUATED)
    register(f"q_tokens_{_side}", query(f"SELECT rec_id, {_cols} FROM {_side}_c"))(lambda c, side=_side: tokens.tokens_wide(getattr(c, side)))
register("q_tokens_long", query("SELECT rec_id, rule_id, token FROM clinic_tokens"))(lambda c: tokens.tokens_long(c.clinic))
register(
    "q_boundary_collisions",
    query(
        f"""SELECT a.rule_id, bare, separated, separated - bare AS collisions FROM (SELECT rule_id, count(DISTINCT token) AS bare FROM register_tokens GROUP BY rule_id) a
JOIN (SELECT rule_id, count(DISTINCT token) AS separated FROM ({V.long_tokens('register_c', sep='|')}) GROUP BY rule_id) b ON a.rule_id = b.rule_id"""
    ),
)(lambda c: tokens.boundary_collisions(c.register))
register("q_hashed_tokens", query(f"SELECT rec_id, rule_id, sha256('{SALT}|' || CAST(rule_id AS VARCHAR) || '|' || token) AS token FROM clinic_tokens"))(lambda c: tokens.hash_tokens(tokens.tokens_long(c.clinic), SALT))
register("q_hashed_link_equiv", query("SELECT rule_id, clinic_id, reg_id FROM subset_pairs"))(lambda c: _hashed_links(c))


def _hashed_links(c: Context) -> DataFrame:
    keyed = lambda std: tokens.hash_tokens(tokens.tokens_long(std, keep=("death_date",)), SALT)
    mine = linkage.token_db(keyed(linkage.validation_subset(c.clinic)))
    return linkage.one_to_one(mine, linkage.token_db(linkage.semi_reduce(keyed(c.register), mine))).select("rule_id", "clinic_id", "reg_id")


# --- earlier rule sets ------------------------------------------------------------------------------------


def _set_score(rules: RuleSet) -> str:
    mine, theirs = V.database(V.long_tokens("clinic_c", rules, where="death_date IS NOT NULL")), V.database(V.long_tokens("register_c", rules))
    return query(V.score("SELECT * FROM own_pairs", rules), own_a=mine, own_b=theirs, own_pairs=V.pairs("own_a", "own_b"))


for _name, _rules in BASELINES.items():
    register(f"q_base_{_name}", _set_score(_rules))(lambda c, rules=_rules: evaluate.scorecard(linkage.subset_pairs(c.clinic, c.register, rules), rules))

_SETS = {"evaluated": EVALUATED, **BASELINES}
_KINDS = [(n, r.id, r.name if n != "evaluated" else f"evaluated.{r.id}", r.codes, r.kind) for n, s in _SETS.items() for r in s]
_KEYED = " UNION ALL ".join(f"SELECT '{n}' AS s, rule_id, count(*) AS n FROM ({V.long_tokens('clinic_c', s)}) GROUP BY rule_id" for n, s in _SETS.items())
_OF_KIND = "SELECT rule, parts, kind, coalesce(n, 0) AS n_complete FROM (VALUES " + ", ".join(map(str, _KINDS)) + f") AS t(s, rule_id, rule, parts, kind) LEFT JOIN ({_KEYED}) k ON t.s = k.s AND t.rule_id = k.rule_id"
register("q_rule_kinds", query(_OF_KIND))(lambda c: _rule_kinds(c))


def _rule_kinds(c: Context) -> DataFrame:
    """Every rule with its kind and the number of clinic records that have its key, counted in one scan."""
    counts = c.clinic.agg(*[F.count(r.token("")).alias(f"{n}_{r.id}") for n, s in _SETS.items() for r in s])
    rows = [F.struct(F.lit(rule).alias("rule"), F.lit(parts).alias("parts"), F.lit(kind).alias("kind"), F.col(f"{n}_{i}").alias("n_complete")) for n, i, rule, parts, kind in _KINDS]
    return counts.select(F.inline(F.array(*rows)))


# The words of part names with their codes, derived by hand.
_SOUNDS = (
    ("red", "RT", "RT", "RT"), ("gear", "JR", "JR", "KR"), ("small", "SML", "SML", "XML"), ("hot", "HT", "HT", "HT"), ("cold", "KLT", "KLT", "KLT"), ("old", "OLT", "ALT", "ALT"),
    ("gizmo", "JSM", "JSM", "KSM"), ("widget", "WJT", "AJT", "FJT"), ("ring", "RNK", "RNK", "RNK"), ("plate", "PLT", "PLT", "PLT"), ("anvil", "ANFL", "ANFL", "ANFL"), ("bolt", "BLT", "PLT", "PLT"),
    ("rod", "RT", "RT", "RT"), ("new", "N", "N", "NF"), ("large", "LRJ", "LRJ", "LRK"), ("blue", "BL", "PL", "PL"),
)
_WORDS = "SELECT DISTINCT unnest(string_split(p_name, ' ')) AS word FROM part"
register("q_phonetic_words", f"SELECT w.word, metaphone, main, alternate FROM ({_WORDS}) w LEFT JOIN (VALUES " + ", ".join(map(str, _SOUNDS)) + ") AS t(word, metaphone, main, alternate) ON w.word = t.word")(lambda c: _sounds(c))


def _sounds(c: Context) -> DataFrame:
    words = c.t.part.select(F.explode(F.split("p_name", " ")).alias("word")).distinct()
    return words.select("word", phonetic.metaphone(F.col("word")).alias("metaphone"), phonetic.double_metaphone(F.col("word")).alias("d")).select("word", "metaphone", F.col("d.primary").alias("main"), F.col("d.alternate").alias("alternate"))
register("q_scorecard_phonetic", None)(lambda c: evaluate.scorecard(linkage.subset_pairs(c.clinic, c.register, PHONETIC), PHONETIC))
register(
    "q_fuzzy_link",
    query(
        f"""SELECT clinic_id, reg_id, CASE WHEN straight THEN 'straight' ELSE 'crossed' END AS how FROM (
SELECT p.clinic_id, p.reg_id, coalesce(levenshtein(a.first_name, b.first_name) <= 1 AND levenshtein(a.last_name, b.last_name) <= 1, FALSE) AS straight,
  coalesce(levenshtein(a.first_name, b.last_name) <= 1 AND levenshtein(a.last_name, b.first_name) <= 1, FALSE) AS crossed
FROM (SELECT DISTINCT a.rec_id AS clinic_id, b.rec_id AS reg_id FROM ({V.long_tokens('clinic_c', RuleSet.of('B'))}) a JOIN ({V.long_tokens('register_c', RuleSet.of('B'))}) b USING (token)) p
JOIN clinic a ON a.rec_id = p.clinic_id JOIN register b ON b.rec_id = p.reg_id) WHERE straight OR crossed"""
    ),
)(lambda c: linkage.link_fuzzy(c.clinic, c.register))
register(
    "q_any_vs_cascade",
    query(
        f"""SELECT x.clinic_id, CAST(n_rules AS BIGINT) AS n_rules, n_targets, min_reg_id, y.rule_id AS first_rule, y.reg_id AS first_reg_id
FROM (SELECT clinic_id, count(*) AS n_rules, count(DISTINCT reg_id) AS n_targets, min(reg_id) AS min_reg_id FROM l2 GROUP BY clinic_id) x
JOIN (SELECT *, row_number() OVER (PARTITION BY clinic_id ORDER BY rule_id) AS rn FROM l2) y ON x.clinic_id = y.clinic_id AND y.rn = 1""",
        l2="SELECT * FROM (" + V.pairs("l2a", "l2b") + ")",
        l2a=V.database(V.long_tokens("clinic_c", BASELINES["legacy"])),
        l2b=V.database(V.long_tokens("register_c", BASELINES["legacy"])),
    ),
)(lambda c: _any_cascade(c))


def _any_cascade(c: Context) -> DataFrame:
    found = linkage.links(c.clinic, c.register, BASELINES["legacy"])
    first = linkage.link_cascade(found, {1: 1, 2: 2}).select("clinic_id", F.col("rule_id").alias("first_rule"), F.col("reg_id").alias("first_reg_id"))
    return linkage.link_any(found).join(first, "clinic_id")


register(
    "q_vendor15_unusable",
    query(
        "SELECT r.rule_id, coalesce(n, 0) AS n_complete, coalesce(n, 0) = 0 AS unusable FROM " + V.ids(BASELINES["vendor15"]) + " r LEFT JOIN (SELECT rule_id, count(*) AS n FROM ("
        + V.long_tokens("strict", BASELINES["vendor15"]) + ") GROUP BY rule_id) t ON r.rule_id = t.rule_id",
        strict="SELECT * REPLACE (CAST(NULL AS VARCHAR) AS gender, CAST(NULL AS VARCHAR) AS zip, CAST(NULL AS VARCHAR) AS address) FROM register_c",
    ),
)(lambda c: _unusable(c))


def _unusable(c: Context) -> DataFrame:
    rules = BASELINES["vendor15"]
    strict = c.register.withColumns({x: F.lit(None).cast("string") for x in ("gender", "zip", "address")})
    n = tokens.tokens_long(strict, rules).groupBy("rule_id").agg(F.count("*").alias("n_complete"))
    return evaluate.rule_list(c.spark, rules).join(n, "rule_id", "left").na.fill(0).withColumn("unusable", F.col("n_complete") == 0)


# --- linking and validation -------------------------------------------------------------------------------

register("q_token_db", query("SELECT * FROM register_db"))(lambda c: linkage.file_db(c.register))
register("q_validation_subset", query(f"SELECT {', '.join(STD)} FROM clinic WHERE death_date IS NOT NULL"))(lambda c: linkage.validation_subset(c.clinic).select(STD))
register("q_one_to_one", query("SELECT * FROM subset_pairs"))(lambda c: c.pairs)
register(
    "q_one_to_one_date_unique",
    query(
        "SELECT * FROM (" + V.pairs("subset_db", "dup_db", "b.min_dod = b.max_dod") + ")", dup_db=V.database(V.long_tokens("register_dup_c"))
    ),
)(lambda c: linkage.subset_pairs(c.clinic, standardize(personas.register_dup_raw(c.t), "reg_id"), unique="date"))
register(
    "q_one_to_one_duplicated_register",
    query("SELECT * FROM (" + V.pairs("subset_db", "dup_db") + ")", dup_db=V.database(V.long_tokens("register_dup_c"))),
)(lambda c: linkage.subset_pairs(c.clinic, standardize(personas.register_dup_raw(c.t), "reg_id")))
register(
    "q_link_outcomes",
    query(
        """SELECT rule_id, outcome, count(*) AS n_keys FROM (SELECT a.rule_id, CASE WHEN a.n_records > 1 THEN 'repeated_in_subset' WHEN b.n_records IS NULL THEN 'absent_in_register'
  WHEN b.n_records > 1 THEN 'repeated_in_register' ELSE 'one_to_one' END AS outcome FROM subset_db a LEFT JOIN register_db b ON a.rule_id = b.rule_id AND a.token = b.token) GROUP BY rule_id, outcome"""
    ),
)(lambda c: linkage.link_outcomes(c.clinic, c.register))
register("q_scorecard", query("SELECT * FROM scorecard"))(lambda c: c.scores)
register("q_scorecard_unreduced", query("SELECT * FROM scorecard"))(lambda c: evaluate.scorecard(linkage.subset_pairs(c.clinic, c.register, reduce=False)))
register("q_scorecard_tolerance", query(V.score("SELECT * FROM subset_pairs", days=4)))(lambda c: evaluate.scorecard(c.pairs, tolerance_days=4))
register("q_dod_gaps", query("SELECT rule_id, CAST(date_diff('day', clinic_dod, reg_dod) AS INTEGER) AS gap_days, count(*) AS n_pairs FROM subset_pairs WHERE reg_dod IS NOT NULL GROUP BY 1, 2"))(lambda c: evaluate.dod_gaps(c.pairs))

_CONFUSION = (
    """SELECT rule_id, tp, fp, known - tp AS fn, people - known - fpu AS tn, CASE WHEN tp + fp > 0 THEN CAST(tp AS DOUBLE) / CAST(tp + fp AS DOUBLE) END AS precision,
  CASE WHEN known > 0 THEN CAST(tp AS DOUBLE) / CAST(known AS DOUBLE) END AS recall, CASE WHEN people - known - fpu + fp > 0 THEN CAST(people - known - fpu AS DOUBLE) / CAST(people - known - fpu + fp AS DOUBLE) END AS specificity,
  CASE WHEN tp + fp + known > 0 THEN CAST(2 * tp AS DOUBLE) / CAST(2 * tp + fp + known - tp AS DOUBLE) END AS f1
FROM (SELECT r.rule_id, coalesce(tp, 0) AS tp, coalesce(fp, 0) AS fp, coalesce(fpu, 0) AS fpu, (SELECT count(*) FROM people) AS people, (SELECT count(*) FROM people WHERE known) AS known
FROM """
    + V.ids()
    + """ r LEFT JOIN (SELECT rule_id, count(*) FILTER (WHERE p.true_person = b.true_person) AS tp, count(*) FILTER (WHERE p.true_person <> b.true_person) AS fp,
  count(*) FILTER (WHERE p.true_person <> b.true_person AND NOT p.known) AS fpu FROM subset_pairs s JOIN people p ON p.rec_id = s.clinic_id JOIN register b ON b.rec_id = s.reg_id GROUP BY rule_id) x ON r.rule_id = x.rule_id)"""
)
_PEOPLE = "SELECT rec_id, true_person, true_person IN (SELECT true_person FROM register) AS known FROM clinic WHERE death_date IS NOT NULL"
register("q_confusion", query(_CONFUSION, people=_PEOPLE))(lambda c: evaluate.confusion(c.pairs, c.clinic, c.register))
register("q_proxy_gap", query(f"SELECT s.rule_id, s.match_rate, q.precision, q.precision - s.match_rate AS gap FROM scorecard s JOIN ({_CONFUSION}) q ON s.rule_id = q.rule_id", people=_PEOPLE))(
    lambda c: c.scores.join(evaluate.confusion(c.pairs, c.clinic, c.register).select("rule_id", "precision"), "rule_id").select("rule_id", "match_rate", "precision", (F.col("precision") - F.col("match_rate")).alias("gap"))
)
_Z = 1.959963984540054
register(
    "q_scorecard_ci",
    query(
        f"""SELECT rule_id, CAST(round(1000000 * (mid - half)) AS BIGINT) AS low_ppm, CAST(round(1000000 * (mid + half)) AS BIGINT) AS high_ppm FROM (
SELECT rule_id, (p + {_Z * _Z} / (n * 2.0)) / ({_Z * _Z} / n + 1.0) AS mid, sqrt(p * (1.0 - p) / n + {_Z * _Z} / (n * n * 4.0)) * {_Z} / ({_Z * _Z} / n + 1.0) AS half
FROM (SELECT rule_id, match_rate AS p, CAST(n_one_to_one AS DOUBLE) AS n FROM scorecard WHERE n_one_to_one > 0))"""
    ),
)(lambda c: _intervals(c))


def _intervals(c: Context) -> DataFrame:
    low, high = evaluate.wilson(F.col("n_match"), F.col("n_one_to_one"), _Z)
    ppm = lambda x: F.round(x * 1_000_000.0).cast("long")
    return c.scores.where("n_one_to_one > 0").select("rule_id", ppm(low).alias("low_ppm"), ppm(high).alias("high_ppm"))


register(
    "q_frontier",
    query(
        """SELECT rule_id, match_rate, n_complete, n_complete > coalesce(max(n_complete) OVER (ORDER BY match_rate DESC, rule_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1) AS on_frontier
FROM (SELECT s.rule_id, match_rate, n_complete FROM scorecard s JOIN (SELECT rule_id, count(*) AS n_complete FROM clinic_tokens GROUP BY rule_id) p ON s.rule_id = p.rule_id WHERE match_rate IS NOT NULL)"""
    ),
)(lambda c: evaluate.frontier(c.scores, profile.profile_tokens(linkage.file_db(c.clinic), c.t.size("customer"))))
register(
    "q_ranking_shift",
    query(
        """SELECT coalesce(a.rule_id, b.rule_id) AS rule_id, rank_a, rank_b, rank_b - rank_a AS shift FROM (SELECT rule_id, CAST(row_number() OVER (ORDER BY match_rate DESC, rule_id) AS INTEGER) AS rank_a FROM scorecard WHERE match_rate IS NOT NULL) a
FULL JOIN (SELECT rule_id, CAST(row_number() OVER (ORDER BY match_rate DESC, rule_id) AS INTEGER) AS rank_b FROM score2 WHERE match_rate IS NOT NULL) b ON a.rule_id = b.rule_id""",
        db2a=V.database(V.long_tokens("clinic2_c", where="death_date IS NOT NULL")),
        db2b=V.database(V.long_tokens("reg2_c")),
        score2=V.score(V.pairs("db2a", "db2b")),
    ),
)(lambda c: _shift(c))


def _shift(c: Context) -> DataFrame:
    reg, clinic = personas.second_pair(c.t)
    other = linkage.subset_pairs(standardize(clinic, "clinic_id"), standardize(reg, "reg_id"))
    return evaluate.ranking_shift(c.scores, evaluate.scorecard(other))


register(
    "q_deceased_overlap",
    query(
        """SELECT count(*) FILTER (WHERE here AND NOT there) AS clinic_only, count(*) FILTER (WHERE NOT here AND there) AS register_only, count(*) FILTER (WHERE here AND there) AS both, count(*) FILTER (WHERE here OR there) AS total
FROM (SELECT death_date IS NOT NULL AS here, rec_id IN (SELECT clinic_id FROM l2) AS there FROM clinic)""",
        l2="SELECT * FROM (" + V.pairs("l2a", "l2b") + ")",
        l2a=V.database(V.long_tokens("clinic_c", BASELINES["legacy"])),
        l2b=V.database(V.long_tokens("register_c", BASELINES["legacy"])),
    ).replace("AS both", 'AS "both"'),
)(lambda c: evaluate.deceased_overlap(c.clinic, linkage.links(c.clinic, c.register, BASELINES["legacy"])))

# --- profiles ---------------------------------------------------------------------------------------------

_FIELDS = {"ssn": ("ssn_raw", "ssn"), "last_name": ("last_name_raw", "last_name"), "first_name": ("first_name_raw", "first_name"), "middle_name": ("middle_name_raw", "middle_name"), "birth_date": ("birth_raw", "birth_date"), "death_date": ("CAST(dod AS VARCHAR)", "death_date")}


def _field_profile(raw: str, std: str, key: str) -> str:
    one = " UNION ALL ".join(
        f"""SELECT '{f}' AS field, count(*) AS n_rows, count(v) AS n_complete, count(DISTINCT v) AS n_distinct, count(*) FILTER (WHERE v IS NOT NULL AND ok IS NULL) AS n_invalid,
  count(*) FILTER (WHERE v IS NOT NULL AND trim(v) <> '' AND ok IS NULL) AS n_invalid_nonblank FROM (SELECT {r} AS v, s.{c} AS ok FROM {raw} r JOIN {std} s ON r.{key} = s.rec_id)"""
        for f, (r, c) in _FIELDS.items()
    )
    return f"SELECT *, CAST(n_rows - n_complete AS DOUBLE) / CAST(n_rows AS DOUBLE) AS null_rate, CAST(n_invalid AS DOUBLE) / CAST(n_rows AS DOUBLE) AS invalid_rate FROM ({one})"


register("q_field_profile_register", query(_field_profile("register_raw", "register", "reg_id")))(lambda c: profile.profile_fields(c.register_raw))
register("q_field_profile_clinic", query(_field_profile("clinic_raw", "clinic", "clinic_id")))(lambda c: profile.profile_fields(c.clinic_raw))


def _token_profile(side: str, n: str) -> str:
    return f"""SELECT r.rule_id, coalesce(c, 0) AS n_complete, coalesce(d, 0) AS n_distinct, CAST(coalesce(c, 0) AS DOUBLE) / CAST({n} AS DOUBLE) AS complete_rate, CAST(coalesce(d, 0) AS DOUBLE) / CAST({n} AS DOUBLE) AS distinct_rate
FROM {V.ids()} r LEFT JOIN (SELECT rule_id, count(*) AS c, count(DISTINCT token) AS d FROM {side}_tokens GROUP BY rule_id) t ON r.rule_id = t.rule_id"""


register("q_token_profile_register", query(_token_profile("register", V.NO)))(lambda c: profile.profile_tokens(linkage.file_db(c.register), c.t.size("orders")))
register("q_token_profile_clinic", query(_token_profile("clinic", "(SELECT count(*) FROM customer)")))(lambda c: profile.profile_tokens(linkage.file_db(c.clinic), c.t.size("customer")))
register("q_completeness_mask", query("SELECT rule_id, count(*) AS n_complete FROM register_tokens GROUP BY rule_id"))(lambda c: profile.completeness_by_mask(c.register))
register("q_token_profile_approx", query("SELECT rule_id, count(*) AS n_complete, TRUE AS near, TRUE AS near_merged FROM register_tokens GROUP BY rule_id"))(lambda c: _approximate(c))


def _approximate(c: Context) -> DataFrame:
    """Whether sketches of the whole file, and merged ones of three deliveries, come within four standard errors."""
    exact = linkage.file_db(c.register).groupBy("rule_id").agg(F.count("*").alias("exact"))
    merged = profile.merged_sketches(*[profile.token_sketches(c.register.where(F.col("rec_id") % 3 == k)) for k in range(3)])
    near = lambda x, rsd: F.abs(F.col(x) - F.col("exact")) <= 4 * rsd * F.col("exact") + 1
    joined = profile.profile_tokens_approx(c.register).join(merged.withColumnRenamed("n_distinct", "n_merged"), "rule_id").join(exact, "rule_id")
    return joined.select("rule_id", "n_complete", near("n_distinct", 0.02).alias("near"), near("n_merged", 0.02).alias("near_merged"))


register("q_heavy_keys", query("SELECT rule_id, token, n_records FROM register_db WHERE n_records >= 100"))(lambda c: profile.heavy_keys(tokens.tokens_long(c.register), 100))
register("q_multiplicity", query("SELECT rule_id, n_records, count(*) AS n_tokens FROM register_db GROUP BY 1, 2"))(lambda c: profile.multiplicity(linkage.file_db(c.register)))
_HEAVY = "SELECT rule_id, token, n_records, CAST(rank AS INTEGER) AS rank FROM (SELECT rule_id, token, n_records, row_number() OVER (PARTITION BY rule_id ORDER BY n_records DESC, token) AS rank FROM register_db) WHERE rank <= 5"
register("q_heavy_tokens", query(_HEAVY))(
    lambda c: linkage.file_db(c.register).select("rule_id", "token", "n_records", F.row_number().over(Window.partitionBy("rule_id").orderBy(F.col("n_records").desc(), "token")).alias("rank")).where("rank <= 5")
)
register(
    "q_ssn_by_birth_decade",
    query("SELECT substr(birth_date, 1, 3) || '0' AS grp, count(*) AS n_rows, count(ssn) AS n_valid, CAST(count(ssn) AS DOUBLE) / CAST(count(*) AS DOUBLE) AS valid_rate FROM clinic GROUP BY 1"),
)(lambda c: profile.rate_by(c.clinic, F.concat(F.substring("birth_date", 1, 3), F.lit("0"))))
register(
    "q_profile_cube",
    query(
        """SELECT c_mktsegment AS segment, quality, CAST(grouping(c_mktsegment, quality) AS BIGINT) AS grouping_id, count(*) AS n_rows, count(ssn) AS n_valid
FROM clinic JOIN customer ON rec_id = c_custkey LEFT JOIN labels ON doc_id = rec_id GROUP BY CUBE (c_mktsegment, quality)"""
    ),
)(
    lambda c: c.clinic.join(c.t.customer, F.col("rec_id") == F.col("c_custkey")).join(c.t.labels, F.col("doc_id") == F.col("rec_id"), "left")
    .cube(F.col("c_mktsegment").alias("segment"), "quality").agg(F.grouping_id().alias("grouping_id"), F.count("*").alias("n_rows"), F.count("ssn").alias("n_valid"))
)
_SINGLE = "(VALUES ('ssn', 6), ('last_name', 18), ('first_name', 19), ('birth_date', 20)) AS x(field, rule_id)"
register(
    "q_reconcile",
    query(
        f"""SELECT x.field, x.rule_id, n_complete - n_invalid AS n_expected, n AS n_tokens, n - (n_complete - n_invalid) AS difference FROM {_SINGLE}
JOIN ({_field_profile('clinic_raw', 'clinic', 'clinic_id')}) f ON f.field = x.field JOIN (SELECT rule_id, count(*) AS n FROM clinic_tokens GROUP BY rule_id) t ON t.rule_id = x.rule_id"""
    ),
)(lambda c: profile.reconcile(profile.profile_fields(c.clinic_raw), profile.profile_tokens(linkage.file_db(c.clinic), c.t.size("customer"))))
# The clinic's first names and birth dates, these as if they had come month first.
_MONTH_FIRST = """SELECT 'birth_date' AS field, count(v) AS n_complete, count(DISTINCT v) AS n_distinct, count(*) FILTER (WHERE v IS NOT NULL AND ok IS NULL) AS n_invalid
FROM (SELECT replace(birth_raw, '-', '') AS v, birth_date AS ok FROM clinic_raw JOIN clinic ON clinic_id = rec_id)
UNION ALL SELECT 'first_name', count(first_name_raw), count(DISTINCT first_name_raw), count(*) FILTER (WHERE first_name_raw IS NOT NULL AND first_name IS NULL) FROM clinic_raw JOIN clinic ON clinic_id = rec_id"""
register("q_table2_example", query(_MONTH_FIRST))(lambda c: _month_first(c.clinic_raw))


def _month_first(raw: DataFrame) -> DataFrame:
    rows = raw.withColumn("mdy", F.regexp_replace("birth_raw", r"^(\d{4})-(\d{2})-(\d{2})$", "$2/$3/$1")).withColumn("birth_raw", cleaning.to_ymd(F.col("mdy"), "mdy"))
    return profile.profile_fields(rows).where(F.col("field").isin("first_name", "birth_date")).select("field", "n_complete", "n_distinct", "n_invalid")


# --- categories and presentation --------------------------------------------------------------------------

register("q_categories", query("SELECT s.*, category FROM scorecard s LEFT JOIN priority p ON s.rule_id = p.rule_id"))(lambda c: present.categorize(c.scores))
# Twenty balances, of each of which the share of customers who hold it is ranked as a rule's match rate is.
_BALANCES = [(i, 500 * i) for i in range(1, 21)]
_HOLD = "SELECT x.rule_id, CAST(count(*) FILTER (WHERE c_acctbal >= x.least) AS DOUBLE) / CAST(count(*) AS DOUBLE) AS match_rate FROM customer, (VALUES " + ", ".join(map(str, _BALANCES)) + ") AS x(rule_id, least) GROUP BY 1"
register("q_paper_categories", V.VIEWS["priority"].replace("SELECT rule_id, match_rate, ", "SELECT rule_id, ").replace("FROM scorecard", f"FROM ({_HOLD})"))(lambda c: _holding(c))


def _holding(c: Context) -> DataFrame:
    counts = c.t.customer.agg(F.count("*").alias("n"), *[F.count_if(F.col("c_acctbal") >= least).alias(f"k{i}") for i, least in _BALANCES])
    rows = counts.select("n", F.inline(F.array(*[F.struct(F.lit(i).alias("rule_id"), F.col(f"k{i}").alias("k")) for i, _ in _BALANCES])))
    return present.rule_priority(rows.where("n > 0").select("rule_id", (F.col("k").cast("double") / F.col("n").cast("double")).alias("match_rate"))).select("rule_id", "category", "priority")


register("q_rule_priority", query("SELECT * FROM priority"))(lambda c: c.priority)
register("q_links", query("SELECT * FROM links"))(lambda c: c.links)
register("q_best_link", query("SELECT * FROM best"))(lambda c: c.best)
register("q_presentation", query("SELECT * FROM presented"))(lambda c: c.presented.select("patient", "clinic_dod", F.col("register.dod").alias("register_dod"), "register.category", "register.rule_id"))
register(
    "q_multi_source",
    query(
        """SELECT rec_id AS patient, death_date AS clinic_dod, 'register' AS source, reg_dod AS dod, category, rule_id FROM clinic JOIN best ON rec_id = clinic_id
UNION ALL SELECT rec_id, death_date, 'register_corrected', reg_dod, category, rule_id FROM clinic JOIN best2 ON rec_id = clinic_id""",
        db2=V.database(V.long_tokens("register2")),
        best2="SELECT * FROM (SELECT l.*, category, row_number() OVER (PARTITION BY clinic_id ORDER BY priority) AS rn FROM (" + V.pairs("clinic_db", "db2") + ") l JOIN priority USING (rule_id)) WHERE rn = 1",
    ),
)(
    lambda c: present.present_sources(c.clinic, {"register": c.best, "register_corrected": c.best2}).select("patient", "clinic_dod", F.inline("sources"))
)
register(
    "q_conflicts",
    query("SELECT clinic_id, count(*) AS n_links, count(DISTINCT reg_id) AS n_targets, min(reg_dod) AS min_dod, max(reg_dod) AS max_dod FROM links GROUP BY clinic_id HAVING count(DISTINCT reg_id) > 1"),
)(lambda c: present.conflicts(c.links))
register("q_shared_targets", query("SELECT reg_id, count(DISTINCT clinic_id) AS n_patients, min(clinic_id) AS first_patient FROM links GROUP BY reg_id HAVING count(DISTINCT clinic_id) > 1"))(lambda c: present.shared_targets(c.links))
register(
    "q_refresh_instability",
    query(
        """SELECT coalesce(a.clinic_id, b.clinic_id) AS patient, CASE WHEN a.clinic_id IS NULL THEN 'appears' WHEN b.clinic_id IS NULL THEN 'vanishes' WHEN a.reg_dod IS NOT DISTINCT FROM b.reg_dod THEN 'stays' ELSE 'changes' END AS change
FROM best a FULL JOIN best3 b ON a.clinic_id = b.clinic_id""",
        db3=V.database(V.long_tokens("register2", where="rec_id % 10 <> 4") + " UNION ALL " + V.long_tokens("grown")),
        grown="SELECT * REPLACE (rec_id + " + V.NO + " AS rec_id) FROM register2 WHERE rec_id % 50 = 3",
        best3="SELECT * FROM (SELECT l.*, category, row_number() OVER (PARTITION BY clinic_id ORDER BY priority) AS rn FROM (" + V.pairs("clinic_db", "db3") + ") l JOIN priority USING (rule_id)) WHERE rn = 1",
    ),
)(lambda c: _refreshed(c))


def _refreshed(c: Context) -> DataFrame:
    """The next delivery corrects dates, withdraws some records and reports some deaths twice."""
    kept = c.register2.where("rec_id % 10 <> 4")
    again = c.register2.where("rec_id % 50 = 3").withColumn("rec_id", F.col("rec_id") + c.t.size("orders"))
    return present.refresh_diff(c.best, present.best_link(linkage.links(c.clinic, kept.unionByName(again)), c.priority))


_STEPS = "(VALUES (0, 'none'), (1, 'clinic'), (2, 'category_1'), (3, 'category_2'), (4, 'category_3')) AS s(step, deaths)"
register(
    "q_cohort_sensitivity",
    query(
        f"""SELECT step, deaths, count(*) AS n_visits, count(*) FILTER (WHERE returned) AS n_returns, CAST(count(*) FILTER (WHERE returned) AS DOUBLE) / CAST(count(*) AS DOUBLE) AS return_rate
FROM (SELECT v.day, returned, step, deaths, CASE WHEN step = 0 THEN NULL WHEN step = 1 THEN clinic_dod ELSE coalesce(clinic_dod, CASE WHEN category <= step - 1 THEN register_dod END) END AS dod
  FROM (SELECT o_custkey AS patient, CAST(o_orderdate AS DATE) AS day, coalesce(date_diff('day', CAST(o_orderdate AS DATE), lead(CAST(o_orderdate AS DATE)) OVER (PARTITION BY o_custkey ORDER BY CAST(o_orderdate AS DATE), o_orderkey)) <= 30, FALSE) AS returned FROM orders) v
  LEFT JOIN presented p ON p.patient = v.patient CROSS JOIN {_STEPS}) WHERE dod IS NULL OR dod > day + 30 GROUP BY step, deaths"""
    ),
)(lambda c: present.sensitivity(c.t.orders.select(F.col("o_custkey").alias("patient"), F.col("o_orderdate").cast("date").alias("day"), F.col("o_orderkey").alias("visit_id")), c.presented))

# --- weights and classes ----------------------------------------------------------------------------------

register("q_value_weights", query("SELECT * FROM weights"))(lambda c: c.weights)
register("q_candidates", query("SELECT * FROM candidates"))(lambda c: c.candidates)
register("q_pair_scores", query("SELECT * FROM pair_scores"))(lambda c: c.pair_scores)
register("q_agreement_class", query("SELECT * FROM classes"))(lambda c: c.classes)
_CHOSEN = """SELECT clinic_id, reg_id, class, score, count(*) OVER (PARTITION BY clinic_id) > 1 AS needs_review FROM (
  SELECT *, rank() OVER (PARTITION BY clinic_id ORDER BY class, score DESC) AS r FROM classes JOIN pair_scores USING (clinic_id, reg_id)) WHERE r = 1"""
register("q_weighted_select", query(_CHOSEN))(lambda c: c.chosen)
register(
    "q_prob_vs_det",
    query(
        f"""SELECT 'deterministic' AS method, count(*) AS n_links, count(*) FILTER (WHERE a.true_person = b.true_person) AS n_right FROM best l JOIN clinic a ON a.rec_id = l.clinic_id JOIN register b ON b.rec_id = l.reg_id
UNION ALL SELECT 'weighted', count(*), count(*) FILTER (WHERE a.true_person = b.true_person) FROM (SELECT * FROM ({_CHOSEN}) WHERE NOT needs_review) l JOIN clinic a ON a.rec_id = l.clinic_id JOIN register b ON b.rec_id = l.reg_id"""
    ),
)(lambda c: _methods(c))


def _methods(c: Context) -> DataFrame:
    truth = lambda std, key, name: std.select(F.col("rec_id").alias(key), F.col("true_person").alias(name))

    def judged(found: DataFrame, method: str) -> DataFrame:
        both = found.select("clinic_id", "reg_id").join(truth(c.clinic, "clinic_id", "x"), "clinic_id").join(truth(c.register, "reg_id", "y"), "reg_id")
        return both.agg(F.count("*").alias("n_links"), F.count_if(F.col("x") == F.col("y")).alias("n_right")).select(F.lit(method).alias("method"), "n_links", "n_right")

    return judged(c.best, "deterministic").unionByName(judged(c.chosen.where("not needs_review"), "weighted"))


# --- register variants, refresh, release ------------------------------------------------------------------

register("q_latest_delivery", query("SELECT person, version, dod FROM (SELECT *, row_number() OVER (PARTITION BY person ORDER BY version DESC, dod DESC) AS rn FROM deliveries) WHERE rn = 1"))(lambda c: c.corrected)
register("q_incremental_equals_full", query("SELECT * FROM register_db"))(
    lambda c: linkage.merge_token_db(linkage.file_db(c.register.where("rec_id % 3 <> 0")), linkage.file_db(c.register.where("rec_id % 3 = 0")))
)
register("q_incremental_retire", query("SELECT * FROM (" + V.database(V.long_tokens("register_c", where="rec_id % 7 <> 1")) + ")"))(lambda c: _retired(c))


def _retired(c: Context) -> DataFrame:
    keys = lambda std: tokens.tokens_long(std, keep=("death_date",))
    stay = c.register.where("rec_id % 7 <> 1")
    return linkage.retire(linkage.file_db(c.register), keys(c.register.where("rec_id % 7 = 1")), keys(stay))


register("q_public_file", query(f"SELECT reg_id, dod FROM register_raw WHERE dod < CAST(DATE '{AS_OF}' - INTERVAL 36 MONTH AS DATE)"))(lambda c: lifecycle.public_file(c.register_raw, AS_OF).select("reg_id", "dod"))
register("q_without_state", query("SELECT reg_id, source, dod FROM register_raw WHERE NOT (source = 'state' AND dod >= DATE '1999-01-01')"))(lambda c: lifecycle.without_state(c.register_raw, "1999-01-01").select("reg_id", "source", "dod"))
register(
    "q_coverage_by_year",
    query(
        """SELECT CAST(year AS INTEGER) AS year, n_deaths, n_deaths - lag(n_deaths) OVER (ORDER BY year) AS change FROM (
SELECT year(dod) AS year, count(*) AS n_deaths FROM register_raw WHERE NOT (source = 'state' AND dod >= DATE '1999-01-01') GROUP BY 1)"""
    ),
)(lambda c: lifecycle.coverage_by_year(lifecycle.without_state(c.register_raw, "1999-01-01")))
_VARIANTS = {"all": "TRUE", "public": f"death_date < CAST(DATE '{AS_OF}' - INTERVAL 36 MONTH AS DATE)", "without_state": "true_person % 5 >= 3"}
register(
    "q_variant_scorecards",
    query(
        " UNION ALL ".join(f"SELECT '{v}' AS variant, * FROM ({V.score(f'SELECT * FROM pairs_{v}')})" for v in _VARIANTS),
        **{f"db_{v}": V.database(V.long_tokens("register_c", where=cond)) for v, cond in _VARIANTS.items()},
        **{f"pairs_{v}": V.pairs("subset_db", f"db_{v}") for v in _VARIANTS},
    ),
)(lambda c: _variants(c))


def _variants(c: Context) -> DataFrame:
    files = {"all": c.register_raw, "public": lifecycle.public_file(c.register_raw, AS_OF), "without_state": lifecycle.without_state(c.register_raw)}
    out = None
    for name, raw in files.items():
        one = evaluate.scorecard(linkage.subset_pairs(c.clinic, standardize(raw, "reg_id"))).select(F.lit(name).alias("variant"), "*")
        out = one if out is None else out.unionByName(one)
    return out


register(
    "q_release_policy",
    query(
        f"""SELECT patient, clinic_dod IS NOT NULL OR register_dod IS NOT NULL AS deceased, clinic_dod,
  CASE WHEN CAST(register_dod + INTERVAL 36 MONTH AS DATE) <= DATE '{AS_OF}' OR coalesce(register_dod = clinic_dod, FALSE) THEN register_dod END AS register_dod FROM presented"""
    ),
)(lambda c: lifecycle.release(c.presented, AS_OF))
register(
    "q_release_policy_year_end",
    query(
        f"""SELECT patient, clinic_dod IS NOT NULL OR register_dod IS NOT NULL AS deceased, clinic_dod,
  CASE WHEN year(register_dod) + 3 < year(DATE '{AS_OF}') OR coalesce(register_dod = clinic_dod, FALSE) THEN register_dod END AS register_dod FROM presented"""
    ),
)(lambda c: lifecycle.release(c.presented, AS_OF, "year_end"))
register(
    "q_refuted_deaths",
    query(
        """SELECT p.patient, register_dod, last_seen, CAST(date_diff('day', register_dod, last_seen) AS INTEGER) AS days_after FROM presented p
JOIN (SELECT patient, max(day) AS last_seen FROM encounters WHERE kind IN ('purchase', 'login', 'click', 'view', 'signup') GROUP BY patient) e ON p.patient = e.patient WHERE last_seen > register_dod + 2"""
    ),
)(lambda c: lifecycle.refute_by_encounter(c.presented, c.encounters, ("purchase", "login", "click", "view", "signup"), 2))
register("q_vital_status", query("SELECT patient, CASE WHEN clinic_dod IS NOT NULL OR register_dod IS NOT NULL THEN 'deceased' ELSE 'unknown' END AS status FROM presented"))(lambda c: lifecycle.vital_status(c.presented))
