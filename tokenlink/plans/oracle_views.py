"""DuckDB text of the person views and of rules, independent of the Spark side."""

from __future__ import annotations

import re

from ..functions.cleaning import ACCENTS, DEFAULT_DENY, PLAIN
from ..operators.rules import EVALUATED, Part, RuleSet

DENY = ", ".join(f"'{x}'" for x in DEFAULT_DENY)
ND, NO = "(SELECT count(*) FROM documents)", "(SELECT count(*) FROM orders)"


def ssn9(p: str) -> str:
    return f"CAST(100000000 + ({p}) * 7919 % 59999 * 10000 + ({p}) * 69621 % 2147483647 % 101 + 1 AS VARCHAR)"


def dob(p: str, shift: int = 0) -> str:
    return f"(DATE '1910-01-01' + CAST((({p}) * 48271 + {shift}) % 2147483647 % 2991 AS INTEGER))"


def w(i: str | int) -> str:
    return f"split_part(text, ' ', CAST({i} AS INTEGER))"


def digits(c: str) -> str:
    return f"regexp_replace({c}, '[^0-9]', '', 'g')"


def letters(c: str, accents: str = "fold") -> str:
    folded = f"translate({c}, '{ACCENTS}', '{PLAIN}')" if accents == "fold" else c
    return f"upper(regexp_replace({folded}, '[^A-Za-z]', '', 'g'))"


def name(c: str, n: int) -> str:
    return f"nullif(substr({letters(c)}, 1, {n}), '')"


def date8(c: str) -> str:
    d = digits(c)
    return f"CASE WHEN length({d}) = 8 AND substr({d}, 1, 4) BETWEEN '1850' AND '2022' THEN {d} END"


def ssn(c: str) -> str:
    d = digits(c)
    return f"CASE WHEN length({d}) = 9 AND substr({d}, 1, 3) NOT IN ('000', '666') AND substr({d}, 1, 1) <> '9' AND substr({d}, 4, 2) <> '00' AND substr({d}, 6, 4) <> '0000' AND {d} NOT IN ({DENY}) THEN {d} END"


def defect(c: str) -> str:
    d = digits(c)
    return f"""CASE WHEN {d} = '' OR {c} IS NULL THEN NULL WHEN {d} IN ({DENY}) THEN {d} WHEN length({d}) <> 9 THEN 'bad-length' WHEN substr({d}, 1, 1) = '9' THEN 'area-9xx'
      WHEN substr({d}, 4, 2) = '00' THEN 'group-00' WHEN substr({d}, 1, 3) = '666' THEN 'area-666' WHEN substr({d}, 1, 3) = '000' THEN 'area-000' WHEN substr({d}, 6, 4) = '0000' THEN 'serial-0000' END"""


def soundex(c: str) -> str:
    code = f"translate({c}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', '01230127022455012623017202')"
    s = f"substr({code}, 1, 1) || replace(substr({code}, 2), '7', '')"
    for k in "123456":
        s = f"regexp_replace({s}, '{k}+', '{k}', 'g')"
    return f"CASE WHEN {c} IS NOT NULL THEN substr({c}, 1, 1) || rpad(substr(replace(substr({s}, 2), '0', ''), 1, 3), 3, '0') END"


def _std(raw: str, key: str) -> str:
    address = f"nullif(regexp_replace(upper(regexp_replace(translate(address_raw, '{ACCENTS}', '{PLAIN}'), '[^A-Za-z0-9]', '', 'g')), '[^A-Z0-9]', '', 'g'), '')"
    return f"""
SELECT *, (CASE WHEN ssn IS NOT NULL THEN 1 ELSE 0 END) + (CASE WHEN last_name IS NOT NULL THEN 2 ELSE 0 END) + (CASE WHEN middle_name IS NOT NULL THEN 4 ELSE 0 END)
     + (CASE WHEN first_name IS NOT NULL THEN 8 ELSE 0 END) + (CASE WHEN birth_date IS NOT NULL THEN 16 ELSE 0 END) AS valid_mask
FROM (SELECT {key} AS rec_id, true_person, {name('first_name_raw', 15)} AS first_name, {name('middle_name_raw', 15)} AS middle_name, {name('last_name_raw', 20)} AS last_name,
        {date8('birth_raw')} AS birth_date, {ssn('ssn_raw')} AS ssn, dod AS death_date,
        CASE WHEN gender_raw IN ('F', 'M') THEN gender_raw END AS gender, CASE WHEN length(zip_raw) = 5 THEN zip_raw END AS zip, {address} AS address FROM {raw})"""


def _coded(std: str) -> str:
    return f"SELECT *, {soundex('last_name')} AS last_sx, {soundex('middle_name')} AS middle_sx, {soundex('first_name')} AS first_sx FROM {std}"


def part(p: Part) -> str:
    if p.transform == "prefix":
        return f"substr({p.field}, 1, {p.n})"
    if p.transform == "last":
        return f"right({p.field}, {p.n})"
    return p.field.replace("_name", "_sx") if p.transform == "soundex" else p.field


def long_tokens(coded: str, rules: RuleSet = EVALUATED, sep: str = "", where: str = "TRUE") -> str:
    glue = f" || '{sep}' || " if sep else " || "
    items = ", ".join(f"struct_pack(rule_id := {r.id}, token := {glue.join(map(part, r.parts))})" for r in rules)
    return f"SELECT rec_id, death_date, u.rule_id, u.token FROM (SELECT rec_id, death_date, unnest([{items}]) AS u FROM {coded} WHERE {where}) WHERE u.token IS NOT NULL"


def database(tokens: str) -> str:
    return f"SELECT rule_id, token, count(*) AS n_records, count(death_date) AS n_dod, min(death_date) AS min_dod, max(death_date) AS max_dod, min(rec_id) AS min_rec_id FROM ({tokens}) GROUP BY rule_id, token"


def pairs(a: str, b: str, alone: str = "b.n_records = 1") -> str:
    return f"SELECT a.rule_id, a.token, a.min_rec_id AS clinic_id, a.min_dod AS clinic_dod, b.min_rec_id AS reg_id, b.min_dod AS reg_dod FROM {a} a JOIN {b} b ON a.rule_id = b.rule_id AND a.token = b.token WHERE a.n_records = 1 AND {alone}"


def ids(rules: RuleSet = EVALUATED) -> str:
    return f"(SELECT unnest([{', '.join(str(r.id) for r in rules)}]) AS rule_id)"


def score(pairs_sql: str, rules: RuleSet = EVALUATED, days: int = 0) -> str:
    ok = f"abs(date_diff('day', clinic_dod, reg_dod)) <= {days}"
    return f"""
SELECT rule_id, n_one_to_one, n_match, n_one_to_one - n_match AS n_nonmatch, CASE WHEN n_one_to_one > 0 THEN CAST(n_match AS DOUBLE) / CAST(n_one_to_one AS DOUBLE) END AS match_rate
FROM (SELECT r.rule_id, coalesce(n, 0) AS n_one_to_one, coalesce(k, 0) AS n_match FROM {ids(rules)} r
      LEFT JOIN (SELECT rule_id, count(*) FILTER (WHERE ({ok}) IS NOT NULL) AS n, count(*) FILTER (WHERE {ok}) AS k FROM ({pairs_sql}) GROUP BY rule_id) s ON r.rule_id = s.rule_id)"""


VIEWS: dict[str, str] = {
    "register_p": f"SELECT o_orderkey AS p, CAST(o_orderdate AS DATE) AS dod, CAST(o_orderkey // {ND} % 4 AS INTEGER) AS g, text FROM orders JOIN documents ON doc_id = o_orderkey % {ND}",
    "register_raw": f"""
SELECT p AS reg_id, p AS true_person, {w('1 + g')} AS first_name_raw, CASE WHEN p % 17 < 8 THEN {w(11)} ELSE '' END AS middle_name_raw, {w('6 + g')} AS last_name_raw,
  replace(CAST({dob('p')} AS VARCHAR), '-', '/') AS birth_raw, {ssn9('p')} AS ssn_raw, dod, substr('FM', CAST(1 + p % 2 AS INTEGER), 1) AS gender_raw, CAST(90000 + p % 250 AS VARCHAR) AS zip_raw,
  CAST(1 + p % 300 AS VARCHAR) || ' ' || {w(12)} AS address_raw, CAST(p % 25 AS INTEGER) AS birth_state, CASE WHEN p % 5 < 3 THEN 'state' ELSE 'other' END AS source,
  CAST(p % 5 AS INTEGER) AS race, CAST(p % 4 AS INTEGER) AS marital, {w(13)} AS father_surname, CAST(p % 25 AS INTEGER) AS residence_state
FROM register_p""",
    "clinic_k": f"SELECT c_custkey AS k, CASE WHEN c_custkey % 20 = 17 THEN (c_custkey - 1) * 10 + 3 WHEN c_custkey % 4 > 1 THEN {NO} + c_custkey ELSE c_custkey * 10 + 3 END AS p FROM customer",
    "clinic_p": f"SELECT k, p, CAST(p // {ND} % 4 AS INTEGER) AS g, text, CAST(o_orderdate AS DATE) AS order_date FROM clinic_k JOIN documents ON doc_id = p % {ND} LEFT JOIN orders ON o_orderkey = p % {NO}",
    "clinic_raw": f"""
SELECT k AS clinic_id, p AS true_person, CASE WHEN k % 11 = 5 THEN substr({w('1 + g')}, 1, 3) WHEN k % 29 = 7 THEN '%^3' ELSE {w('1 + g')} END AS first_name_raw,
  CASE WHEN k % 9 < 3 THEN {w(11)} END AS middle_name_raw, CASE WHEN k % 13 = 6 THEN {w('6 + g')} || 'e' ELSE {w('6 + g')} END AS last_name_raw,
  CASE WHEN k % 97 = 9 THEN '1803-02-01' WHEN k % 23 = 4 THEN CAST({dob('p', 1)} AS VARCHAR) ELSE CAST({dob('p')} AS VARCHAR) END AS birth_raw,
  CASE WHEN k % 100 < 20 THEN '999-99-9999' WHEN k % 100 < 33 THEN '888-88-8888' WHEN k % 100 < 36 THEN '000-00-0000' WHEN k % 100 = 36 THEN '912-34-5678' WHEN k % 100 = 37 THEN '123-00-4567'
       WHEN k % 100 = 38 THEN '666-12-3456' WHEN k % 100 = 39 THEN '000-12-3456' WHEN k % 100 = 40 THEN '123-45-6789' WHEN k % 100 = 41 THEN '111-11-1111' WHEN k % 100 <= 56 THEN NULL
       ELSE substr({ssn9('p')}, 1, 3) || '-' || substr({ssn9('p')}, 4, 2) || '-' || substr({ssn9('p')}, 6, 4) END AS ssn_raw,
  CASE WHEN k % 5 < 2 THEN order_date + CASE WHEN k % 7 = 0 THEN 4 ELSE 0 END END AS dod, CASE WHEN k % 31 <> 3 THEN substr('FM', CAST(1 + p % 2 AS INTEGER), 1) END AS gender_raw,
  CASE WHEN k % 6 = 1 THEN '94305' ELSE CAST(90000 + p % 250 AS VARCHAR) END AS zip_raw, CAST(1 + p % 300 AS VARCHAR) || ' ' || {w(12)} AS address_raw, CAST(p % 25 AS INTEGER) AS birth_state,
  CASE WHEN k % 8 <> 2 THEN CAST(p % 5 AS INTEGER) END AS race, CAST(CASE WHEN k % 9 = 4 THEN (p + 1) % 4 ELSE p % 4 END AS INTEGER) AS marital, {w(13)} AS father_surname, CAST(CASE WHEN k % 10 = 3 THEN (p + 1) % 25 ELSE p % 25 END AS INTEGER) AS residence_state
FROM clinic_p""",
    "register": _std("register_raw", "reg_id"),
    "clinic": _std("clinic_raw", "clinic_id"),
    "register_c": _coded("register"),
    "clinic_c": _coded("clinic"),
    "register_dup_raw": f"SELECT * FROM register_raw UNION ALL SELECT * REPLACE (reg_id + {NO} AS reg_id) FROM register_raw WHERE true_person % 25 = 3",
    "register_dup": _std("register_dup_raw", "reg_id"),
    "register_dup_c": _coded("register_dup"),
    "reg2_raw": """
SELECT p_partkey AS reg_id, p_partkey AS true_person, split_part(p_name, ' ', 1) AS first_name_raw, CAST(NULL AS VARCHAR) AS middle_name_raw, split_part(p_name, ' ', 2) AS last_name_raw,
  CAST(DATE '1930-01-01' + CAST(p_partkey * 48271 % 2147483647 % 401 AS INTEGER) AS VARCHAR) AS birth_raw, """ + ssn9("p_partkey") + """ AS ssn_raw,
  DATE '1995-01-01' + CAST(p_partkey * 69621 % 2147483647 % 2400 AS INTEGER) AS dod, CAST(NULL AS VARCHAR) AS gender_raw, CAST(NULL AS VARCHAR) AS zip_raw, CAST(NULL AS VARCHAR) AS address_raw FROM part""",
    "clinic2_raw": "SELECT s_suppkey AS clinic_id, r.* EXCLUDE (reg_id) REPLACE (CASE WHEN s_suppkey % 3 <> 0 THEN ssn_raw END AS ssn_raw, dod + CASE WHEN s_suppkey % 9 = 1 THEN 4 ELSE 0 END AS dod) FROM supplier JOIN reg2_raw r ON r.reg_id = s_suppkey * 20 + 1",
    "reg2": _std("reg2_raw", "reg_id"),
    "clinic2": _std("clinic2_raw", "clinic_id"),
    "reg2_c": _coded("reg2"),
    "clinic2_c": _coded("clinic2"),
    "register_tokens": long_tokens("register_c"),
    "clinic_tokens": long_tokens("clinic_c"),
    "subset_tokens": long_tokens("clinic_c", where="death_date IS NOT NULL"),
    "register_db": database("SELECT * FROM register_tokens"),
    "clinic_db": database("SELECT * FROM clinic_tokens"),
    "subset_db": database("SELECT * FROM subset_tokens"),
    "subset_pairs": pairs("subset_db", "register_db"),
    "scorecard": score("SELECT * FROM subset_pairs"),
    "priority": "SELECT rule_id, match_rate, CASE WHEN match_rate * 100.0 > 80 THEN 1 WHEN match_rate * 100.0 >= 50 THEN 2 ELSE 3 END AS category, CAST(row_number() OVER (ORDER BY match_rate DESC, rule_id) AS INTEGER) AS priority FROM scorecard WHERE match_rate IS NOT NULL",
    "links": "SELECT rule_id, clinic_id, clinic_dod, reg_id, reg_dod FROM (" + pairs("clinic_db", "register_db") + ")",
    "best": "SELECT clinic_id, rule_id, category, priority, reg_id, reg_dod FROM (SELECT l.*, category, priority, row_number() OVER (PARTITION BY clinic_id ORDER BY priority) AS rn FROM links l JOIN priority USING (rule_id)) WHERE rn = 1",
    "presented": "SELECT c.rec_id AS patient, c.death_date AS clinic_dod, b.reg_dod AS register_dod, b.category, b.rule_id FROM clinic c LEFT JOIN best b ON c.rec_id = b.clinic_id",
    "deliveries": "SELECT l_orderkey AS person, l_linenumber AS version, CAST(l_shipdate AS DATE) AS dod FROM lineitem",
    "corrected": "SELECT person, dod FROM (SELECT *, row_number() OVER (PARTITION BY person ORDER BY version DESC, dod DESC) AS rn FROM deliveries) WHERE rn = 1",
    "register2": "SELECT r.* REPLACE (coalesce(c.dod, r.death_date) AS death_date) FROM register_c r LEFT JOIN corrected c ON r.rec_id = c.person",
    "encounters": "SELECT event_id, user_id AS patient, CAST(ts AS DATE) - CAST(8400 + user_id * 17 % 2000 AS INTEGER) AS day, event_type AS kind FROM events",
    "loose_mine": long_tokens("clinic_c", RuleSet.of("S4 B", "L F3 B", "L~ F~ B", "L M F Y")),
    "loose_theirs": long_tokens("register_c", RuleSet.of("S4 B", "L F3 B", "L~ F~ B", "L M F Y")),
    "candidates": "SELECT DISTINCT a.rec_id AS clinic_id, b.rec_id AS reg_id FROM loose_mine a JOIN loose_theirs b USING (rule_id, token)",
    "weights": "SELECT field, value, n, CAST(round(log2(CAST(total AS DOUBLE) / CAST(n AS DOUBLE)) * 1000000) AS BIGINT) AS weight FROM (SELECT field, value, count(*) AS n, sum(count(*)) OVER (PARTITION BY field) AS total FROM ("
    + " UNION ALL ".join(f"SELECT '{f}' AS field, {f} AS value FROM register" for f in ("first_name", "middle_name", "last_name", "birth_date"))
    + ") WHERE value IS NOT NULL GROUP BY field, value)",
    "pair_scores": "SELECT clinic_id, reg_id, CAST(" + " + ".join(f"coalesce(w{i}.weight, 0)" for i in range(4)) + " AS BIGINT) AS score FROM candidates JOIN clinic a ON a.rec_id = clinic_id JOIN register b ON b.rec_id = reg_id "
    + " ".join(f"LEFT JOIN weights w{i} ON w{i}.field = '{f}' AND w{i}.value = a.{f} AND a.{f} = b.{f}" for i, f in enumerate(("first_name", "middle_name", "last_name", "birth_date"))),
    "classes": """
SELECT clinic_id, reg_id, CASE WHEN known AND digits >= 8 AND first_ok AND initial_ok AND last_ok AND year_ok AND month_ok AND sex_ok AND state_ok THEN 1 WHEN known AND digits >= 7 THEN 2 WHEN known THEN 5
  WHEN CAST(first_ok AS INT) + CAST(coalesce(same_initial, FALSE) AS INT) + CAST(last_ok AS INT) + CAST(same_year AS INT) + CAST(month_ok AS INT) + CAST(day_ok AS INT) + CAST(sex_ok AS INT) + CAST(state_ok AS INT) + CAST(race_ok AS INT)
       + CAST(marital_ok AS INT) + CAST(father_ok AS INT) >= 8 THEN 3 ELSE 4 END AS class
FROM (SELECT candidates.clinic_id, candidates.reg_id, a.ssn IS NOT NULL AND b.ssn IS NOT NULL AS known, """
    + " + ".join(f"CASE WHEN substr(a.ssn, {i}, 1) = substr(b.ssn, {i}, 1) THEN 1 ELSE 0 END" for i in range(1, 10))
    + """ AS digits, coalesce(a.first_name = b.first_name, FALSE) AS first_ok, substr(a.middle_name, 1, 1) IS NOT DISTINCT FROM substr(b.middle_name, 1, 1) AS initial_ok, substr(a.middle_name, 1, 1) = substr(b.middle_name, 1, 1) AS same_initial,
    coalesce(substr(a.birth_date, 1, 4) = substr(b.birth_date, 1, 4), FALSE) AS same_year, coalesce(a.last_name = b.last_name, FALSE) AS last_ok,
    coalesce(abs(CAST(substr(a.birth_date, 1, 4) AS INT) - CAST(substr(b.birth_date, 1, 4) AS INT)) <= 3, FALSE) AS year_ok, coalesce(substr(a.birth_date, 5, 2) = substr(b.birth_date, 5, 2), FALSE) AS month_ok,
    coalesce(substr(a.birth_date, 7, 2) = substr(b.birth_date, 7, 2), FALSE) AS day_ok, coalesce(a.gender = b.gender, FALSE) AS sex_ok, coalesce(ra.birth_state = rb.birth_state, FALSE) AS state_ok, coalesce(ra.race = rb.race, FALSE) AS race_ok,
    coalesce(ra.marital = rb.marital, FALSE) AS marital_ok, coalesce(a.gender = 'F' AND ra.father_surname = rb.father_surname, FALSE) AS father_ok
  FROM candidates JOIN clinic a ON a.rec_id = candidates.clinic_id JOIN register b ON b.rec_id = candidates.reg_id JOIN clinic_raw ra ON ra.clinic_id = candidates.clinic_id JOIN register_raw rb ON rb.reg_id = candidates.reg_id)""",
}


SHARED = ("register_raw", "clinic_raw", "register", "clinic", "candidates")


def query(body: str, **more: str) -> str:
    """``body`` below the views it uses; ``more`` are views of its own."""
    views = VIEWS | more
    order: dict[str, None] = {}

    def need(text: str, above: tuple[str, ...] = ()) -> None:
        for x in dict.fromkeys(re.findall(r"[a-z_0-9]+", text)):
            if x in views and x not in order and x not in above:
                need(views[x], (*above, x))
                order[x] = None

    need(body)
    # what is used by several views is computed once
    return ("WITH " + ",\n".join(f"{x} AS {'MATERIALIZED ' if x in SHARED else ''}({views[x]})" for x in order) + "\n" if order else "") + body
