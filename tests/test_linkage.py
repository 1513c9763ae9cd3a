from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from tokenlink.functions import cleaning, phonetic
from tokenlink.functions.sql import register as register_sql
from tokenlink.operators import evaluate, linkage, present, profile, tokens, weights
from tokenlink.operators.rules import EVALUATED, Part, RuleSet
from tokenlink.plans import linkage_queries as Q
from tokenlink.plans.context import Context
from tokenlink.sources import written


@pytest.fixture(scope="module")
def ctx(spark, data):
    c = Context(spark, data)
    c.__dict__["register"] = c.register.cache()
    c.__dict__["clinic"] = c.clinic.cache()
    return c


def one(spark, expr):
    return spark.range(1).select(expr.alias("x")).first()["x"]


@pytest.mark.parametrize("bad", ["000-12-3456", "666-12-3456", "900-12-3456", "999-12-3456", "123-00-4567", "123-45-0000", "12345678", "1234567890", "", "   ", *cleaning.DEFAULT_DENY])
def test_invalid_numbers(spark, bad):
    assert one(spark, cleaning.valid_ssn(F.lit(bad))) is None


def test_worked_example(spark):
    s, b = cleaning.valid_ssn(F.lit("123-35-4789")), cleaning.valid_date(cleaning.to_ymd(F.lit("2008/12/25")))
    assert one(spark, s) == "123354789" and one(spark, b) == "20081225"
    row = spark.range(1).select(F.lit(1).alias("rec_id"), s.alias("ssn"), b.alias("birth_date"))
    assert tokens.tokens_wide(row, RuleSet.of("S B")).first()["t1"] == "12335478920081225"
    assert one(spark, cleaning.valid_ssn(F.lit("222-22-2222"))) == "222222222"


@pytest.mark.parametrize(("raw", "clean"), [("Müller-Lüdenscheidt", "MULLERLUDENSCHEIDT"), ("O'Néil 3rd", "ONEILRD"), ("%^3", None), ("", None), (None, None), ("ß", "S"), ("x" * 40, "X" * 20)])
def test_names(spark, raw, clean):
    assert one(spark, cleaning.clean_name(F.lit(raw).cast("string"), 20)) == clean


@pytest.mark.parametrize(("raw", "ok"), [("1850-01-01", True), ("2022-12-31", True), ("1849-12-31", False), ("2023-01-01", False), ("195-1-1", False)])
def test_year_window(spark, raw, ok):
    assert (one(spark, cleaning.valid_date(cleaning.to_ymd(F.lit(raw)))) is not None) == ok


def test_month_first_dates(spark):
    assert one(spark, cleaning.to_ymd(F.lit("5/7/1950"), "mdy")) == "19500507"
    assert one(spark, cleaning.to_ymd(F.lit("1950"), "mdy")) is None


@pytest.mark.parametrize(("word", "code"), [("ASHCRAFT", "A261"), ("TYMCZAK", "T522"), ("PFISTER", "P236"), ("HONEYMAN", "H555"), ("LEE", "L000")])
def test_soundex(spark, word, code):
    assert one(spark, phonetic.soundex(F.lit(word))) == code


@pytest.mark.parametrize(("a", "b"), [("KNIGHT", "NIGHT"), ("PHILIP", "FILIP"), ("WRIGHT", "RIGHT"), ("SMITH", "SMYTH")])
def test_metaphone(spark, a, b):
    code = spark.createDataFrame([(a, b)], "a string, b string").select(phonetic.metaphone(F.col("a")).alias("a"), phonetic.metaphone(F.col("b")).alias("b"), phonetic.double_metaphone(F.col("a")).alias("d")).first()
    assert code["a"] == code["b"] and code["d"]["primary"] == code["a"]
    assert phonetic.metaphone_code("") is None and phonetic.metaphone_code("THOMAS")[0] == "0"


# Words with their published double Metaphone codes.
DOUBLE = {
    "testing": ("TSTN", "TSTN"), "The": ("0", "T"), "jumped": ("JMPT", "AMPT"), "Kuczewski": ("KSSK", "KXFS"), "McClelland": ("MKLL", "MKLL"), "san jose": ("SNHS", "SNHS"), "xenophobia": ("SNFP", "SNFP"),
    "richard": ("RXRT", "RKRT"), "Smith": ("SM0", "XMT"), "Schmidt": ("XMT", "SMT"), "Snider": ("SNTR", "XNTR"), "Schneider": ("XNTR", "SNTR"), "Cabrillo": ("KPRL", "KPR"), "Thumb": ("0M", "TM"),
    "Thomas": ("TMS", "TMS"), "Caesar": ("SSR", "SSR"), "Chianti": ("KNT", "KNT"), "Michael": ("MKL", "MXL"), "night": ("NT", "NT"), "Wagner": ("AKNR", "FKNR"), "Jose": ("HS", "HS"), "laugh": ("LF", "LF"),
    "Campbell": ("KMPL", "KMPL"), "raspberry": ("RSPR", "RSPR"), "Zhao": ("J", "J"), "Xavier": ("SF", "SFR"), "breaux": ("PR", "PR"), "Arnow": ("ARN", "ARNF"), "Filipowicz": ("FLPT", "FLPF"), "Accident": ("AKST", "AKST"),
    "bellocchio": ("PLX", "PLX"), "edge": ("AJ", "AJ"), "Edgar": ("ATKR", "ATKR"), "hugh": ("H", "H"), "island": ("ALNT", "ALNT"), "sugar": ("XKR", "SKR"), "resnais": ("RSN", "RSNS"), "rogier": ("RJ", "RJR"),
    "tichner": ("TXNR", "TKNR"), "ghiradelli": ("JRTL", "JRTL"), "Tagliaro": ("TKLR", "TLR"), "biaggi": ("PJ", "PK"), "Vorhees": ("FRS", "FRS"), "Jankelowicz": ("JNKL", "ANKL"),
}


def test_double_metaphone():
    assert {w: phonetic.double_metaphone_codes(w) for w in DOUBLE} == DOUBLE
    assert phonetic.double_metaphone_codes(None) == phonetic.double_metaphone_codes("%3") == (None, None)


def test_double_metaphone_ends():
    """Any word is read to its end, in codes of the usual letters."""
    rng = random.Random(1)
    for _ in range(20_000):
        main, other = phonetic.double_metaphone_codes("".join(rng.choice("ABCDEFGHIJKLMNOPQRSTUVWXYZ ") for _ in range(rng.randint(1, 9))), 99)
        assert main is None or set(main + other) <= set("A0FHJKLMNPRSTX")


def test_phonetic_rules(spark):
    std = spark.createDataFrame([(1, "Smith", "Jose", "19500507"), (2, "Smyth", "Jose", "19500507"), (3, "Schmidt", None, "19500507")], "rec_id long, last_name string, first_name string, birth_date string")
    rules = RuleSet.of("L^ F^ B", "L^^ F^^ B", "L~ F~ B")
    assert {r.kind for r in rules} == {"phonetic"}
    rows = tokens.tokens_wide(std, rules).orderBy("rec_id").collect()
    assert [tuple(r)[1:] for r in rows] == [("SM0JS19500507", "SM0HS19500507", "S530J20019500507")] * 2 + [(None, None, None)]


def test_rule_catalog():
    assert len(EVALUATED) == 20
    assert Part.parse("S4").transform == "last" and Part.parse("Y").n == 4
    with pytest.raises(ValueError):
        Part.parse("Q")
    by = {r.id: r for r in EVALUATED}
    assert by[1].refines(by[2]) and by[2].refines(by[3]) and by[15].refines(by[17]) and by[10].refines(by[16])
    assert not by[3].refines(by[2])
    assert EVALUATED.with_rule("L Z3").rules[-1].id == 21


def test_token_null_iff_part_null(ctx):
    wide = tokens.tokens_wide(ctx.clinic).join(ctx.clinic, "rec_id")
    for r in EVALUATED:
        missing = F.lit(False)
        for f in r.fields:
            missing = missing | F.col(f).isNull()
        assert wide.where(F.col(f"t{r.id}").isNull() != missing).count() == 0


def test_one_to_one_by_nested_loop(ctx):
    """All pairs compared in plain Python."""
    clinic = [r.asDict() for r in ctx.clinic.collect() if r["death_date"]]
    reg = [r.asDict() for r in ctx.register.collect()]
    for codes in ("S B", "L F3 B", "S4 B", "L M1 F", "B"):
        rules = RuleSet.of(codes)

        def key(row, rule=rules.rules[0]):
            out = ""
            for p in rule.parts:
                if row[p.field] is None:
                    return None
                v = row[p.field]
                out += v[: p.n] if p.transform == "prefix" else v[-p.n :] if p.transform == "last" else v
            return out

        mine, theirs = [(key(x), x["rec_id"]) for x in clinic], [(key(x), x["rec_id"]) for x in reg]
        expected = set()
        for k, i in mine:
            if k is not None and sum(k == m for m, _ in mine) == 1 and len(hits := [j for t, j in theirs if t == k]) == 1:
                expected.add((i, hits[0]))
        got = {(r["clinic_id"], r["reg_id"]) for r in linkage.subset_pairs(ctx.clinic, ctx.register, rules).collect()}
        assert got == expected, codes


def test_scorecard_invariants(ctx):
    rows = ctx.scores.collect()
    assert len(rows) == 20
    for r in rows:
        assert r["n_match"] + r["n_nonmatch"] == r["n_one_to_one"]
        assert (r["match_rate"] is None) == (r["n_one_to_one"] == 0)
    plain = evaluate.scorecard(linkage.subset_pairs(ctx.clinic, ctx.register, reduce=False)).collect()
    assert sorted(rows) == sorted(plain)
    shuffled = evaluate.scorecard(linkage.subset_pairs(ctx.clinic.repartition(7), ctx.register.repartition(5))).collect()
    assert sorted(rows) == sorted(shuffled)


def test_duplicate_register_record_breaks_links(ctx):
    pairs = ctx.pairs.collect()
    target = pairs[0]["reg_id"]
    twice = ctx.register.unionByName(ctx.register.where(F.col("rec_id") == target).withColumn("rec_id", F.col("rec_id") + 1_000_000))
    after = linkage.subset_pairs(ctx.clinic, twice).collect()
    assert {p["reg_id"] for p in pairs} - {p["reg_id"] for p in after} == {target}
    by_date = linkage.subset_pairs(ctx.clinic, twice, unique="date").collect()
    assert {(p["rule_id"], p["clinic_id"]) for p in by_date} >= {(p["rule_id"], p["clinic_id"]) for p in pairs}


def test_hashed_and_compact_keys_link_alike(ctx):
    mine = tokens.tokens_long(linkage.validation_subset(ctx.clinic), keep=("death_date",))
    theirs = tokens.tokens_long(ctx.register, keep=("death_date",))
    expected = {(r["rule_id"], r["clinic_id"], r["reg_id"]) for r in ctx.pairs.collect()}
    for how in (tokens.compact, lambda x: tokens.hash_tokens(x, "s")):
        got = linkage.one_to_one(linkage.token_db(how(mine)), linkage.token_db(how(theirs))).collect()
        assert {(r["rule_id"], r["clinic_id"], r["reg_id"]) for r in got} == expected


def test_profiles_agree(ctx):
    n = ctx.t.size("orders")
    full = {r["rule_id"]: r for r in profile.profile_tokens(linkage.file_db(ctx.register), n).collect()}
    mask = {r["rule_id"]: r["n_complete"] for r in profile.completeness_by_mask(ctx.register).collect()}
    approx = {r["rule_id"]: r for r in profile.profile_tokens_approx(ctx.register, rsd=0.02).collect()}
    for i, r in full.items():
        assert r["n_distinct"] <= r["n_complete"] <= n
        assert mask[i] == r["n_complete"] == approx[i]["n_complete"]
        assert abs(approx[i]["n_distinct"] - r["n_distinct"]) <= 0.06 * max(r["n_distinct"], 50)
    for a in EVALUATED:
        for b in EVALUATED.coarser_than(a):
            assert full[a.id]["n_complete"] <= full[b.id]["n_complete"]


def test_key_sample_keeps_whole_groups(ctx):
    db = linkage.file_db(ctx.register)
    sampled = linkage.token_db(tokens.key_sample(tokens.tokens_long(ctx.register, keep=("death_date",)), 4))
    assert sampled.exceptAll(db).count() == 0 and 0 < sampled.count() < db.count()


def test_every_pair_has_one_class(ctx):
    counts = {r["class"]: r["count"] for r in ctx.classes.groupBy("class").count().collect()}
    assert set(counts) <= {1, 2, 3, 4, 5} and sum(counts.values()) == ctx.candidates.count()


def test_em_separates(ctx):
    est = weights.estimate_mu(weights.patterns(ctx.candidates, ctx.clinic, ctx.register), len(weights.WEIGHTED))
    assert 0 < est["share"] < 1 and (est["m"] > est["u"]).sum() >= 3


def test_wilson(spark):
    low, high = evaluate.wilson(F.lit(920), F.lit(1081))
    assert abs(one(spark, low) * 100 - 82.86) < 0.01 and one(spark, high) < 0.88


def test_semi_reduction_falls_back(ctx, monkeypatch):
    long = tokens.tokens_long(ctx.register, RuleSet.of("S"))
    keys = tokens.tokens_long(linkage.validation_subset(ctx.clinic), RuleSet.of("S"))
    short = linkage.semi_reduce(long, keys).count()
    monkeypatch.setattr(written, "BROADCAST_BYTES", -1)
    assert linkage.semi_reduce(long, keys).count() == short


def test_heavy_keys_are_shared_out(spark, monkeypatch):
    """A key that most records carry is cut into shares, without losing or repeating a pair."""
    mine = spark.createDataFrame([(i, 1, "x" if i < 5 else f"k{i}") for i in range(20)], "clinic_id long, rule_id int, token string")
    theirs = spark.createDataFrame([(i, 1, "x" if i < 300 else f"k{i % 20}") for i in range(400)], "reg_id long, rule_id int, token string")
    pairs = lambda: sorted(map(tuple, linkage.shared_keys(mine, theirs, heavy=16).collect()))
    expected = sorted((a["clinic_id"], b["reg_id"]) for a in mine.collect() for b in theirs.collect() if a["token"] == b["token"])
    assert pairs() == expected
    monkeypatch.setattr(written, "BROADCAST_BYTES", -1)
    assert pairs() == expected


def test_fuzzy_links_by_all_pairs(spark):
    """Blocking by birth date and remnants of a name loses no pair, though most records share a default birth date."""
    rng = random.Random(4)
    name = lambda: "".join(rng.choice("ABC") for _ in range(rng.randint(1, 5)))
    people = lambda n: [(i, name() if rng.random() < 0.9 else None, name(), "19000101" if rng.random() < 0.7 else f"1950010{rng.randint(1, 3)}") for i in range(n)]
    a, b = people(40), people(80)
    shape = "rec_id long, first_name string, last_name string, birth_date string"

    def near(x, y, k):
        row = list(range(len(y) + 1))
        for i, c in enumerate(x, 1):
            new = [i]
            for j, d in enumerate(y, 1):
                new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (c != d)))
            row = new
        return row[-1] <= k

    for k in (1, 2):
        got = {(r["clinic_id"], r["reg_id"]): r["how"] for r in linkage.link_fuzzy(spark.createDataFrame(a, shape), spark.createDataFrame(b, shape), k).collect()}
        expected = {}
        for i, f, s, d in a:
            for j, g, t, e in b:
                if d == e and f and g:
                    if near(f, g, k) and near(s, t, k):
                        expected[i, j] = "straight"
                    elif near(f, t, k) and near(s, g, k):
                        expected[i, j] = "crossed"
        assert got == expected


def test_class_three_counts_eleven_items(spark):
    """A number is unknown: any eight of the eleven items make class 3, and seven do not."""
    fields = dict(first_name="ANN", middle_name="B", last_name="LEE", father_surname="ROE", birth_date="19500507", gender="F", race=1, marital=2, birth_state=3)
    other = dict(first_name="EVE", middle_name="C", last_name="KAY", father_surname="POE", birth_date="19510608", gender="M", race=4, marital=3, birth_state=9)
    shape = "ssn string, first_name string, middle_name string, last_name string, birth_date string, gender string, birth_state int, race int, marital int, father_surname string"
    record = lambda x: tuple(None if f == "ssn" else x[f] for f in weights.CLASS_FIELDS)
    # items of a record: each field is one, and the birth date three; another sex than F takes the father's surname with it
    parts = [("first_name", 1), ("middle_name", 1), ("last_name", 1), ("father_surname", 1), ("birth_date", 3), ("race", 1), ("marital", 1), ("birth_state", 1)]
    rows, expected = [], []
    for mask in range(1 << len(parts)):
        changed = {f: other[f] if mask >> i & 1 else fields[f] for i, (f, _) in enumerate(parts)} | {"gender": "F"}
        rows.append((mask, record(fields), record(changed)))
        expected.append((mask, 3 if 11 - sum(n for i, (_, n) in enumerate(parts) if mask >> i & 1) >= 8 else 4))
    blank = fields | {"middle_name": None, "race": 0, "marital": 9, "birth_state": 9}
    rows.append((999, record(fields | {"middle_name": None}), record(blank)))  # two blank initials are no agreement
    expected.append((999, 4))
    order = {f: k for k, f in enumerate(weights.CLASS_FIELDS)}
    assert [x.split(" ")[0] for x in shape.split(", ")] == list(order)
    frame = spark.createDataFrame(rows, f"i int, a struct<{shape.replace(" ", ":").replace(",:", ",")}>, b struct<{shape.replace(' ', ':').replace(',:', ',')}>")
    assert sorted(map(tuple, frame.select("i", weights.agreement_class()).collect())) == expected


def test_plans(ctx):
    plan = linkage.file_db(ctx.register.sparkSession.read.parquet(f"{ctx.t.path}/orders.parquet").select(F.col("o_orderkey").alias("rec_id"), *[F.lit("A").alias(f) for f in ("ssn", "last_name", "middle_name", "first_name", "birth_date")], F.col("o_orderdate").cast("date").alias("death_date")))
    text = plan._jdf.queryExecution().executedPlan().toString()
    assert text.count("Exchange hashpartitioning") == 1 and "Python" not in text and "NestedLoop" not in text


def test_sql_functions(spark):
    register_sql(spark)
    row = spark.sql("SELECT std_name('Zoë', 15) n, std_date('1950/05/07') d, std_ssn('123-35-4789') s, std_ssn('000-12-3456') bad").first()
    assert tuple(row) == ("ZOE", "19500507", "123354789", None)
    got = spark.sql("SELECT * FROM token_rows(map('ssn', '123354789', 'last_name', 'LEE'), 'S4 L, L B')").collect()
    assert [tuple(r) for r in got] == [("S4 L", "4789LEE")]


def reads(df, table):
    """Whether the plan scans the table."""
    return any(f"/{table}.parquet" in f for f in df.inputFiles())


def test_categories_as_published(spark, data):
    """The published counts, one-to-one and agreeing, of the twenty rules give the published categories; the query reads customers."""
    one = (1074, 3232, 4084, 3296, 1103, 4445, 1081, 7611, 1170, 1572, 3847, 2325, 4240, 5198, 1260, 2592, 4821, 521, 427, 79)
    agree = (914, 2647, 3292, 2696, 938, 3398, 920, 2636, 986, 934, 2972, 767, 3206, 3249, 1039, 760, 3098, 66, 56, 4)
    rates = spark.createDataFrame([(i, k / n) for i, (n, k) in enumerate(zip(one, agree, strict=True), 1)], "rule_id int, match_rate double")
    got = [(r["rule_id"], r["category"]) for r in present.rule_priority(rates).orderBy("priority").collect()]
    assert got == [(i, 1) for i in (7, 1, 5, 9, 15, 2, 4, 3)] + [(i, 2) for i in (11, 6, 13, 17, 14, 10)] + [(i, 3) for i in (8, 12, 16, 19, 18, 20)]
    assert reads(Q.QUERIES["q_paper_categories"](spark, data), "customer")


def test_phonetic_words(spark, data):
    """Published codes of ten words; the query codes the words of part names."""
    published = {
        "science": ("SNS", "SNS", "SNS"), "quick": ("KK", "KK", "KK"), "brown": ("BRN", "PRN", "PRN"), "fox": ("FKS", "FKS", "FKS"), "jumped": ("JMPT", "JMPT", "AMPT"),
        "over": ("OFR", "AFR", "AFR"), "lazy": ("LS", "LS", "LS"), "dogs": ("TKS", "TKS", "TKS"), "the": ("0", "0", "T"), "wright": ("RT", "RT", "RT"),
    }
    words = spark.createDataFrame([(w,) for w in published], "word string")
    got = words.select("word", phonetic.metaphone(F.col("word")).alias("m"), phonetic.double_metaphone(F.col("word")).alias("d")).collect()
    assert {r["word"]: (r["m"], r["d"]["primary"], r["d"]["alternate"]) for r in got} == published
    assert reads(Q.QUERIES["q_phonetic_words"](spark, data), "part")


def test_rule_kinds_count_records(spark, data):
    """Kinds come with the clinic's keys of each rule, which agree with the keys themselves."""
    df = Q.QUERIES["q_rule_kinds"](spark, data)
    assert reads(df, "customer")
    n = {r["rule"]: r["n_complete"] for r in df.collect()}
    keys = Q.QUERIES["q_tokens_long"](spark, data).groupBy("rule_id").count().collect()
    assert {k: v for k, v in n.items() if k.startswith("evaluated.") and v} == {f"evaluated.{r['rule_id']}": r["count"] for r in keys}


def test_profile_of_month_first_dates(spark, data):
    """Five known records by hand; the query profiles the clinic's."""
    five = (("JOHN", "1950-05-07"), ("JOHN", "1950-05-07"), ("MARY", "2008-12-25"), ("PETER", None), ("%^3", "1999-01-31"))
    raw = spark.createDataFrame([(*x, None, None, None, None) for x in five], "first_name_raw string, birth_raw string, ssn_raw string, last_name_raw string, middle_name_raw string, dod date")
    assert {tuple(r) for r in Q._month_first(raw).collect()} == {("birth_date", 4, 3, 0), ("first_name", 5, 4, 1)}
    assert reads(Q.QUERIES["q_table2_example"](spark, data), "customer")
