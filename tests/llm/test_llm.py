from __future__ import annotations

import collections
import hashlib
import math
import random
import re
import time
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from tokenlink.llm import decontamination, html, licenses, linededup, neardup, packing, pii, quality, rules, scratch, sharding
from tokenlink.llm.scratch import table

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, shard string, bucket string, n_words string, score string, comp string"
#: Nulls in any column, empty and long texts, ties, repeated rows, further columns whose names clash.
ODD = [
    (1, None, None, None, None, "x", "y", "z", "s", "c"),
    (2, "", "en", "a", 0, None, None, None, None, None),
    (None, "no id here at all", "en", "a", 3, "x", "y", "z", "s", "c"),
    (4, "same text twice", "en", None, 3, "x", "y", "z", "s", "c"),
    (4, "same text twice", "en", None, 3, "x", "y", "z", "s", "c"),
    (5, "word " * 60_000, "en", "a", 3, "x", "y", "z", "s", "c"),
    (6, " \t\n\x0b\x0c\r ", "xx", "a", 3, "x", "y", "z", "s", "c"),
    (7, "9" * 30_000 + " " + "a." * 20_000 + "@", "en", "a", 3, "x", "y", "z", "s", "c"),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA)


@pytest.fixture(scope="module")
def docs(spark, data):
    return table(spark, data, "documents").cache()


@pytest.fixture(scope="module")
def labels(spark, data):
    return table(spark, data, "labels").cache()


def apply_all(spark, frame, labels):
    """Every operator over a table; what each returns."""
    items = spark.createDataFrame([(1, "a b c d e"), (2, None), (3, "")], "item_id long, text string")
    pages = frame.select(F.col("doc_id").alias("page_id"), F.col("source").alias("url"), F.col("text").alias("html"))
    return {
        "shards": sharding.assign_shards(frame),
        "pii": pii.digest(frame),
        "redact": pii.redact(frame),
        "html": html.main_text(pages),
        "dup": neardup.near_duplicates(frame, 2),
        "rules": rules.judge(frame, labels),
        "pack": packing.pack(frame),
        "score": quality.classify(frame, labels),
        "licenses": licenses.digest(frame),
        "lines": linededup.drop_boilerplate(frame),
        "bench": decontamination.contaminated(frame, items),
        "clean": decontamination.clean(frame, items),
        "one": neardup.keep_one(frame),
    }


def test_odd_rows(spark, odd, labels):
    """Each odd row has the result that the docstrings define."""
    rows = {k: v.collect() for k, v in apply_all(spark, odd, labels).items()}
    assert rows.pop("bench") == []
    packed = rows.pop("pack")
    assert {len(v) for v in rows.values()} == {len(ODD)}
    by = lambda name, key="doc_id": collections.defaultdict(list, {i: [r for r in rows[name] if r[key] == i] for i in {x[0] for x in ODD}})
    assert sorted((str(r["doc_id"]), r["size"], r["text_crc32"]) for r in rows["shards"]) == sorted((str(x[0]), len((x[1] or "").encode()) + 1, zlib.crc32((x[1] or "").encode())) for x in ODD)
    assert sorted(r["slot"] * 16 + r["shard"] for r in rows["shards"]) == list(range(len(ODD)))
    nothing = hashlib.sha256(b"").hexdigest()
    assert all(r["base_sha256"] == nothing and r["spans"] == "" for r in rows["pii"])
    assert {r["doc_id"]: r["text"] for r in rows["redact"]} == {x[0]: x[1] for x in ODD}
    assert by("html", "page_id")[1][0]["text"] == by("html", "page_id")[6][0]["text"] == ""
    assert [r["text"] for r in by("html", "page_id")[4]] == ["same text twice"] * 2 and len(by("html", "page_id")[5][0]["text"]) == 299_999
    assert {(r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in rows["dup"]} == {(1, 0, 1, True), (2, 0, 2, True), (None, 4, None, True), (4, 2, 4, True), (5, 1, 5, True), (6, 0, 6, True), (7, 1, 7, True)}
    assert {(r["doc_id"], r["n_words"], r["base_failed"], r["kept"]) for r in rows["rules"]} == {(1, 0, True, False), (2, 0, True, False), (None, 5, True, False), (4, 3, True, False), (5, 60_000, True, False), (6, 0, True, False), (7, 2, True, False)}
    assert by("rules")[5][0]["n_repeat_words"] == 60_000
    assert len({r["score"] for r in by("score")[1] + by("score")[2]}) == 1 and all(0 <= r["score"] <= 1 for r in rows["score"])
    assert {(r["doc_id"], r["n_words"], r["labels"], r["score"]) for r in rows["licenses"]} == {(1, 0, "", 0), (2, 0, "", 0), (None, 5, "", 0), (4, 3, "", 0), (5, 60_000, "", 0), (6, 0, "", 0), (7, 20_001, "", 0)}
    assert {(r["doc_id"], r["text"], r["n_dropped"]) for r in rows["lines"]} == {(x[0], x[1], 0) for x in ODD}
    for name in ("clean", "one", "redact"):
        assert sorted(map(str, map(tuple, rows[name]))) == sorted(map(str, ODD)), name
    assert [(r["piece"], r["start"], r["length"]) for r in packed if r["doc_id"] in (1, 2)] == [(0, 0, 1)] * 2
    assert sum(r["length"] for r in packed if r["doc_id"] == 5) == 60_001 and sum(r["doc_id"] == 4 for r in packed) == 2


def test_empty_table(spark, odd, labels):
    for name, df in apply_all(spark, odd.where("false"), labels.where("false")).items():
        assert df.count() == 0, name


def test_sharding(docs):
    rows = sharding.assign_shards(docs, bucket_rows=16).collect()
    assert sorted(r["doc_id"] for r in rows) == sorted(r["doc_id"] for r in docs.collect())
    by = collections.defaultdict(list)
    for r in rows:
        by[r["shard"]].append(r["slot"])
    assert set(by) == set(range(16)) and all(sorted(v) == list(range(len(v))) for v in by.values())
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1
    text = {r["doc_id"]: (r["text"] or "").encode() for r in docs.collect()}
    assert all(r["text_crc32"] == zlib.crc32(text[r["doc_id"]]) and r["size"] == len(text[r["doc_id"]]) + 1 for r in rows)
    again = sharding.assign_shards(docs, bucket_rows=16).collect()
    assert sorted(map(tuple, rows), key=str) == sorted(map(tuple, again), key=str)
    other = sharding.assign_shards(docs, bucket_rows=16, seed=3).collect()
    assert {(r["doc_id"], r["shard"]) for r in rows} != {(r["doc_id"], r["shard"]) for r in other}


def test_shards_depend_on_rows_and_seed_alone(spark, docs):
    """Other partitions, another order and another plan give the same permutation."""
    rows = docs.union(docs.limit(0)).repartition(1).collect()
    expected = sorted(map(tuple, sharding.assign_shards(docs, bucket_rows=16).collect()), key=str)
    for parts, adaptive in ((7, "false"), (3, "true")):
        spark.conf.set("spark.sql.shuffle.partitions", parts)
        spark.conf.set("spark.sql.adaptive.enabled", adaptive)
        try:
            turned = spark.createDataFrame(rows[::-1], docs.schema).repartition(parts)
            assert sorted(map(tuple, sharding.assign_shards(turned, bucket_rows=16).collect()), key=str) == expected
        finally:
            spark.conf.set("spark.sql.shuffle.partitions", 4)
            spark.conf.set("spark.sql.adaptive.enabled", "true")


def test_shards_by_hand(spark, docs):
    """A textbook shuffle of every bucket, from the hashes that pass one wrote, gives the places."""
    rows = docs.select(F.struct(F.col("doc_id").alias("id"), (F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + 1).alias("size"), F.crc32(F.coalesce("text", F.lit("")).cast("binary")).alias("crc")).alias("row"))
    buckets = collections.defaultdict(list)
    for r in sharding.scattered(rows, docs.count(), 16, 17).collect():
        buckets[r["bucket"]].append((r["lot"], r["copy"], r["row"]["id"]))
    places, at = {}, 0
    for b in sorted(buckets):
        own = [x[-1] for x in sorted(buckets[b])]
        for chunk in range(0, len(own), 32):
            part = own[chunk : chunk + 32]
            ks = spark.range(len(part)).select(F.pmod(F.xxhash64(F.lit(19), F.lit(b).cast("long"), F.lit(chunk // 32).cast("long"), F.col("id").cast("int")), F.col("id") + 1)).collect()
            for i, (j,) in enumerate(ks):
                part[i], part[j] = part[j], part[i]
            for x in part:
                places[x] = at
                at += 1
    got = {r["doc_id"]: r["slot"] * 16 + r["shard"] for r in sharding.assign_shards(docs, bucket_rows=16).collect()}
    assert got == places


def test_shards_of_equal_rows(spark, monkeypatch):
    """A row that makes up most of the table is dealt copy by copy."""
    monkeypatch.setattr(sharding, "_COPIES", 8)
    frame = spark.createDataFrame([(7, "same")] * 300 + [(None, None)] * 40 + [(i, f"t{i}") for i in range(60)], "doc_id long, text string")
    rows = sharding.assign_shards(frame, 4, bucket_rows=16).collect()
    by = collections.defaultdict(list)
    for r in rows:
        by[r["shard"]].append(r["slot"])
    assert len(rows) == 400 and all(sorted(v) == list(range(100)) for v in by.values())
    assert min(collections.Counter(r["shard"] for r in rows if r["doc_id"] == 7).values()) > 40
    assert sharding.scattered(frame.select(F.struct("doc_id", "text").alias("row")), 400, 16, 1).groupBy("bucket").count().agg(F.max("count")).first()[0] < 40


def test_shards_written(spark, docs, tmp_path):
    sharding.write_shards(docs, str(tmp_path / "out"), n_shards=4, bucket_bytes=1 << 16)
    back = spark.read.parquet(str(tmp_path / "out"))
    assert back.select(docs.columns).exceptAll(docs).count() == 0 and back.count() == docs.count()


PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def base_spans(text):
    out = []
    for rank, (kind, pattern) in enumerate(PATTERNS.items()):
        for m in re.finditer(pattern, text):
            d = re.sub("[^0-9]", "", m[0])
            luhn = sum(int(c) if i % 2 == 0 else int(c) * 2 - 9 * (int(c) > 4) for i, c in enumerate(reversed(d))) % 10 == 0
            if {"email": True, "ip": kind != "ip" or max(map(int, m[0].split("."))) <= 255, "card": 12 <= len(d) <= 19 and luhn, "phone": 9 <= len(d) <= 15}[kind]:
                out.append((m.start(), rank, m.end(), kind))
    return sorted(out)


def test_pii_base(spark, docs):
    rng = random.Random(2)
    alphabet = "ab@.@.-+ 0123456789  ()-.é\n_%"
    made = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 80))) for _ in range(400)]
    made += ["a@b.c+d@e.f", "1.2.3.4.5.6.7.8", "0000255.1.1.1", "256.1.1.1", "4111 1111 1111 1111", "x4111-1111-1111-1111 2", "+1 (487) 555-7209", "+49 1", "a@b@c.d"]
    texts = dict(enumerate([r["text"] or "" for r in docs.collect()] + made))
    frame = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    for r in pii.digest(frame).collect():
        spans = base_spans(texts[r["doc_id"]])
        listed = ",".join(f"{k}:{a}:{b}" for a, _, b, k in spans)
        assert r["base_sha256"] == hashlib.sha256(listed.encode()).hexdigest(), texts[r["doc_id"]]
        assert [r[f"n_{k}"] for k in PATTERNS] == [sum(s[3] == k for s in spans) for k in PATTERNS]
        assert set(listed.split(",")) - {""} <= set(r["spans"].split(","))


def test_pii_spelled_prefilter(spark):
    """Every match of the generator passes its prefilter."""
    pattern = next(p for name, _, p in pii.GENERATORS if name == "spelled_email")
    texts = ["john.doe@example dot com", "john@example[dot]com", "john@example (dot) org", "john at  example.com", "JOHN AT EXAMPLE DOT COM", "john(at)example.com", "john @ example.com", "jo.doe@corp[dot]com", "jo.doe (AT) corp <dot> com"]
    rng = random.Random(9)
    texts += ["".join(rng.choice(("jo", " ", "at", "@", "(", ")", "ex", ".", "dot", "com")) for _ in range(12)) for _ in range(3000)]
    frame = spark.createDataFrame([(t,) for t in texts], "text string").where(F.col("text").rlike(pattern))
    assert frame.count() > 50
    assert [r["text"] for r in frame.where(~F.col("text").rlike(pii.SPELLED)).collect()] == []


def test_pii_added_and_redaction(spark):
    text = "mail joe (at) foo dot com, call (555) 123-4567, ssn 123-45-6789. On 2024-05-01 order 12345-67."
    row = spark.createDataFrame([(1, text)], "doc_id long, text string")
    kinds = [x.split(":")[0] for x in pii.digest(row).first()["spans"].split(",")]
    assert kinds == ["email", "phone", "ssn"]
    assert pii.redact(row).first()["text"] == "mail [email], call [phone], ssn [ssn]. On 2024-05-01 order 12345-67."
    models, cuts = pii.fitted(spark)
    rows = pii._examples(60, 99)  # other rows than those fitted on
    frame = spark.createDataFrame([(i, r["match"], r["left"], r["right"]) for i, r in enumerate(rows)], "i int, match string, left string, right string")
    f = {r["i"]: r["f"] for r in frame.select("i", pii._features(F.struct("match", "left", "right")).alias("f")).collect()}
    right = [(models[r["name"]].probability(np.array([f[i]]))[0] >= cuts[r["name"]], r["y"]) for i, r in enumerate(rows)]
    kept = [y for k, y in right if k]
    assert np.mean(kept) >= 0.95 and sum(kept) >= 0.7 * sum(y for _, y in right)


def test_pii_sweeps(spark):
    """Positions, overlaps with base spans and the choice among candidates, against all pairs."""
    rng = random.Random(3)
    kinds = "array<struct<start:int,rank:int,end:int,kind:string,score:double>>"
    rows = []
    for i in range(60):
        n = rng.choice((0, 1, 5, 300))
        span = lambda: (s := rng.randrange(40 + 12 * n), rng.randrange(6), s + rng.randint(7, 60), "k", rng.random())
        base = sorted((*span()[:3], "k", 1.0) for _ in range(n // 3))
        rows.append((i, base, sorted({span() for _ in range(n)}), [rng.randint(0, 9) for _ in range(n)]))
    frame = spark.createDataFrame(rows, f"i int, base {kinds}, wide {kinds}, sizes array<int>")
    got = frame.select("i", pii._apart(F.col("wide"), F.col("base")).alias("apart"), pii._best(F.col("wide")).alias("best"), pii._running(F.col("sizes"), lambda a, b: a + b).alias("sums")).collect()
    over = lambda a, b: a[0] < b[2] and b[0] < a[2]
    for (_, base, wide, sizes), r in zip(rows, sorted(got), strict=True):
        assert list(map(tuple, r["apart"])) == [x for x in wide if not any(over(x, b) for b in base)]
        assert list(map(tuple, r["best"])) == [x for x in wide if not any(over(x, o) and (o[4], *(-v for v in o[:3])) > (x[4], *(-v for v in x[:3])) for o in wide if o != x)]
        assert r["sums"] == np.cumsum(sizes, dtype=int).tolist()


def test_pii_columns_and_regions(spark):
    """Input columns pass unchanged; overlapping spans are masked whole; nulls stay null."""
    row = spark.createDataFrame([(1, "x +30 0000 0000 0004 y 1.2.3.4", "base", "added"), (2, None, None, "z")], "doc_id long, text string, base string, added string")
    got = {r["doc_id"]: r for r in pii.redact(row).collect()}
    assert got[1]["base"] == "base" and got[1]["added"] == "added" and got[2]["text"] is None
    assert pii.digest(row).where("doc_id = 1").first()["spans"] == "phone:2:20,card:3:20,ip:23:30"
    assert got[1]["text"] == "x [phone] y [ip]"


def test_pii_planted_secrets(spark):
    """Recall of added spans on the tokens planted in the given documents; documents without data get none."""
    docs = table(spark, "/root/testdata/sf0.1", "documents")
    rows = docs.join(pii.digest(docs).select("doc_id", "spans"), "doc_id").collect()
    planted = caught = 0
    for r in rows:
        secrets = {tuple(map(int, x.split(":")[1:])) for x in r["spans"].split(",") if x.startswith("secret")}
        tokens = {m.span(1) for m in re.finditer(r'token = "([0-9a-f]{40})"', r["text"] or "")}
        planted, caught = planted + len(tokens), caught + len(tokens & secrets)
        if not re.search("[0-9@]", r["text"] or ""):
            assert r["spans"] == ""
    assert planted > 100 and caught >= 0.98 * planted


def test_rules_features_and_guarantee(docs, labels):
    texts = {r["doc_id"]: r["text"] or "" for r in docs.collect()}
    for r in rules.judge(docs, labels).collect():
        t = texts[r["doc_id"]]
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        grams = list(zip(w, w[1:], w[2:], strict=False))
        n = collections.Counter(grams)
        cover = {i + k for i, g in enumerate(grams) if n[g] > 1 for k in range(3)}
        lines = [x for x in t.split("\n") if x.strip(" \t\x0b\x0c\r")]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(cover))
        assert r["base_failed"] == (len(w) < 50 or 100 * len(cover) > 50 * len(w))
        assert not (r["base_failed"] and r["kept"])


def test_binomial_bound():
    assert abs(rules.binomial_upper(0, 100, 0.05) - (1 - 0.05 ** (1 / 100))) < 1e-9
    assert abs(rules.binomial_upper(5, 100, 0.05) - 0.1022537) < 1e-4
    assert rules.binomial_upper(3, 3, 0.05) == rules.binomial_upper(0, 0, 0.05) == 1.0
    for n in (1, 7, 60, 500):
        for k in range(0, n, max(1, n // 9)):
            for p in (0.01, 0.05, 0.3, 0.9):
                assert abs(rules.binomial_cdf(k, n, p) - sum(math.comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(k + 1))) < 1e-9
    assert 0.05 < rules.binomial_upper(50_000, 1_000_000, 0.05) < 0.0505


def sampled(rng, n, chances):
    """Counts of n rows: one in two is bad; ``chances`` gives for each rule how often a good and a bad row is rejected, and at which step."""
    out = {}
    for _ in range(n):
        good = rng.random() < 0.5
        first = tuple(rng.randrange(len(r[4])) if rng.random() < c[not good] else len(r[4]) for r, c in zip(rules.RULES, chances, strict=True))
        g, b = out.get(first, (0, 0))
        out[first] = (g + good, b + (not good))
    return out


def test_guarantee_of_the_whole_verdict():
    """Over many draws, a verdict that truly rejects more than the risk is accepted no more often than the level."""
    rng = random.Random(11)
    chances = [(0.03, 0.3), (0.02, 0.2), (0.03, 0.1), (0.04, 0.2), (0.02, 0.2), (0.03, 0.3)]
    broken = accepted = 0
    for _ in range(150):
        steps = rules.certified(sampled(rng, 500, chances), sampled(rng, 500, chances), 0.05, 0.1)
        if steps:
            accepted += 1
            stays = math.prod(1 - c[0] * s / len(r[4]) for c, s, r in zip(chances, steps, rules.RULES, strict=True))
            broken += 1 - stays > 0.05
    assert accepted > 75 and broken <= 0.1 * 150 + 8


def test_path_of_verdicts():
    """Each verdict is stricter than the last, and the first takes the step with the most bad rows a good one."""
    rng = random.Random(12)
    counts = sampled(rng, 400, [(0.02, 0.3)] * len(rules.RULES))
    steps = rules.path(counts, 0.5)
    assert all(all(x <= y for x, y in zip(a, b, strict=True)) and a != b for a, b in zip(steps, steps[1:], strict=False))
    options = [(r, k) for r, x in enumerate(rules.RULES) for k in range(1, len(x[4]) + 1)]
    lost = lambda r, k, own: sum(n[own] for f, n in counts.items() if f[r] < k)
    best = max(lost(r, k, 1) / (lost(r, k, 0) + 1) for r, k in options)
    (r, k), = [(r, k) for r, k in enumerate(steps[0]) if k]
    assert lost(r, k, 1) / (lost(r, k, 0) + 1) == best


def test_verdict_on_given_labels(spark):
    """On the given documents some bad text beyond the base rules goes, and good text stays within the risk."""
    docs, labels = (table(spark, "/root/testdata/sf0.1", t) for t in ("documents", "labels"))
    rows = rules.judge(docs, labels).join(labels, "doc_id").where("not base_failed").select("kept", "quality").collect()
    good, bad = ([r["kept"] for r in rows if r["quality"] == q] for q in (1, 0))
    assert np.mean(good) >= 0.95 and np.mean(bad) < 0.9


def jaccard(a, b):
    return len(a & b) / max(1, len(a | b))


def shingles(text, k):
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])


def components_of(texts, k):
    sets = {i: shingles(t, k) for i, t in texts.items()}
    up = {i: i for i in sets}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    ids = sorted(sets)
    for x, i in enumerate(ids):
        for j in ids[x + 1 :]:
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = root(i), root(j)
                up[max(a, b)] = min(a, b)
    return {i: root(i) for i in ids}, {i: len(s) for i, s in sets.items()}


@pytest.mark.parametrize("k", [2, 5])
def test_near_duplicates(spark, docs, k):
    rng = random.Random(k)
    words = [f"w{i}" for i in range(400)]
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for family in range(4):  # families of edited copies, many of them around the threshold
        base = [rng.choice(words) for _ in range(150)]
        for _ in range(40):
            copy = base[:]
            for _ in range(rng.randint(0, 14)):
                copy[rng.randrange(150)] = rng.choice(words)
            texts[10_000 + len(texts)] = " ".join(copy)
    expected, sizes = components_of(texts, k)
    frame = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = neardup.near_duplicates(frame, k).collect()
    assert {r["doc_id"]: r["component_id"] for r in got} == expected
    assert all(r["n_shingles"] == sizes[r["doc_id"]] and r["kept"] == (r["doc_id"] == expected[r["doc_id"]]) for r in got)


def test_near_duplicate_blocks(spark, monkeypatch):
    """The same result when buckets and clusters are cut into many blocks."""
    rng = random.Random(7)
    base = [f"w{rng.randrange(300)}" for _ in range(120)]
    texts = {i: " ".join(w if rng.random() > rng.choice((0.02, 0.06, 0.1)) else f"x{rng.randrange(300)}" for w in base) for i in range(120)}
    monkeypatch.setattr(neardup, "_BLOCK", 16)
    monkeypatch.setattr(neardup, "_BLOCK_SHINGLES", 700)
    expected = components_of(texts, 2)[0]
    for limit in (neardup._REFINED, 10):
        monkeypatch.setattr(neardup, "_REFINED", limit)
        got = neardup.near_duplicates(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), 2).collect()
        assert {r["doc_id"]: r["component_id"] for r in got} == expected


def test_near_duplicates_of_shared_ids(spark):
    """Rows that share an id are one document; unrelated groups stay apart, and repeated rows do not count."""
    a, b, c, d = (prose(x, 40) for x in "abcd")
    rows = [(5, a), (5, b), (3, b + " end"), (9, a + " end"), (5, a), (7, c), (8, c), (8, d), (8, d), (6, None), (6, ""), (None, a), (1, d + " end"), (2, prose("e", 40))]
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), 2).collect()
    assert len(got) == len(rows)
    assert {(r["doc_id"], r["component_id"]) for r in got} == {(5, 3), (3, 3), (9, 3), (7, 1), (8, 1), (1, 1), (6, 6), (2, 2), (None, None)}
    assert all(r["kept"] == (r["doc_id"] is None or r["doc_id"] == r["component_id"]) for r in got)


def test_odd_sketch_estimates():
    rng, draws = np.random.default_rng(1), neardup._draws()
    for j in (0.7, 0.8, 0.9, 0.97):
        errors = []
        for _ in range(30):
            n = 600
            common = int(2 * n * j / (1 + j))
            pool = rng.integers(0, 2**64, 2 * n - common, dtype=np.uint64)
            a, b = np.sort(pool[:n]), np.sort(np.concatenate([pool[:common], pool[n:]]))
            x, y = (neardup.signature(s, draws)[1].view(np.uint64) for s in (a, b))
            errors.append(float(neardup.estimate(np.bitwise_count(x ^ y).sum())) - common / (2 * n - common))
        assert abs(np.mean(errors)) < 0.03 and np.max(np.abs(errors)) < neardup.SLACK


def test_packing_round_trip(spark, docs):
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(packing.vocabulary_path())
    texts = {r["doc_id"]: r["text"] or "" for r in docs.collect()} | {90_001: "ÀÉ µª don't it's ﬁne <|endoftext|>. x_y 123abc É. ²³ \x1c ΑΣ.", 90_002: ""}
    frame = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    packed = packing.pack(frame, capacity=512)
    rows = packed.collect()
    ids = {i: [*tokenizer.encode(t, add_special_tokens=False).ids, 1] for i, t in texts.items()}
    places = collections.defaultdict(list)
    for r in rows:
        own = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(own) == r["length"] and zlib.crc32(np.array(own, "<u4").tobytes()) == r["ids_crc32"]
        assert r["start"] == 512 * r["piece"]
        places[r["sequence_id"]].append((r["offset"], r["length"]))
    assert {i: sum(r["length"] for r in rows if r["doc_id"] == i) for i in ids} == {i: len(x) for i, x in ids.items()}
    for p in places.values():
        at = 0
        for offset, n in sorted(p):
            assert offset == at
            at += n
        assert at <= 512
    assert len(places) <= 1.02 * -(-sum(map(len, ids.values())) // 512) + 2
    whole = {r["sequence_id"]: r["ids"] for r in packing.sequences(frame, packed, capacity=512).collect()}
    assert sum(map(len, whole.values())) == sum(map(len, ids.values()))


def test_word_ids_are_the_tokenizers():
    """Looking words up gives the tokenizer's ids, whatever the text."""
    from tokenizers import Tokenizer

    tokenizer, words, rng = Tokenizer.from_file(packing.vocabulary_path()), packing.Words(packing.vocabulary_path()), random.Random(12)
    pools = ["abcXYZ", "İIıiÉéßẞΣσςŉǰΐﬁﬀ", "\u0307\u0301\u0300\u0345\u200d\u200c\xad", "0123456789²³½٣", "'.,;:!?%*$#&|<>()-_=+/\\\"`~@[]{}^", " \n\t\r\x0b\x0c\x1c\x85\xa0\u2003\u3000\u2028", "中文日本かな한국", "😀👍🏽🇩🇪", "ªµºʰˀ", "<|endoftext|>", "ΑΒΓДЖЙйё", "אبہक\u093f힣\uffff\ufffd"]
    letters = "".join(pools)

    def text():
        kind, n = rng.random(), rng.randint(0, 14)
        if kind < 0.3:
            return "".join(rng.choice(rng.choice(pools)) for _ in range(n))
        if kind < 0.5:
            return "".join(rng.choice(letters) for _ in range(n))
        if kind < 0.7:
            return "".join(chr(rng.choice((rng.randrange(32, 0x250), rng.randrange(0x250, 0x2000), rng.randrange(32, 127), rng.randrange(0x2000, 0xD7FF)))) for _ in range(n))
        return " ".join("".join(rng.choice("abcdefİéÀ'") for _ in range(rng.randint(1, 6))) + rng.choice(("", ".", ",", "!?", "%*")) for _ in range(4))

    for t in ["İ!", "xİ.", "İ\u0307!", *(text() for _ in range(100_000))]:
        assert packing.token_bytes(t, words) == np.array(tokenizer.encode(t, add_special_tokens=False).ids, "<u4").tobytes(), ascii(t)


def test_sum_of_squares_choice():
    """Each choice leaves the least sum of squared counts, by trying all of them."""
    rng = np.random.default_rng(3)
    lengths = rng.integers(1, 31, 120)
    bins, offsets = packing.sum_of_squares(lengths, 30)
    fill: dict[int, int] = {}
    total = lambda f: sum(n * n for g, n in collections.Counter(30 - x for x in f.values()).items() if g)
    for x, b, o in zip(lengths.tolist(), bins.tolist(), offsets.tolist(), strict=True):
        options = [total(fill | {k: fill[k] + x}) for k in fill if fill[k] + x <= 30] + [total(fill | {"new": x})]
        assert fill.get(b, 0) == o
        fill[b] = o + x
        assert fill[b] <= 30 and total(fill) == min(options)


def test_quality_held_out(spark):
    docs, labels = (table(spark, "/root/testdata/sf0.01", t) for t in ("documents", "labels"))
    rows = quality.classify(docs, labels).join(labels, "doc_id").where(quality.fold() == quality.HELD_OUT).collect()
    good, bad = [r["score"] for r in rows if r["quality"]], [r["score"] for r in rows if not r["quality"]]
    assert np.mean([g > b for g in good for b in bad]) > 0.95
    assert np.mean([r["predicted"] == r["quality"] for r in rows]) > 0.9


def test_quality_scores_by_hand(docs, labels):
    """Features counted in Python and table entries summed one by one give the scores."""
    model = quality.train(docs, labels)
    scores = {r["doc_id"]: r["score"] for r in quality.scored(docs, model).collect()}
    ratio = lambda a, b: a / max(b, 1)
    for r in docs.collect():
        t = r["text"] or ""
        w, lines = re.findall(r"[^\x20\x09-\x0D]+", t), t.split("\n")
        n, size = max(len(w), 1), max(len(t), 1)
        count = lambda p: len(re.findall(p, t))
        x = [math.log1p(len(w)), len(set(w)) / n, (len(set(w)) - math.sqrt(n)) / n, len(t) / n, ratio(len(t.encode()), size), n / len(lines), len(set(lines)) / len(lines)]
        x += [count(r"[#*$%&<>{}\\^~=_]") / n, t.count("|") / n, t.count("!") / n, t.count(".") / n, t.count(",") / n, count("[A-Z]") / size, count("[0-9]") / size]
        cell = lambda edges: sum(v >= e for e in edges[0] for v in [edges[1]])
        total = model.bias
        for shape, edges, v in zip(model.shapes, model.edges, x, strict=True):
            total += shape[cell((edges, v))]
        for (i, j), surface in zip(model.pairs, model.surfaces, strict=True):
            total += surface[cell((model.coarse[i], x[i])) * (len(model.coarse[j]) + 1) + cell((model.coarse[j], x[j]))]
        assert abs(scores[r["doc_id"]] - 1 / (1 + math.exp(-total))) < 1e-9
    assert len(model.pairs) == model.n_pairs and len(set(scores.values())) > 20


def test_quality_ignores_held_out_labels(docs, labels):
    flipped = labels.withColumn("quality", F.when(quality.fold() == quality.HELD_OUT, 1 - F.col("quality")).otherwise(F.col("quality")))
    a, b = (quality.classify(docs, x).select("doc_id", "score").collect() for x in (labels, flipped))
    assert sorted(a) == sorted(b)


def test_license_notices(spark):
    texts = {
        1: "Released under the MIT License, see file. General Public License!",
        2: "Licensed under the Apach Licence, Version 2.0",
        3: "Permission is hereby granted, free of charge, to any persom obtaining a copy",
        4: "nothing to see here, a licence to thrill",
        5: "mit mit license license apache license",
    }
    got = {r["doc_id"]: r for r in licenses.digest(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()}
    assert (got[1]["n_base"], got[1]["first_word"], got[1]["last_word"], got[1]["base_labels"]) == (2, 3, 7, "gpl,mit")
    assert (got[2]["base_labels"], got[2]["labels"]) == ("", "apache") and 0.8 < got[2]["score"] < 1
    assert got[3]["labels"] == "mit" and got[4]["labels"] == "" and got[4]["score"] == 0
    assert (got[5]["n_base"], got[5]["first_word"], got[5]["last_word"]) == (2, 1, 4)


def edited(rng, text, n, inner=True):
    """``text`` after n insertions, deletions and replacements of letters within words."""
    s = list(text)
    for _ in range(n):
        i = rng.randrange(1, len(s) - 1)
        s[i : i + 1] = rng.choice(([rng.choice("qzx")], [s[i], rng.choice("qzx")], [] if s[i] != " " else [" "]))
    return " ".join("".join(s).split())


def test_license_seeds_lose_nothing():
    """Every insertion, deletion and replacement within the bound is found, though only exact pieces are looked up."""
    rng, scanner = random.Random(4), licenses.Scanner()
    for label, text, errors, exact in licenses.NOTICES:
        for _ in range(20):
            s = edited(rng, text, rng.randint(0, errors)) + (f" {exact}" if exact else "")
            before, after = "before " * rng.randint(0, 3), " after" * rng.randint(0, 3)
            got = [x for x in scanner.fuzzy((before + s + after).split()) if x[2] == label]
            assert got and any(abs(a - before.count("before")) <= 1 for a, *_ in got), s


def test_license_against_a_search_without_seeds():
    """The same matches as running every pattern over the whole text, windows merged or not."""
    rng, scanner = random.Random(5), licenses.Scanner()
    fillers = "the license software public of and general copy version free notice".split()
    for _ in range(150):
        parts = []
        for _ in range(rng.randint(1, 6)):
            parts += [rng.choice(fillers) for _ in range(rng.randint(0, 8))]
            _, text, errors, exact = rng.choice(licenses.NOTICES)
            parts += (edited(rng, text, rng.randint(0, errors + 1)) + " " + exact).split()
        joined = " ".join(parts)
        expected = {x.label for x, p in zip(scanner.notices, scanner.patterns, strict=True) if p.search(joined)}
        assert {x[2] for x in scanner.fuzzy(parts)} == expected, joined


def test_license_spans():
    scanner = licenses.Scanner()
    words = "the mozila public license and mozilla public license here".split()
    assert [x[:3] for x in scanner.fuzzy(words)] == [(1, 4, "mpl"), (5, 8, "mpl")]
    assert [x[:3] for x in scanner.fuzzy("see spdx licence identifier bsl 1 0".split())] == [(1, 7, "boost")]
    began = time.time()
    assert len(scanner.fuzzy("gnu general public license and".split() * 5_000)) >= 5_000
    assert time.time() - began < 30


def passage_distance(item, text):
    """Brute force: the least word edit distance from the item to any passage."""
    row = [0] * (len(text) + 1)
    for i, x in enumerate(item, 1):
        new = [i]
        for j, y in enumerate(text, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return min(row)


def test_decontamination(spark, docs):
    rng = random.Random(6)
    words = [f"w{i}" for i in range(3000)]
    items = {i: [rng.choice(words) for _ in range(rng.randint(12, 60))] for i in range(60)}
    texts, planted = {}, 0
    for d in range(300):
        text = [rng.choice(words) for _ in range(rng.randint(5, 300))]
        if d % 2:
            piece = items[rng.randrange(60)][:]
            for _ in range(rng.randint(0, max(1, len(piece) // 6))):
                k = rng.randrange(len(piece))
                piece[k : k + 1] = rng.choice(([], [rng.choice(words)], [piece[k], rng.choice(words)]))
            at = rng.randrange(len(text))
            text[at:at] = piece
        texts[d] = text
    expected = {(d, i): e for d, t in texts.items() for i, w in items.items() if (e := passage_distance(w, t)) <= int(decontamination.ERRORS * len(w))}
    frame = spark.createDataFrame([(d, " ".join(t)) for d, t in texts.items()], "doc_id long, text string")
    bench = spark.createDataFrame([(i, " ".join(w)) for i, w in items.items()], "item_id long, text string")
    rows = decontamination.contaminated(frame, bench).collect()
    got = {(r["doc_id"], r["item_id"]): r["errors"] for r in rows}
    assert set(got) <= set(expected)
    assert len(got) >= 0.97 * len(expected) and {k for k, e in expected.items() if e == 0} <= set(got)
    assert np.mean([got[k] == expected[k] for k in got]) > 0.97
    assert decontamination.clean(frame, bench).count() == 300 - len({d for d, _ in got})


def prose(seed, n):
    rng = random.Random(seed)
    return " ".join("".join(rng.choice("bdfgklmnprst") + rng.choice("aeiou") for _ in range(3)) for _ in range(n))


def test_best_passage():
    """The banded rows give the distance and place of a search over all passages."""
    rng = np.random.default_rng(0)
    for _ in range(200):
        item, text = rng.integers(0, 5, rng.integers(1, 8)), rng.integers(0, 5, rng.integers(0, 15))
        options = [(edits(item, text[i:j]), j, j - i) for j in range(len(text) + 1) for i in range(j + 1)]
        errors, end, length = min(options)
        assert decontamination.best_passage(item, text, len(item)) == (errors, end - length, end)
        assert decontamination.best_passage(item, text, errors - 1) is None


def edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


@pytest.mark.parametrize("n", [5, 12, 30, 40, 41, 75, 100, 300, 1000])
def test_decontamination_recall(n):
    """The target recall holds at every length and share of edits."""
    for share in (0.05, 0.1, 0.15):
        assert decontamination.miss(n, share, 40) <= 1 - decontamination.RECALL


def test_decontamination_groups(spark, monkeypatch):
    """Items beyond a group's size are looked for in further groups; long items, repeated rows and nulls included."""
    items = {i: prose(f"item {i}", 20 + 90 * (i % 3)) for i in range(12)}
    rows = [(d, f"{prose(f'a {d}', 40)} {items[d % 12]} {prose(f'b {d}', 40)}" if d % 3 else prose(f"clean {d}", 100)) for d in range(36)]
    rows += [rows[1], (None, items[0]), (99, None), (100, "")]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    bench = spark.createDataFrame([*items.items(), (77, None), (78, " ")], "item_id long, text string")
    expected = sorted([(d, d % 12, 0, 40, 40 + 20 + 90 * (d % 12 % 3)) for d in range(36) if d % 3] + [(1, 1, 0, 40, 150)])
    for limit in (1 << 20, 800):
        monkeypatch.setattr(decontamination, "GROUP_BYTES", limit)
        got = sorted(map(tuple, decontamination.contaminated(frame, bench).where("doc_id is not null").collect()))
        assert got == expected
    assert decontamination.clean(frame, bench).count() == 12 + 3


@pytest.mark.parametrize("limit", [64 << 20, -1])
def test_line_dedup(spark, monkeypatch, limit):
    """Whether the lists are broadcast or joined in shares."""
    monkeypatch.setattr(scratch, "BROADCAST_BYTES", limit)
    rows = [(i, f"menu\nstory {i}\n\n menu \nfoot {i % 3}", "a" if i < 90 else None) for i in range(100)]
    got = {r["doc_id"]: r for r in linededup.drop_boilerplate(spark.createDataFrame(rows, "doc_id long, text string, source string"), 0.5, 3).collect()}
    assert got[0]["text"] == "story 0\n\nfoot 0" and (got[0]["n_lines"], got[0]["n_dropped"]) == (4, 2)
    assert got[95]["text"] == "story 95\n\nfoot 2"


def test_line_dedup_of_copies(spark):
    """Copies of a document do not turn its lines into boilerplate; what other documents repeat still goes."""
    text = lambda i: f"menu of the site\n{prose(i, 60)}\n{prose(f'end {i}', 30)}"
    rows = [(i, text("copy" if i < 3 else i), "few") for i in range(20)]
    rows += [(100 + i, text("large") + (f"\nnear {i}" if i % 2 else "") if i < 20 else text(100 + i), "many") for i in range(60)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {r["doc_id"]: r["text"] for r in linededup.drop_boilerplate(frame, classes=neardup.near_duplicates(frame), counts=False).collect()}
    assert got == {i: t.removeprefix("menu of the site\n") for i, t, _ in rows}


def test_pipeline(spark, data):
    """Every stage against brute force on its own input."""
    import corpus_pipeline as p

    assert [n for n, _ in p.STAGES] == ["quality_classifier", "line_dedup", "minhash_near_dedup", "benchmark_decontamination", "best_fit_packing"]
    docs = table(spark, data, "documents")
    columns, kept = docs.columns, [docs.collect()]
    for name, stage in p.STAGES[:-1]:
        docs = stage(spark, docs, data).checkpoint()
        assert docs.columns == columns, name
        kept.append(docs.collect())
    raw, good, lines, single, clean = ({r["doc_id"]: r for r in rows} for rows in kept)
    # the classifier keeps rows as they are, those that it predicts to be good
    predicted = {r["doc_id"] for r in quality.classify(table(spark, data, "documents"), table(spark, data, "labels")).where("predicted = 1").collect()}
    assert set(good) == predicted and all(good[i] == raw[i] for i in good)
    # a line goes if it stands in three classes of near-duplicates of its source and over a twentieth of them
    classes = components_of({i: r["text"] for i, r in good.items()}, 5)[0]
    holders, sizes = collections.defaultdict(set), collections.defaultdict(set)
    strip = lambda x: x.strip(" \t\x0b\x0c\r")
    for i, r in good.items():
        sizes[r["source"]].add(classes[i])
        for x in (r["text"] or "").split("\n"):
            holders[r["source"], strip(x)].add(classes[i])
    gone = {(s, x) for (s, x), c in holders.items() if x and len(c) >= 3 and len(c) > 0.05 * len(sizes[s])}
    for i, r in good.items():
        text = None if r["text"] is None else "\n".join(x for x in r["text"].split("\n") if (r["source"], strip(x)) not in gone)
        assert lines[i]["text"] == text and lines[i]["n_chars"] == (None if text is None else len(text))
    # the smallest id of each class stays
    left = components_of({i: r["text"] for i, r in lines.items()}, 5)[0]
    assert set(single) == set(left.values()) and all(single[i] == lines[i] for i in single)
    # documents with a passage of the benchmark go
    items = [w for r in table(spark, data, "benchmark").collect() if (w := (r["text"] or "").lower().split())]
    near = lambda t: any(passage_distance(w, t) <= int(decontamination.ERRORS * len(w)) for w in items if len(set(w) & set(t)) >= len(set(w)) - int(decontamination.ERRORS * len(w)))
    assert set(clean) == {i for i, r in single.items() if not near((r["text"] or "").lower().split())}
    rows = p.run(spark, data).collect()
    places = collections.defaultdict(list)
    for r in rows:
        places[r["sequence_id"]].append((r["offset"], r["length"]))
    assert {r["doc_id"] for r in rows} == set(clean)
    for own in places.values():
        ends = np.cumsum([0, *(n for _, n in sorted(own))])
        assert [at for at, _ in sorted(own)] == ends[:-1].tolist() and ends[-1] <= packing.CAPACITY
