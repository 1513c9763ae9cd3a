"""Personal data by candidate generation, boosted trees and calibrated thresholds, in DataFrame functions only.

Base patterns (email, ip, card, phone) are found leftmost and without overlap, each kind by itself, checked,
and always kept.  Wider generators then propose further, possibly overlapping spans: spelled-out emails,
phone numbers without a plus sign, national numbers, bank account numbers, dotted cards, IPv6 addresses, and
secrets: opaque strings such as keys and tokens.
Boosted trees score them on format and on the words around them; a candidate stays if its calibrated
probability reaches its kind's threshold and no base span or better candidate overlaps it.

The trees are fitted on the driver on candidates from seeded templates (a fixed number, no corpus rows);
features of those candidates come from the same expressions that score the corpus.  Half of the templates'
rows are held out: they calibrate the probability and set thresholds at ``PRECISION``.

Positions count code points, the end is exclusive.  Rows are handled one by one, without a shuffle, and in time
linear in a text and its spans: positions and the sweep over spans are running sums and maxima in blocks, and a
candidate, whose length the generators bound, meets a bounded number of others.

Defined results.  A null text is an empty text: no spans and the digest of the empty string; redaction leaves it
null.  Null ids, ties and repeated rows are rows like any other, and an empty table gives none.  Further columns
pass through unchanged; names beginning with two underscores are kept free.
"""

from __future__ import annotations

import json
import random
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .boosting import Booster

# Base patterns.  Possessive repeats keep Java's matcher iterative; they and the look-behinds (a match can
# begin only where its run of characters begins, or where the last match ended) change no match.
BASE = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
RANK = {k: i for i, k in enumerate(BASE)}

#: Generators of further candidates: name, kind, pattern.
GENERATORS = (
    ("spelled_email", "email", r"(?i)(?<![A-Za-z0-9._%+-])[a-z0-9._%+-]{2,64}+(?: ?[\[({<]? ?@|(?: | ?[\[({<] ?)at) ?[\])}>]? ?[a-z0-9-]{2,63}+(?:(?:\.| [\[({<]? ?dot ?[\])}>]? |[\[({<] ?dot ?[\])}>])[a-z0-9-]{2,63}+){1,3}+"),
    ("local_phone", "phone", r"(?<![0-9+.-])(?:\([0-9]{2,5}+\)|0?[0-9]{2,5}+)[\x20./-]{1,2}+[0-9]{2,4}+(?:[\x20./-][0-9]{2,5}+){1,3}+(?![0-9])"),
    ("national_id", "ssn", r"(?<![0-9-])[0-9]{3}[\x20-][0-9]{2}[\x20-][0-9]{4}(?![0-9-])"),
    ("account", "iban", r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}+(?: ?[A-Z0-9]{1,3})?+(?![A-Za-z0-9])"),
    ("dotted_card", "card", r"(?<![0-9.])[0-9]{4}[._/][0-9]{4}[._/][0-9]{4}[._/][0-9]{1,7}+(?![0-9])"),
    ("ipv6", "ip", r"(?i)(?<![0-9a-z:])[0-9a-f]{1,4}+(?::{1,2}[0-9a-f]{1,4}+){3,7}+(?![0-9a-z:])"),
    ("secret", "secret", r"(?<![A-Za-z0-9_/+-])(?=[A-Za-z_/+-]*+[0-9])[A-Za-z0-9_/+-]{20,128}+={0,2}(?![A-Za-z0-9_/+=-])"),
)
#: What every match of the first generator holds: its part from the "at" on, which follows a blank or a bracket.
SPELLED = r"(?:@|[ \[({<][aA][tT]) ?[\])}>]? ?[A-Za-z0-9-]{2,63}+(?:\.[A-Za-z0-9-]| ?[\[({<]? ?[dD][oO][tT])"
_KINDS = ("email", "ip", "card", "phone", "ssn", "iban", "secret")
PRECISION = 0.98
_CONTEXT = 28
#: Elements that a running sum or maximum takes in one go.
_RUN = 128
#: No candidate is longer than 400 or shorter than 7 code points and those of a generator are apart, so that a
#: candidate overlaps fewer others than this.
_NEIGHBOURS = 7 * (400 // 7 + 2)


def _let(value: Column, use) -> Column:
    """``use(value)`` with the value computed once."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def _running(values: Column, op) -> Column:
    """op over each prefix of an array of ints."""

    def over(own: Column) -> Column:
        put = lambda acc, x: F.concat(acc, F.array(F.when(F.size(acc) > 0, op(F.element_at(acc, -1), x)).otherwise(x)))
        return F.aggregate(own, F.expr("cast(array() as array<int>)"), put)

    def joined(local: Column) -> Column:
        heads = over(F.transform(local, lambda b: F.element_at(b, -1)))
        return _let(heads, lambda h: F.flatten(F.transform(local, lambda b, k: F.when(k == 0, b).otherwise(F.transform(b, lambda x: op(F.get(h, k - 1), x))))))

    blocks = F.transform(F.sequence(F.lit(0), F.floor((F.size(values) - 1) / _RUN).cast("int")), lambda k: over(F.slice(values, k * _RUN + 1, F.lit(_RUN))))
    return F.when(F.size(values) > 0, F.when(F.size(values) <= _RUN, over(values)).otherwise(_let(blocks, joined))).otherwise(F.expr("cast(array() as array<int>)"))


def _located(text: Column, pattern: str) -> Column:
    """array<struct<start,end,match,left,right>>; positions are running sums over what a split leaves between matches."""
    nothing = F.expr("cast(array() as array<struct<start:int,end:int,match:string,left:string,right:string>>)")

    def spans(found: Column, between: Column) -> Column:
        sizes = F.transform(found, lambda m, i: F.length(m) + F.length(F.get(between, i)))
        span = lambda m, i, ends: F.struct(
            (F.get(ends, i) - F.length(m)).alias("start"), F.get(ends, i).alias("end"), m.alias("match"), F.right(F.get(between, i), F.lit(_CONTEXT)).alias("left"), F.left(F.get(between, i + 1), F.lit(_CONTEXT)).alias("right")
        )
        return _let(_running(sizes, lambda a, b: a + b), lambda ends: F.transform(found, lambda m, i: span(m, i, ends)))

    def split(found: Column) -> Column:
        return F.when(F.size(found) > 0, _let(F.split(text, pattern, -1), lambda between: spans(found, between))).otherwise(nothing)

    return _let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), split)


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    padded = F.lpad(digits, 19, "0")

    def at(i: int) -> Column:
        d = F.substring(padded, i + 1, 1).cast("int")
        return d if i % 2 == 0 else d * 2 - F.when(d > 4, 9).otherwise(0)

    return reduce(lambda a, b: a + b, map(at, range(19))) % 10 == 0


_OCTET = r"0*+(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9][0-9]?)?"


def _valid(kind: str, match: Column) -> Column:
    if kind == "ip":
        return match.rlike(rf"^{_OCTET}(?:\.{_OCTET}){{3}}$")
    if kind == "card":
        d = _digits(match)
        return F.length(d).between(12, 19) & _luhn(d)
    if kind == "phone":
        return F.length(_digits(match)).between(9, 15)
    return F.lit(True)


def _features(x: Column) -> Column:
    m, left, right = x["match"], F.lower(x["left"]), F.lower(x["right"])
    num = lambda c: c.cast("double")
    near = lambda words: num(left.rlike(rf"(?:^|[^\p{{L}}])(?:{words})[^\p{{L}}]{{0,6}}(?:is |ist |est |es )?[^\p{{L}}]{{0,3}}$") | right.rlike(rf"^[^\p{{L}}]{{0,4}}(?:{words})(?:[^\p{{L}}]|$)"))
    d = _digits(m)
    return F.array(
        num(F.length(m)),
        num(F.length(d)),
        num(F.regexp_count(m, F.lit(r"[\x20./-]"))),
        num(F.regexp_count(m, F.lit(r"[A-Za-z]"))),
        num(m.rlike(r"^\([0-9]+\)|^0[0-9]")),
        num(m.rlike(r"(?i)[\[({<] ?(?:at|@)|[\])}>]|@| at ")),
        num(m.rlike(r"(?i)(?:dot|\.) ?[\])}>]? ?(?:com|org|net|edu|de|fr|es|uk|io|info|example)$")),
        num(m.rlike(r"^(?:19|20)[0-9]{2}[./ -](?:0?[1-9]|1[0-2])[./ -]|^[0-3]?[0-9][./ -][01]?[0-9][./ -](?:19|20)?[0-9]{2}$")),
        num(_luhn(F.right(d, F.lit(19)))),
        num(m.rlike(r"^(?!000|666|9)[0-9]{3}.(?!00)[0-9]{2}.(?!0000)[0-9]{4}$")),
        num(m.rlike(r"::|[a-fA-F]")),
        near("call|phone|tel|telephone|telefon|fax|mobile|cell|whatsapp|teléfono|téléphone|ring|dial"),
        near("mail|e-mail|email|contact|write|correo|courriel|reach"),
        near("ssn|social security|social|tax id|taxpayer|national id"),
        near("iban|account|konto|compte|cuenta|bank"),
        near("card|visa|mastercard|credit|karte|carte|tarjeta"),
        near("ip|ipv6|host|address|server|addr"),
        near("order|invoice|version|isbn|part|ref|date|page|room|total|score|serial|model|figure|section|chapter|since|from|sku|batch|lot"),
        near("token|secret|password|passwd|pwd|api_key|apikey|api key|access_key|key|bearer|auth|authorization|credential|clave|schlüssel|jeton"),
        near("commit|sha|md5|checksum|digest|hash|etag|file|path|url|image|src|href|class|revision"),
        num(F.regexp_count(m, F.lit(r"[0-9][A-Za-z]"))),
        num(F.regexp_count(m, F.lit(r"[/_+-]"))),
        num(F.regexp_count(m, F.lit(r"[A-Z]"))),
        num(F.size(F.array_distinct(F.split(m, "")))),
        num(x["left"].rlike(r"[\p{L}\p{N}]$")),
        num(x["right"].rlike(r"^[\p{L}\p{N}]")),
    )


def _examples(n: int, seed: int) -> list[dict]:
    """Candidates from templates: what each generator is meant to find, and what merely looks like it."""
    rng = random.Random(seed)
    digits = lambda k: "".join(rng.choice("0123456789") for _ in range(k))
    word = lambda: "".join(rng.choice("bcdfghklmnprstvw") + rng.choice("aeiou") for _ in range(rng.randint(2, 4)))

    def luhn(k: int) -> str:
        body = digits(k - 1)
        total = sum(int(c) if i % 2 else (int(c) * 2 - 9 * (int(c) > 4)) for i, c in enumerate(reversed(body)))
        return body + str(-total % 10)

    alnum = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    opaque = lambda alphabet, k: "".join(rng.choice(alphabet) for _ in range(k - 1)) + rng.choice("0123456789")
    four = lambda s, by: by.join(s[i : i + 4] for i in range(0, len(s), 4))
    good = {
        "spelled_email": (lambda: rng.choice(("{a} at {b} dot {c}", "{a} [at] {b} [dot] {c}", "{a}(at){b}.{c}", "{a} @ {b}.{c}", "{a} (at) {b} (dot) {c}")).format(a=word(), b=word(), c=rng.choice(("com", "org", "net", "de"))), ("email: ", "contact ", "mail ", "write to ", "")),
        "local_phone": (lambda: rng.choice(("({}) {}-{}", "{}-{}-{}", "0{} {} {}", "{}.{}.{}")).format(digits(3), digits(3), digits(4)), ("call ", "phone: ", "tel. ", "fax ", "mobile ", "")),
        "national_id": (lambda: f"{rng.randint(100, 665)}-{rng.randint(10, 99)}-{rng.randint(1000, 9999)}", ("ssn ", "SSN: ", "social security ", "tax id ", "")),
        "account": (lambda: rng.choice("DE FR ES GB".split()) + four(digits(20), rng.choice(("", " "))), ("iban ", "IBAN: ", "account ", "bank ", "")),
        "dotted_card": (lambda: four(luhn(16), rng.choice("._/")), ("card ", "visa ", "credit card ", "")),
        "ipv6": (lambda: ":".join(f"{rng.randint(4096, 65535):x}" for _ in range(8)), ("host ", "ip ", "server ", "addr ", "")),
        "secret": (lambda: rng.choice((lambda: opaque("0123456789abcdef", rng.choice((32, 40, 64))), lambda: opaque(alnum, rng.randint(20, 44)), lambda: rng.choice(("sk_live_", "ghp_", "AKIA")) + opaque(alnum, 24)))(), ('token = "', "token: ", 'api_key="', "key = ", "secret: ", "password=", "Authorization: Bearer ", "key: ")),
    }
    bad = {
        "spelled_email": (lambda: rng.choice(("{a} at {b} . {c}", "{a} at {b}.{c}", "{a} at {b} dot {c}")).format(a=word(), b=word(), c=word()), ("look ", "arrived ", "the ", "")),
        "local_phone": (lambda: rng.choice((f"{rng.randint(1900, 2030)}-{rng.randint(10, 12)}-{rng.randint(10, 28)}", f"{rng.randint(10, 28)}.{rng.randint(10, 12)}.{rng.randint(1900, 2030)}", f"{digits(3)} {digits(3)} {digits(3)}", f"{digits(5)}-{digits(4)}-{digits(2)}-{digits(3)}")), ("order ", "invoice ", "since ", "version ", "date ", "ref ", "total ", "")),
        "national_id": (lambda: f"{rng.choice(('000', '666', str(rng.randint(900, 999))))}-{digits(2)}-{digits(4)}", ("part ", "order ", "ref ", "serial ", "")),
        "account": (lambda: rng.choice("ZZ XQ AB".split()) + four(digits(10), ""), ("serial ", "model ", "part ", "lot ", "batch ")),
        "dotted_card": (lambda: four(digits(16), rng.choice("._/")), ("serial ", "version ", "part ", "batch ", "ref ")),
        "ipv6": (lambda: ":".join(f"{rng.randint(10, 59)}" for _ in range(rng.choice((4, 5)))), ("score ", "from ", "total ", "section ", "")),
        "secret": (lambda: rng.choice((lambda: "/".join(word() for _ in range(5)) + digits(2), lambda: "_".join(word() for _ in range(4)) + "_" + digits(4), lambda: "-".join((digits(4), digits(2), digits(2), digits(6), digits(6))), lambda: opaque("0123456789abcdef", rng.choice((32, 40, 64))), lambda: digits(24)))(), ("file ", "path ", "commit ", "sha256: ", "md5 = ", "see ", "image ", "")),
    }
    out = []
    for i in range(n):
        for name, kind, _ in GENERATORS:
            make, before = (good if i % 2 else bad)[name]
            out.append({"name": name, "kind": kind, "y": i % 2, "fold": i // 2 % 2, "match": make(), "left": rng.choice(("", word() + " ")) + rng.choice(before), "right": rng.choice(("", ".", " " + word(), ", " + word()))})
    return out


_fitted: tuple[dict[str, Booster], dict[str, float]] | None = None


def fitted(spark: SparkSession, n: int = 120, seed: int = 5) -> tuple[dict[str, Booster], dict[str, float]]:
    """A booster and a threshold for each generator; fitted once a process."""
    global _fitted
    if _fitted is None:
        rows = _examples(n, seed)
        shape = "array<struct<i:int,match:string,left:string,right:string>>"
        data = json.dumps([{"i": i, "match": r["match"], "left": r["left"], "right": r["right"]} for i, r in enumerate(rows)], ensure_ascii=False)
        # the JSON is a literal of fixed size, so the candidates never leave the JVM's own relation
        table = spark.range(1).select(F.inline(F.from_json(F.lit(data), shape)))
        values = {r["i"]: r["f"] for r in table.select("i", _features(F.struct("match", "left", "right")).alias("f")).collect()}
        models, cuts = {}, {}
        for name, _, _ in GENERATORS:
            own = [i for i, r in enumerate(rows) if r["name"] == name]
            x, y, fold = np.array([values[i] for i in own]), np.array([rows[i]["y"] for i in own], float), np.array([rows[i]["fold"] for i in own])
            models[name] = Booster(16).fit(x[fold == 0], y[fold == 0]).calibrate(x[fold == 1], y[fold == 1])
            p, truth = models[name].probability(x[fold == 1]), y[fold == 1]
            order = [(t, truth[p >= t].mean()) for t in np.unique(p)]
            cuts[name] = max(0.5, min((float(t) for t, right in order if right >= PRECISION), default=1.1))
        _fitted = models, cuts
    return _fitted


def find_spans(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with ``__base`` and ``__added``, arrays of (start, rank, end, kind, score), sorted."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    models, cuts = fitted(docs.sparkSession)
    # cheaper to look for than the patterns, and computed once
    docs = docs.withColumn("__digit", text.rlike("[0-9]")).withColumn("__spelled", text.rlike(SPELLED))
    digit = F.col("__digit")
    may = {"email": F.instr(text, "@") > 0, "ip": digit, "card": digit, "phone": F.instr(text, "+") > 0}
    none = F.expr("cast(array() as array<struct<start:int,rank:int,end:int,kind:string,score:double>>)")

    def record(x: Column, kind: str, score: Column) -> Column:
        return F.struct(x["start"].alias("start"), F.lit(_KINDS.index(kind)).alias("rank"), x["end"].alias("end"), F.lit(kind).alias("kind"), score.alias("score"))

    def checked(kind: str, pattern: str) -> Column:
        good = F.filter(_located(text, pattern), lambda x: _valid(kind, x["match"]))
        return F.when(may[kind], F.transform(good, lambda x: record(x, kind, F.lit(1.0)))).otherwise(none)

    def selected(name: str, kind: str, pattern: str) -> Column:
        featured = F.transform(_located(text, pattern), lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"), _features(x).alias("f")))
        scored = F.transform(featured, lambda x: record(x, kind, models[name].column(x["f"])))
        return F.when(worth.get(name, digit), F.filter(scored, lambda x: x["score"] >= cuts[name])).otherwise(none)

    worth = {"spelled_email": F.col("__spelled"), "ipv6": digit & (F.instr(text, ":") > 0)}
    base, added = [checked(*x) for x in BASE.items()], [selected(*x) for x in GENERATORS]
    found = docs.withColumn("__base", F.array_sort(F.concat(*base))).withColumn("__wide", F.array_sort(F.array_distinct(F.concat(*added))))
    found = found.withColumn("__wide", F.when((F.size("__wide") > 0) & (F.size("__base") > 0), _apart(F.col("__wide"), F.col("__base"))).otherwise(F.col("__wide")))
    return found.withColumn("__added", F.when(F.size("__wide") > 1, _best(F.col("__wide"))).otherwise(F.col("__wide"))).drop("__wide", "__digit", "__spelled")


def _over(a: Column, b: Column) -> Column:
    return (a["start"] < b["end"]) & (b["start"] < a["end"])


def _apart(wide: Column, base: Column) -> Column:
    """The candidates that no base span overlaps: a sweep over both by start, base first."""
    tagged = lambda spans, own: F.transform(spans, lambda x: F.struct(x["start"].alias("start"), F.lit(own).alias("own"), x.alias("span")))

    def kept(merged: Column) -> Column:
        reach = _running(F.transform(merged, lambda x: F.when(x["own"] == 0, x["span"]["end"]).otherwise(0)), lambda a, b: F.greatest(a, b))

        def free(reach: Column) -> Column:
            later = lambda x, k: F.exists(F.slice(merged, k + 2, F.lit(_NEIGHBOURS)), lambda y: (y["own"] == 0) & (y["start"] < x["span"]["end"]))
            marked = F.transform(merged, lambda x, k: F.when((x["own"] == 1) & (F.get(reach, k) <= x["start"]) & ~later(x, k), x["span"]))
            return F.filter(marked, lambda x: x.isNotNull())

        return _let(reach, free)

    return _let(F.array_sort(F.concat(tagged(base, 0), tagged(wide, 1))), kept)


def _best(wide: Column) -> Column:
    """The candidates, sorted, that no better one overlaps."""
    better = lambda a, b: (a["score"] > b["score"]) | ((a["score"] == b["score"]) & (F.struct(a["start"], a["rank"], a["end"]) < F.struct(b["start"], b["rank"], b["end"])))
    around = lambda k: F.slice(wide, F.greatest(k + 1 - _NEIGHBOURS, F.lit(1)), F.lit(2 * _NEIGHBOURS))
    return F.filter(F.transform(wide, lambda x, k: F.when(~F.exists(around(k), lambda o: _over(x, o) & better(o, x)), x)), lambda x: x.isNotNull())


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"], x["end"])), ",")


def digest(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    found = find_spans(docs.select(id_col, text_col), text_col)
    count = lambda kind: F.size(F.filter("__base", lambda x: x["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select(
        id_col, *map(count, BASE), F.sha2(_listed(F.col("__base")), 256).alias("base_sha256"), _listed(F.array_sort(F.concat("__base", "__added"))).alias("spans")
    )


def redact(docs: DataFrame, text_col: str = "text", mask: str = "[{}]") -> DataFrame:
    """``docs`` with every span's characters replaced by its kind; overlapping spans are masked whole, as the first's kind."""
    found, text = find_spans(docs, text_col), F.col(text_col)

    def masked(spans: Column, reach: Column) -> Column:
        # regions begin where no earlier span reaches; each holds what its spans reach
        firsts = F.filter(F.sequence(F.lit(0), F.size(spans) - 1), lambda k: (k == 0) | (F.get(reach, k - 1) <= F.get(spans, k)["start"]))

        def written(at: Column) -> Column:
            since = lambda i: F.when(i == 0, F.lit(0)).otherwise(F.get(reach, F.get(at, i) - 1))
            part = lambda k, i: F.concat(F.substring(text, since(i) + 1, F.get(spans, k)["start"] - since(i)), F.format_string(mask.replace("{}", "%s"), F.get(spans, k)["kind"]))
            return F.concat(F.array_join(F.transform(at, part), ""), F.substring(text, F.element_at(reach, -1) + 1, F.length(text)))

        return _let(firsts, written)

    found = found.withColumn("__spans", F.array_sort(F.concat("__base", "__added")))
    reach = _running(F.transform("__spans", lambda x: x["end"]), lambda a, b: F.greatest(a, b))
    cleaned = F.when(F.size("__spans") > 0, _let(reach, lambda r: masked(F.col("__spans"), r))).otherwise(text)
    return found.select(*[cleaned.alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns])
