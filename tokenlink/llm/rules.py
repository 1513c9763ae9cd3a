"""Quality rules whose cutoffs carry a guarantee, in DataFrame functions only.

A rule rejects a text whose measure lies beyond a cutoff, taken from a fixed ladder from lenient to strict; the
verdict of a stratum (language) is that no rule rejects.  Its cutoffs are chosen on labelled documents in two
halves, dealt by the hash of the id.  The first half proposes: cutoffs are tightened one by one, always the one
that costs the fewest good documents for the bad ones it rejects, which gives a path of ever stricter verdicts.
The second half tests: along the path, a verdict is accepted while the exact binomial (Clopper-Pearson) upper
bound of the share of good documents it rejects, by all its rules together, stays within ``risk``.  The path does
not depend on the second half, so testing it in order and stopping at the first failure needs no correction for
its length (fixed-sequence testing); the level is divided by the number of strata tested (Bonferroni).  So with
confidence 1 - ``level``, no stratum's verdict rejects more than ``risk`` of its good documents.

A stratum with too few good labels to pass even with no rejection is not tested and has no cutoffs.  All labelled
rows count; what reaches the driver is counts by stratum, half, label and the first step of each ladder that
rejects, of which there are no more than the ladders' lengths multiply to, however many rows there are.

Independent of labels, a text fails the base rules with under 50 words, or with over half of its words in
repeated three-word windows.

Defined results.  A null text has no words and fails the base rules.  A null or rare stratum is judged by
the base rules alone.  Repeated ids in the labels count once for each pair of rows.  An empty table gives no
rows; without labels the base rules judge.  A very long text is measured whole.  Further columns of the input
are not read, except that :func:`measured` keeps them: there, measures replace columns of their names.
"""

from __future__ import annotations

import math

from itertools import chain

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .scratch import materialize

#: Word separators: blank, tab, line feed, vertical tab, form feed, carriage return.
SPACE = " \t\n\x0b\x0c\r"
_SPACE_CLASS = r"[\x20\x09-\x0D]"


def _repeated_words(grams: Column) -> Column:
    """Words inside windows whose hash occurs twice or more; ``grams`` holds the hash of the window at each word."""
    placed = F.array_sort(F.transform(grams, lambda g, i: F.struct(g.alias("g"), i.alias("i"))))

    def twins(s: Column) -> Column:
        same = lambda i, j: F.coalesce(F.get(s, i)["g"] == F.get(s, j)["g"], F.lit(False))
        at = F.filter(F.transform(s, lambda x, k: F.when(same(k, k - 1) | same(k, k + 1), x["i"])), lambda x: x.isNotNull())
        return F.array_sort(at)

    def covered(p: Column) -> Column:
        # a window covers three words unless the next one begins earlier
        gaps = F.zip_with(p, F.slice(p, F.lit(2), F.size(p)), lambda a, b: F.least(F.lit(3), F.coalesce(b - a, F.lit(3))))
        return F.aggregate(gaps, F.lit(0), lambda acc, x: acc + x)

    once = lambda value, use: F.get(F.transform(F.array(value), use), F.lit(0))
    return once(placed, lambda s: once(twins(s), covered))


MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper")


def measured(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, n_upper."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    trimmed = F.trim(text, F.lit(SPACE))
    words = F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, f"{_SPACE_CLASS}+", -1))
    out = docs.withColumn("__w", words).withColumn("n_words", F.size("__w").cast("long"))
    w = F.col("__w")
    grams = F.when(
        F.col("n_words") >= 3,
        F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2))),
    ).otherwise(F.array().cast("array<bigint>"))
    out = out.withColumn("__g", grams).withColumn("__lines", F.filter(F.split(text, "\n", -1), lambda x: F.trim(x, F.lit(SPACE)) != ""))
    g = F.col("__g")
    return out.select(
        *[F.col(f"`{c}`") for c in docs.columns if c not in MEASURES],
        "n_words",
        F.length(F.array_join("__w", "")).cast("long").alias("word_chars"),
        F.regexp_count(text, F.lit(r"[#*$%&|<>]")).cast("long").alias("n_symbols"),
        (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("long").alias("n_dup_lines"),
        F.when(F.size(F.array_distinct(g)) == F.size(g), F.lit(0)).otherwise(_repeated_words(g)).cast("long").alias("n_repeat_words"),
        F.size("__lines").cast("long").alias("n_lines"),
        F.regexp_count(text, F.lit("[A-Z]")).cast("long").alias("n_upper"),
    )


#: Rules: name, measure as a ratio of two columns, direction (1: large values are bad), ladder from lenient to strict.
RULES = (
    ("symbols", "n_symbols", "n_words", 1, (2.0, 1.0, 0.5, 0.3, 0.2, 0.15, 0.1, 0.07, 0.05)),
    ("repeats", "n_repeat_words", "n_words", 1, (0.9, 0.7, 0.5, 0.4, 0.3, 0.25, 0.2, 0.15, 0.1)),
    ("dup_lines", "n_dup_lines", "n_lines", 1, (0.9, 0.7, 0.5, 0.4, 0.3, 0.25, 0.2)),
    ("upper", "n_upper", "word_chars", 1, (0.9, 0.7, 0.5, 0.3, 0.2, 0.15, 0.1)),
    ("long_words", "word_chars", "n_words", 1, (14.0, 12.0, 10.0, 9.0, 8.0, 7.5, 7.0)),
    ("short_words", "word_chars", "n_words", -1, (1.5, 2.0, 2.5, 3.0, 3.5, 4.0)),
)


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def _first_step(rule: tuple) -> Column:
    """The first step of the rule's ladder that rejects a row; the ladder's length if none does."""
    _, over, under, sign, ladder = rule
    value = F.col(over) / F.when(F.col(under) > 0, F.col(under))
    beyond = lambda c: value > c if sign > 0 else value < c
    # a stricter step rejects whatever a more lenient one does
    return F.lit(len(ladder)) - sum((F.coalesce(beyond(c), F.lit(False)).cast("int") for c in ladder), F.lit(0))


def binomial_cdf(k: int, n: int, p: float) -> float:
    """Probability of k or fewer of n: a regularized incomplete beta function, by its continued fraction (Lentz)."""
    if k >= n:
        return 1.0
    a, b, x = n - k, k + 1, 1 - p
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x))
    swap = x > (a + 1) / (a + b + 2)
    if swap:
        a, b, x = b, a, 1 - x
    tiny = 1e-300
    guard = lambda v: v if abs(v) > tiny else tiny
    c, d = 1.0, 1 / guard(1 - (a + b) * x / (a + 1))
    fraction = d
    for m in range(1, 10_000):
        for numerator in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d, c = 1 / guard(1 + numerator * d), guard(1 + numerator / c)
            step = c * d
            fraction *= step
        if abs(step - 1) < 1e-14:
            break
    part = front * fraction / a
    return 1 - part if swap else part


def binomial_upper(k: int, n: int, level: float) -> float:
    """Clopper-Pearson: the largest p under which k or fewer of n still has probability ``level``."""
    if n == 0 or k >= n:
        return 1.0
    low, high = k / n, 1.0
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if mid < 1 and binomial_cdf(k, n, mid) > level else (low, mid)
    return high


#: Counts of good and bad rows by the first rejecting step of every rule.
Counts = dict[tuple[int, ...], tuple[int, int]]


def path(counts: Counts, risk: float) -> list[tuple[int, ...]]:
    """Ever stricter verdicts: for each rule the number of steps taken on its ladder.  They end where the proposing
    half loses twice the risk, beyond which no test would pass, or where no bad row is left to reject."""
    now, out = tuple(0 for _ in RULES), []
    alive, good = dict(counts), sum(g for g, _ in counts.values())
    lost = 0
    while True:
        best = None
        for r, (*_, ladder) in enumerate(RULES):
            # what each further step of this rule would reject
            found = sorted((steps[r] + 1, g, b) for steps, (g, b) in alive.items() if steps[r] < len(ladder))
            g = b = 0
            for i, (taken, more_good, more_bad) in enumerate(found):
                g, b = g + more_good, b + more_bad
                if b and (i + 1 == len(found) or found[i + 1][0] != taken):
                    best = max(best or (-1.0,), (b / (g + 1), b, -r, -taken, g))
        if best is None or lost + best[4] > 2 * risk * good:
            return out
        r, taken, lost = -best[2], -best[3], lost + best[4]
        now = now[:r] + (taken,) + now[r + 1 :]
        alive = {steps: n for steps, n in alive.items() if steps[r] >= taken}
        out.append(now)


def certified(propose: Counts, test: Counts, risk: float, level: float) -> tuple[int, ...] | None:
    """The strictest verdict on the path of ``propose`` before the first that ``test`` does not bear out."""
    accepted, good = None, sum(g for g, _ in test.values())
    for steps in path(propose, risk):
        rejected = sum(g for first, (g, _) in test.items() if any(f < s for f, s in zip(first, steps, strict=True)))
        if rejected >= good or binomial_cdf(rejected, good, risk) > level:
            break
        accepted = steps
    return accepted


def certified_cutoffs(labelled: DataFrame, id_col: str = "doc_id", stratum_col: str = "lang", risk: float = 0.05, level: float = 0.05) -> dict[str, tuple[int, ...]]:
    """Stratum to the number of steps taken on each rule's ladder, from measured rows with a 0/1 ``quality``."""
    judged = labelled.where(~base_failed() & F.col("quality").isNotNull() & F.col(stratum_col).isNotNull())
    firsts = [_first_step(r).alias(f"__{i}") for i, r in enumerate(RULES)]
    rows = judged.select(F.col(stratum_col).cast("string").alias("__s"), F.pmod(F.xxhash64(id_col), F.lit(2)).alias("__half"), (F.col("quality") == 1).cast("int").alias("__good"), *firsts)
    # (1 - risk) ** n is what n good rows without a rejection can show at best
    least = math.ceil(math.log(level) / math.log1p(-risk))
    steps = [f"__{i}" for i in range(len(RULES))]
    counted = materialize(rows.groupBy("__s", "__half", *steps).agg(F.sum("__good").alias("g"), F.count("*").alias("n")))
    enough = counted.where("__half = 1").groupBy("__s").agg(F.sum("g").alias("good")).where(F.col("good") >= least).select("__s")
    halves: dict[str, tuple[Counts, Counts]] = {}
    for row in counted.join(enough, "__s", "left_semi").collect():
        halves.setdefault(row["__s"], ({}, {}))[row["__half"]][tuple(row[c] for c in steps)] = (row["g"], row["n"] - row["g"])
    found = {s: certified(*both, risk, level / len(halves)) for s, both in halves.items()}
    return {s: x for s, x in found.items() if x}


def verdict(cutoffs: dict[str, tuple[int, ...]], stratum_col: str = "lang") -> Column:
    """True where neither the base rules nor any certified cutoff rejects."""
    passed = ~base_failed()
    if cutoffs:
        taken = F.create_map(*chain.from_iterable((F.lit(s), F.array(*map(F.lit, x))) for s, x in sorted(cutoffs.items())))
        own = F.element_at(taken, F.col(stratum_col).cast("string"))
        for i, r in enumerate(RULES):
            passed = passed & F.coalesce(_first_step(r) >= F.get(own, F.lit(i)), F.lit(True))
    return passed


def judge(docs: DataFrame, labels: DataFrame, risk: float = 0.05, level: float = 0.05, id_col: str = "doc_id", text_col: str = "text", stratum_col: str = "lang") -> DataFrame:
    """One row per document: id, stratum, measures, base_failed, kept."""
    rows = materialize(measured(docs.select(id_col, text_col, stratum_col), text_col).drop(text_col))
    marked = rows.join(labels.select(F.col(id_col).alias("__id"), "quality"), F.col(id_col) == F.col("__id"))
    cutoffs = certified_cutoffs(marked, id_col, stratum_col, risk, level)
    return rows.withColumn("base_failed", base_failed()).withColumn("kept", verdict(cutoffs, stratum_col))
