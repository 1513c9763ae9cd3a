"""Boilerplate lines by their frequency within a site.

For every site the pages that hold a line are divided by the pages of the site; a line whose share exceeds
``max_ratio``, on at least ``min_pages`` pages, is boilerplate there and is dropped from that site's pages.
Lines are compared after trimming blanks; blank lines are never counted and never dropped.

A page with L lines adds L to the sum of all shares, so a site has fewer than (mean lines a page) /
``max_ratio`` boilerplate lines, whatever its size: the lists stay short.  They are written and measured before
they meet the pages: broadcast up to a fixed size, so that texts are never shuffled, and beyond it joined with
every site cut into shares, so that no task holds a hot site.

Defined results.  A null text stays null with no lines.  A null site is a site of its own.  A line repeated
in one page counts once for the page; every copy of it is dropped.  Repeated rows are separate pages, unless
``classes`` tells which documents are copies: the documents of a class then count as one page of their site, so
that copies do not turn their own text into boilerplate.
Pages whose every line goes keep their row, with an empty text.  An empty table gives no rows.  A very long text is
one row like any other.  Further columns pass unchanged; columns named ``n_lines`` or ``n_dropped`` are replaced
where counts are asked for, and names beginning with two underscores are kept free.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import attach

_BLANKS = " \t\x0b\x0c\r"


def _line_key(line: F.Column) -> F.Column:
    return F.xxhash64(F.trim(line, F.lit(_BLANKS)))


def _lines(text: F.Column) -> F.Column:
    return F.split(text, "\n", -1)


def boilerplate_lines(docs: DataFrame, max_ratio: float = 0.05, min_pages: int = 3, site_col: str = "source", text_col: str = "text", classes: DataFrame | None = None, id_col: str = "doc_id") -> DataFrame:
    """(site, line_key, pages, site_pages) of the lines to drop; ``classes``: (doc_id, component_id)."""
    keys = F.array_distinct(F.transform(F.filter(_lines(F.col(text_col)), lambda x: F.trim(x, F.lit(_BLANKS)) != ""), _line_key))
    per_page = docs.select(F.col(site_col).alias("site"), keys.alias("keys"), *([F.col(id_col).cast("long").alias("__id"), F.xxhash64(text_col).alias("__own")] if classes is not None else []))
    if classes is None:
        lines, pages = per_page.select("site", F.explode("keys").alias("line_key")), per_page.select("site")
    else:
        of = classes.where("doc_id is not null").groupBy(F.col("doc_id").alias("__id")).agg(F.min("component_id").alias("class"))
        # a document without an id has no class but its text
        per_page = per_page.join(of, "__id", "left").select("site", "keys", F.coalesce("class", "__own").alias("class"))
        lines = per_page.select("site", "class", F.explode("keys").alias("line_key")).distinct()
        pages = per_page.select("site", "class").distinct()
    held = lines.groupBy("site", "line_key").agg(F.count("*").alias("pages")).where(F.col("pages") >= min_pages)
    sites = pages.groupBy(F.col("site").alias("of")).agg(F.count("*").alias("site_pages"))
    return attach(held, sites, "site", "of", 64).where(F.col("pages") > F.lit(max_ratio) * F.col("site_pages")).select("site", "line_key", "pages", "site_pages")


def drop_boilerplate(docs: DataFrame, max_ratio: float = 0.05, min_pages: int = 3, site_col: str = "source", text_col: str = "text", counts: bool = True, classes: DataFrame | None = None) -> DataFrame:
    """``docs`` with the text cleaned; ``counts`` adds n_lines and n_dropped (blank lines left out)."""
    lists = boilerplate_lines(docs, max_ratio, min_pages, site_col, text_col, classes).groupBy(F.col("site").alias("__site")).agg(F.collect_set("line_key").alias("__drop"))
    joined = attach(docs, lists, site_col, "__site", 64 + 8 * F.size("__drop")).withColumn("__lines", _lines(F.col(text_col)))
    some = F.col("__drop").isNotNull()
    kept = F.when(some, F.filter("__lines", lambda x: (F.trim(x, F.lit(_BLANKS)) == "") | ~F.array_contains(F.col("__drop"), _line_key(x)))).otherwise(F.col("__lines"))
    joined = joined.withColumn("__kept", kept)
    full = lambda c: F.coalesce(F.size(F.filter(c, lambda x: F.trim(x, F.lit(_BLANKS)) != "")), F.lit(0)).cast("long")
    gone = F.when(F.col(text_col).isNull(), F.lit(0)).otherwise(F.size("__lines") - F.size("__kept")).cast("long")
    out = [F.array_join("__kept", "\n").alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns if not (counts and c in ("n_lines", "n_dropped"))]
    return joined.select(*out, *([full("__lines").alias("n_lines"), gone.alias("n_dropped")] if counts else []))
