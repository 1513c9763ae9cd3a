"""Main text of web pages: what a host's suffix array does not find on its other pages, within the article.

A page is read into blocks of visible text in page order.  Mark-up tells of each block whether it lies in the
article and whether it surely belongs to the frame (navigation, footers, forms, comments, adverts and so on),
or only may (a class name like ``related`` or ``legal``).  The article is the innermost kind of container
(``<article>``, ``<main>``, a container named as content) that holds half of the text of all containers.

All blocks of all pages of a host, frame and article alike, are joined into one token stream with a break of
its own after each page.  Its suffixes are sorted by prefix doubling; a run of ``MIN_RUN`` tokens or more that
stands on several pages makes a stretch of equal neighbours there.  Overlapping runs cover their blocks, and

* a block that runs of two pages cover whole goes, unless an ``<article>`` or ``<main>`` vouches for it;
* runs on ``MIN_PAGES`` pages and over ``MAX_RATIO`` of the host's go from inside longer blocks too, unless an
  ``<article>`` or ``<main>`` vouches for the block;
* inside those, a block of ``MIN_RUN`` tokens or more goes if the runs that cover it stand on ``MIN_PAGES`` pages and
  over ``MARKED_RATIO`` of the host's: what its template writes into articles.  Less frequent lines are theirs;
* a block that may be frame goes if runs of two pages cover most of it;
* a block that surely is frame, or stands outside the page's article, goes, repeated or not.

Copies count as one page, so that they never make each other's text boilerplate: pages of equal article
blocks, and pages whose runs of ``COPY_RUN`` tokens agree to ``COPY``.  Where near copies would take in over half of
``TEMPLATE`` or more different pages, what they share is the host's template, and they count each.

The stream is cut between pages, never the host: pages are read in bundles of about ``GROUP_CHARS`` characters of
mark-up.  There suffixes are sorted not by prefix doubling, which :func:`kept_texts` does for a host in memory, but by
a hash of 64 bits of host and first ``MIN_RUN`` tokens, by which equal stretches of all bundles are merged.  Copies are
found among all pages of a host (near ones compared by 32 bits a run), and runs counted on all of them, so how pages
are bundled, however large a host is, decides nothing.  Which runs are counted follows from what they can decide:

* where all of a host's blocks are vouched for, or surely frame, only runs on over half of its classes matter.  Such a
  run stands, in some bundle, on over that share of the bundle's classes; each bundle names the cells (some bits of
  the hash) of those, and what all that name a cell have found tells whether it can reach half.  The few that can are
  counted in every bundle of the host; most bundles have none, and mark-up alone tells their texts;
* on a host with a block in doubt (no ``<article>`` or ``<main>`` vouches for it, or it may be frame) each bundle names
  the cells of all its runs, and those whose cell another bundle has too, or that its own pages repeat, are counted.

Near copies are compared, in each MinHash band, with one page only.  Two that agree, but neither with that page, may
therefore stay apart if no other band or page links them: on hosts without marked articles they count as two.

Inside a block white space of any kind becomes one blank; character references are decoded; blocks are joined
by line feeds.  Defined results.  A null page or one without text has an empty text.  A null or odd address
has the host ''.  Copies of a page (same id, address and page) count as one page for repetition, and each
keeps its row.  A very long page is read in time proportional to its length and may fill a bundle alone.  An
empty table gives no rows.  Further columns are not read, so their names cannot clash.
"""

from __future__ import annotations

import hashlib
import itertools
import math
import pickle
import re
from collections import Counter
from collections.abc import Iterator
from html import unescape
from typing import Any

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .neardup import _confirmed, components
from .scratch import attach, materialize

MIN_RUN = 8
MAX_RATIO, MARKED_RATIO, MIN_PAGES = 0.05, 0.5, 3
#: Characters of mark-up in a bundle, and in a share of the cells; neither changes a result.
GROUP_CHARS, SHARE_CHARS = 4 << 20, 64 << 20
#: Near copies: similarity, tokens of a run, least number of pages that may share a template.
COPY, COPY_RUN, TEMPLATE = 0.7, 4, 8
#: MinHash bands that bring near copies together, and samples of a band.
BANDS, ROWS = 24, 3

_TAG = re.compile(r"""<(?:(/?)([a-zA-Z][a-zA-Z0-9:-]*+)((?:[^<>"']|"[^"]*"|'[^']*')*+)>|(/?)([a-zA-Z][a-zA-Z0-9:-]*+)([^>]*+)>|[!?][^>]*+>)""")
_ATTR = re.compile(r"""([^\s"'<>/=]++)(?:\s*+=\s*+(?:"([^"]*)"|'([^']*)'|([^\s"'>]++)))?+""")
_HOST = r"^[a-zA-Z][a-zA-Z0-9+.-]*+://(?:[^/@?#]*+@)?([^/:?#]+)"

_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_HIDDEN = frozenset("script style noscript template svg iframe object canvas audio video head title select option textarea button".split())
_FRAME = frozenset("nav footer aside form dialog menu".split())
_BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html li main menu nav ol p pre section summary table tbody td tfoot th thead title tr ul".split()
)
_RAW = frozenset("script style textarea title noscript template iframe".split())
_NAMED = r"(?:^|[\s_-])(?:{})(?:$|[\s_-])"
_SURE = re.compile(
    _NAMED.format(
        r"ads?|adverts?|advert\w+|adsense|banners?|sponsor\w*|nav|navbar|navigation|menus?|breadcrumbs?|sidebar|footer|masthead|site-header|page-header|topbar|"
        r"comments?|commentlist|disqus|respond|repl(?:y|ies)|share|sharing|newsletter|subscribe|subscription|signup|login|cookies?|consent|gdpr|notices?|popup|modal|toolbar|pagination|pager"
    ),
    re.I,
)
_MAYBE = re.compile(_NAMED.format(r"promo\w*|related|recommend\w*|side|social|search|alerts?|widgets?|copyright|legal|disclaimer"), re.I)
_FRAME_ROLE = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar toolbar".split())
_CONTENT_NAME = re.compile(_NAMED.format("content|main|post|entry|story|article|article-body|post-body|page-body"), re.I)
#: What an opening tag ends.
_ENDS = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_PARAGRAPH_ENDS = _BLOCK - {"body", "html", "tbody", "td", "tfoot", "th", "thead", "tr"}

#: What mark-up says of a block: text, no doubt about frame, perhaps frame; kind of container it stands in.
SURE, MAYBE = 2, 1
ARTICLE, MAIN, CONTENT = 3, 2, 1


def _tags(html: str) -> Iterator[tuple[str, bool, str, str]]:
    """(text before, closing, tag, attributes); the last has no tag.  No character is scanned for more than one tag
    that does not end: beyond the last ``>`` nothing is a tag."""
    at, look, last = 0, 0, html.rfind(">")
    while (low := html.find("<", look)) >= 0 and low < last:
        if html.startswith("<!--", low):
            end = html.find("-->", low + 4)
            yield html[at:low], False, "", ""
            at = look = len(html) if end < 0 else end + 3
            continue
        m = _TAG.match(html, low)
        if not m:
            look = low + 1
            continue
        tag = (m[2] or m[5] or "").lower()
        closing = bool(m[1] or m[4])
        yield html[at:low], closing, tag, m[3] or m[6] or ""
        at = look = m.end()
        if tag in _RAW and not closing:
            end = re.compile(rf"</{tag}\b[^>]*+>?", re.I).search(html, at)
            at = look = end.end() if end else len(html)
    yield re.sub(r"<(?:[a-zA-Z/?]|!(?!--))[^>]*\Z|<!--.*\Z", "", html[at:], count=1, flags=re.S), False, "", ""


def blocks(html: str | None) -> list[tuple[int, int, str]]:
    """(frame: 0, ``MAYBE`` or ``SURE``; nearest kind of container; text) of each block with text."""
    out: list[tuple[int, int, str]] = []
    held: list[str] = []
    stack: list[tuple[str, bool, int, int]] = []  # tag, hidden, frame, container
    opened: Counter[str] = Counter()
    state = (False, 0, 0)

    def flush() -> None:
        if held:
            text = " ".join(unescape("".join(held)).split())
            held.clear()
            if text:
                out.append((state[1], state[2], text))

    def pop_to(tags: set[str] | frozenset[str], stop: frozenset[str]) -> None:
        nonlocal state
        if not any(opened[t] for t in tags):
            return  # so a long stack is not searched in vain
        for k in range(len(stack) - 1, -1, -1):
            if stack[k][0] in tags:
                opened.subtract(x[0] for x in stack[k:])
                del stack[k:]
                state = stack[-1][1:] if stack else (False, 0, 0)
                return
            if stack[k][0] in stop:
                return

    for before, closing, tag, written in _tags(html or ""):
        if before and not state[0]:
            held.append(before)
        if not tag:
            continue
        if tag in _BLOCK:
            flush()
        elif tag in ("br", "img", "wbr", "input"):
            held.append(" ")
        if closing:
            pop_to({tag}, frozenset() if tag in _BLOCK else _BLOCK)
            continue
        if tag in _VOID or tag in _RAW:
            continue
        if tag in _PARAGRAPH_ENDS:
            pop_to({"p"}, _BLOCK - {"p"})
        if tag in _ENDS:
            pop_to(_ENDS[tag], frozenset(("ul", "ol", "dl", "table", "menu", "select")))
        hidden, frame, container = state
        attrs = {k.lower(): unescape(a or b or c) for k, a, b, c in _ATTR.findall(written)} if written.strip(" /") else {}
        name, role = f"{attrs.get('class', '')} {attrs.get('id', '')}", attrs.get("role", "").lower()
        hidden = hidden or tag in _HIDDEN or (tag in _BLOCK and "hidden" in attrs)
        if tag not in ("html", "body", "main"):
            named = 0 if name == " " else SURE if _SURE.search(name) else MAYBE if _MAYBE.search(name) else 0
            sure = tag in _FRAME or role in _FRAME_ROLE or (tag == "header" and container < MAIN)
            frame = max(frame, SURE if sure and tag != "article" else named)
        if frame < SURE:
            content = tag in ("div", "section") and name != " " and _CONTENT_NAME.search(name)
            container = max(container, ARTICLE if tag == "article" else MAIN if tag == "main" or role == "main" else CONTENT if content else 0)
        if written.endswith("/") and tag not in _BLOCK:
            continue
        stack.append((tag, hidden, frame, container))
        opened[tag] += 1
        state = (hidden, frame, container)
    flush()
    return out


def article_level(found: list[tuple[int, int, str]]) -> int:
    """The innermost kind of container that holds half of the text of all containers (0: there are none)."""
    size = [0, 0, 0, 0]
    for frame, container, text in found:
        if frame < SURE:
            for k in range(container + 1):
                size[k] += len(text)
    return next((k for k in (ARTICLE, MAIN, CONTENT) if size[k] and 2 * size[k] >= size[CONTENT]), 0)


def judged(html: str | None) -> tuple[int, list[str], list[int]]:
    """Kind of the article's container, texts of all blocks, and what mark-up says of each (0: article)."""
    found = blocks(html)
    level = article_level(found)
    return level, [t for _, _, t in found], [SURE if c < level else f for f, c, _ in found]


def suffix_ranks(stream: np.ndarray, length: int) -> np.ndarray:
    """Rank of each suffix among all, compared by its first ``length`` symbols; equal prefixes share a rank."""
    rank = np.unique(stream, return_inverse=True)[1].astype(np.int64)
    done = 1
    while done < length:
        step = min(done, length - done)
        second = np.append(rank[step:], np.full(min(step, len(rank)), -1))[: len(rank)]
        rank = np.unique(rank * (len(rank) + 2) + second + 1, return_inverse=True)[1].astype(np.int64)
        done += step
    return rank


def _distinct_pages(rank: np.ndarray, page: np.ndarray) -> np.ndarray:
    """For each suffix, on how many pages its run stands."""
    both = _distinct(rank * (int(page.max(initial=0)) + 1) + page)
    return np.bincount(both // (int(page.max(initial=0)) + 1), minlength=int(rank.max(initial=0)) + 1)[rank]


def _distinct(values: np.ndarray) -> np.ndarray:
    """Rising; sorting is far quicker here than the hashing of :func:`numpy.unique`."""
    values = np.sort(values)
    return values[np.append(True, values[1:] != values[:-1])] if len(values) else values


def _spread(starts: np.ndarray, length: int) -> np.ndarray:
    """Which tokens are covered by runs beginning where ``starts`` holds."""
    total = np.append(0, np.cumsum(starts))
    at = np.arange(1, len(starts) + 1)
    return total[at] > total[np.maximum(at - length, 0)]


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return h ^ (h >> np.uint64(29))


def page_classes(rank: np.ndarray, own: np.ndarray, page: np.ndarray, n: int) -> np.ndarray:
    """A class for each page; copies share it.  ``rank``: short runs of the stream; ``own``: where they lie in article text."""
    rng = np.random.default_rng(3)
    values = rng.permutation(int(rank.max(initial=0)) + 1).astype(np.uint64)[rank]
    salts = rng.integers(0, 2**63, BANDS * ROWS, dtype=np.uint64) | np.uint64(1)
    bounds = np.searchsorted(page, np.arange(n + 1))
    up, first, bodies, sets = np.arange(n), {}, {}, {}
    # a page that agrees with another to COPY shares as large a part of its distinct runs with some page
    size = int(rank.max(initial=0)) + 1
    pairs = _distinct(page[own] * size + rank[own])
    holders = np.bincount(pairs % size, minlength=size)
    runs, common = np.bincount(pairs // size, minlength=n), np.bincount(pairs[holders[pairs % size] >= 2] // size, minlength=n)
    signs = np.zeros((n, BANDS * ROWS), np.uint64)
    for k in np.flatnonzero((runs > 0) & (common >= COPY * runs)).tolist():  # pages without article text are no copies
        mine = values[bounds[k] : bounds[k + 1]][own[bounds[k] : bounds[k + 1]]]
        up[k] = bodies.setdefault(mine.tobytes(), k)
        if up[k] == k:
            sets[k] = mine = _distinct(mine)
            signs[k] = np.min([_mixed(mine[at : at + 4096, None] * salts[0] + salts).min(0) for at in range(0, len(mine), 4096)], axis=0)
    exact = up.copy()

    def root(k: int) -> int:
        while up[k] != k:
            k = up[k]
        return k

    for k in sets:
        for band, sign in enumerate(signs[k].reshape(BANDS, ROWS)):
            other = first.setdefault((band, sign.tobytes()), k)
            if (a := root(other)) != (b := root(k)):
                common = len(np.intersect1d(sets[other], sets[k], assume_unique=True))
                if common >= COPY * (len(sets[other]) + len(sets[k]) - common):
                    up[max(a, b)] = min(a, b)
    near = np.array([root(k) for k in range(n)], np.int64)
    leads = np.flatnonzero(exact == np.arange(n))
    if len(leads) >= TEMPLATE and 2 * np.bincount(near[leads]).max() > len(leads):
        return exact
    return near


class Stream:
    """Pages given by :func:`judged` as one stream of token numbers with a break after each page."""

    def __init__(self, pages: list[tuple[int, list[str], list[int]]], markup: bool):
        words = pc.split_pattern(pa.array([t for _, texts, _ in pages for t in texts], pa.large_string()), " ")
        tokens = words.flatten().dictionary_encode()
        counts, number = np.diff(words.offsets.to_numpy()), np.array([len(texts) for _, texts, _ in pages], np.int64)
        self.counts = counts.tolist()  # tokens of each block
        ends = np.append(0, np.cumsum(counts))[np.cumsum(number)] if len(pages) else number
        sizes = np.diff(ends, prepend=0)
        total = int(sizes.sum()) + len(pages)
        self.page = np.repeat(np.arange(len(pages)), sizes + 1)
        self.starts = (ends - sizes + np.arange(len(pages))).tolist()
        breaks = ends + np.arange(len(pages))
        text = np.ones(total, bool)
        text[breaks] = False
        self.ids, self.own = np.empty(total, np.int64), np.zeros(total, bool)
        self.ids[text] = tokens.indices.to_numpy()
        self.ids[breaks] = -1 - np.arange(len(pages))  # the break differs for each page, so no run crosses it
        self.own[text] = np.repeat(np.array([not markup or f < SURE for _, _, frames in pages for f in frames], bool), counts)
        self.distinct = tokens.dictionary
        self.left = np.append(breaks[self.page] - np.arange(total), 0)[:total]  # tokens up to the break

    def keys(self, length: int) -> np.ndarray:
        """Hash of the run that begins at each token; where the break is nearer, of no meaning."""
        words = np.append(self.distinct.to_numpy(zero_copy_only=False), "")
        token = pd.util.hash_array(words, categorize=False)[np.maximum(self.ids, -1)]
        padded, out = np.append(token, np.zeros(length, np.uint64)), np.zeros(len(token), np.uint64)
        for j in range(length):
            out = out * np.uint64(0xD6E8FEB86659FD93) + padded[j : j + len(token)]
        return _mixed(out)


def _marked(page: tuple[int, list[str], list[int]], markup: bool) -> str:
    """Main text of a page none of whose runs stands elsewhere."""
    return "\n".join([t for t, frame in zip(page[1], page[2], strict=True) if not markup or frame < SURE])


def _cut(pages: list[tuple[int, list[str], list[int]]], stream: Stream, holders: np.ndarray, classes: np.ndarray, length: int, markup: bool) -> list[str]:
    """Main texts, by the number of classes of the host's pages that hold the run at each token, and the number of all its classes."""
    frequent = lambda ratio: (holders >= MIN_PAGES) & (holders > ratio * classes)
    often, two, most = frequent(MAX_RATIO), _spread(holders >= 2, length), _spread(frequent(MARKED_RATIO), length)
    touched, out, counts = np.bincount(stream.page[two], minlength=len(pages)) > 0, [], iter(stream.counts)
    for k, (_, texts, frames) in enumerate(pages):
        own = list(itertools.islice(counts, len(texts)))
        if not touched[k]:
            out.append(_marked(pages[k], markup))
            continue
        at, level, rest = stream.starts[k], pages[k][0] if markup else 0, []
        for text, n, frame in zip(texts, own, frames, strict=True):
            span = slice(at, at + n)
            at += n
            if markup and frame == SURE:
                continue
            a = two[span]
            if (n >= length and most[span].all()) or (level < MAIN and a.all()) or (markup and frame == MAYBE and 2 * a.sum() > n):
                continue
            if level < MAIN and often[span].any():
                # inside a block that stays only frequent runs are cut, and those that lie in it whole
                first = _spread(np.append(often[span][: max(0, n - length + 1)], np.zeros(min(length - 1, n), bool)), length)
                text = " ".join([x for x, gone in zip(text.split(" "), first, strict=True) if not gone])
            rest.append(text)
        out.append("\n".join(x for x in rest if x))
    return out


def kept_texts(pages: list[tuple[int, list[str], list[int]]], length: int = MIN_RUN, markup: bool = True) -> list[str]:
    """Main texts of a host's pages that fit in memory, each given by :func:`judged`; without ``markup`` runs alone decide."""
    stream = Stream(pages, markup)
    if len(stream.ids) == len(pages):
        return [""] * len(pages)
    short = suffix_ranks(stream.ids, COPY_RUN)
    cls = page_classes(short, stream.own & (stream.left >= COPY_RUN), stream.page, len(pages))
    rank, whole = suffix_ranks(stream.ids, length), stream.left >= length
    holders = np.where(whole, _distinct_pages(np.where(whole, rank, rank.max() + 1 + np.arange(len(rank))), cls[stream.page]), 0)
    return _cut(pages, stream, holders, np.full(len(holders), len(np.unique(cls))), length, markup)


def _hashed(*parts: bytes) -> int:
    return int.from_bytes(hashlib.blake2b(b"\0".join(parts), digest_size=8).digest(), "little", signed=True)


def _zipped(value: Any) -> bytes:
    return zstandard.compress(pickle.dumps(value, 5))


def _unzipped(data: bytes) -> Any:
    return pickle.loads(zstandard.decompress(data))


def _each(batch: pa.RecordBatch) -> Iterator[tuple]:
    """The rows of a batch, one at a time, since each may be large."""
    return (tuple(c[k].as_py() for c in batch.columns) for k in range(batch.num_rows))


def _packed(keys: np.ndarray) -> bytes:
    """Rising keys as differences, byte by byte, so that the high bytes, which are zero, cost nothing."""
    steps = np.diff(keys, prepend=np.uint64(0)).astype("<u8")
    return zstandard.compress(np.ascontiguousarray(steps.view(np.uint8).reshape(-1, 8).T).tobytes())


def _unpacked(data: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.decompress(data), np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view("<u8")[:, 0], dtype=np.uint64)


class Bundle:
    """Pages of any hosts: (page_id, url, uid, hash of the host, judged page) each."""

    def __init__(self, rows: list[tuple[int | None, str | None, int, int, tuple[int, list[str], list[int]]]], length: int, markup: bool):
        self.rows, self.length, self.judged = rows, length, [r[4] for r in rows]
        self.stream = Stream(self.judged, markup)
        self.hosts = np.array([r[3] for r in rows], np.int64).view(np.uint64)
        self.whole = self.stream.left >= length

    def keys(self) -> np.ndarray:
        return _mixed(self.stream.keys(self.length) + self.hosts[self.stream.page])

    def runs(self) -> tuple[np.ndarray, np.ndarray]:
        """(key, page) of each suffix that is whole; sorted by key, equal runs of a host are neighbours."""
        return self.keys()[self.whole], self.stream.page[self.whole]

    def signs(self) -> tuple[list[int | None], list[list[int]]]:
        """For each page a hash of its article's runs of ``COPY_RUN`` tokens in order (null: it has none), and its MinHash bands."""
        articles: list[int | None] = []
        signs, has = np.zeros((len(self.rows), BANDS * ROWS), np.uint64), np.zeros(len(self.rows), bool)
        for k, runs in enumerate(self.article_runs()):
            articles.append(_hashed(self.hosts[k].tobytes(), runs.tobytes()) if len(runs) else None)
            if len(runs):
                signs[k], has[k] = np.min([_sampled(runs[at : at + 4096]) for at in range(0, len(runs), 4096)], axis=0), True
        bands = self.hosts[:, None] + np.arange(1, BANDS + 1, dtype=np.uint64)
        for j in range(ROWS):
            bands = _mixed(bands * np.uint64(0xD6E8FEB86659FD93) + signs[:, j::ROWS] + np.uint64(1))
        return articles, [x if y else [] for x, y in zip(bands.view(np.int64).tolist(), has.tolist(), strict=True)]

    def article_runs(self) -> Iterator[np.ndarray]:
        keys, own = self.stream.keys(COPY_RUN), self.stream.own & (self.stream.left >= COPY_RUN)
        bounds = np.searchsorted(self.stream.page, np.arange(len(self.rows) + 1))
        for k in range(len(self.rows)):
            yield keys[bounds[k] : bounds[k + 1]][own[bounds[k] : bounds[k + 1]]]


_SALTS = np.random.default_rng(3).integers(0, 2**32, (2, BANDS * ROWS), dtype=np.uint32) | np.uint32(1)


def _sampled(runs: np.ndarray) -> np.ndarray:
    """The least hash of the runs under each of the functions of MinHash."""
    h = (runs >> np.uint64(32)).astype(np.uint32)[:, None] * _SALTS[0]
    h ^= h >> np.uint32(15)
    h *= _SALTS[1]
    h ^= h >> np.uint32(13)
    return h.min(0)


def _by_share(keys: np.ndarray, share_bits: int, bits: int) -> list[tuple[int, slice]]:
    """Shares of rising keys of ``bits`` bits, by their first ``share_bits``, and where each lies."""
    share = (keys >> np.uint64(bits - share_bits)).astype(np.int64)
    names, starts = np.unique(share, return_index=True)
    return [(int(s), slice(a, b)) for s, a, b in zip(names, starts, [*starts[1:], len(keys)], strict=True)] if len(keys) else []


def _in_doubt(page: tuple[int, list[str], list[int]], markup: bool) -> bool:
    """Whether runs of two pages can decide anything on a page: where an article vouches for blocks only those of most pages can."""
    return bool(page[1]) if not markup else any(f < SURE and (f == MAYBE or page[0] < MAIN) for f in page[2])


def _lists(rows: DataFrame, key: str, name: str, *columns: str) -> DataFrame:
    return rows.groupBy(key).agg(F.collect_list(F.struct(*columns)).alias(name)).withColumnRenamed(key, "__" + key)


def _attached(bundles: DataFrame, lists: DataFrame, row_bytes: Column) -> DataFrame:
    return attach(bundles, lists, "bundle", "__bundle", row_bytes)


def _data_bytes(name: str) -> Column:
    return F.expr(f"aggregate({name}, 0L, (n, r) -> n + 32 + length(r.data))")


def _classes(pages: DataFrame, bundles: DataFrame, length: int, markup: bool) -> DataFrame:
    """(__bundle, copies, hosts) of pages (bundle, page, host, article, bands, doubt).  ``copies``: (page, class) of the pages that
    have copies on their host, which share a class.  ``hosts``: what the bundle has to know of its pages' hosts, those left
    out on which no run can decide: how many classes there are; whether a page is in doubt (its runs are then compared
    one by one); and else the most classes of the bundle that a run may stand on without being named, by how many more in
    all it must stand on to be counted, and the number of parts that its runs are dealt into."""
    leads = materialize(pages.where("article IS NOT NULL").groupBy("article").agg(F.min(F.struct("bundle", "page")).alias("at"), F.first("host").alias("host"), F.first("bands").alias("bands"), F.count("*").alias("n")))
    banded = leads.select("article", F.explode("bands").alias("band"))
    firsts = banded.groupBy("band").agg(F.min("article").alias("a"), F.count("*").alias("n")).where("n > 1").select(F.col("band").alias("__band"), "a")
    pairs = materialize(attach(banded, firsts, "band", "__band", 32).where("a < article").select("a", F.col("article").alias("b")).distinct())

    asked = leads.join(pairs.select(F.explode(F.array("a", "b")).alias("article")).distinct(), "article").select("article", "at.bundle", "at.page")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data, wanted in _each(batch):
                held = _unzipped(data)
                bundle = Bundle([held[w["page"]] for w in wanted], length, markup)
                found = [_distinct((x >> np.uint64(32)).astype(np.uint32)).view(np.int32) for x in bundle.article_runs()]  # 32 bits tell a pair's runs apart
                yield pa.RecordBatch.from_arrays([pa.array([w["article"] for w in wanted], pa.int64()), pa.array(found, pa.list_(pa.int32()))], names=["node", "shingles"])

    full = _attached(bundles, _lists(asked, "bundle", "wanted", "article", "page"), F.size("wanted") * 64).where("wanted IS NOT NULL").select("data", "wanted").mapInArrow(sets, "node long, shingles array<int>")
    near = components(_confirmed(pairs, materialize(full), COPY))
    named = leads.select("article", "host", "n").join(near, leads["article"] == near["node"], "left").withColumn("near", F.coalesce("comp", "article")).drop("node", "comp")
    sizes = named.groupBy("host", "near").count().groupBy("host").agg(F.sum("count").alias("leads"), F.max("count").alias("most"))
    template = sizes.where(f"leads >= {TEMPLATE} AND 2 * most > leads").select(F.col("host").alias("__host"), F.lit(True).alias("template"))
    named = materialize(attach(named, template, "host", "__host", 16).withColumn("class", F.when(F.col("template"), F.col("article")).otherwise(F.col("near"))))
    counted = named.groupBy("host", "class").agg(F.sum("n").alias("n"))
    alone = pages.where("article IS NULL").groupBy("host").agg(F.count("*").alias("k"))
    classes = counted.groupBy("host").agg(F.count("*").alias("k")).union(alone).groupBy("host").agg(F.sum("k").alias("classes")).withColumnRenamed("host", "__host")
    copies = named.join(counted.where("n > 1").select("class"), "class").select(F.col("article").alias("__article"), "class")
    told = materialize(attach(pages.select("bundle", "page", "host", "article", "doubt"), copies, "article", "__article", 32).drop("article"))
    local = materialize(told.groupBy("bundle", "host").agg((F.count_if(F.isnull("class")) + F.count_distinct("class")).alias("here"), F.bool_or("doubt").alias("doubt")))
    # a run of over half of the host's classes stands, in some bundle, on over that part of the bundle's (those of several bundles count in each)
    every = local.groupBy("host").agg(F.sum("here").alias("sum"), F.count("*").alias("bundles"), F.bool_or("doubt").alias("doubted")).withColumnRenamed("host", "__host")
    every = materialize(every.join(classes, "__host").where(f"doubted OR classes >= {MIN_PAGES}"))
    unnamed = F.expr("here * classes div (2 * sum)")
    known = materialize(attach(local, every, "host", "__host", 48).where("classes IS NOT NULL").withColumn("unnamed", unnamed))
    most = known.groupBy("host").agg(F.sum("unnamed").alias("most")).withColumnRenamed("host", "__host")
    lacking = F.greatest(F.expr("classes div 2 + 1"), F.lit(MIN_PAGES)) - F.col("most")
    known = attach(known, most, "host", "__host", 24).withColumn("lacking", lacking).withColumn("parts", F.ceil(F.col("bundles") / 256))
    hosts = _lists(known, "bundle", "hosts", "host", "classes", F.col("doubted").alias("doubt"), "unnamed", "lacking", "parts")
    return materialize(hosts.join(_lists(told.where("class IS NOT NULL"), "bundle", "copies", "page", "class"), "__bundle", "left"))


def main_text(pages: DataFrame, length: int = MIN_RUN, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", markup: bool = True) -> DataFrame:
    """(page_id, url, text), one row a page; without ``markup`` the host's runs decide alone."""
    url, html = F.col(url_col).cast("string"), F.col(html_col)
    host = F.coalesce(F.lower(F.regexp_extract(url, _HOST, 1)), F.lit(""))
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), url.alias("url"), html.alias("html"), host.alias("host"), F.xxhash64(id_col, url, html).alias("uid"))
    sizes = materialize(rows.select("uid", F.coalesce(F.length("html"), F.lit(0)).alias("size")))
    repeated = not sizes.groupBy("uid").count().where("count > 1").isEmpty()
    chars = sizes.agg(F.sum("size")).first()[0] or 0
    share_bits = max(6, math.ceil(math.log2(chars / SHARE_CHARS + 1)))
    bits = min(64, max(share_bits + 8, math.ceil(math.log2(chars + 1)) + 2))  # of a cell: how many, only tells how many runs are counted in vain
    limit = GROUP_CHARS

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0

        def full() -> pa.RecordBatch:
            bundle = Bundle(held, length, markup)
            articles, bands = bundle.signs()
            told = [{"host": r[3], "article": a, "bands": b, "doubt": _in_doubt(r[4], markup)} for r, a, b in zip(held, articles, bands, strict=True)]
            one = {"bundle": [held[0][2]], "data": [_zipped(held)], "pages": [told]}
            return pa.RecordBatch.from_pydict(one, schema=_BUNDLE)

        for batch in batches:
            for page_id, url, html, host, uid in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                held.append((page_id, url, uid, _hashed(host.encode(errors="surrogatepass")), judged(html)))
                size += len(html or "")
                if size >= limit:
                    yield full()
                    held, size = [], 0
        if held:
            yield full()

    def those(data: bytes, names: set[int]) -> tuple[Bundle, list[int]]:
        """The pages of these hosts, and their numbers in the bundle."""
        held = _unzipped(data)
        chosen = [k for k, r in enumerate(held) if r[3] in names]
        return Bundle([held[k] for k in chosen], length, markup), chosen

    def class_of(chosen: list[int], copies: list[dict] | None) -> tuple[np.ndarray, np.ndarray]:
        """Classes of pages, and whether they have copies at all."""
        known = {c["page"]: c["class"] for c in copies or []}
        return np.array([known.get(k, 0) for k in chosen], np.int64), np.array([k in known for k in chosen], bool)

    def cells_in_doubt(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, data, hosts in _each(batch):
                bundle, _ = those(data, {h["host"] for h in hosts if h["doubt"]})
                cells = _distinct(bundle.runs()[0] >> np.uint64(64 - bits))
                yield pa.RecordBatch.from_pylist([{"bundle": name, "share": s, "data": _packed(cells[at])} for s, at in _by_share(cells, share_bits, bits)], schema=_SHARE)

    def common(pdf: pd.DataFrame) -> pd.DataFrame:
        cells = [_unpacked(x) for x in pdf["data"]]
        every, n = np.unique(np.concatenate(cells), return_counts=True)
        found = [np.packbits(n[np.searchsorted(every, x)] > 1) for x in cells]
        return pdf[["bundle", "share"]].assign(data=[zstandard.compress(x.tobytes()) if x.any() else None for x in found]).dropna()

    def cells_of_many(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Cells of runs on so many of a bundle's classes that they may stand on over half of the host's, and on how many beyond ``unnamed``."""
        for batch in batches:
            for data, hosts, copies in _each(batch):
                known = [h for h in hosts if not h["doubt"]]
                place = {h["host"]: i for i, h in enumerate(known)}
                bundle, chosen = those(data, set(place))
                cls, copy = class_of(chosen, copies)
                number = np.where(copy, np.unique(cls, return_inverse=True)[1], len(chosen) + np.arange(len(chosen)))
                of = np.array([place[r[3]] for r in bundle.rows], np.int64)
                unnamed = np.array([h["unnamed"] for h in known], np.int64)
                keys, page = bundle.runs()
                every, cell, times = np.unique(keys >> np.uint64(64 - bits), return_inverse=True, return_counts=True)
                some = times[cell] > unnamed[of[page]]
                cell, page = cell[some], page[some]
                both = _distinct((of[page] * len(every) + cell) * (2 * len(chosen)) + number[page])
                both, n = np.unique(both // (2 * len(chosen)), return_counts=True)
                of, cell = both // max(1, len(every)), every[both % max(1, len(every))]
                beyond = n - unnamed[of]
                of, cell, beyond = of[beyond > 0], cell[beyond > 0], beyond[beyond > 0]
                bounds, out = np.searchsorted(of, np.arange(len(known) + 1)), []
                for h, a, b in zip(known, bounds, bounds[1:]):
                    part = cell[a:b] % np.uint64(h["parts"])
                    for p in range(h["parts"] if b > a else 0):
                        mine = part == p
                        if mine.any():
                            out.append({"host": h["host"], "part": p, "lacking": h["lacking"], "data": _zipped((_packed(cell[a:b][mine]), beyond[a:b][mine].astype(np.int32)))})
                yield pa.RecordBatch.from_pylist(out, schema=_MANY)

    def summed(pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        for (host, _), rows in pdf.groupby(["host", "part"]):
            parts = [_unzipped(x) for x in rows["data"]]
            every, place = np.unique(np.concatenate([_unpacked(x) for x, _ in parts]), return_inverse=True)
            enough = every[np.bincount(place, np.concatenate([n for _, n in parts]), len(every)) >= rows["lacking"].iloc[0]]
            if len(enough):
                out.append((host, _packed(enough)))
        return pd.DataFrame(out, columns=["host", "data"])

    def candidates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, data, replies, many, hosts, copies in _each(batch):
                doubt = {h["host"] for h in hosts if h["doubt"]}
                bundle, chosen = those(data, doubt | {m["host"] for m in many or []})
                keys, page = bundle.runs()
                cells = keys >> np.uint64(64 - bits)
                in_doubt = np.array([r[3] in doubt for r in bundle.rows], bool)[page]
                cell, times = np.unique(cells[in_doubt], return_counts=True)
                asked = times > 1
                where = dict(_by_share(cell, share_bits, bits))
                for r in replies or []:
                    part = asked[where[r["share"]]]
                    part |= np.unpackbits(np.frombuffer(zstandard.decompress(r["data"]), np.uint8), count=len(part)).astype(bool)
                common_cells = _distinct(np.concatenate([cell[asked], *[_unpacked(m["data"]) for m in many or []]]))
                if not len(common_cells):
                    continue
                at = np.minimum(np.searchsorted(common_cells, cells), len(common_cells) - 1)
                some = common_cells[at] == cells
                keys, stretch = np.unique(keys[some], return_inverse=True)
                n = len(bundle.rows)
                both = _distinct(stretch * n + page[some])
                stretch, page = both // n, both % n
                cls, copy = class_of(chosen, copies)
                single = np.bincount(stretch[~copy[page]], minlength=len(keys)).astype(np.int32)
                names, number = np.unique(cls, return_inverse=True)
                held = _distinct(stretch[copy[page]] * len(names) + number[page[copy[page]]])
                of, cls = held // len(names), names[held % len(names)]
                out = []
                for s, at in _by_share(keys, share_bits, 64):
                    a, b = np.searchsorted(of, [at.start, at.stop])
                    out.append({"bundle": name, "share": s, "data": _zipped((_packed(keys[at]), single[at], (of[a:b] - at.start).astype(np.int32), cls[a:b]))})
                yield pa.RecordBatch.from_pylist(out, schema=_SHARE)

    def counted(pdf: pd.DataFrame) -> pd.DataFrame:
        parts = [_unzipped(x) for x in pdf["data"]]
        keys = [_unpacked(x[0]) for x in parts]
        every = _distinct(np.concatenate(keys))
        place = [np.searchsorted(every, x) for x in keys]
        total = np.bincount(np.concatenate(place), np.concatenate([x[1] for x in parts]), len(every)).astype(np.int64)
        names, number = np.unique(np.concatenate([x[3] for x in parts]), return_inverse=True)
        if len(names):
            held = _distinct(np.concatenate([p[x[2]] for p, x in zip(place, parts, strict=True)]) * len(names) + number)
            total += np.bincount(held // len(names), minlength=len(every))
        found = [(k[total[p] > 1], total[p][total[p] > 1]) for k, p in zip(keys, place, strict=True)]
        return pdf[["bundle", "share"]].assign(data=[_zipped((_packed(k), n)) if len(k) else None for k, n in found]).dropna()

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data, replies, hosts in _each(batch):
                rows = _unzipped(data)
                if replies:
                    bundle = Bundle(rows, length, markup)
                    parts = [_unzipped(r["data"]) for r in sorted(replies, key=lambda r: r["share"])]
                    shared, n = np.concatenate([_unpacked(k) for k, _ in parts]), np.concatenate([n for _, n in parts])
                    keys = bundle.keys()
                    place = np.minimum(np.searchsorted(shared, keys), len(shared) - 1)
                    holders = np.where(bundle.whole & (shared[place] == keys), n[place], 0)
                    known = {h["host"]: h["classes"] for h in hosts}
                    classes = np.array([known.get(r[3], 0) for r in rows], np.int64)
                    texts = _cut(bundle.judged, bundle.stream, holders, classes[bundle.stream.page], length, markup)
                else:
                    texts = [_marked(r[4], markup) for r in rows]
                ids, urls, uids = list(zip(*[r[:3] for r in rows], strict=True))
                yield pa.RecordBatch.from_pydict({"page_id": ids, "url": urls, "uid": uids, "text": texts}, schema=_TEXTS)

    distinct = rows.dropDuplicates(["uid"]) if repeated else rows
    bundles = materialize(distinct.select("page_id", "url", "html", "host", "uid").mapInArrow(read, "bundle long, data binary, pages array<struct<host: long, article: long, bands: array<long>, doubt: boolean>>"))
    share = "bundle long, share int, data binary"
    stored = bundles.select("bundle", "data")
    told = _classes(bundles.select("bundle", F.posexplode("pages").alias("page", "p")).select("bundle", "page", "p.*"), stored, length, markup)
    known = _attached(stored, told, F.size("hosts") * 64 + F.coalesce(F.size("copies"), F.lit(0)) * 24)
    in_doubt, others = F.exists("hosts", lambda h: h["doubt"]), F.exists("hosts", lambda h: ~h["doubt"])
    cells = known.where(in_doubt).select("bundle", "data", "hosts").mapInArrow(cells_in_doubt, share).groupBy("share").applyInPandas(common, share)
    named = known.where(others).select("data", "hosts", "copies").mapInArrow(cells_of_many, "host long, part int, lacking long, data binary")
    many = named.groupBy(F.pmod(F.xxhash64("host", "part"), F.lit(1 << share_bits)).alias("share")).applyInPandas(summed, "host long, data binary")
    many = told.select("__bundle", F.explode("hosts.host").alias("host")).join(materialize(many), "host").withColumnRenamed("__bundle", "bundle")
    asked = _attached(_attached(known, _lists(cells, "bundle", "replies", "share", "data"), _data_bytes("replies")), _lists(many, "bundle", "many", "host", "data"), _data_bytes("many"))
    asked = asked.where(in_doubt | F.isnotnull("many")).select("bundle", "data", "replies", "many", "hosts", "copies").mapInArrow(candidates, share)
    replies = asked.groupBy("share").applyInPandas(counted, share)
    found = _attached(known, _lists(replies, "bundle", "replies", "share", "data"), _data_bytes("replies")).select("data", "replies", "hosts").mapInArrow(keep, "page_id long, url string, uid long, text string")
    if repeated:
        found = rows.select("page_id", "url", "uid").join(found.select("uid", "text"), "uid")
    return found.select("page_id", "url", "text")


_SHARE = pa.schema([("bundle", pa.int64()), ("share", pa.int32()), ("data", pa.binary())])
_MANY = pa.schema([("host", pa.int64()), ("part", pa.int32()), ("lacking", pa.int64()), ("data", pa.binary())])
_TEXTS = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("uid", pa.int64()), ("text", pa.string())])
_BUNDLE = pa.schema(
    [
        ("bundle", pa.int64()),
        ("data", pa.binary()),
        ("pages", pa.list_(pa.struct([("host", pa.int64()), ("article", pa.int64()), ("bands", pa.list_(pa.int64())), ("doubt", pa.bool_())]))),
    ]
)
