from __future__ import annotations

import collections
import pathlib
import random
import re
import time

import numpy as np
import pytest

from tokenlink.llm import html, scratch
from tokenlink.llm.scratch import table

def prose(seed, n):
    rng = random.Random(seed)
    return " ".join("".join(rng.choice("bdfgklmnprst") + rng.choice("aeiou") for _ in range(3)) for _ in range(n))


PAGE = """<!DOCTYPE html><html><head><title>T</title><script>var t="</p>";</script></head><body><nav><a>Home</a></nav>
<div class="ad">Buy &amp; sell</div><article><h1>Title &amp;amp</h1><p><b>One  two<br>three<p>Four&nbsp;five</p><div class="comments"><p>First!</p></div><form>Mail <input></form><ul><li>x<li>y</ul></article><aside>more</aside><footer>&copy; us</footer>"""


def texts_of(spark, pages, **options):
    frame = spark.createDataFrame(pages, "page_id long, url string, html string")
    return {r["page_id"]: r["text"] for r in html.main_text(frame, **options).collect()}


@pytest.mark.parametrize(
    ("page", "text"),
    [
        (PAGE, "Title &amp\nOne two three\nFour five\nx\ny"),
        ("<p>a</p>tail <b>b", "a\ntail b"),
        ("a < b & c", "a < b & c"),
        (None, ""),
        ("", ""),
        ("a <!-- x --> b <!-- c", "a b"),
        # a teaser in the main part is not the article; class names that only sound like frame need the host's word
        ("<main><h1>T</h1><p>body of the text</p><article class=card>teaser</article></main>", "T\nbody of the text\nteaser"),
        ("<main>x<article><p>the article itself is longer</article></main>", "the article itself is longer"),
        ("<article><p class=legal>law</p><p class='post hidden '>a</p><math><mi>x</mi></math><p hidden>no</p><div id=related-work>b</div></article>", "law\na\nx\nb"),
    ],
)
def test_page(page, text):
    assert html.kept_texts([html.judged(page)]) == [text]


def test_long_pages_are_read_in_linear_time():
    began = time.time()
    for page in ("<a " * 3_000_000, "<a " * 3_000_000 + ">", "<! " * 3_000_000, "<a '" * 2_000_000, "<p " + "a" * 5_000_000 + ">", "<div>" * 100_000 + "</p>" * 100_000, "<!--" * 1_000_000):
        html.blocks(page)
    assert time.time() - began < 60


def test_html_unmarked_hosts(spark):
    """Runs that two pages of a host share go; what is unique stays; other hosts do not matter."""
    menu = "welcome to our site please read our very long terms of use"
    pages = [(i, f"http://h{i % 2}.example/{i}", f"<body><div>{menu if i % 2 else menu.replace('our', str(i))}</div><p>story number {i} tells {i * 7} things about topic {i * 13} alone</p></body>") for i in range(40)]
    got = {r["page_id"]: r["text"] for r in html.main_text(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    for i in range(40):
        own = f"story number {i} tells {i * 7} things about topic {i * 13} alone"
        assert got[i] == (own if i % 2 else f"{menu.replace('our', str(i))}\n{own}")


@pytest.mark.parametrize(
    "mark", ["<article>{}</article>", "<div id=content>{}</div>", "<div class='post main'>{}</div>", "<div>{}</div>"],
)
def test_html_repeated_within_marked(spark, mark):
    """A notice that a host repeats inside its articles goes; copies, edited copies and rare quotations stay."""
    notice, quote = prose("notice", 12), prose("quote", 15)
    own = {i: [prose(i, 40), prose(f"end {i}", 30)] for i in range(50)}
    own |= {i: [prose("copy", 60), prose(f"last {i}" if i > 60 else "last", 10)] for i in range(50, 70)}
    own[3][0] += f" {quote} {prose('x', 9)}"
    own[4][0] = f"{prose('y', 9)} {quote} {own[4][0]}"
    pages = [(i, f"http://h.example/{i}", f"<body>{mark.format(''.join(f'<p>{x}</p>' for x in [p[0], notice, p[1]]))}</body>") for i, p in own.items()]
    assert texts_of(spark, pages) == {i: "\n".join(p) for i, p in own.items()}


def test_suffix_ranks():
    rng = np.random.default_rng(5)
    s = rng.integers(0, 3, 200).astype(np.uint64)
    rank = html.suffix_ranks(s, 7)
    prefix = [tuple(s[i : i + 7].tolist()) for i in range(200)]
    order = sorted(set(prefix))
    assert [order.index(p) for p in prefix] == rank.tolist()




def runs_by_hand(pages, length):
    """Brute force over all runs: what stays of pages that no mark-up speaks for, copies being absent."""
    holders = collections.defaultdict(set)
    streams = [[w for b in blocks for w in b.split(" ")] for blocks in pages]
    for k, s in enumerate(streams):
        for i in range(len(s) - length + 1):
            holders[tuple(s[i : i + length])].add(k)
    out = []
    for s, blocks in zip(streams, pages, strict=True):
        covered, at, rest = set(), 0, []
        for i in range(len(s) - length + 1):
            if len(holders[tuple(s[i : i + length])]) >= 2:
                covered |= set(range(i, i + length))
        for b in blocks:
            w = b.split(" ")
            own, at = range(at, at + len(w)), at + len(w)
            if covered.issuperset(own):
                continue
            cut = set()
            for i in range(len(w) - length + 1):
                n = len(holders[tuple(w[i : i + length])])
                if n >= html.MIN_PAGES and n > html.MAX_RATIO * len(pages):
                    cut |= set(range(i, i + length))
            rest.append(" ".join(x for i, x in enumerate(w) if i not in cut))
        out.append("\n".join(x for x in rest if x))
    return out


def test_runs_against_all_runs():
    rng = random.Random(8)
    shared = [prose(f"shared {i}", rng.randint(3, 20)) for i in range(12)]
    for trial in range(20):
        pages = []
        for k in range(rng.randint(2, 60)):
            own = [prose(f"{trial} {k} {i}", rng.randint(20, 40)) for i in range(3)]
            blocks = own + rng.sample(shared, rng.randint(0, 4))
            if rng.random() < 0.5:
                blocks[0] += " " + rng.choice(shared) + " " + prose(f"{trial} {k} tail", 3)
            rng.shuffle(blocks)
            pages.append(blocks)
        got = html.kept_texts([(0, b, [0] * len(b)) for b in pages])
        assert got == runs_by_hand(pages, html.MIN_RUN)


def test_names_in_doubt_need_repetition(spark):
    """A block named ``related`` goes where the host repeats it, and stays where its text is the page's own."""
    for same in (True, False):
        pages = [(i, "http://h.example/", f"<article><p>{prose(i, 30)}</p><div class=related>{prose('links' if same else f'links {i}', 10)}</div></article>") for i in range(10)]
        assert texts_of(spark, pages) == {i: prose(i, 30) + ("" if same else "\n" + prose(f"links {i}", 10)) for i in range(10)}


def test_real_pages(spark):
    """On the given pages: articles whole, and the runs alone, without mark-up, find most of the frame."""
    rows = table(spark, "/root/testdata/sf0.1", "pages").collect()
    got = {r["page_id"]: r["text"] for r in html.main_text(table(spark, "/root/testdata/sf0.1", "pages")).collect()}
    alone = {r["page_id"]: r["text"] for r in html.main_text(table(spark, "/root/testdata/sf0.1", "pages"), markup=False).collect()}
    frame = gone = article = lost = 0
    for r in rows:
        own = re.search(r"<article>(.*?)(?:</article>|\Z)", r["html"], re.S)[1]
        assert got[r["page_id"]] == "\n".join(t for _, _, t in html.blocks(own))
        left = collections.Counter(alone[r["page_id"]].split("\n"))
        _, texts, marks = html.judged(r["html"])
        for t, mark in zip(texts, marks, strict=True):
            n, stays = t.count(" ") + 1, left[t] > 0
            left[t] -= stays
            frame, gone, article, lost = frame + n * (mark > 0), gone + n * (mark > 0 and not stays), article + n * (mark == 0), lost + n * (mark == 0 and not stays)
    assert gone > 0.6 * frame and lost < 0.03 * article


def test_groups_and_repeated_rows(spark, monkeypatch):
    """Hosts cut into groups still lose what every page carries; equal rows share one decision."""
    notice = prose("notice", 12)
    pages = [(i, "http://h.example/", f"<div><p>{notice}</p><p>{prose(i, 30)}</p></div>") for i in range(60)]
    pages += [pages[7]] * 50
    monkeypatch.setattr(html, "GROUP_CHARS", 5000)
    for limit in (64 << 20, -1):
        monkeypatch.setattr(scratch, "BROADCAST_BYTES", limit)
        assert texts_of(spark, pages) == {i: prose(i, 30) for i in range(60)}
    frame = spark.createDataFrame(pages, "page_id long, url string, html string")
    assert html.main_text(frame).count() == 110


def test_the_size_of_a_host_decides_nothing(spark, monkeypatch):
    """Runs and copies are those of the whole host, however few of its pages are read together."""
    rng = random.Random(4)
    rare = [prose(f"rare {i}", 12) for i in range(30)]
    judged, pages = [], []
    for i in range(150):
        own = [prose(f"{i} {k}", rng.randint(10, 40)) for k in range(3)]
        copy = i >= 120  # near copies of ten pages
        blocks = [prose("menu", 14)] * (i % 3 > 0) + ([prose(f"{i % 10} {k} copy", 30) for k in range(4)] + own[:1] if copy else own) + [rare[i % 30]] * (i < 60)
        judged.append((0, blocks, [0] * len(blocks)))
        pages.append((i, "http://h.example/", "".join(f"<p>{x}</p>" for x in blocks)))
    pages += [(1000 + i, f"http://h{i}.example/", page) for i, (_, _, page) in enumerate(pages[:5])]
    for marked in (False, True):
        if marked:
            judged, pages = [(3, b, f) for _, b, f in judged], [(i, u, f"<article>{p}</article>") for i, u, p in pages]
        want = dict(enumerate(html.kept_texts(judged))) | {1000 + i: html.kept_texts(judged[i : i + 1])[0] for i in range(5)}
        for chars in (1 << 20, 4000):
            monkeypatch.setattr(html, "GROUP_CHARS", chars)
            assert texts_of(spark, pages) == want


def test_lines_of_most_pages_are_found_however_pages_are_bundled(spark, monkeypatch):
    """Where articles vouch for their blocks, lines of over half of a host's pages go, even if no bundle holds two of them."""
    rng = random.Random(6)
    hosts = {}
    for h, n in enumerate((2, 3, 5, 24, 60)):
        lines = [(prose(f"line {h} {k}", 10), share) for k, share in enumerate((0.4, 0.5, 0.55, 0.8))]
        hosts[h] = []
        for i in range(n):
            copied = i % 4 == 3  # copies count as one page, wherever they are read
            own = [prose(f"copied {h}", 60)] if copied else [prose(f"{h} {i} {k}", 25) for k in range(2)]
            own += [text for k, (text, share) in enumerate(lines) if (k % 2 if copied else i * 7 % n < share * n)]
            mark = rng.choice(["article", "main"])
            hosts[h].append(f"<nav>{lines[1][0]}</nav><{mark}>{''.join(f'<p>{x}</p>' for x in own)}</{mark}>")
    hosts[4][5] += f"<div class=related>{prose('line 4 0', 10)}</div>"  # a block in doubt: all runs of its host are compared
    pages = [(1000 * h + i, f"http://h{h}.example/", page) for h, found in hosts.items() for i, page in enumerate(found)]
    want = {1000 * h + i: text for h, found in hosts.items() for i, text in enumerate(html.kept_texts([html.judged(p) for p in found]))}
    assert any(want[1000 * h + i] != "\n".join(t for _, _, t in html.blocks(p.split("</nav>")[1])) for h, found in hosts.items() for i, p in enumerate(found))
    rng.shuffle(pages)
    for chars in (1, 3000, 1 << 20):
        monkeypatch.setattr(html, "GROUP_CHARS", chars)
        assert texts_of(spark, pages) == want


def test_runs_that_cannot_decide_are_not_stored(spark, tmp_path):
    """Beside the pages themselves next to nothing is written where articles vouch for their blocks."""
    pages = spark.createDataFrame([(i, f"http://h{i % 3}.example/", f"<article><p>{prose(i, 400)}</p></article>") for i in range(600)], "page_id long, url string, html string").coalesce(1)
    size = lambda path: sum(f.stat().st_size for f in pathlib.Path(path).rglob("*.parquet"))
    pages.write.option("compression", "zstd").parquet(str(tmp_path / "pages"))
    folder = scratch.shared_dir(spark).removeprefix("file:")
    before = size(folder)
    assert html.main_text(spark.read.parquet(str(tmp_path / "pages"))).count() == 600
    assert size(folder) - before < 1.4 * size(tmp_path / "pages")


def test_hashes_of_tokens():
    """Runs are told apart by all their tokens, of whatever script, and the break of a page ends them."""
    stream = html.Stream([(0, ["a b c", "é ü \x00 \U0001f600"], [0, 2]), (0, [], []), (0, ["b c é ü"], [0])], True)
    keys = stream.keys(2)
    assert stream.counts == [3, 4, 4] and stream.starts == [0, 8, 9] and stream.left.tolist() == [7, 6, 5, 4, 3, 2, 1, 0, 0, 4, 3, 2, 1, 0]
    assert stream.own.tolist() == [True] * 3 + [False] * 6 + [True] * 4 + [False]
    assert keys[1] == keys[9] and keys[2] == keys[10] and keys[3] == keys[11] and len(set(keys[:7].tolist())) == 7
