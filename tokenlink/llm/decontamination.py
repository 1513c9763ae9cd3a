"""Benchmark items inside documents, by a randomized embedding of edit distance and bit sampling.

Texts and items are sequences of word codes.  A random walk reads a sequence: at each step it writes the word
it stands on and then, by a random bit drawn for that step and word, moves on or stays.  Two sequences at
edit distance d write the same words but for about d squared steps, so edit distance becomes Hamming
distance.  Each of ``WALKS`` walks samples ``PICKS`` steps; a window and an item that write the same words
there are candidates, and the exact edit distance of the passage around the candidate confirms or refuses them.

The embedding's distortion grows with the number of edits, so items of more than ``PIECE`` words are walked in
pieces of half to all of that length.  If a passage lies within ``ERRORS`` of an item, some piece lies within
``ERRORS`` of its part of the passage (on average all do), and one piece found is enough: recall does not
fall with an item's length.  ``WALKS`` and ``PICKS`` are set for ``RECALL`` of a piece with all the edits
allowed; :func:`miss` measures it by simulation.

Windows are as long as pieces and begin at every word.  An edit spoils one word and two word pairs at most, so
a window that lies within the allowed distance of a piece holds nearly all of its words and pairs among the
items'; running counts find the windows that do, and only those are embedded.  This count loses nothing.

The items travel with the tasks, in groups of bounded size; every group is compared with every document.

A document is contaminated by an item if a passage of it lies within ``ERRORS`` of the item's words.  Defined
results: null or wordless texts and items match nothing; an empty table gives no rows; repeated rows, of
documents or items, give their rows each; a null id stays null; an item occurring several times in a document
gives one row, with its nearest passage: of equals the one that ends first, and of those the shortest.  Time
is linear in a document's length, but for passages under verification.  Columns but the id and the text are
not read, so their names cannot clash.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from itertools import repeat
from uuid import uuid4

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import without

#: Share of an item's words that may be inserted, deleted or replaced.
ERRORS = 0.15
#: Longest piece; walks and sampled steps; what they reach for pieces with all edits allowed.
PIECE, WALKS, PICKS, RECALL = 40, 32, 4, 0.95
#: Bytes of the items that travel with a task at once.
GROUP_BYTES = 32 << 20


def words(text: str | None) -> list[bytes]:
    return (text or "").encode().lower().split()


def _ends(item: np.ndarray, text: np.ndarray, anchored: bool) -> np.ndarray:
    """Least edit distance from the item to a passage that ends before each position; ``anchored``: and begins at 0."""
    at = np.arange(len(text) + 1)
    cost = at.copy() if anchored else np.zeros(len(text) + 1, np.int64)
    for i, x in enumerate(item.tolist(), 1):
        new = cost + 1
        np.minimum(new[1:], cost[:-1] + (text != x), out=new[1:])
        new[0] = i
        # a step along the text costs one: a running minimum of what precedes
        cost = np.minimum.accumulate(new - at) + at
    return cost


def best_passage(item: np.ndarray, text: np.ndarray, most: int) -> tuple[int, int, int] | None:
    """(errors, start, end) of the passage of ``text`` nearest to ``item``, if within ``most``."""
    cost = _ends(item, text, False)
    end = int(cost.argmin())
    if cost[end] > most:
        return None
    back = _ends(item[::-1], text[max(0, end - len(item) - most) : end][::-1], True)
    return int(cost[end]), end - int(back.argmin()), end


def cut(n: int) -> list[tuple[int, int]]:
    """(start, end) of the pieces of an item of n words: equal parts of at most ``PIECE`` words."""
    k = -(-n // PIECE)
    return [(n * i // k, n * (i + 1) // k) for i in range(k)]


class Index:
    """Pieces of similar length and the samples of their walks."""

    def __init__(self, pieces: list[tuple[int, int, np.ndarray]], n_codes: int):
        self.owner = [i for i, _, _ in pieces]
        self.offset = [o for _, o, _ in pieces]
        coded = [c for _, _, c in pieces]
        self.lost = int(ERRORS * max(map(len, coded)))
        # the walk of the shortest piece bounds the steps that may be sampled
        self.n = min(map(len, coded))
        rng = np.random.default_rng(9)
        self.salts = np.random.default_rng(10).integers(0, 2**63, n_codes, dtype=np.uint64) | np.uint64(1)
        self.steps = max(PICKS, self.n + self.n // 2)
        self.sampled = np.zeros((self.steps, WALKS), bool)
        for r in range(WALKS):
            self.sampled[rng.choice(self.steps, PICKS, replace=False), r] = True
        self.draws = rng.integers(0, 2**63, (self.steps, WALKS), dtype=np.uint64) | np.uint64(1)
        keys = np.concatenate([self.keys(c, np.zeros(1, np.int64)) for c in coded], axis=1)
        self.order = np.argsort(keys, axis=1)
        self.sorted = np.take_along_axis(keys, self.order, axis=1)

    def keys(self, codes: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """What each walk writes at its sampled steps, for windows beginning at ``starts``: walks by starts."""
        padded = np.append(codes, np.zeros(self.steps + 1, codes.dtype))
        salted = self.salts[padded]
        at = np.tile(starts, (WALKS, 1))
        out = np.zeros(at.shape, np.int64)
        for sampled, draw in zip(self.sampled, self.draws, strict=True):
            if sampled.any():
                out[sampled] = out[sampled] * np.int64(1_000_003) + padded[at[sampled]]
            at += ((salted[at] * draw[:, None]) >> np.uint64(63)).astype(np.int64)
        return out

    def candidates(self, codes: np.ndarray, known: np.ndarray, pairs: np.ndarray) -> Iterator[tuple[int, int]]:
        """(item, where it would begin); known and pairs are running counts of the items' words and word pairs."""
        size = len(codes)
        at = np.arange(size)
        ends = np.minimum(at + self.n, size)
        # of the first n words of a match at most ``lost`` are foreign
        ok = (known[ends] - known[at] >= self.n - self.lost) & (pairs[np.maximum(ends - 1, at)] - pairs[at] >= self.n - 1 - 2 * self.lost)
        starts = np.flatnonzero(ok)
        for block in range(0, len(starts), 4096):
            own = starts[block : block + 4096]
            for r, keys in enumerate(self.keys(codes, own)):
                low, high = np.searchsorted(self.sorted[r], keys, "left"), np.searchsorted(self.sorted[r], keys, "right")
                for k in np.flatnonzero(high > low):
                    for i in self.order[r, low[k] : high[k]]:
                        yield self.owner[i], int(own[k]) - self.offset[i]


class Group:
    """Items that are looked for together, and the indexes of their pieces."""

    def __init__(self, items: list[tuple[int, list[bytes]]]):
        self.ids: dict[bytes, int] = {}
        self.names = [i for i, _ in items]
        self.coded = [np.array([self.ids.setdefault(x, len(self.ids) + 1) for x in w]) for _, w in items]
        self.base = len(self.ids) + 1
        self.pairs = np.unique(np.concatenate([*(c[:-1] * self.base + c[1:] for c in self.coded), np.array([-1])]))
        pieces = sorted(((i, a, c[a:b]) for i, c in enumerate(self.coded) for a, b in cut(len(c))), key=lambda x: len(x[2]))
        blocks: list[list] = []
        for piece in pieces:  # the shortest of a block is close to all of it
            if not blocks or len(piece[2]) > 1.6 * len(blocks[-1][0][2]):
                blocks.append([])
            blocks[-1].append(piece)
        self.indexes = [Index(b, self.base) for b in blocks]
        self.least = min((x.n - x.lost for x in self.indexes), default=1)

    def search(self, text: str | None) -> Iterator[tuple[int, int, int, int]]:
        """(item, errors, first word, word after the last)."""
        w = words(text)
        codes = np.fromiter(map(self.ids.get, w, repeat(0)), np.int64, len(w))
        is_known = codes > 0
        if is_known.sum() < self.least:
            return
        known = np.append(0, np.cumsum(is_known))
        pair = codes[:-1] * self.base + codes[1:]
        both = is_known[:-1] & is_known[1:]
        hit = np.zeros(len(pair), bool)
        some = pair[both]
        hit[both] = self.pairs[np.minimum(np.searchsorted(self.pairs, some), len(self.pairs) - 1)] == some
        pairs = np.append(0, np.cumsum(hit))
        places: dict[int, set[int]] = {}
        for x in self.indexes:
            for i, start in x.candidates(codes, known, pairs):
                places.setdefault(i, set()).add(start)
        for i, starts in sorted(places.items()):
            if got := self.verified(self.coded[i], sorted(starts), codes):
                yield self.names[i], *got

    def verified(self, item: np.ndarray, starts: list[int], codes: np.ndarray) -> tuple[int, int, int] | None:
        """The best passage for an item around the places where it may begin; places that overlap are searched as one."""
        most = int(ERRORS * len(item))
        for x in starts:
            if x >= 0 and np.array_equal(codes[x : x + len(item)], item):
                return 0, x, x + len(item)
        # a piece stands off from its place by the edits before it, and its window by those within it
        wide = most + int(ERRORS * PIECE)
        regions: list[list[int]] = []
        for x in starts:
            low, high = max(0, x - wide), min(len(codes), x + len(item) + wide)
            # a window's own count of the item's words refuses most candidates
            if np.isin(codes[low:high], item).sum() < len(item) - most:
                continue
            if regions and low <= regions[-1][1]:
                regions[-1][1] = high
            else:
                regions.append([low, high])
        best = None
        for low, high in regions:
            got = best_passage(item, codes[low:high], most)
            if got and (best is None or got[0] < best[0]):
                best = got[0], got[1] + low, got[2] + low
        return best


def miss(n: int, share: float, trials: int = 200, seed: int = 1) -> float:
    """Share of items of n words that are not found in a passage with ``share`` of them edited (simulated)."""
    rng = np.random.default_rng(seed)
    lost = 0
    for _ in range(trials):
        item = [b"i%d" % x for x in rng.integers(0, 10_000, n)]
        passage = item[:]
        for _ in range(int(share * n)):
            k = int(rng.integers(len(passage)))
            new = b"x%d" % rng.integers(10_000)
            passage[k : k + 1] = ([], [new], [passage[k], new])[rng.integers(3)]
        around = [b" ".join(b"y%d" % x for x in rng.integers(0, 10_000, 30)) for _ in range(2)]
        lost += not list(Group([(0, item)]).search(b" ".join([around[0], *passage, around[1]]).decode()))
    return lost / trials


def _groups(items: DataFrame, item_id: str, text_col: str) -> Iterator[list[tuple[int, list[bytes]]]]:
    rows = items.where(F.col(text_col).isNotNull()).select(F.col(item_id).cast("long").alias("i"), F.col(text_col).alias("t")).orderBy("i", "t")
    group, size = [], 0
    for row in rows.toLocalIterator():
        if w := words(row["t"]):
            if group and size + len(row["t"]) > GROUP_BYTES:
                yield group
                group, size = [], 0
            group.append((row["i"], w))
            size += len(row["t"])
    yield group


_built: dict[str, Group] = {}


def _group(name: str, shared: Broadcast) -> Group:
    """The group of this name; a worker keeps the last one, so that its tasks build the indexes once."""
    if name not in _built:
        _built.clear()
        _built[name] = Group(shared.value)
    return _built[name]


def contaminated(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id") -> DataFrame:
    """(doc_id, item_id, errors, first_word, last_word) of every item found in a document."""

    def scan(group: list) -> DataFrame:
        shared, name = docs.sparkSession.sparkContext.broadcast(group), uuid4().hex  # at most GROUP_BYTES and an item

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            searched = _group(name, shared)
            for batch in batches:
                out: list[tuple] = []
                for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    out += [(doc_id, *x) for x in searched.search(text)]
                cols = list(zip(*out, strict=True)) or [()] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["doc_id", "item_id", "errors", "first_word", "last_word"])

        return docs.select(F.col(id_col).cast("long"), text_col).mapInArrow(run, "doc_id long, item_id long, errors long, first_word long, last_word long")

    return reduce(DataFrame.unionByName, map(scan, _groups(items, item_id, "text")))


def clean(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without the contaminated ones; rows without an id are judged by nobody's hits and stay."""
    bad = contaminated(docs, items, id_col, text_col).select(F.col("doc_id").alias("__bad")).where("__bad is not null")
    return without(docs, F.col(id_col).cast("long"), bad)
