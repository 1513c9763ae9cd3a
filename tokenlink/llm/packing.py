"""Sum-of-squares packing of tokenized documents into sequences.

Only documents longer than a sequence are cut, into full pieces and a last shorter one.  Full pieces are
sequences by themselves.  The others are dealt by hash into groups of bounded size, and in each group, longest
first, a piece goes where the squared counts of open sequences per residual gap sum to the least: a new
sequence, or the fullest-fitting one of an open gap; of equal choices the tightest gap wins.

Tokenizing looks words up: this tokenizer drops white space and never joins words across it, so a text's ids
are those of its blank-separated words in order.

Defined results.  A null or empty text is one piece holding the closing id alone.  Null ids and repeated rows
are packed like any other row, and equal pieces, being alike, may take each other's places.  A very long text is
cut, never shortened.  An empty table gives no rows.  Only the id and the text are read, so no other column's name
can clash.
"""

from __future__ import annotations

import zlib
from array import array
from collections.abc import Iterator
from math import ceil

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import materialize

CAPACITY, CLOSE = 4096, 1
_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, salt long"
_PLACED = "doc_id long, piece int, start long, length long, ids_crc32 long, bin int, offset long"


def vocabulary_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class Words(dict):
    """Packed little-endian ids of a word, remembered up to a bound."""

    LIMIT = 1 << 20

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        super().__init__()
        tokenizer = Tokenizer.from_file(path)
        self.encode, self.merge = tokenizer.encode, tokenizer.model.tokenize
        # the usual byte alphabet of such vocabularies: printable Latin-1 stands for itself, the rest is shifted
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        shifted = {b: chr(256 + k) for k, b in enumerate(x for x in range(256) if x not in plain)}
        self.alphabet = [shifted.get(b, chr(b)) for b in range(256)]

    def __missing__(self, word: str) -> bytes:
        # the tokenizer lowers letters and ends a piece where letters meet marks, so a word's ids are those of
        # its lowered form, and of its letters and its closing marks, one after the other; a word of lowered
        # Latin letters is a single piece, which goes straight to the merges
        body = word.rstrip(".,;:!?%*$#&|")
        # a lowered letter may end in a combining mark, which would join the marks that follow
        if body != word and body[-1:].lower().isalpha() and "<|" not in word:
            ids = self[body] + self[word[len(body) :]]
        elif word.isalpha() and max(word) < "\u0100":
            low = word.lower()
            ids = self[low] if low != word else array("I", [x.id for x in self.merge("".join(map(self.alphabet.__getitem__, word.encode())))]).tobytes()
        else:
            ids = np.array(self.encode(word, add_special_tokens=False).ids, dtype="<u4").tobytes() if word else b""
        if len(self) >= self.LIMIT:
            self.clear()
        self[word] = ids
        return ids


def token_bytes(text: str | None, words: Words) -> bytes:
    """The ids of a text, four bytes each, without the closing id."""
    return b"".join(map(words.__getitem__, (text or "").replace("\n", " ").split(" ")))


_CLOSE_BYTES = np.array([CLOSE], dtype="<u4").tobytes()


def cut(docs: DataFrame, path: str, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row a piece; ``with_ids`` adds its ids."""

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = Words(path)
        for batch in batches:
            cols: list[list] = [[] for _ in range(6 + with_ids)]
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids = token_bytes(text, words) + _CLOSE_BYTES
                for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                    own = ids[at : at + 4 * capacity]
                    crc = zlib.crc32(own)
                    row = (doc_id, k, at // 4, len(own) // 4, crc, zlib.crc32(f"{doc_id}:{k}".encode(), crc), *([np.frombuffer(own, "<u4").astype("int32")] if with_ids else ()))
                    for c, v in zip(cols, row, strict=True):
                        c.append(v)
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int32())]
            names = ["doc_id", "piece", "start", "length", "ids_crc32", "salt", "ids"]
            n = len(cols)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds[:n], strict=True)], names=names[:n])

    return docs.select(F.col(id_col).cast("long"), text_col).mapInArrow(pieces, _PIECES + (", ids array<int>" if with_ids else ""))


def sum_of_squares(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of every piece, taken in the given order.

    A piece of length x moves an open bin from gap g to gap g - x, which changes the sum of squared counts by
    2 (n[g-x] - n[g] + 1), or, where it fills the bin, by 1 - 2 n[g]; a new bin changes it by 2 n[c-x] + 1.
    """
    n = np.zeros(capacity + 1, dtype=np.int64)
    open_bins: list[list[int]] = [[] for _ in range(capacity + 1)]
    fill: list[int] = []
    bins, offsets = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    for k, x in enumerate(lengths.tolist()):
        gaps = np.flatnonzero(n[x:]) + x
        choice = capacity  # a new bin
        if len(gaps):
            change = 2 * (n[gaps - x] - n[gaps] + 1)
            if gaps[0] == x:
                change[0] = 1 - 2 * n[x]
            best = int(change.argmin())  # the first is the tightest
            if change[best] <= 2 * n[capacity - x] + 1:
                choice = int(gaps[best])
        if choice == capacity:
            b = len(fill)
            fill.append(0)
        else:
            n[choice] -= 1
            b = open_bins[choice].pop()
        bins[k], offsets[k] = b, fill[b]
        fill[b] += x
        if (left := capacity - fill[b]) > 0:
            n[left] += 1
            open_bins[left].append(b)
    return bins, offsets


def pack(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, group_pieces: int = 8192, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    found = materialize(cut(docs, path or vocabulary_path(), capacity, id_col, text_col))
    short = found.where(F.col("length") < capacity)
    groups = max(1, ceil(short.count() / group_pieces))

    def place(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["length", "salt", "doc_id", "piece"], ascending=[False, True, True, True], kind="stable", ignore_index=True)
        pdf["bin"], pdf["offset"] = sum_of_squares(pdf["length"].to_numpy(), capacity)
        return pdf[["doc_id", "piece", "start", "length", "ids_crc32", "bin", "offset", "group"]]

    placed = short.withColumn("group", F.pmod(F.xxhash64("salt"), F.lit(groups)).cast("int")).groupBy("group").applyInPandas(place, _PLACED + ", group int")
    # a group holds fewer than 2^31 sequences; full pieces take the negative numbers
    shared = placed.withColumn("sequence_id", F.col("group") * F.lit(1 << 31) + F.col("bin"))
    full = found.where(F.col("length") == capacity).withColumn("sequence_id", -1 - F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long"))
    cols = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
    return shared.select(cols).unionByName(full.select(cols))


def sequences(docs: DataFrame, packed: DataFrame, path: str | None = None, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(sequence_id, ids): the packed sequences themselves; ids need unique document ids."""
    pieces = cut(docs, path or vocabulary_path(), capacity, id_col, text_col, with_ids=True).select("doc_id", "piece", "ids")
    joined = packed.join(pieces, ["doc_id", "piece"])
    return joined.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("parts")).select(
        "sequence_id", F.flatten(F.transform("parts", lambda x: x["ids"])).alias("ids")
    )
