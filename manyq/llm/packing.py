"""Packing of tokenised documents into sequences: shortest pack first, over the histogram of lengths.

Every document is tokenised once and cut at multiples of the sequence length, so that a piece's ids do not depend on the
packing. Packing then works on the histogram of piece lengths alone, which has at most as many entries as a sequence has
tokens: lengths are placed longest first, each into the packs that are shortest so far, and packs of equal content are
counted, not listed. The patterns so made go back to the pieces by rank: the r-th piece of a length takes the r-th place
that the patterns hold for it. Ranks are taken within (length, slice of doc_ids) and moved on by the counts of the slices
before, so a length that a third of all pieces share is no single task's work.

A sequence is padded to its full length, except at a power of two.

Defined cases: null and empty texts are the end id alone. Rows that repeat, or share a doc_id, are documents of their own;
ties in rank go by doc_id, start, then checksum. A null doc_id is packed like any other. An empty table gives an empty
result. Extra columns are not read.
"""

from __future__ import annotations

import functools
import re
import struct
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from manyq.llm.arrow import NOT_BLANK, Words, give_back, slabs, text_bytes
from manyq.llm.common import lean_batches, materialise, table

LENGTH, END_ID = 4096, 2
#: Words whose ids a worker remembers; beyond, it starts anew.
KEPT_WORDS = 800_000
# Fixed value: the tokenizer's own pattern, as it applies to lower-case ASCII.
ASCII_PIECES = re.compile(rb"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^\sa-z0-9]+")
#: Slices of doc_ids in which ranks are taken.
SLICES = 64


class Remembered:
    """About the last `most` entries: two dicts, of which the older is let go when the newer is full."""

    def __init__(self, most: int):
        self.most, self.newer, self.older = most // 2, {}, {}

    def look_up(self, keys: list[bytes], make: Callable[[list[bytes]], list[bytes]]) -> list[bytes]:
        """The values of distinct keys, those not known made by `make`."""
        out = list(map(self.newer.get, keys))
        gaps = [i for i, v in enumerate(out) if v is None]
        if gaps:
            old = [self.older.get(keys[i]) for i in gaps]
            made = iter(make([keys[i] for i, v in zip(gaps, old, strict=True) if v is None]))
            if len(self.newer) + len(gaps) > self.most:
                self.older, self.newer = self.newer, {}
            for i, v in zip(gaps, old, strict=True):
                out[i] = next(made) if v is None else v
                if len(keys[i]) <= 64:
                    self.newer[keys[i]] = out[i]
        return out


class WordIds:
    """The ids of texts as little-endian 32-bit words.

    White space parts this vocabulary's pieces, so words are encoded one by one and remembered. A new word of ASCII alone
    is lower-cased and cut as the tokenizer itself would, and its pieces are remembered as well; a word that holds one of the
    vocabulary's special tokens goes to the tokenizer whole, which gives that token its own id.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        special = [t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.special = re.compile(b"|".join(map(re.escape, special)) or b"(?!)")
        self.coder = Words(NOT_BLANK)
        self.words, self.pieces = Remembered(KEPT_WORDS), Remembered(KEPT_WORDS)

    def _encode(self, new: list[bytes]) -> list[bytes]:
        encoded = self.tokenizer.encode_batch_fast([w.decode() for w in new], add_special_tokens=False) if new else []
        return [struct.pack(f"<{len(e.ids)}I", *e.ids) for e in encoded]

    def _new(self, words: list[bytes]) -> list[bytes]:
        cut = [ASCII_PIECES.findall(w.lower()) if w.isascii() and not self.special.search(w) else None for w in words]
        pieces = list({p for x in cut if x for p in x})
        own = dict(zip(pieces, self.pieces.look_up(pieces, self._encode), strict=True))
        other = iter(self._encode([w for w, x in zip(words, cut, strict=True) if x is None]))
        return [next(other) if x is None else own[x[0]] if len(x) == 1 else b"".join(map(own.__getitem__, x)) for x in cut]

    def of_all(self, texts: list[bytes]) -> list[np.ndarray]:
        """Each text's ids. Equal words of all texts are found by hash and looked up once."""
        joined, starts, ends, first, (hashes,) = self.coder.located(texts)
        _, at, place = np.unique(hashes, return_index=True, return_inverse=True)
        ids = self.words.look_up([joined[a:b] for a, b in zip(starts[at].tolist(), ends[at].tolist(), strict=True)], self._new)
        size = np.array([len(i) >> 2 for i in ids], np.int64)
        flat = np.frombuffer(b"".join(ids), "<u4")
        own = size[place]
        stop = np.concatenate([[0], np.cumsum(own)])
        out = flat[np.repeat((np.cumsum(size) - size)[place] - stop[:-1], own) + np.arange(stop[-1])]
        return [out[stop[first[i]] : stop[first[i + 1]]] for i in range(len(texts))]


@functools.lru_cache(maxsize=2)
def word_ids(path: str) -> WordIds:
    return WordIds(path)


def pieces_of(docs: DataFrame, tokenizer_path: str, length: int = LENGTH, end_id: int = END_ID) -> DataFrame:
    """(doc_id, doc_tokens, start, length, ids_crc32) for every piece of every row."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        coder = word_ids(tokenizer_path)
        for batch in batches:
            row, tokens, starts, sizes, sums = [], [], [], [], []
            texts = text_bytes(batch.column(1))
            for lo, hi, _ in slabs(texts, 4 << 20):
                for i, ids in enumerate(coder.of_all(texts[lo:hi]), lo):
                    ids = ids.tobytes() + end
                    for at in range(0, len(ids), 4 * length):
                        own = ids[at : at + 4 * length]
                        row.append(i)
                        tokens.append(len(ids) // 4)
                        starts.append(at // 4)
                        sizes.append(len(own) // 4)
                        sums.append(zlib.crc32(own))
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(row, pa.int32())), *[pa.array(x, pa.int64()) for x in (tokens, starts, sizes, sums)]], ["doc_id", "doc_tokens", "start", "length", "ids_crc32"])
        give_back()

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, doc_tokens long, start long, length long, ids_crc32 long")


Pattern = tuple[tuple[int, int], ...]  # (piece length, how many), in the order placed


def pack_histogram(counts: dict[int, int], length: int = LENGTH) -> list[tuple[Pattern, int]]:
    """Patterns with their counts, covering the histogram exactly."""
    groups: dict[int, dict[Pattern, int]] = {}  # by room left
    rooms: list[int] = []

    def put(room: int, pattern: Pattern, n: int) -> None:
        own = groups.setdefault(room, {})
        own[pattern] = own.get(pattern, 0) + n

    for size in sorted(counts, reverse=True):
        left = counts[size]
        while left:
            room = max(groups, default=-1)
            if room < size:
                fit = length // size
                full, rest = divmod(left, fit)
                # All that is left is of this length and no pack has room: new packs, filled evenly.
                if full:
                    put(length - fit * size, ((size, fit),), full)
                if rest:
                    put(length - rest * size, ((size, rest),), 1)
                break
            pattern, n = groups[room].popitem()
            if not groups[room]:
                del groups[room]
            if left < n:
                put(room, pattern, n - left)
                n = left
            grown = (*pattern[:-1], (size, pattern[-1][1] + 1)) if pattern[-1][0] == size else (*pattern, (size, 1))
            put(room - size, grown, n)
            left -= n
    return [(p, n) for _, own in sorted(groups.items()) for p, n in own.items()]


def padding(patterns: list[tuple[Pattern, int]], length: int = LENGTH) -> int:
    """Tokens of padding over all sequences."""
    fills = [(sum(s * k for s, k in p), n) for p, n in patterns]
    return sum(n * (length - f) for f, n in fills if f & (f - 1))


def places(patterns: list[tuple[Pattern, int]]) -> dict[str, np.ndarray]:
    """The runs of places that patterns hold, by piece length and then rank.

    size: piece length; rank: first rank of the run; base: first sequence; each: places in one sequence; offset: of the first.
    A pattern's runs are at most the distinct lengths, so all of them together stay small however many pieces there are.
    """
    base, run = 0, []
    ranks: dict[int, int] = {}
    for pattern, n in patterns:
        at = 0
        for size, k in pattern:
            run.append((size, ranks.get(size, 0), base, k, at))
            ranks[size] = ranks.get(size, 0) + n * k
            at += size * k
        base += n
    out = np.array(sorted(run), np.int64).reshape(-1, 5)
    return dict(zip(("size", "rank", "base", "each", "offset"), out.T, strict=True))


def ranked(pieces: DataFrame) -> DataFrame:
    """pieces with `rank`, from 0, of each within its length."""
    sliced = pieces.withColumn("slice", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.lit(SLICES)).cast("int"))
    before = Window.partitionBy("length").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    # At most LENGTH * SLICES rows, whatever the input.
    counts = sliced.groupBy("length", "slice").agg(F.count("*").alias("n"))
    moved = counts.select("length", "slice", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    own = F.row_number().over(Window.partitionBy("length", "slice").orderBy("doc_id", "start", "ids_crc32", "doc_tokens"))
    return sliced.withColumn("own", own).join(F.broadcast(moved), ["length", "slice"]).withColumn("rank", F.col("own") - 1 + F.col("before")).drop("slice", "own", "before")


def pack(docs: DataFrame, tokenizer_path: str, length: int = LENGTH) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    lean_batches(docs.sparkSession)
    pieces = materialise(pieces_of(docs, tokenizer_path, length), "pieces")
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `length` rows
    runs = places(pack_histogram(histogram, length))
    kind = pieces.schema["doc_id"].dataType.simpleString()
    columns = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = {int(s): i for i, s in reversed(list(enumerate(runs["size"])))}
        last = {int(s): i + 1 for i, s in enumerate(runs["size"])}
        for batch in batches:
            size, rank = (batch.column(batch.schema.names.index(c)).to_numpy() for c in ("length", "rank"))
            at = np.empty(len(size), np.int64)
            for s in np.unique(size).tolist():
                own = size == s
                at[own] = first[s] + np.searchsorted(runs["rank"][first[s] : last[s]], rank[own], "right") - 1
            over = rank - runs["rank"][at]
            sequence = runs["base"][at] + over // runs["each"][at]
            offset = runs["offset"][at] + over % runs["each"][at] * size
            yield pa.RecordBatch.from_arrays([*[batch.column(batch.schema.names.index(c)) for c in columns], pa.array(sequence), pa.array(offset)], [*columns, "sequence_id", "offset"])

    schema = f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    return ranked(pieces).select(*columns, "rank").mapInArrow(run, schema)


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
