"""Byte-level BPE by backtracking over longest matches, with exact round trip.

Bytes are mapped to the 256 Latin-1 characters, so that an Aho-Corasick automaton over the vocabulary finds every token
that starts at a place. Merging by ranks gives the one sequence of tokens in which every two neighbours are compatible:
merging the two tokens' bytes by ranks gives just these two back. The encoder takes the longest token, goes back to
the next shorter one where a pair is not compatible, and never visits a dead place twice, so its time is linear in the
text; compatibility of a pair is worked out once by walking both tokens' merge trees, then remembered.

Pieces between pattern matches repeat, so each worker keeps those it has seen, up to a fixed number; this changes no
result. Nulls count as empty: no tokens, two digests of nothing. Rows that repeat come back once each; extra columns are
not read. Encoded text is UTF-8, as the library has it; decoding an encoded text gives its bytes back.
"""

from __future__ import annotations

import base64
import functools
import hashlib
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from manyq.llm.common import lean_batches, table

#: Pieces that a worker remembers; beyond, it starts anew. Pairs of tokens likewise.
KEPT_PIECES, KEPT_PAIRS = 500_000, 500_000


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f) if a}


class BacktrackingBpe:
    """Encoder and decoder for one vocabulary of byte strings by rank."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.pattern = ranks, regex.compile(pattern)
        self.bytes_of = {i: t for t, i in ranks.items()}
        # The automaton runs over reversed bytes: then the tokens that end at a place there start at it here.
        self.automaton = ahocorasick.Automaton()
        for token, i in ranks.items():
            self.automaton.add_word(token[::-1].decode("latin-1"), i)
        self.automaton.make_automaton()
        self.size_of = {i: len(t) for t, i in ranks.items()}
        #: The longest shorter token with the same start.
        self.shorter = {i: next((ranks[t[:k]] for k in range(len(t) - 1, 0, -1) if t[:k] in ranks), None) for t, i in ranks.items()}
        self.parts: dict[int, tuple[int, int] | None] = {}
        self.pairs: dict[tuple[int, int], bool] = {}
        self.pieces: dict[str, tuple[int, ...]] = {}
        for i in sorted(self.bytes_of):
            self.parts[i] = self._split(i)

    def _split(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge makes this one, None for a single byte or a token that no merge reaches."""
        whole = self.bytes_of[token]
        if len(whole) == 1:
            return None
        merged = self._merge(whole, token)
        return (merged[0], merged[1]) if len(merged) == 2 else None

    def _merge(self, whole: bytes, below: int) -> list[int]:
        """Merge bytes by rank with the tokens under a rank only; used once for each token and in tests."""
        own = [whole[i : i + 1] for i in range(len(whole))]
        while len(own) > 1:
            best, at = min(((self.ranks.get(own[i] + own[i + 1], below), i) for i in range(len(own) - 1)))
            if best >= below:
                break
            own[at : at + 2] = [own[at] + own[at + 1]]
        return [self.ranks[x] for x in own]

    def compatible(self, a: int, b: int) -> bool:
        """Whether merging the bytes of a and b together leaves a and b."""
        if (known := self.pairs.get((a, b))) is not None:
            return known
        first, second, limit, out = a, b, 1 << 62, None
        while out is None:
            if self.ranks.get(self.bytes_of[first] + self.bytes_of[second], limit) < limit:
                out = False
                break
            # Undo the merge that came last, the right one of equals. A merge across the border must have come before it.
            left, right = self.parts[first], self.parts[second]
            if left and (first > second or not right):
                limit, first = first, left[1]
            elif right:
                limit, second = second + 1, right[0]
            else:
                out = True
        if len(self.pairs) >= KEPT_PAIRS:
            self.pairs.clear()
        self.pairs[a, b] = out
        return out

    def encode_piece(self, piece: bytes) -> list[int]:
        """The tokens of one piece."""
        if (whole := self.ranks.get(piece)) is not None:
            return [whole]
        n = len(piece)
        # Of the tokens that start at a place the longest comes first; as a key's last value stays, it must come last.
        longest = dict(reversed(list(self.automaton.iter(piece[::-1].decode("latin-1")))))
        size_of, shorter, pairs = self.size_of, self.shorter, self.pairs
        out: list[int] = []
        dead = bytearray(n + 1)
        at, token = 0, longest.get(n - 1)
        while at < n:
            if token is None:  # nothing fits here: never come back, and shorten what led here
                dead[at] = 1
                if not out:
                    raise ValueError("the vocabulary lacks a byte")
                token = out.pop()
                at -= size_of[token]
                token = shorter[token]
                continue
            to = at + size_of[token]
            fits = not dead[to]
            if fits and out:
                fits = pairs.get((out[-1], token))
                if fits is None:
                    fits = self.compatible(out[-1], token)
            if fits:
                out.append(token)
                at, token = to, longest.get(n - 1 - to)
            else:
                token = shorter[token]
        return out

    def encode(self, text: str) -> list[int]:
        """The ids of a text, each pattern match encoded for itself."""
        kept, out = self.pieces, []
        for piece in self.pattern.findall(text):
            ids = kept.get(piece)
            if ids is None:
                ids = self.encode_piece(piece.encode())
                if len(piece) <= 64:
                    if len(kept) >= KEPT_PIECES:
                        kept.clear()
                    kept[piece] = tuple(ids)
            out += ids
        return out

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


@functools.lru_cache(maxsize=2)
def coder(path: str, pattern: str) -> BacktrackingBpe:
    return BacktrackingBpe(load_ranks(path), pattern)


def encode_decode(docs: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) for every row."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    lean_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = coder(ranks_path, pattern)
        for batch in batches:
            n, a, b = [], [], []
            for text in batch.column(1):
                ids = bpe.encode(text.as_py() or "")
                n.append(len(ids))
                a.append(hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest())
                b.append(hashlib.sha256(bpe.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode_ids(docs: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """(doc_id, ids array<int>) for every row."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    lean_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = coder(ranks_path, pattern)
        for batch in batches:
            ids = [bpe.encode(t.as_py() or "") for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, ids array<int>")


def op8_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return encode_decode(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)
