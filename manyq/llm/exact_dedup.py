"""Exact deduplication by content-defined chunk recipes.

A text (A-Z lower-cased, UTF-8) is cut where a rolling hash of its last 16 bytes has zero low bits, so equal passages
are cut alike. Chunks are deduplicated to verified identifiers: the distinct (digest, bytes) pairs are grouped, bytes
compared, and a digest that stands for different bytes gets ordinals. A document then is its recipe, the ordered list
of its chunk identifiers, and texts are equal exactly when recipes are. Each distinct chunk moves once from each task
that holds it; documents themselves never move, and groups of copies are found on recipes.

Defined cases: null text counts as empty (an empty recipe). Rows that repeat with one doc_id are one document each time:
all of them are kept where that doc_id is the largest. A null doc_id never beats a number; where all are null, keep_id
is null and they are kept. Extra columns are not read; `keep_one` passes them through.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from manyq.llm.arrow import random_table, slabs, text_bytes
from manyq.llm.common import ascii_lower, lean_batches, materialise, table, whole_text

#: Mean, least and most bytes of a chunk. The least covers the rolling window, so that a cut depends on its own chunk alone.
MEAN_BITS, LEAST, MOST = 11, 512, 16384

Digest = Callable[[bytes], bytes]


def _cuts(slab: np.ndarray, gear: np.ndarray) -> np.ndarray:
    """Places after which the hash of the last 16 bytes allows a cut."""
    h = gear[slab]
    for step in (1, 2, 4, 8):
        h[step:] = h[step:] + (h[:-step] << np.uint32(step))
    return np.flatnonzero((h >> np.uint32(32 - MEAN_BITS)) == 0) + 1


def chunk_ends(text: bytes) -> list[int]:
    """The ends of the chunks of one text."""
    return _ends(_cuts(np.frombuffer(text, np.uint8), random_table(7, dtype=np.uint32)), 0, len(text)) if text else []


def _ends(cuts: np.ndarray, start: int, stop: int) -> list[int]:
    ends, at = [], start
    own = cuts[np.searchsorted(cuts, start + LEAST) : np.searchsorted(cuts, stop)].tolist()
    for c in own:
        while c - at > MOST:
            at += MOST
            ends.append(at)
        if c - at >= LEAST:
            at = c
            ends.append(at)
    while stop - at > MOST:
        at += MOST
        ends.append(at)
    if at < stop:
        ends.append(stop)
    return ends


def _chunked(batches: Iterator[pa.RecordBatch], digest: Digest, with_chunks: bool) -> Iterator[pa.RecordBatch]:
    gear = random_table(7, dtype=np.uint32)
    for batch in batches:
        texts = [t.lower() for t in text_bytes(batch.column(1))]
        seen: dict[bytes, bytes] = {}
        recipes, whole = [], []
        for lo, hi, at in slabs(texts):
            slab = b"".join(texts[lo:hi])
            cuts = _cuts(np.frombuffer(slab, np.uint8), gear) if slab else np.empty(0, np.int64)
            for i in range(hi - lo):
                start, ids = int(at[i]), []
                for end in _ends(cuts, start, int(at[i + 1])):
                    body = slab[start:end]
                    ids.append(d := digest(body))
                    if with_chunks and seen.setdefault(d, body) != body:
                        yield _chunk_batch([d], [body])  # another text of the same digest: it must be seen too
                    start = end
                recipes.append(b"".join(ids))
                whole.append(hashlib.sha256(texts[lo + i]).hexdigest() if not with_chunks else "")
        if with_chunks:
            yield _chunk_batch(list(seen), list(seen.values()))
        else:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(recipes, pa.binary()), pa.array(whole)], ["doc_id", "recipe", "text_sha256"])


def _chunk_batch(digests: list[bytes], bodies: list[bytes]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(digests, pa.binary()), pa.array(bodies, pa.binary())], ["digest", "body"])


def _digest(body: bytes) -> bytes:
    return xxhash.xxh3_128_digest(body)


def chunks_of(docs: DataFrame, digest: Digest = _digest) -> DataFrame:
    """The distinct (digest, body) pairs of all documents."""
    found = docs.select("doc_id", "text").mapInArrow(lambda b: _chunked(b, digest, True), "digest binary, body binary")
    return found.distinct()


def recipes_of(docs: DataFrame, digest: Digest = _digest) -> DataFrame:
    """(doc_id, recipe, text_sha256) for every row; the recipe is verified: equal exactly when texts are.

    The chunks are checked first. Digests that stand for different bytes (with 128 bits: as good as never) get ordinals
    by their bytes, which are written behind the recipes that hold them.
    """
    lean_batches(docs.sparkSession)
    id_type = docs.schema["doc_id"].dataType.simpleString()
    plain = docs.select("doc_id", "text").mapInArrow(lambda b: _chunked(b, digest, False), f"doc_id {id_type}, recipe binary, text_sha256 string")
    clashing = materialise(chunks_of(docs, digest).groupBy("digest").agg(F.count("*").alias("n")).where("n > 1").select("digest"), "clashing")
    if clashing.isEmpty():
        return plain
    width = len(digest(b""))
    ordinals = chunks_of(docs, digest).join(clashing, "digest", "left_semi").withColumn("ordinal", F.row_number().over(Window.partitionBy("digest").orderBy("body")))
    placed = docs.select("text").distinct().mapInArrow(lambda b: _placed(b, digest), "text_sha256 string, place int, digest binary, body binary")
    told = placed.join(ordinals, ["digest", "body"]).groupBy("text_sha256").agg(F.array_sort(F.collect_list(F.struct("place", "ordinal"))).alias("told"))
    suffix = F.to_json("told").cast("binary")
    both = plain.join(told, "text_sha256", "left").withColumn("recipe", F.when(F.col("told").isNull(), F.col("recipe")).otherwise(F.concat("recipe", F.lit(b"|" * width), suffix)))
    return both.select("doc_id", "recipe", "text_sha256")


def _placed(batches: Iterator[pa.RecordBatch], digest: Digest) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for text in (t.lower() for t in text_bytes(batch.column(0))):
            ends = chunk_ends(text)
            bodies = [text[a:b] for a, b in zip([0, *ends], ends, strict=False)]
            n = len(bodies)
            yield pa.RecordBatch.from_arrays([pa.array([hashlib.sha256(text).hexdigest()] * n, pa.string()), pa.array(range(n), pa.int32()), pa.array([digest(b) for b in bodies], pa.binary()), pa.array(bodies, pa.binary())], ["text_sha256", "place", "digest", "body"])


def find_copies(docs: DataFrame, digest: Digest = _digest) -> DataFrame:
    """One row per row of docs: doc_id, keep_id, group_size, kept, text_sha256."""
    recipes = materialise(recipes_of(docs, digest), "recipes")
    groups = recipes.groupBy("recipe").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    found = recipes.join(groups.where("group_size > 1"), "recipe", "left")
    keep_id = F.when(F.col("group_size").isNull(), F.col("doc_id")).otherwise(F.col("keep_id"))
    return found.select(
        "doc_id",
        keep_id.alias("keep_id"),
        F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"),
        F.coalesce(F.col("doc_id") == keep_id, keep_id.isNull()).alias("kept"),
        "text_sha256",
    )


def keep_one(docs: DataFrame) -> DataFrame:
    """docs without the rows that find_copies drops: a row is told by doc_id and text, so texts that share a doc_id do not fall with one another."""
    gone = find_copies(docs).where(~F.col("kept")).select(F.col("doc_id").alias("manyq__gone"), F.col("text_sha256").alias("manyq__sha")).distinct()
    same = docs["doc_id"].eqNullSafe(F.col("manyq__gone")) & (F.sha2(ascii_lower(whole_text(docs["text"])), 256) == F.col("manyq__sha"))
    return docs.join(gone, same, "left_anti")


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_copies(table(spark, sf_dir, "documents"))


ORACLE_SQL = """
WITH t AS (SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS s FROM documents)
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, s AS text_sha256
FROM t WINDOW w AS (PARTITION BY s)
"""
