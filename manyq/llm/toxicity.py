"""Toxicity scores by a factorization machine over hashed terms.

A text's terms are the hashes of its distinct lower-cased words. Besides a weight, each term has a short vector, and the
score adds the inner products of the vectors of all pairs of terms: what an insult means beside a group's name is
learned as such, which additive weights miss. Pair sums come from the sum of the vectors, so scoring is linear in the
terms. Terms are weighted by how rare they are among the learned rows.

The model is fitted on a bounded sample of labelled rows, `sample_rows` of them taken by the order of a hash of doc_id;
its size is fixed by `BITS` and `FACTORS`. Every row of every table is scored on its whole text.

Defined cases: null and empty texts have no terms and get the score of the bias. Labels that are null, or doc_ids that
are, teach nothing; a doc_id with contradicting labels counts once, as toxic. Without labelled rows of both classes the
score is the share of toxic ones (0 without any). Rows that repeat come back once each; extra columns pass through `keep_below`.
"""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from manyq.llm.arrow import LETTERS, Words, give_back, slabs, text_bytes
from manyq.llm.common import lean_batches, table

BITS, FACTORS = 19, 8
#: Bytes of the word starts that are terms besides the whole words: languages that inflect hide a word in many forms.
PREFIXES = (4, 6)
#: An odd factor that makes the term of what occurs more than once from the term of what occurs.
AGAIN = 2654435761
THRESHOLD = 0.7


def term_lists(texts: list[bytes]) -> list[np.ndarray]:
    """The distinct hashed terms of each text, sorted: words, word starts, and again either that come more than once."""
    words, out = Words(LETTERS), []
    for lo, hi, _ in slabs(texts):
        _, _, _, first, hashes = words.located([t.decode().lower().encode() for t in texts[lo:hi]], PREFIXES)
        terms = np.stack([(h >> np.uint64(64 - BITS)).astype(np.int32) for h in hashes], 1)
        for i in range(hi - lo):
            own, n = np.unique(terms[first[i] : first[i + 1]], return_counts=True)
            again = (own[n > 1].astype(np.int64) * AGAIN & ((1 << BITS) - 1)).astype(np.int32)
            out.append(np.unique(np.concatenate([own, again])))
    return out


@dataclass
class Machine:
    """A factorization machine: bias, weights, vectors, and the value of each term (0: never learned)."""

    bias: float
    weights: np.ndarray
    vectors: np.ndarray
    values: np.ndarray

    def margins(self, terms: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Of rows whose terms are terms[first[i]:first[i + 1]]."""
        n = len(first) - 1
        row = np.repeat(np.arange(n), np.diff(first))
        live = self.values[terms] > 0
        row, terms = row[live], terms[live]
        x = self.values[terms]
        out = self.bias + np.bincount(row, x * self.weights[terms], n)
        for f in range(self.vectors.shape[1]):
            own = x * self.vectors[terms, f]
            out += 0.5 * (np.bincount(row, own, n) ** 2 - np.bincount(row, own * own, n))
        return out

    def scores(self, texts: list[bytes]) -> np.ndarray:
        """Of whole texts, a slab at a time, so that memory does not follow the batch."""
        out = [np.empty(0)]
        for lo, hi, _ in slabs(texts):
            lists = term_lists(texts[lo:hi])
            first = np.cumsum([0, *map(len, lists)])
            out.append(1 / (1 + np.exp(-np.clip(self.margins(np.concatenate(lists), first), -60, 60))))
        return np.concatenate(out)


def fit(lists: list[np.ndarray], toxic: np.ndarray, epochs: int = 6, rate: float = 0.2, sparse: float = 1e-3, seed: int = 5, least_rows: int = 4, least_steps: int = 300) -> Machine:
    """Logistic loss with adaptive steps and a penalty that sets idle weights to zero; the rare class is weighted up."""
    n, rng = len(lists), np.random.default_rng(seed)
    share = float(toxic.mean()) if n else 0.0
    size = 1 << BITS
    if not n or share in (0.0, 1.0):
        bias = -60.0 if share == 0 else 60.0
        return Machine(bias, np.zeros(size, np.float32), np.zeros((size, FACTORS), np.float32), np.zeros(size, np.float32))
    rows = np.zeros(size, np.int64)
    for own in lists:
        rows[own] += 1
    values = np.where(rows >= min(least_rows, max(1, n // 50)), 1 - rows / n, 0).astype(np.float32)
    machine = Machine(float(np.log(share / (1 - share))), np.zeros(size, np.float32), np.zeros((size, FACTORS), np.float32), values)
    machine.vectors[values > 0] = rng.normal(0, 0.003, (int((values > 0).sum()), FACTORS))
    seen_w, seen_v, seen_b = np.full(size, 1e-4, np.float32), np.full((size, FACTORS), 1e-4, np.float32), 1e-4
    weight = np.where(toxic > 0, min(4.0, 0.5 / share), 1.0)
    lists = [x[values[x] > 0] for x in lists]
    batch = min(256, max(16, n // 32))
    for _ in range(max(epochs, -(-least_steps * batch // n))):
        order = rng.permutation(n)
        for at in range(0, n, batch):
            own = order[at : at + batch]
            terms = np.concatenate([lists[i] for i in own])
            row = np.repeat(np.arange(len(own)), [len(lists[i]) for i in own])
            first = np.concatenate([[0], np.cumsum([len(lists[i]) for i in own])])
            x = values[terms]
            slope = (1 / (1 + np.exp(-np.clip(machine.margins(terms, first), -30, 30))) - toxic[own]) * weight[own] / len(own)
            xv = x[:, None] * machine.vectors[terms]
            sums = np.stack([np.bincount(row, xv[:, f], len(own)) for f in range(FACTORS)], 1)
            used, place = np.unique(terms, return_inverse=True)
            gw = np.bincount(place, slope[row] * x, len(used))
            part = (slope[row] * x)[:, None] * (sums[row] - xv)
            gv = np.stack([np.bincount(place, part[:, f], len(used)) for f in range(FACTORS)], 1)
            seen_w[used] += gw**2
            seen_v[used] += gv**2
            step_w, step_v = rate / np.sqrt(seen_w[used]), 0.1 * rate / np.sqrt(seen_v[used])
            w, v = machine.weights[used] - step_w * gw, machine.vectors[used] - step_v * gv
            machine.weights[used] = np.sign(w) * np.maximum(np.abs(w) - step_w * sparse, 0)
            machine.vectors[used] = np.sign(v) * np.maximum(np.abs(v) - step_v * sparse, 0)
            gb = float(slope.sum())
            seen_b += gb * gb
            machine.bias -= rate * gb / seen_b**0.5
    return machine


def held_out(doc: Column) -> Column:
    """Rows whose labels are never learned: crc32 of the doc_id as text leaves 1 by 3."""
    return F.coalesce(F.crc32(doc.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def learn(docs: DataFrame, labels: DataFrame, sample_rows: int = 20_000, seed: int = 5) -> Machine:
    """Fit a machine on at most sample_rows labelled rows that are not held out."""
    lean_batches(docs.sparkSession)
    known = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & ~held_out(F.col("doc_id")))
    chosen = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    # Of several texts under one doc_id the least is learned, in any run; at most sample_rows rows come here.
    texts = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.max("toxic").alias("toxic"))
    kind = texts.schema["doc_id"].dataType.simpleString()

    def terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            packed = [x.tobytes() for x in term_lists(text_bytes(b.column(1)))]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(packed, pa.binary()), b.column(2).cast(pa.int32())], ["doc_id", "terms", "toxic"])

    def train(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = sorted((r["doc_id"], r["terms"], r["toxic"]) for b in batches for at in range(0, b.num_rows, 500) for r in b.slice(at, 500).to_pylist())
        toxic = np.array([y > 0 for _, _, y in rows], float)
        machine = fit([np.frombuffer(t, np.int32) for _, t, _ in rows], toxic, seed=seed)
        used = np.flatnonzero(machine.values)
        small = (machine.bias, used.astype(np.int32), machine.weights[used], machine.vectors[used], machine.values[used])
        yield pa.RecordBatch.from_arrays([pa.array([zlib.compress(pickle.dumps(small), 1)], pa.binary())], ["machine"])
        give_back()

    hashed = texts.mapInArrow(terms, f"doc_id {kind}, terms binary, toxic int")
    # One task by design: at most sample_rows rows, of 4 bytes a term.
    packed = hashed.repartition(1).mapInArrow(train, "machine binary")
    bias, used, weights, vectors, values = pickle.loads(zlib.decompress(packed.first()[0]))
    size = 1 << BITS
    out = Machine(bias, np.zeros(size, np.float32), np.zeros((size, FACTORS), np.float32), np.zeros(size, np.float32))
    out.weights[used], out.vectors[used], out.values[used] = weights, vectors, values
    return out


def with_scores(docs: DataFrame, machine: Machine) -> DataFrame:
    """(doc_id, text, ... all columns of docs, manyq__score)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            scores = machine.scores(text_bytes(b.column(b.schema.names.index("text"))))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(scores, pa.float64())], [*b.schema.names, "manyq__score"])
        give_back()

    lean_batches(docs.sparkSession)
    schema = type(docs.schema)([*docs.schema.fields]).add("manyq__score", "double")
    return docs.mapInArrow(run, schema)


def keep_below(docs: DataFrame, machine: Machine, threshold: float = THRESHOLD) -> DataFrame:
    """docs without those that score at least the threshold."""
    return with_scores(docs, machine).where(F.col("manyq__score") < threshold).select(*docs.columns)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = with_scores(docs, learn(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.col("manyq__score").alias("score"), (F.col("manyq__score") >= THRESHOLD).cast("int").alias("predicted"))
