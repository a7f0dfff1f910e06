"""Approximate nearest neighbours: a forest of random-projection trees, one shared queue, exact reranking.

The measure is the largest inner product. As trees split by direction, vectors are first lengthened by one component
that gives all of them one norm (queries get zero there), which keeps the order of inner products. The trees are grown on
at most `fit_rows` rows, taken by the order of a hash of vec_id; every row is then indexed, once in each tree. A query
walks all trees through one priority queue, nearest places first, until the leaves it has reached hold `share` of the
distinct rows (estimated on the sample); the leaves' rows are scored exactly, in double precision, and the best of all
leaves returned. A row that several of the query's leaves hold counts in the first tree that does, so `looked`, the number
of rows a query was compared with, is a number of distinct rows. Trees split tables of any size: a leaf is meant to hold a
24th of the rows, and never more than 6144. A leaf returns only
rows that reach the query's k-th best score among those rows of the growing sample that the query's own leaves hold: the
best of all leaves do, and so many rows do in any case.

Leaves meet queries in cogroups of bounded size: a leaf with many rows or many queries (copies of one vector) is cut into
chunks of both. `share` trades cost for recall: vectors without structure, such as most of the tests' tables, have no
near neighbours to find quickly, and recall above 0.9 needs more than half of all rows looked at; structured ones need
little. `exact` is the full scan.

Defined cases: vectors that are null, empty, zero, of another dimension than most, or hold null or non-finite components
take no part, neither do rows without vec_id. Rows that repeat a vec_id are one candidate, with its best score; a query's
own vec_id is never returned. Fewer candidates than wanted are all returned where all are reached; an empty table gives
an empty result. Extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from manyq.llm.common import table
from manyq.llm.forest import Tree, grow_forest, leaf_members, probe

CHUNK = 8192


def usable(rows: DataFrame, vector: str = "embedding") -> DataFrame:
    """(vec_id, vector) of the rows that take part, all of the commonest dimension."""
    fine = lambda v: F.coalesce(v.isNotNull() & ~F.isnan(v.cast("double")) & (F.abs(v.cast("double")) < float("inf")), F.lit(False))
    good = rows.where(F.col("vec_id").isNotNull() & F.col(vector).isNotNull() & F.forall(vector, fine) & F.exists(vector, lambda v: v != 0))
    good = good.select("vec_id", F.col(vector).alias("vector"))
    common = good.groupBy(F.size("vector").alias("dim")).count().orderBy(F.desc("count"), "dim").first()
    return good.where(F.size("vector") == (common["dim"] if common else 0))


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 1)


def _lengthened(x: np.ndarray, norm2: float) -> np.ndarray:
    x = x.astype(np.float64)
    return np.concatenate([x, np.sqrt(np.maximum(0, norm2 - (x * x).sum(1)))[:, None]], 1)


def _norm2(vector: str) -> Column:
    return F.aggregate(vector, F.lit(0.0), lambda s, v: s + v.cast("double") * v.cast("double"))


def kth_best(rough: np.ndarray, k: int) -> np.ndarray:
    """Each row's k-th largest entry; minus infinity where there are fewer."""
    return np.partition(rough, rough.shape[1] - k, axis=1)[:, rough.shape[1] - k] if rough.shape[1] >= k else np.full(len(rough), -np.inf)


def best_of(queries: np.ndarray, query_ids: np.ndarray, known: np.ndarray, rows: np.ndarray, ids: np.ndarray, k: int, covered: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query index, row index, score) of each query's k best rows, ties to the smaller id; the query's own id is left out.

    known: a score that k rows of the table are known to reach; rows below it are left out. covered: pairs that another leaf scores.
    """
    rough = queries @ rows.T
    rough[covered] = -np.inf
    rough[query_ids[:, None] == ids[None, :]] = -np.inf
    least = np.maximum(kth_best(rough, k), known)
    slack = 1e-9 * (1 + np.abs(np.where(np.isfinite(least), least, 0)))
    q, r = np.nonzero((rough >= (least - slack)[:, None]) & np.isfinite(rough))
    score = np.einsum("ij,ij->i", queries[q], rows[r])  # the same sum for equal vectors, wherever they stand
    order = np.lexsort((ids[r], -score, q))
    q, r, score = q[order], r[order], score[order]
    place = np.arange(len(q)) - np.searchsorted(q, q)
    return q[place < k], r[place < k], score[place < k]


def _layers(ids: np.ndarray) -> list[np.ndarray]:
    """Indices by how often their id came before: each layer has an id once."""
    order = np.argsort(ids, kind="stable")
    own = ids[order]
    place = np.arange(len(own)) - np.searchsorted(own, own)
    return [np.sort(order[place == p]) for p in range(int(place.max()) + 1)]


def _dealt(tree: np.ndarray, leaf: np.ndarray, parts_v: list[np.ndarray], parts_q: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    nv, nq = np.empty(len(tree), np.int64), np.empty(len(tree), np.int64)
    for t in range(len(parts_v)):
        own = tree == t
        nv[own], nq[own] = parts_v[t][leaf[own]], parts_q[t][leaf[own]]
    return nv, nq


def search(rows: DataFrame, is_query: Column, k: int = 20, trees: int = 6, leaf_rows: int | None = None, share: float = 0.74, fit_rows: int = 20_000) -> DataFrame:
    """(query_id, rank, vec_id, score, looked) of the k best found for each usable row that is_query (a condition on vec_id) holds for."""
    spark = rows.sparkSession
    good = usable(rows)
    kind = rows.schema["vec_id"].dataType.simpleString()
    total, norm2 = good.agg(F.count("*"), F.max(_norm2("vector"))).first()
    schema = f"query_id {kind}, rank int, vec_id {kind}, score double, looked long"
    if not total:
        return spark.createDataFrame([], schema)
    chosen = good.orderBy(F.xxhash64("vec_id"), "vec_id").limit(fit_rows).select("vec_id", "vector").collect()
    sample = _lengthened(np.array([r["vector"] for r in chosen]), norm2)
    # Rows that share a vec_id count once towards what is known to be reached.
    _, once = np.unique(np.array([r["vec_id"] for r in chosen], np.int64), return_index=True)
    seen_ids, seen = np.array([r["vec_id"] for r in chosen], np.int64)[once], sample[once, :-1].T.copy()
    # The forest's size is bounded by the sample; leaves of larger tables are cut into chunks.
    if leaf_rows is None:
        leaf_rows = min(6144, max(16, total // 24))
    forest: list[Tree] = grow_forest(sample, trees, max(8, leaf_rows * len(sample) // total))
    members = leaf_members(forest, sample[once])
    # Small tables are looked through, so that k candidates are found wherever there are as many.
    wanted = int(np.ceil(max(share, min(1.0, 8 * k / total)) * len(once)))
    first_leaf = np.cumsum([0, *[t.leaves for t in forest]])

    def leaves(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _lengthened(_matrix(b.column(1)), norm2)
            for t, tree in enumerate(forest):
                leaf, n = np.unique(tree.leaf_of(x), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(leaf), t, np.int32)), pa.array(leaf.astype(np.int32)), pa.array(n)], ["tree", "leaf", "n"])

    def tally(df: DataFrame) -> list[np.ndarray]:
        out = [np.zeros(t.leaves, np.int64) for t in forest]
        for r in df.groupBy("tree", "leaf").agg(F.sum("n").alias("n")).collect():  # a row per leaf of the forest
            out[r["tree"]][r["leaf"]] = r["n"]
        return out

    counts = tally(good.mapInArrow(leaves, "tree int, leaf int, n long"))

    def ways(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray, np.ndarray, list[np.ndarray]]]:
        for b in batches:
            x = _matrix(b.column(1)).astype(np.float64)
            found, reached = zip(*[probe(forest, members, np.append(v, 0.0), wanted) for v in x], strict=True) if len(x) else ((), ())
            at = np.repeat(np.arange(len(x)), [len(f) for f in found])
            flat = np.array([p for f in found for p in f], np.int64).reshape(-1, 2)
            yield b, at, flat[:, 0], flat[:, 1], reached

    def asked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, _, tree, leaf, _ in ways(batches):
            both, n = np.unique(np.stack([tree, leaf], 1), axis=0, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(both[:, 0].astype(np.int32)), pa.array(both[:, 1].astype(np.int32)), pa.array(n)], ["tree", "leaf", "n"])

    queries = good.where(is_query)
    asks = tally(queries.mapInArrow(asked, "tree int, leaf int, n long"))
    parts_v = [np.maximum(1, -(-c // CHUNK)) for c in counts]
    parts_q = [np.maximum(1, -(-a // CHUNK)) for a in asks]

    def copies(b: pa.RecordBatch, at: np.ndarray, tree: np.ndarray, leaf: np.ndarray, is_row: bool, known: np.ndarray, marks: np.ndarray) -> pa.RecordBatch:
        """Each row to its own chunk of rows (or queries) and to all chunks of the other side."""
        nv, nq = _dealt(tree, leaf, parts_v, parts_q)
        own, other = (nv, nq) if is_row else (nq, nv)
        ids = b.column(0).to_numpy()[at]
        mine = (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(32)).astype(np.int64) % own
        to = np.repeat(np.arange(len(at)), other)
        theirs = np.arange(len(to)) - np.repeat(np.cumsum(other) - other, other)
        v, q = (mine[to], theirs) if is_row else (theirs, mine[to])
        columns = [pa.array(a.astype(np.int32)) for a in (tree[to], leaf[to], v, q)]
        take = pa.array(at[to])
        return pa.RecordBatch.from_arrays([*columns, b.column(0).take(take), b.column(1).take(take), pa.array(known[at[to]]), pa.array([m.tobytes() for m in marks], pa.binary()).take(take)], ["tree", "leaf", "v", "q", "id", "vector", "known", "marks"])

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _lengthened(_matrix(b.column(1)), norm2)
            codes = np.stack([t.leaf_of(x) for t in forest], 1).astype(np.int32)
            for t in range(len(forest)):
                leaf = codes[:, t]
                live = np.flatnonzero(asks[t][leaf] > 0)
                yield copies(b, live, np.full(len(live), t), leaf[live], True, np.zeros(len(x)), codes)

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, at, tree, leaf, reached in ways(batches):
            x, ids = _matrix(b.column(1)).astype(np.float64), b.column(0).to_numpy()
            known = np.empty(len(x))
            for lo in range(0, len(x), 256):
                rough = x[lo : lo + 256] @ seen
                rough[~np.array(reached[lo : lo + 256]) | (ids[lo : lo + 256, None] == seen_ids[None, :])] = -np.inf
                known[lo : lo + 256] = kth_best(rough, k)
            looked = np.zeros((len(x), first_leaf[-1]), bool)
            looked[at, first_leaf[tree] + leaf] = True
            yield copies(b, at, tree, leaf, False, known, np.packbits(looked, axis=1))

    def score(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        tree = int(key[0].as_py())
        ask_ids, ids, known = left["id"].to_numpy(), right["id"].to_numpy(), left["known"].to_numpy()
        if not len(ask_ids) or not len(ids):
            return pa.table({"query_id": left["id"][:0], "vec_id": right["id"][:0], "score": pa.array([], pa.float64()), "looked": pa.array([], pa.int64())})
        x, y = (_matrix(t["vector"].combine_chunks()).astype(np.float64) for t in (left, right))
        into = np.unpackbits(np.frombuffer(b"".join(left["marks"].to_pylist()), np.uint8).reshape(len(x), -1), axis=1, count=int(first_leaf[-1])).astype(bool)
        codes = np.frombuffer(b"".join(right["marks"].to_pylist()), np.int32).reshape(len(y), -1)
        parts, looked = [], np.zeros(len(x), np.int64)
        for rows_ in _layers(ids):  # rows that share a vec_id must not take each other's places
            for lo in range(0, len(x), 512):
                covered = np.zeros((len(x[lo : lo + 512]), len(rows_)), bool)
                for t in range(tree):  # rows that an earlier tree of the query's holds are scored there
                    covered |= into[lo : lo + 512, first_leaf[t] + codes[rows_, t]]
                looked[lo : lo + 512] += (~covered).sum(1)
                q, r, s = best_of(x[lo : lo + 512], ask_ids[lo : lo + 512], known[lo : lo + 512], y[rows_], ids[rows_], k, covered)
                parts.append((q + lo, rows_[r], s))
        q, r, s = (np.concatenate(p) for p in zip(*parts, strict=True))
        found = pa.table({"query_id": pa.array(ask_ids[q], left["id"].type), "vec_id": pa.array(ids[r], right["id"].type), "score": s, "looked": np.zeros(len(q), np.int64)})
        # A query's looks are told on a row without vec_id.
        told = pa.table({"query_id": pa.array(ask_ids, left["id"].type), "vec_id": pa.nulls(len(ask_ids), right["id"].type), "score": pa.nulls(len(ask_ids), pa.float64()), "looked": looked})
        return pa.concat_tables([found, told])

    vector = good.schema["vector"].dataType.simpleString()
    dealt = f"tree int, leaf int, v int, q int, id {kind}, vector {vector}, known double, marks binary"
    by = ("tree", "leaf", "v", "q")
    asking, indexed = queries.mapInArrow(ask, dealt), good.mapInArrow(index, dealt)
    met = asking.groupBy(*by).cogroup(indexed.groupBy(*by)).applyInArrow(score, f"query_id {kind}, vec_id {kind}, score double, looked long")
    one = met.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"), F.sum("looked").alias("looked"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc_nulls_last("score"), "vec_id"))
    looked = F.sum("looked").over(Window.partitionBy("query_id"))
    ranked = one.withColumn("rank", rank).withColumn("looked", looked).where((F.col("rank") <= k) & F.col("vec_id").isNotNull())
    return ranked.select("query_id", "rank", "vec_id", "score", "looked")


def exact(rows: DataFrame, is_query: Column, k: int = 20) -> DataFrame:
    """What search approximates, by brute force within a single task for each query; for tests and for measuring recall."""
    good = usable(rows)
    dot = F.aggregate(F.zip_with("x", "y", lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda s, v: s + v)
    both = good.where(is_query).select(F.col("vec_id").alias("query_id"), F.col("vector").alias("x")).join(good.select("vec_id", F.col("vector").alias("y")), F.col("query_id") != F.col("vec_id"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return both.select("query_id", "vec_id", dot.alias("score")).withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op7_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)
