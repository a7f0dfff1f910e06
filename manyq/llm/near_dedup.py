"""Near duplicates by MinHash with tensored banding, links confirmed on full sets.

A document's set holds the hashes of its distinct word shingles. Instead of fresh hashes for every table, two collections
of `HALVES` small keys, each of two minhashes, are computed, and all pairs of a key from either make the table keys:
2 * 2 * HALVES minhashes stand for HALVES^2 tables of four rows. Two sets of similarity p share a table unless they
miss all keys of a collection; at 0.85 that is about 2e-5.

Equal sets are one class and only their least document goes on. In every table the documents of a key go to the group of
the key's least document, so any two that share a key meet in a group; no pairs are listed. A group is searched twice,
first by the minhashes themselves (at least `AGREE` of 36 agree, which a linked pair fails with 2e-5), which tells whose
full sets are fetched, then exactly on these: a few members are held against all, then each member outside the largest
component against all, through an inverted index, until the group's components are known. Only links that join two
components are returned. Groups too large for a task are cut into blocks, and all pairs of blocks are searched.

Defined cases: null and empty texts have an empty set and link with nothing; texts of fewer words than a shingle are one
shingle as a whole. Rows that repeat are one document, each with the same result. Rows without doc_id link with nothing:
component_id is null and they are kept. Extra columns pass through `keep_least`; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from manyq.llm.arrow import NOT_BLANK, Words, give_back, mix, random_table, slabs, text_bytes
from manyq.llm.common import lean_batches, materialise, table, whole_text
from manyq.llm.components import components

HALVES = 9
HASHES = 4 * HALVES
#: Of the minhashes, how many must agree before full sets are fetched (for similarities of 0.8 and more).
AGREE = 19
#: Members, and shingles, of a group's block.
BLOCK_ROWS, BLOCK_SHINGLES = 4096, 4_000_000


def shingle_sets(texts: list[bytes], words: int) -> list[np.ndarray]:
    """The sorted distinct 64-bit shingle hashes of each text."""
    coder, out = Words(NOT_BLANK), []
    for lo, hi, _ in slabs(texts):
        hashes, first = coder.of([t.lower() for t in texts[lo:hi]])
        n = len(hashes)
        rolled = np.zeros(n, np.uint64)
        for k in range(words):
            if n > k:
                rolled[: n - k] = mix(rolled[: n - k] + hashes[k:])
        for i in range(hi - lo):
            a, b = int(first[i]), int(first[i + 1])
            if b - a >= words:
                out.append(np.unique(rolled[a : b - words + 1]))
            elif b > a:
                out.append(np.array([xxhash.xxh3_64_intdigest(hashes[a:b].tobytes())], np.uint64))
            else:
                out.append(np.empty(0, np.uint64))
    return out


def minhashes(sets: list[np.ndarray]) -> np.ndarray:
    """HASHES 32-bit minhashes of each set; those of an empty set mean nothing."""
    odd, out = random_table(23, HASHES), np.zeros((len(sets), HASHES), np.uint32)
    full = [i for i, s in enumerate(sets) if len(s)]
    at = 0
    while at < len(full):  # a slab of about 100,000 hashes at a time
        to, n = at, 0
        while to < len(full) and (n == 0 or n + len(sets[full[to]]) <= 100_000):
            n += len(sets[full[to]])
            to += 1
        own = full[at:to]
        flat = np.concatenate([sets[i] for i in own])
        first = np.cumsum([0, *[len(sets[i]) for i in own[:-1]]])
        for k in range(HASHES):
            moved = flat * odd[k]
            out[own, k] = (np.minimum.reduceat(moved ^ (moved >> np.uint64(32)), first) >> np.uint64(32)).astype(np.uint32)
        at = to
    return out


def signatures(docs: DataFrame, words: int) -> DataFrame:
    """(doc_id, n, digest, hashes): size and 128-bit digest of the set, and its minhashes."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = shingle_sets(text_bytes(batch.column(1)), words)
            hashes = minhashes(sets)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(map(len, sets), pa.int64()), pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in sets], pa.binary()), pa.array([h.tobytes() for h in hashes], pa.binary())], ["doc_id", "n", "digest", "hashes"])
        give_back()

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n long, digest binary, hashes binary")


def table_keys(signed: DataFrame) -> DataFrame:
    """(key, doc_id): HALVES^2 rows for every row of (doc_id, hashes)."""
    kind = signed.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        salt = random_table(29, HALVES * HALVES).reshape(1, HALVES, HALVES)
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                part = batch.slice(lo, 1000)
                h = np.frombuffer(b"".join(part.column(1).to_pylist()), np.uint32).reshape(-1, HASHES).astype(np.uint64)
                half = mix(h[:, 0::2] << np.uint64(32) | h[:, 1::2])
                keys = mix(half[:, :HALVES, None] + mix(half[:, None, HALVES:] + salt))
                ids = part.column(0).take(pa.array(np.repeat(np.arange(part.num_rows), HALVES * HALVES)))
                yield pa.RecordBatch.from_arrays([pa.array(keys.ravel().view(np.int64)), ids], ["key", "doc_id"])
        give_back()

    return signed.select("doc_id", "hashes").mapInArrow(run, f"key long, doc_id {kind}")


def _blocked(members: DataFrame, weight: str, most: int) -> DataFrame:
    """members (g, doc_id, n, ...) with block, a, b: each row goes to all pairs of blocks (a <= b) that its own is in."""
    blocks = members.groupBy("g").agg(F.ceil(F.sum(weight) / most).cast("int").alias("blocks")).where("blocks > 1")
    own = members.join(blocks, "g", "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    own = own.withColumn("block", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int"))
    pairs = own.withColumn("other", F.explode(F.when(F.col("blocks") == 1, F.array(F.lit(0))).otherwise(F.sequence(F.lit(0), F.col("blocks") - 1))))
    return pairs.withColumns({"a": F.least("block", "other"), "b": F.greatest("block", "other")}).drop("blocks", "other")


def _fits(n: np.ndarray, of: int, percent: int) -> np.ndarray:
    return 100 * np.minimum(n, of) >= percent * np.maximum(n, of)


def _live(ids: list, hashes: np.ndarray, n: np.ndarray, block: np.ndarray, percent: int) -> np.ndarray:
    """Which members have another that sizes and minhashes allow to link."""
    live = np.zeros(len(ids), bool)
    apart = len(set(block.tolist())) > 1
    for i in range(len(ids)):
        may = _fits(n, int(n[i]), percent)
        if apart:
            may &= block != block[i]
        may[i] = False
        at = np.flatnonzero(may)
        if len(at):
            hit = at[(hashes[at] == hashes[i]).sum(1) >= AGREE]
            if len(hit):
                live[i] = True
                live[hit] = True
    return live


def _links(sets: list[np.ndarray], n: np.ndarray, block: np.ndarray, percent: int) -> list[tuple[int, int]]:
    """Links that make the members' components, found exactly."""
    m = len(sets)
    owner = np.repeat(np.arange(m), n)
    flat = np.concatenate(sets)
    order = np.argsort(flat, kind="stable")
    tokens, owner = flat[order], owner[order]
    parent = list(range(m))
    out: list[tuple[int, int]] = []
    apart = len(set(block.tolist())) > 1

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    def against_all(y: int) -> None:
        lo, hi = np.searchsorted(tokens, sets[y], "left"), np.searchsorted(tokens, sets[y], "right")
        size = hi - lo
        places = np.repeat(lo - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(int(size.sum()))
        shared = np.bincount(owner[places], minlength=m)
        for x in np.flatnonzero(100 * shared >= percent * (n + n[y] - shared)).tolist():
            if x != y and not (apart and block[x] == block[y]) and (a := root(x)) != (b := root(y)):
                parent[max(a, b)] = min(a, b)
                out.append((x, y))

    done = set(range(0, m, max(1, m // 4)))
    for y in done:
        against_all(y)
    roots = [root(x) for x in range(m)]
    largest = int(np.bincount(roots).argmax())
    for y in range(m):
        if y not in done and roots[y] != largest:
            against_all(y)
    return out


def find_groups(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """One row per row of docs: doc_id, n_shingles, component_id, kept. Documents link from a similarity of percent / 100."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    lean_batches(docs.sparkSession)
    signed = materialise(signatures(docs, words), "signed")
    classes = signed.where(F.col("doc_id").isNotNull() & (F.col("n") > 0)).groupBy("digest").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies"))
    classes = materialise(classes, "classes")
    alone = signed.join(classes.select("digest", "doc_id"), ["digest", "doc_id"], "left_semi").dropDuplicates(["digest", "doc_id"])
    keys = table_keys(alone)
    shared = keys.groupBy("key").agg(F.min("doc_id").alias("g"), F.count("*").alias("rows")).where("rows > 1").select("key", "g")
    met = keys.join(shared.hint("shuffle_hash"), "key").select("g", "doc_id").distinct()
    met = materialise(met.join(alone.select("doc_id", "n", "hashes"), "doc_id"), "met")

    def sift(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches(list(batches))
        hashes = np.frombuffer(b"".join(rows["hashes"].to_pylist()), np.uint32).reshape(-1, HASHES)
        live = _live(rows["doc_id"].to_pylist(), hashes, rows["n"].to_numpy(), rows["block"].to_numpy(), percent)
        yield from rows.select(["g", "doc_id"]).filter(pa.array(live)).combine_chunks().to_batches()

    one = F.lit(1)
    dealt = _blocked(met.withColumn("one", one), "one", BLOCK_ROWS).drop("one")
    live = materialise(dealt.groupBy("g", "a", "b").applyInArrow(sift, f"g {kind}, doc_id {kind}").distinct(), "live")

    def own_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = shingle_sets(text_bytes(batch.column(1)), words)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(map(len, sets), pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], ["doc_id", "n", "shingles"])
        give_back()

    texts = docs.select("doc_id", "text").join(live.select("doc_id").distinct().hint("shuffle_hash"), "doc_id", "left_semi")
    sets = texts.mapInArrow(own_sets, f"doc_id {kind}, n long, shingles binary")

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches(list(batches)).sort_by("doc_id")
        own = [np.frombuffer(s, np.uint64) for s in rows["shingles"].to_pylist()]
        found = _links(own, rows["n"].to_numpy(), rows["block"].to_numpy(), percent)
        ids = rows["doc_id"].combine_chunks()
        yield pa.RecordBatch.from_arrays([ids.take(pa.array([x[k] for x in found], pa.int32())) for k in (0, 1)], ["u", "v"])

    full = live.join(sets, "doc_id")
    links = _blocked(full, "n", BLOCK_SHINGLES).groupBy("g", "a", "b").applyInArrow(search, f"u {kind}, v {kind}")
    least = components(links)
    # From a class's least document to the least of its component; classes of one document need no join on the digest.
    of_class = classes.join(least, classes["doc_id"] == least["node"], "left").select("digest", F.coalesce("component", "doc_id").alias("component_id"), "copies", F.col("component").isNotNull().alias("moved"))
    known = of_class.where("copies > 1 OR moved").select("digest", "component_id").hint("shuffle_hash")
    found = signed.select("doc_id", "n", "digest").join(known, "digest", "left")
    component = F.when(F.col("doc_id").isNull() | (F.col("n") == 0) | F.col("component_id").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
    return found.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def keep_least(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """docs without those that link to a document of a smaller doc_id in their component. A doc_id that several texts share names no one document: its rows stay."""
    gone = find_groups(docs, words, percent).where(~F.col("kept")).select("doc_id")
    own = docs.select("doc_id", F.xxhash64(whole_text(F.col("text"))).alias("h")).join(gone.hint("shuffle_hash"), "doc_id", "left_semi")
    sure = own.groupBy(F.col("doc_id").alias("manyq__gone")).agg(F.min("h").alias("least"), F.max("h").alias("most")).where("least = most").select("manyq__gone").hint("shuffle_hash")
    return docs.join(sure, F.col("doc_id") == F.col("manyq__gone"), "left_anti")


def op5_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_groups(table(spark, sf_dir, "documents"), words=3, percent=85)


def groups_sql(docs: str, words: int, percent: int, name: str) -> str:
    """Common tables name_sets (doc_id, n_shingles) and name_least (doc_id, component_id) by brute force."""
    grams = " || ' ' || ".join(f"w[i + {k}]" if k else "w[i]" for k in range(words))
    return f"""
{name}_words AS (
  SELECT doc_id, [x FOR x IN regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[ \\x09-\\x0D]+') IF x <> ''] AS w
  FROM {docs}),
{name}_shingles AS (
  SELECT DISTINCT doc_id, CASE WHEN len(w) >= {words} THEN {grams} ELSE array_to_string(w, ' ') END AS s
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - {words - 1}, 1) + 1)) AS i FROM {name}_words WHERE len(w) > 0)),
{name}_sets AS (SELECT d.doc_id, count(s) AS n_shingles FROM {docs} d LEFT JOIN {name}_shingles s ON d.doc_id = s.doc_id GROUP BY d.doc_id),
{name}_pairs AS (SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS hits FROM {name}_shingles a JOIN {name}_shingles b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY 1, 2),
{name}_links AS (
  SELECT u, v FROM {name}_pairs JOIN {name}_sets a ON a.doc_id = u JOIN {name}_sets b ON b.doc_id = v
  WHERE 100 * hits >= {percent} * (a.n_shingles + b.n_shingles - hits)),
{name}_reach AS (
  SELECT doc_id, doc_id AS component_id FROM {name}_sets
  UNION
  SELECT l.v, r.component_id FROM {name}_reach r JOIN {name}_links l ON l.u = r.doc_id),
{name}_least AS (SELECT doc_id, min(component_id) AS component_id FROM {name}_reach GROUP BY doc_id)"""


ORACLE_SQL = (
    "WITH RECURSIVE "
    + groups_sql("documents", 3, 85, "op5")
    + " SELECT s.doc_id, s.n_shingles, l.component_id, s.doc_id = l.component_id AS kept FROM op5_sets s JOIN op5_least l ON s.doc_id = l.doc_id"
)
