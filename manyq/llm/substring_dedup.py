"""Repeated substrings by suffix sorting: every byte that a string of `SPAN` bytes covers which also starts earlier goes.

All suffixes of a corpus cannot be sorted in one place, and most repeat nothing. So every start of a 100-byte string is
given an anchor: of the string's 24-byte grams the one of least hash. Equal strings have equal anchors at equal offsets,
and neighbouring starts mostly share one, so an anchor stands for a run of about 38 starts. Anchors that occur once are
done. Of the rest, runs whose bytes agree as a whole (by the anchor's and their own 64-bit hashes) are copies of the first
of them. Where an anchor
has different runs, as at the edges of a repeated passage, the first run of each kind goes to a deep-shallow suffix sort,
which finds the equal 100-byte strings among them and so the first start of each. An anchor of very many kinds of runs is
cut by the hash of the 100-byte strings themselves, which keeps equal ones together, so that no task's work grows with it.

Hashes, ids and run lengths are moved; texts move by doc_id alone, once for the edges' bytes and once to be cut.

Defined cases: null text counts as empty; texts under 100 bytes lose nothing. Rows without doc_id match nothing and lose
nothing. Rows that repeat with one doc_id are one document: none makes the other a repeat, and what is found in one is
removed from all of them. Extra columns pass through `without_repeats`; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from manyq.llm.arrow import _powers_to, mix, random_table, slabs, text_bytes
from manyq.llm.common import lean_batches, materialise, table
from manyq.llm.suffix_sort import equal_runs

SPAN, GRAM = 100, 24
#: Kinds of runs of one anchor beyond which it is cut by the strings' hashes.
MOST_KINDS = 2000
#: Bytes of a segment: a segment's places fit the low bits of an anchor's sort key.
PLACE_BITS = 20
SEGMENT = 900_000


def runs_of(texts: list[bytes], span: int = SPAN) -> tuple[np.ndarray, ...]:
    """(row, first start, starts, anchor hash, hash of the run's bytes) of the runs of starts that share an anchor, over all texts."""
    values, others, out = random_table(41), random_table(43), []
    width, low = span - GRAM + 1, np.uint64((1 << PLACE_BITS) - 1)

    def add(slab: np.ndarray, row: np.ndarray, valid: np.ndarray, base: np.ndarray) -> None:
        """row, valid, base: of every start in the slab its text, whether its string ends there too, its text's first place."""
        up, down = _powers_to(len(slab))
        sums = np.zeros(len(slab) + 1, np.uint64)
        np.cumsum(values[slab] * up[: len(slab)], out=sums[1:])
        grams = mix((sums[GRAM:] - sums[:-GRAM]) * down[: len(slab) - GRAM + 1])
        least, step = (grams & ~low) | np.arange(len(grams), dtype=np.uint64), 1
        while step * 2 <= width:
            least = np.minimum(least[:-step], least[step:])
            step *= 2
        if step < width:
            least = np.minimum(least[: len(least) - (width - step)], least[width - step :])
        at = np.flatnonzero(valid[: len(least)])
        anchor = (least[at] & low).astype(np.int64)
        first = np.flatnonzero(np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (row[at[1:]] != row[at[:-1]])])) if len(at) else np.empty(0, np.int64)
        start, n = at[first], np.diff(np.append(first, len(at)))
        np.cumsum(others[slab] * up[: len(slab)], out=sums[1:])
        whole = mix((sums[start + n + (span - 1)] - sums[start]) * down[start])
        out.append((row[start], start - base[start], n, grams[anchor[first]], whole))

    for lo, hi, at in slabs(texts, SEGMENT):
        if hi - lo == 1 and len(texts[lo]) > SEGMENT:
            for s in range(0, len(texts[lo]) - span + 1, SEGMENT):
                part = np.frombuffer(texts[lo], np.uint8)[s : s + SEGMENT + span - 1]
                n = len(part)
                add(part, np.full(n, lo), np.arange(n) <= n - span, np.full(n, -s))
            continue
        slab = np.frombuffer(b"".join(texts[lo:hi]), np.uint8)
        if len(slab) < span:
            continue
        size = np.diff(at)
        row, base = np.repeat(np.arange(lo, hi), size), np.repeat(at[:-1], size)
        add(slab, row, np.arange(len(slab)) + span <= np.repeat(at[1:], size), base)
    parts = list(zip(*out, strict=True)) or [[]] * 5
    kinds = (np.int64, np.int64, np.int64, np.uint64, np.uint64)
    return tuple(np.concatenate(p) if len(p) else np.empty(0, k) for p, k in zip(parts, kinds, strict=True))  # type: ignore[return-value]


def _anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(h, n): the anchors of a batch and how many runs each has there."""
    for batch in batches:
        h, n = np.unique(runs_of(text_bytes(batch.column(1)))[3], return_counts=True)
        yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(n.astype(np.int64))], ["h", "n"])


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(h, c, doc, start, n): every run with its anchor's hash and its bytes'."""
    for batch in batches:
        row, start, n, h, c = runs_of(text_bytes(batch.column(1)))
        yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(c.view(np.int64)), batch.column(0).take(pa.array(row)), pa.array(start.astype(np.int32)), pa.array(n.astype(np.int32))], ["h", "c", "doc", "start", "n"])


def _strings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From (doc, text, runs): the bytes of runs; those of an anchor of many kinds string by string, dealt by their hashes."""
    for batch in batches:
        texts = text_bytes(batch.column(1))
        row, h, part, start, n, body = [], [], [], [], [], []
        for i, runs in enumerate(batch.column(2).to_pylist()):
            for r in runs:
                s, k, parts = r["start"], r["n"], -(-r["kinds"] // MOST_KINDS)
                for a, m in [(s, k)] if parts == 1 else [(s + j, 1) for j in range(k)]:
                    own = texts[i][a : a + m + SPAN - 1]
                    row.append(i)
                    h.append(r["h"])
                    part.append(0 if parts == 1 else 1 + xxhash.xxh3_64_intdigest(own) % (parts * 32))
                    start.append(a)
                    n.append(m)
                    body.append(own)
        yield pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(part, pa.int64()), batch.column(0).take(pa.array(row, pa.int32())), pa.array(start, pa.int32()), pa.array(n, pa.int32()), pa.array(body, pa.binary())], ["h", "part", "doc", "start", "n", "body"])


def _later_starts(rows: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """(row, start) of all starts whose string is found at an earlier start of rows."""
    n = rows["n"].to_numpy().astype(np.int64)
    bodies = rows["body"].to_pylist()
    size = np.array([len(b) for b in bodies], np.int64)
    base = np.cumsum(size) - size
    row = np.repeat(np.arange(len(n)), n)
    within = np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)
    doc, start = rows["doc"].to_pylist(), rows["start"].to_numpy().astype(np.int64)[row] + within
    late = []
    for same in equal_runs(np.frombuffer(b"".join(bodies), np.uint8), base[row] + within, SPAN):
        least = min((doc[row[i]], start[i]) for i in same)
        late += [i for i in same if (doc[row[i]], start[i]) > least]
    at = np.sort(np.array(late, np.int64))
    return row[at], start[at]


def _sorted_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Over rows in the order of (h, part): the spans that later starts cover. Works on whole groups, many at a time."""

    def spans(rows: pa.Table) -> pa.RecordBatch:
        row, start = _later_starts(rows)
        first = np.flatnonzero(np.concatenate([[True], (row[1:] != row[:-1]) | (start[1:] != start[:-1] + 1)])) if len(row) else np.empty(0, np.int64)
        last = np.append(first[1:], len(row)) - 1 if len(row) else first
        return pa.RecordBatch.from_arrays([rows["doc"].combine_chunks().take(pa.array(row[first])), pa.array(start[first].astype(np.int32)), pa.array((start[last] + SPAN).astype(np.int32))], ["doc", "a", "b"])

    held: list[pa.RecordBatch] = []
    size = 0
    for batch in batches:
        for lo in range(0, batch.num_rows, 2000):
            part = batch.slice(lo, 2000)
            if size > 4_000_000:
                rows = pa.Table.from_batches([*held, part])
                h, p = rows["h"].to_numpy(), rows["part"].to_numpy()
                new = np.flatnonzero((h[1:] != h[:-1]) | (p[1:] != p[:-1]))
                if len(new):
                    yield spans(rows.slice(0, int(new[-1]) + 1))
                    held, size = rows.slice(int(new[-1]) + 1).combine_chunks().to_batches(), 0
                    continue
            held.append(part)
            size += pc.sum(pc.binary_length(part.column(5))).as_py() or 0
    if held:
        yield spans(pa.Table.from_batches(held))


def _rank(doc: str, start: str):
    """(doc, start) as one number that orders alike."""
    return F.col(doc).cast("decimal(20,0)") * F.lit(2**31).cast("decimal(10,0)") + F.col(start).cast("decimal(10,0)")


def _settled(df: DataFrame, label: str) -> DataFrame:
    """df written, and Spark told to let go of the shuffle files that made it: it does so when the driver collects garbage."""
    out = materialise(df, label)
    df.sparkSession.sparkContext._jvm.System.gc()
    return out


def repeated_spans(docs: DataFrame) -> DataFrame:
    """(doc, a, b): spans of bytes to remove; those of one document may overlap."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    lean_batches(docs.sparkSession)
    texts = docs.where(F.col("doc_id").isNotNull() & (F.octet_length("text") >= SPAN)).select(F.col("doc_id").alias("doc"), "text")
    shared = texts.mapInArrow(_anchors, "h long, n long").groupBy("h").agg(F.sum("n").alias("n")).where("n > 1").select("h").hint("shuffle_hash")
    runs = _settled(texts.mapInArrow(_runs, f"h long, c long, doc {kind}, start int, n int").join(shared, "h"), "runs")
    firsts = runs.groupBy("h", "c").agg(F.min(_rank("doc", "start")).alias("least"), F.min("n").alias("n"), F.count("*").alias("rows"))
    firsts = _settled(firsts, "firsts")
    copied = runs.join(firsts.where("rows > 1").select("h", "c", "least").hint("shuffle_hash"), ["h", "c"]).where(_rank("doc", "start") > F.col("least"))
    whole = _settled(copied.select("doc", F.col("start").alias("a"), (F.col("start") + F.col("n") + F.lit(SPAN - 1)).alias("b")), "copied")
    many = firsts.groupBy("h").agg(F.count("*").alias("kinds")).where("kinds > 1").hint("shuffle_hash")
    block = F.lit(2**31).cast("decimal(10,0)")
    heads = firsts.join(many, "h").select(F.floor(F.col("least") / block).cast(kind).alias("doc"), F.struct("h", F.pmod("least", block).cast("int").alias("start"), "n", "kinds").alias("run"))
    wanted = heads.groupBy("doc").agg(F.collect_list("run").alias("runs")).hint("shuffle_hash")
    strings = texts.join(wanted, "doc").select("doc", "text", "runs").mapInArrow(_strings, f"h long, part long, doc {kind}, start int, n int, body binary")
    dealt = strings.repartition("h", "part").sortWithinPartitions("h", "part")
    edges = _settled(dealt.mapInArrow(_sorted_out, f"doc {kind}, a int, b int"), "edges")
    return whole.unionByName(edges)


def cut_spans(docs: DataFrame, spans: DataFrame) -> DataFrame:
    """All columns of docs, `manyq__kept` (the bytes that stay), `manyq__bytes`, `manyq__removed` and `manyq__spans` (removed bytes, maximal removed runs)."""
    listed = spans.groupBy(F.col("doc").alias("manyq__doc")).agg(F.collect_list(F.struct("a", "b")).alias("manyq__cuts")).hint("shuffle_hash")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names = batch.schema.names
            kept, sizes, gone, runs = [], [], [], []
            for text, cuts in zip(text_bytes(batch.column(names.index("text"))), batch.column(names.index("manyq__cuts")).to_pylist(), strict=True):
                at, out, count = 0, [], 0
                last = -1
                for a, b in sorted((c["a"], min(c["b"], len(text))) for c in cuts or ()):
                    if a > last:
                        count += 1
                        out.append(text[at:a])
                    at = last = max(last, b)
                out.append(text[at:])
                kept.append(b"".join(out))
                sizes.append(len(text))
                gone.append(len(text) - len(kept[-1]))
                runs.append(count)
            columns = [batch.column(i) for i, c in enumerate(names) if c != "manyq__cuts"]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(kept, pa.binary()), *[pa.array(x, pa.int64()) for x in (sizes, gone, runs)]], [*[c for c in names if c != "manyq__cuts"], "manyq__kept", "manyq__bytes", "manyq__removed", "manyq__spans"])

    schema = type(docs.schema)([*docs.schema.fields]).add("manyq__kept", "binary").add("manyq__bytes", "long").add("manyq__removed", "long").add("manyq__spans", "long")
    joined = docs.join(listed, F.col("doc_id") == F.col("manyq__doc"), "left").select(*[docs[c] for c in docs.columns], "manyq__cuts")
    return joined.mapInArrow(run, schema)


def without_repeats(docs: DataFrame) -> DataFrame:
    """docs with the bytes that stay as their text, in UTF-8; a character that a span's border cuts is replaced."""
    cut = cut_spans(docs, repeated_spans(docs))
    return cut.select(*[F.decode("manyq__kept", "UTF-8").alias("text") if c == "text" else F.col(c) for c in docs.columns])


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    cut = cut_spans(docs, repeated_spans(docs))
    return cut.select("doc_id", F.col("manyq__bytes").alias("n_bytes"), F.col("manyq__removed").alias("n_removed"), F.col("manyq__spans").alias("n_spans"), F.sha2("manyq__kept", 256).alias("kept_sha256"))


def brute_force(rows: list[tuple[int, str | None]], span: int = SPAN) -> list[tuple[int, int, int, int, str]]:
    """The same by a table of all strings, for tests: (doc_id, n_bytes, n_removed, n_spans, kept_sha256)."""
    seen: set[bytes] = set()
    out = []
    for doc, text in sorted(rows, key=lambda r: r[0]):
        raw = (text or "").encode()
        gone = bytearray(len(raw))
        for i in range(len(raw) - span + 1):
            if (s := raw[i : i + span]) in seen:
                gone[i : i + span] = b"\x01" * span
            seen.add(s)
        kept = bytes(c for c, g in zip(raw, gone, strict=True) if not g)
        out.append((doc, len(raw), sum(gone), len([x for x in bytes(gone).split(b"\x00") if x]), hashlib.sha256(kept).hexdigest()))
    return out
