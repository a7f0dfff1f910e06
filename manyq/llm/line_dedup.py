"""Line deduplication with keep bitmaps, in DataFrame operations only.

Every line's key is hashed to 128 bits. The hashes are dealt to equal ranges of the hash space (hashes are uniform, so
equal ranges need no sampling pass), sorted by (hash, document, position), and streamed: the first document of a run
keeps its lines, the others lose theirs. A line that a third of all documents hold would fill one range, so this is
done twice: first with a salt from the document, which spreads a hash over all ranges and leaves one document per hash
and salt, then over those few. Only hashes, ids and positions are moved; what comes back is one row for each document
that loses lines, with a bitmap in 64-bit words of which all-ones words are left out.

Defined cases: null text counts as empty, one empty line. A row without doc_id takes no part and stays whole. Rows
with equal doc_id are one document: none of them makes the other's lines repeats. Rows that repeat wholly get equal
bitmaps. Extra columns pass through `apply_bitmaps`; columns of the docs named like the bitmaps' own are kept, as the
bitmaps travel under one name, `manyq__line_drops`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from manyq.llm.common import BLANKS, ascii_lower, shuffle_width, table, whole_text

WORD = 64
#: Hash ranges to a shuffle partition, so that partitions come out even.
LANES = 16


def lines_of(text: Column) -> Column:
    return F.split(whole_text(text), "\n", -1)


def line_key(line: Column) -> Column:
    return ascii_lower(F.btrim(line, F.lit(BLANKS)))


def _row_key(text: Column) -> Column:
    return F.xxhash64(whole_text(text))


def _in_ranges(df: DataFrame, n: int, salt: Column) -> DataFrame:
    """Deal rows to equal ranges of the hash space, many to a partition, each moved on by the salt."""
    lanes = LANES * n
    lane = F.shiftright(F.shiftrightunsigned("h1", 33) * F.lit(lanes), 31)
    return df.withColumn("lane", F.pmod(lane + salt * LANES, F.lit(lanes)).cast("int")).repartition(n, "lane")


def drop_bitmaps(docs: DataFrame, min_chars: int = 10, doc: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document that loses lines: doc, row_key, drops array<struct<word int, bits bigint>>.

    A cleared keep bit is a set bit here; words without any are left out (the keep bitmap's all-ones words).
    """
    n = shuffle_width(docs.sparkSession)
    lines = (
        docs.where(F.col(doc).isNotNull())
        .select(F.col(doc).alias("doc"), _row_key(F.col(text)).alias("row_key"), F.posexplode(lines_of(F.col(text))).alias("pos", "line"))
        .select("doc", "row_key", "pos", line_key(F.col("line")).alias("key"))
        .where(F.char_length("key") >= min_chars)
        .select("doc", "row_key", "pos", F.xxhash64("key").alias("h1"), F.xxhash64(F.lit(0x5EED), "key").alias("h2"))
        .withColumn("salt", F.pmod(F.xxhash64("doc"), F.lit(n)).cast("int"))
    )
    stream = lambda *by: F.first("doc").over(Window.partitionBy("lane", *by).orderBy("doc", "pos").rowsBetween(Window.unboundedPreceding, 0))
    salted = _in_ranges(lines, n, F.col("salt")).withColumn("first_doc", stream("h1", "h2", "salt"))
    late = salted.where(F.col("doc") > F.col("first_doc")).select("doc", "row_key", "pos")
    left = salted.where(F.col("doc") == F.col("first_doc")).select("doc", "row_key", "pos", "h1", "h2")
    rest = _in_ranges(left, n, F.lit(0)).withColumn("first_doc", stream("h1", "h2"))
    drops = late.unionByName(rest.where(F.col("doc") > F.col("first_doc")).select("doc", "row_key", "pos"))
    words = drops.groupBy("doc", "row_key", F.floor(F.col("pos") / WORD).cast("int").alias("word")).agg(
        F.bit_or(F.expr(f"shiftleft(1L, pos % {WORD})")).alias("bits")
    )
    return words.groupBy("doc", "row_key").agg(F.collect_list(F.struct("word", "bits")).alias("manyq__line_drops"))


def apply_bitmaps(docs: DataFrame, bitmaps: DataFrame, doc: str = "doc_id", text: str = "text") -> DataFrame:
    """docs with `manyq__lines` (long, before dropping), `manyq__dropped` (long) and `manyq__kept` (the lines that stay, joined)."""
    lines, drops = lines_of(F.col(text)), F.col("manyq__line_drops")
    n_words = F.floor((F.size(lines) + WORD - 1) / WORD).cast("int")
    by_word = F.map_from_entries(drops)
    dense = F.transform(F.sequence(F.lit(0), n_words - 1), lambda w: F.coalesce(by_word[w], F.lit(0).cast("long")))
    clear = lambda i: F.get(F.col("manyq__dense"), F.floor(i / WORD).cast("int")).bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), i % WORD)) == 0
    side = bitmaps.select(F.col("doc").alias("manyq__doc"), F.col("row_key").alias("manyq__row"), "manyq__line_drops").hint("shuffle_hash")
    joined = docs.join(side, (F.col(doc) == F.col("manyq__doc")) & (_row_key(F.col(text)) == F.col("manyq__row")), "left")
    return (
        joined.withColumn("manyq__lines", F.size(lines).cast("long"))
        .withColumn("manyq__dropped", F.coalesce(F.aggregate(drops, F.lit(0).cast("long"), lambda s, w: s + F.bit_count(w["bits"])), F.lit(0).cast("long")))
        .withColumn("manyq__dense", F.when(drops.isNotNull(), dense))
        .withColumn("manyq__kept", F.when(drops.isNull(), whole_text(F.col(text))).otherwise(F.array_join(F.filter(lines, lambda _, i: clear(i)), "\n")))
        .drop("manyq__doc", "manyq__row", "manyq__line_drops", "manyq__dense")
    )


def dedup_lines(docs: DataFrame, min_chars: int = 10) -> DataFrame:
    """docs with the lines that stay as their text; every document stays."""
    kept = apply_bitmaps(docs, drop_bitmaps(docs, min_chars))
    return kept.select(*[F.col("manyq__kept").alias("text") if c == "text" else F.col(c) for c in docs.columns])


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    kept = apply_bitmaps(docs, drop_bitmaps(docs))
    return kept.select("doc_id", F.col("manyq__lines").alias("n_lines"), F.col("manyq__dropped").alias("n_dropped"), F.sha2("manyq__kept", 256).alias("kept_sha256"))


#: Also the second stage of the pipeline's SQL; {docs} is the table it reads.
LINES_SQL = """
{name}_lines AS (
  SELECT doc_id, i AS pos, parts[i] AS line,
         translate(trim(parts[i], chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM (SELECT doc_id, parts, unnest(range(1, len(parts) + 1)) AS i
        FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM {docs}))),
{name}_first AS (SELECT key, min(doc_id) AS f FROM {name}_lines WHERE length(key) >= 10 GROUP BY key),
{name}_out AS (
  SELECT l.doc_id, count(*) AS n_lines,
         count(*) FILTER (coalesce(l.doc_id > f.f, false)) AS n_dropped,
         coalesce(string_agg(l.line, chr(10) ORDER BY l.pos) FILTER (NOT coalesce(l.doc_id > f.f, false)), '') AS kept
  FROM {name}_lines l LEFT JOIN {name}_first f ON l.key = f.key
  GROUP BY l.doc_id)"""

ORACLE_SQL = (
    "WITH "
    + LINES_SQL.format(name="op1", docs="documents")
    + " SELECT doc_id, n_lines::BIGINT AS n_lines, n_dropped::BIGINT AS n_dropped, sha256(kept) AS kept_sha256 FROM op1_out"
)
