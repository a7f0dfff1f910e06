"""Secret scans through an incremental ledger of blobs, in DataFrame operations only.

A version is a row: a path (here doc_id) and its whole text. A blob is a distinct text, addressed by the SHA-256 of its
UTF-8. The ledger has one row per blob and rule version with the spans found. A scan reads one text for each blob that
the ledger lacks for this rule version, appends what it finds, and joins the findings of all blobs back to all paths,
so copies, later versions and reruns cost one hash each. Only hashes and ids are grouped; the hot group of a text with
many copies is summed up before the shuffle, and the join back is one that Spark splits at run time.

Spans come from built-in expressions: the lengths of a text's matches and of the pieces between them, summed by a window,
give the offsets, in code points.

Defined cases: null text counts as empty (no spans). Rows that repeat come back once each. A doc_id may be of
any type, and null is a path like any other. Extra columns of the input are not read. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from manyq.llm.common import scratch_path, table, whole_text

RULE_VERSION = "2026-1"

# The patterns of the contract, in the order in which kinds are listed.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{12,}"
HEX = r"[0-9a-f]{32,}"
#: Added by this operator's rule set: a private key's first line, and signed web tokens.
PRIVATE_KEY = r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----"
WEB_TOKEN = r"eyJ[A-Za-z0-9_-]{10,}\.eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}"

BASE_KINDS = ("assign", "access", "hex")
KINDS = (*BASE_KINDS, "private_key", "web_token")
PATTERNS = {"assign": ASSIGN, "access": ACCESS, "hex": HEX, "private_key": PRIVATE_KEY, "web_token": WEB_TOKEN}
#: The least length of group 2, by kind. Greedy runs make a least length in the other patterns the same as dropping after.
LEAST_VALUE = {"assign": 8}

SPANS_TYPE = "array<struct<start:int,kind:int,end:int>>"
STEPS_TYPE = "array<struct<kind:int,at:int,piece:int,hit:int,value:int>>"


def _steps(text: Column, kind: str) -> Column:
    """The kind's matches, leftmost and not overlapping, as lengths in code points: of the piece before, the match, and its value."""
    found = F.regexp_extract_all(text, F.lit(PATTERNS[kind]), F.lit(0))
    pieces = F.split(text, PATTERNS[kind], -1)
    values = F.regexp_extract_all(text, F.lit(PATTERNS[kind]), F.lit(2)) if kind in LEAST_VALUE else found
    steps = F.arrays_zip(F.slice(pieces, 1, F.size(found)).alias("piece"), found.alias("hit"), values.alias("value"))
    lengths = lambda x, i: F.struct(F.lit(KINDS.index(kind)).alias("kind"), i.alias("at"), *[F.char_length(x[c]).alias(c) for c in ("piece", "hit", "value")])
    return F.when(F.size(found) == 0, F.array().cast(STEPS_TYPE)).otherwise(F.transform(steps, lengths))


def blob_spans(blobs: DataFrame) -> DataFrame:
    """(blob, spans) of (blob, text): all spans of a text, by start, then kind as listed. Rows with one blob count once.

    Offsets are running sums of lengths within (blob, kind), so a text's cost grows with its length and its matches alone.
    """
    steps = blobs.select("blob", F.concat(*[_steps(F.col("text"), k) for k in KINDS]).alias("steps"))
    each = steps.groupBy("blob").agg(F.any_value("steps").alias("steps")).select("blob", F.explode_outer("steps").alias("s")).select("blob", "s.*")
    upto = Window.partitionBy("blob", "kind").orderBy("at").rowsBetween(Window.unboundedPreceding, 0)
    placed = each.withColumn("end", F.sum(F.col("piece") + F.col("hit")).over(upto).cast("int"))
    least = F.lit(True)
    for kind, n in LEAST_VALUE.items():
        least = least & ((F.col("kind") != KINDS.index(kind)) | (F.col("value") >= n))
    span = F.struct((F.col("end") - F.col("hit")).alias("start"), F.col("kind"), F.col("end"))
    return placed.groupBy("blob").agg(F.array_sort(F.collect_list(F.when(least & F.col("kind").isNotNull(), span))).cast(SPANS_TYPE).alias("spans"))


def blob_id(text: Column) -> Column:
    return F.unhex(F.sha2(whole_text(text), 256))


def scan_unseen(versions: DataFrame, ledger: DataFrame | None, doc: str = "doc_id", text: str = "text") -> DataFrame:
    """Ledger rows (blob, rule_version, spans) for the blobs of versions that the ledger lacks for this rule version."""
    path = _path(versions, doc).alias("path")
    unseen = versions.select(blob_id(F.col(text)).alias("blob"), path).groupBy("blob").agg(F.min("path").alias("path"))
    if ledger is not None:
        unseen = unseen.join(ledger.where(F.col("rule_version") == RULE_VERSION).select("blob"), "blob", "left_anti")
    texts = versions.select(path, whole_text(F.col(text)).alias("text"))
    one_each = texts.join(unseen.hint("shuffle_hash"), "path", "inner").where(blob_id(F.col("text")) == F.col("blob"))
    return blob_spans(one_each.select("blob", "text")).select("blob", F.lit(RULE_VERSION).alias("rule_version"), "spans")


def _path(versions: DataFrame, doc: str) -> Column:
    """A version's path as something that is never null, of whatever type doc is."""
    whole = versions.schema[doc].dataType.typeName() in ("byte", "short", "integer", "long")
    return F.coalesce(F.col(doc), F.lit(-(2**63))) if whole else F.coalesce(F.concat(F.lit("/"), F.col(doc).cast("string")), F.lit(""))


def brought_up(versions: DataFrame, ledger_path: str, doc: str = "doc_id", text: str = "text") -> DataFrame:
    """The ledger at ledger_path for this rule version, after scanning what it lacked of versions.

    The ledger is a Parquet folder, made where there is none; each scan appends what it scanned.
    """
    spark = versions.sparkSession
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(ledger_path)
    there = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where)
    read = lambda: spark.read.schema(f"blob binary, rule_version string, spans {SPANS_TYPE}").parquet(ledger_path)
    scan_unseen(versions, read() if there else None, doc, text).write.mode("append").parquet(ledger_path)
    return read().where(F.col("rule_version") == RULE_VERSION).select("blob", "spans")


def scan(versions: DataFrame, ledger_path: str, doc: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, blob, spans) for every version, found or not; the ledger at ledger_path is brought up to date."""
    ledger = brought_up(versions, ledger_path, doc, text).where(F.size("spans") > 0)
    paths = versions.select(F.col(doc).alias("doc_id"), blob_id(F.col(text)).alias("blob"))
    found = paths.join(ledger, "blob", "left")
    return found.select("doc_id", "blob", F.coalesce("spans", F.array().cast(SPANS_TYPE)).alias("spans"))


def written(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["start"], x["end"])), ",")


def redact(docs: DataFrame, mark: str = "[SECRET]") -> DataFrame:
    """docs with every span, overlapping ones merged, replaced by the mark. All documents stay; only found texts change."""
    ledger = brought_up(docs, scratch_path(docs.sparkSession, "ledger"))
    before = Window.partitionBy("blob").orderBy("start", "end").rowsBetween(Window.unboundedPreceding, -1)
    each = ledger.where(F.size("spans") > 0).select("blob", F.inline("spans")).withColumn("from", F.coalesce(F.max("end").over(before), F.lit(0)))
    # What stays of a text: before every span that no earlier one reaches, and after the last.
    kept = F.when(F.col("start") >= F.col("from"), F.struct("from", F.col("start").alias("to")))
    cuts = each.groupBy(F.col("blob").alias("manyq__blob")).agg(F.array_sort(F.collect_list(kept)).alias("manyq__cuts"), F.max("end").alias("manyq__tail")).hint("shuffle_hash")
    text = whole_text(docs["text"])
    # Four bytes a code point make a piece's place a product; a mark of byte order before each is what decoding takes away.
    told = F.array(F.struct(F.encode(text, "UTF-32").alias("b"), F.col("manyq__cuts").alias("cuts"), F.col("manyq__tail").alias("tail")))
    piece = lambda b, lo, n: F.decode(F.concat(F.unhex(F.lit("0000FEFF")), F.substr(b, 4 * lo + 1, 4 * n)), "UTF-32")
    clean = lambda x: F.concat(F.array_join(F.transform(x["cuts"], lambda c: F.concat(piece(x["b"], c["from"], c["to"] - c["from"]), F.lit(mark))), ""), piece(x["b"], x["tail"], F.octet_length(x["b"])))
    both = docs.join(cuts, blob_id(docs["text"]) == F.col("manyq__blob"), "left")
    return both.select(*[F.when(F.col("manyq__tail").isNull(), docs["text"]).otherwise(F.get(F.transform(told, clean), 0)).alias("text") if c == "text" else docs[c] for c in docs.columns])


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = scan(docs, scratch_path(spark, "ledger"))
    of = lambda k: F.size(F.filter("spans", lambda x: x["kind"] == KINDS.index(k))).cast("long").alias(f"n_{k}")
    base = F.filter("spans", lambda x: x["kind"] < len(BASE_KINDS))
    return found.select("doc_id", *[of(k) for k in BASE_KINDS], F.sha2(written(base), 256).alias("base_sha256"), written(F.col("spans")).alias("spans"))


def _sql_kind(kind: str, source: str) -> str:
    pattern = PATTERNS[kind].replace("'", "''")
    value = f"regexp_extract_all(t, '{pattern}', 2)" if kind in LEAST_VALUE else "hits"
    return f"""
  SELECT doc_id, start, {KINDS.index(kind)} AS kind, '{kind}' AS name, start + length(hit) AS stop FROM (
    SELECT doc_id, hits[i] AS hit, vals[i] AS val,
           list_sum([length(x) FOR x IN pieces[1:i]])::BIGINT + coalesce(list_sum([length(x) FOR x IN hits[1:i - 1]]), 0)::BIGINT AS start
    FROM (SELECT doc_id, hits, pieces, vals, unnest(range(1, len(hits) + 1)) AS i FROM (
      SELECT doc_id, hits, {value} AS vals, regexp_split_to_array(t, '{pattern}') AS pieces
      FROM (SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '{pattern}') AS hits FROM {source})))
  ) WHERE length(val) >= {LEAST_VALUE.get(kind, 0)}"""


SPANS_SQL = " UNION ALL ".join(_sql_kind(k, "documents") for k in KINDS)

ORACLE_SQL = f"""
WITH s AS ({SPANS_SQL}),
g AS (SELECT doc_id, count(*) FILTER (kind = 0) AS a, count(*) FILTER (kind = 1) AS b, count(*) FILTER (kind = 2) AS c,
        string_agg(concat(name, ':', start, ':', stop), ',' ORDER BY start, kind) FILTER (kind < {len(BASE_KINDS)}) AS base,
        string_agg(concat(name, ':', start, ':', stop), ',' ORDER BY start, kind) AS every
      FROM s GROUP BY doc_id)
SELECT d.doc_id, coalesce(a, 0)::BIGINT AS n_assign, coalesce(b, 0)::BIGINT AS n_access, coalesce(c, 0)::BIGINT AS n_hex,
       sha256(coalesce(base, '')) AS base_sha256, coalesce(every, '') AS spans
FROM documents d LEFT JOIN g ON d.doc_id = g.doc_id
"""
