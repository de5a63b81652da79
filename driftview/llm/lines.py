"""Removal of lines that many documents share."""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftview.llm.scratch import columns, fresh, materialize

BLANKS = " \t\n\x0b\x0c\r"


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z and nothing else; the fast built-in where there is only ASCII."""
    plain = F.octet_length(text) == F.char_length(text)
    return F.when(plain, F.lower(text)).otherwise(F.translate(text, string.ascii_uppercase, string.ascii_lowercase))


def line_key(line: Column) -> Column:
    return F.btrim(line, F.lit(BLANKS))


def _digest(key: Column) -> Column:
    return F.struct(F.xxhash64(key).alias("h1"), F.xxhash64(F.lit("line"), key).alias("h2"))


def shared_lines(docs: DataFrame, doc_id: str, text: str, min_chars: int, min_documents: int) -> tuple[DataFrame, DataFrame]:
    """Distinct line keys of each document as (doc_id, h1, h2), and those of ``min_documents`` or more with the document that keeps them."""
    keys = F.array_distinct(F.filter(F.transform(F.split(ascii_lower(F.col(text)), "\n"), line_key), lambda k: F.char_length(k) >= min_chars))
    found = docs.where(F.col(doc_id).isNotNull()).select(F.col(doc_id).alias("doc_id"), F.explode(F.transform(keys, _digest)).alias("k")).select("doc_id", "k.h1", "k.h2")
    heavy = found.groupBy("h1", "h2").agg(F.count_distinct("doc_id").alias("n"), F.max("doc_id").alias("keeper")).where(F.col("n") >= min_documents)
    return found, materialize(heavy.select("h1", "h2", "keeper"), "shared-lines", by_size=True)


def drop_shared_lines(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", min_chars: int = 40, min_documents: int = 5) -> DataFrame:
    """The documents' columns with ``text`` less its shared lines, and two counts, (n_lines, n_dropped), in ``line_counts``.

    A line's key is the line without white space of ASCII at its ends and with
    A-Z in lower case.  Keys of ``min_chars`` code points or more that stand in
    ``min_documents`` distinct ids or more are dropped from all documents but
    the one of largest id.  Keys are compared by 128 bits of hashes.

    Counts are combined before they are shuffled; lines meet the keys to drop
    in an equi-join, which splits hot keys; each document gets the keys that it
    loses, and its lines are filtered in place, so their order never changes.
    A null or empty text is one empty line.  Rows with a null id lose nothing
    and are not counted.  Repeated rows of an id count once and lose the same
    lines.  An empty table gives an empty result; other columns pass through, but for one
    named line_counts, which is replaced.
    """
    found, heavy = shared_lines(docs, doc_id, text, min_chars, min_documents)
    lost = found.join(heavy, ["h1", "h2"]).where("doc_id <> keeper").groupBy("doc_id").agg(F.collect_set(F.struct("h1", "h2")).alias("__lost"))
    kept_name, lost_name, owner = (fresh(docs, x) for x in ("__kept", "__lost", "__owner"))
    lost = lost.select(F.col("doc_id").alias(owner), F.col("__lost").alias(lost_name))
    whole = F.coalesce(F.col(text), F.lit(""))
    lines = F.split(whole, "\n")
    pairs = F.filter(F.arrays_zip(lines.alias("line"), F.split(ascii_lower(whole), "\n").alias("key")), lambda p: ~F.array_contains(F.col(lost_name), _digest(line_key(p["key"]))))
    kept = F.when(F.col(lost_name).isNull(), lines).otherwise(F.transform(pairs, lambda p: p["line"]))
    joined = docs.join(lost, docs[doc_id] == lost[owner], "left")
    n = F.size(lines).cast("long")
    rest = [c for c, name in zip(columns(docs), docs.columns, strict=True) if name != "line_counts"]
    out = joined.withColumn(kept_name, kept).withColumn("line_counts", F.struct(n.alias("n_lines"), (n - F.size(kept_name)).alias("n_dropped")))
    return out.withColumn(text, F.array_join(kept_name, "\n")).select(*rest, "line_counts")


ORACLE_SQL = """
WITH d AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents),
l AS (SELECT doc_id, unnest(lines) AS line, generate_subscripts(lines, 1) AS pos FROM d),
k AS (SELECT doc_id, pos, line,
        translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
h AS (SELECT key, max(doc_id) AS keeper FROM k WHERE length(key) >= 40 GROUP BY key HAVING count(DISTINCT doc_id) >= 5),
m AS (SELECT k.doc_id, k.pos, k.line, h.keeper IS NOT NULL AND k.doc_id <> h.keeper AS lost FROM k LEFT JOIN h ON k.key = h.key)
SELECT doc_id, count(*) AS n_lines, CAST(sum(CAST(lost AS INT)) AS BIGINT) AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT lost), '')) AS kept_sha256
FROM m GROUP BY doc_id
"""
