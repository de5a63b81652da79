"""Exact fingerprints of canonical texts, in built-in functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from driftview.llm.scratch import materialize

#: White space that is left after compatibility composition.
SPACES = r"[\x09-\x0D\x20\x85\u1680\u2028\u2029]+"
#: Fingerprints are sent to every task up to this many, about 64 MB; beyond it they are shuffled.
BROADCAST_ROWS = 1_000_000
MAX_SLOTS = 1 << 16
SALTS = 64


def canonical(text: Column) -> Column:
    """Compatibility composition, case folding, composition anew, and one blank for each run of white space, none at the ends.

    Folding can take a letter apart that another spelling leaves whole, so its
    output is composed as well.  Texts of ASCII alone need lower-casing only;
    others go through ICU in the JVM.
    """
    compose = lambda t: F.call_function("java_method", F.lit("com.ibm.icu.text.Normalizer"), F.lit("compose"), t, F.lit(True))
    folded = F.call_function("java_method", F.lit("com.ibm.icu.lang.UCharacter"), F.lit("foldCase"), compose(text), F.lit(True))
    same = F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(compose(folded))
    return F.btrim(F.regexp_replace(same, SPACES, " "))


def digest(canon: Column) -> Column:
    """128 bits of a canonical text, as 32 hexadecimal digits."""
    part = lambda h: F.lpad(F.lower(F.hex(h)), 16, "0")
    return F.concat(part(F.xxhash64(canon)), part(F.xxhash64(F.lit("fingerprint"), canon)))


def equal_groups(marked: DataFrame, docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``marked`` with the groups of equal canonical text: its columns and (group_id, group_size).

    ``marked`` has a row for each row of ``docs``, with doc_id and fingerprint
    among its columns.  Rows are grouped by fingerprint.  Where a group has
    several rows, their canonical texts are compared byte by byte: smallest and
    largest, which tasks combine before they shuffle, are equal if all are.
    Fingerprints that hold different texts are grouped anew by the text itself.
    A group's id is its smallest doc_id, its size counts all of its rows.  Rows
    with a null id are counted and named by their group, whose id is null only
    if it holds no other.

    Rows meet their groups by broadcast while these are few; beyond, fingerprints
    are dealt to SALTS parts each, so that a large group is no single task's.
    """
    sums = marked.groupBy("fingerprint").agg(F.count("*").alias("group_size"), F.min("doc_id").alias("group_id"))
    several = materialize(sums.where("group_size > 1"), "equal", by_size=True)
    few = several.count() <= BROADCAST_ROWS
    canon = canonical(F.coalesce(F.col(text), F.lit("")))
    rows = docs.select(F.col(doc_id).alias("doc_id"), canon.alias("canon")).withColumn("fingerprint", digest(F.col("canon")))
    wanted = several.select("fingerprint")
    rows = rows.join(F.broadcast(wanted) if few else wanted, "fingerprint", "left_semi")
    mixed = materialize(rows.groupBy("fingerprint").agg(F.min("canon").alias("lo"), F.max("canon").alias("hi")).where("lo <> hi").select("fingerprint"), "mixed", by_size=True)
    if few:
        found = marked.join(F.broadcast(several), "fingerprint", "left")
    else:
        salted = several.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        found = marked.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int")).join(salted, ["fingerprint", "salt"], "left")
    found = found.select(*marked.columns, F.when(F.col("group_size").isNull(), F.col("doc_id")).otherwise(F.col("group_id")).alias("group_id"), F.coalesce("group_size", F.lit(1)).alias("group_size"))
    if not mixed.limit(1).count():
        return found
    again = rows.join(mixed, "fingerprint")
    parts = again.groupBy("fingerprint", "canon").agg(F.count("*").alias("part_size"), F.min("doc_id").alias("part_id"))
    # rows of one id can differ in text: the smaller part is taken, as ids are keys elsewhere
    apart = again.join(parts, ["fingerprint", "canon"]).groupBy(F.col("doc_id").alias("d"), F.col("fingerprint").alias("f")).agg(F.min(F.struct("part_size", "part_id")).alias("part"))
    split = found.join(apart, found["doc_id"].eqNullSafe(F.col("d")) & (found["fingerprint"] == F.col("f")), "left")
    own = lambda a, b: F.when(F.col("part").isNull(), F.col(b)).otherwise(F.col(f"part.{a}")).alias(b)
    return split.select(*marked.columns, own("part_id", "group_id"), own("part_size", "group_size"))


def with_next(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", rows_per_slot: int = 64) -> DataFrame:
    """(doc_id, text, next_text): each document beside the next one in ascending id, the last beside the first.

    Ids are dealt to slots of about equal counts along their quantiles, in
    order; the first document of a slot is also sent to the slot before, so that
    one shuffle brings all neighbours together.  Null ids come first, equal ids
    are ordered by text, and null texts are empty.
    """
    low = -(1 << 63)
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    quantiles = F.percentile_approx("doc_id", F.array(*[F.lit(k / 128) for k in range(129)]), 20_000)
    n, cuts = rows.agg(F.count("*"), quantiles).first()
    if cuts is None:
        slot = F.lit(0).cast("long")
    else:
        cuts = sorted(set(cuts))
        each = max(1, min(n // rows_per_slot, MAX_SLOTS) // max(1, len(cuts)))
        steps = F.lit(cuts)
        at = F.greatest(F.lit(1), F.size(F.filter(steps, lambda c: c <= F.col("doc_id"))))
        left = F.element_at(steps, at)
        right = F.coalesce(F.try_element_at(steps, at + 1), left + 1)
        inside = F.least(F.lit(1 - 1e-12), F.greatest(F.lit(0.0), (F.col("doc_id") - left).cast("double") / (right - left).cast("double")))
        slot = F.coalesce((at - 1) * each + F.floor(inside * each), F.lit(0)).cast("long")
    placed = rows.withColumn("slot", slot).withColumn("key", F.coalesce("doc_id", F.lit(low)))
    firsts = placed.groupBy("slot").agg(F.min("key").alias("first"))
    by_slot = Window.orderBy("slot")  # MAX_SLOTS + 129 rows at most
    before = F.coalesce(F.lag("slot").over(by_slot), F.last("slot").over(by_slot.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    firsts = firsts.select(F.col("slot").alias("s"), "first", before.alias("before"))
    joined = placed.join(F.broadcast(firsts), (placed["slot"] == F.col("s")) & (placed["key"] == F.col("first")), "left")
    seats = F.when(F.col("before").isNull(), F.array(F.struct(F.col("slot").alias("at"), F.lit(0).alias("guest")))).otherwise(F.array(F.struct(F.col("slot").alias("at"), F.lit(0).alias("guest")), F.struct(F.col("before").alias("at"), F.lit(1).alias("guest"))))
    seated = joined.select("doc_id", "key", "text", F.explode(seats).alias("seat")).select("doc_id", "key", "text", "seat.at", "seat.guest")
    order = Window.partitionBy("at").orderBy("guest", "key", "text")
    return seated.withColumn("next_text", F.lead("text").over(order)).where("guest = 0").select("doc_id", "text", "next_text")


def fingerprint_report(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Fingerprints of documents and of their edited texts, with groups of equal documents.

    The edited text has the last quarter of the code points, rounded down,
    replaced by as many of the next document's first ones, or all.  Likeness is
    1 where two canonical texts are equal byte by byte, else 0.  A null or
    empty text is empty; empty texts are equal.  Repeated rows are equal
    documents.  Rows with a null id come first in the order of documents and are
    fingerprinted and grouped as all others.  A lone document is its own next
    one.  An empty table gives an empty result; other columns are ignored.
    """
    pairs = with_next(docs, doc_id, text)
    n = F.char_length("text")
    cut = F.floor(n / 4).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), n - cut), F.substring(F.col("next_text"), F.lit(1), cut))
    rows = pairs.select("doc_id", n.cast("long").alias("n_chars"), canonical(F.col("text")).alias("c"), edited.alias("edited"), canonical(F.col("next_text")).alias("c_next"))
    rows = rows.withColumn("c_edited", canonical(F.col("edited")))
    like = lambda a, b: (F.col(a) == F.col(b)).cast("double")
    marked = materialize(rows.select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), digest(F.col("c")).alias("fingerprint"), digest(F.col("c_edited")).alias("edited_fingerprint"), like("c", "c_edited").alias("near_edited"), like("c", "c_next").alias("near_next")), "marked")
    return equal_groups(marked, docs, doc_id, text)
