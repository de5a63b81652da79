"""A mix of sources at target weights, by weighted fair queueing."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from driftview.llm.scratch import materialize

WEIGHTS = (5, 2, 1)
#: A packet has so many words at most, and at most this share of its source's target, but a word at least.
PACKET, PACKET_SHARE = 256, 100
#: Ranges of virtual time whose words are added up on the way to the cut.
MAX_RANGES, ROWS_PER_RANGE = 1 << 16, 64


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def with_places(rows: DataFrame, order: Sequence[Column], sums: Sequence[str], label: str) -> DataFrame:
    """``rows`` with their ``place`` from 0 in a total order, and for each name of ``sums`` the sum over all earlier rows, ``<name>_before``.

    Rows are dealt to ranges of the order, the ranges' sums are added up, a row
    for each, and every range is numbered by itself.
    """
    placed = materialize(rows.repartitionByRange(*order).withColumn("range", F.spark_partition_id()), label, by_size=True)
    earlier = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)  # a row for each shuffle partition
    names = {"place": F.count("*"), **{f"{c}_before": F.sum(c) for c in sums}}
    totals = placed.groupBy("range").agg(*[f.alias(n) for n, f in names.items()])
    offsets = totals.select("range", *[F.coalesce(F.sum(n).over(earlier), F.lit(0)).alias(f"{n}_0") for n in names])
    inside = Window.partitionBy("range").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    found = placed.join(F.broadcast(offsets), "range")
    return found.select(*rows.columns, *[(F.col(f"{n}_0") + F.coalesce(f.over(inside), F.lit(0))).alias(n) for n, f in names.items()])


def source_targets(sized: DataFrame, weights: Sequence[int], budget: float, max_repeats: int) -> tuple[DataFrame, int]:
    """(source, source_size, n_docs, target), a row for each source, and the budget in words.

    Sources in code point order, null last, take the weights in turn.  A target
    is the source's share of the budget, but ``max_repeats`` times its own size
    at most; what is cut off is shared anew.  In order of limit over weight, the
    first source that its share of what the earlier ones leave does not fill
    settles the level for all later ones.
    """
    sums = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_docs"))
    rows = with_places(sums, [F.col("source").asc_nulls_last()], [], "sources")
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.col("place") % len(weights) + 1).cast("int")).cast("long")
    rows = rows.select("source", "source_size", "n_docs", weight.alias("weight"), (F.col("source_size") * max_repeats).alias("cap"))
    rows = materialize(with_places(rows, [F.col("cap").cast("double") / F.col("weight"), F.col("source").asc_nulls_last()], ["cap", "weight"], "limits"), "filled", by_size=True)
    words, shares = rows.agg(F.sum("source_size"), F.sum("weight")).first()
    total = int((words or 0) * float(budget))
    level = (F.lit(total) - F.col("cap_before")).cast("double") / (F.lit(shares) - F.col("weight_before")).cast("double")
    rows = rows.withColumn("level", level)
    settled = rows.where(F.col("level") * F.col("weight") <= F.col("cap").cast("double")).agg(F.min_by("level", "place")).first()[0]
    cap = F.col("cap").cast("double")
    target = cap if settled is None else F.least(cap, F.lit(settled) * F.col("weight"))
    return rows.select("source", "source_size", "n_docs", target.alias("target")), total


def packets(max_repeats: int) -> Column:
    """A document's packets, copy after copy, as {words, upto, finish}: ``upto`` counts its source's words up to a packet's end, ``finish`` is that over the target."""
    size, start, whole, quantum = (F.col(c) for c in ("size", "start", "source_size", "quantum"))
    pieces = F.sequence(F.lit(0).cast("long"), F.ceil(size / quantum) - 1)

    def copy(k: Column) -> Column:
        end = lambda p: F.least(size, (p + 1) * quantum)
        upto = lambda p: k * whole + start + end(p)
        return F.transform(pieces, lambda p: F.struct((end(p) - p * quantum).alias("words"), upto(p).alias("upto"), (upto(p).cast("double") / F.col("target")).alias("finish")))

    copies = F.flatten(F.transform(F.sequence(F.lit(0).cast("long"), F.lit(max_repeats - 1).cast("long")), copy))
    return F.when(size > 0, copies).otherwise(F.array().cast("array<struct<words: bigint, upto: bigint, finish: double>>"))


def queued(sized: DataFrame, targets: DataFrame) -> DataFrame:
    """Documents in their source's shuffled queue: with their source's columns, ``quantum`` and ``start``, the words of the queue before them.

    A source of n documents is dealt to about sqrt(n) ranges of the hash, whose
    sums are added up first, so no task sees a whole source.
    """
    quantum = F.greatest(F.lit(1), F.least(F.lit(PACKET), F.floor(F.col("target") / PACKET_SHARE))).cast("long")
    # hot sources are split by the join, as adaptive execution sees fit
    rows = sized.join(targets.withColumn("quantum", quantum), sized["source"].eqNullSafe(targets["source"])).drop(targets["source"])
    part = F.floor(F.conv(F.substring("h", 1, 8), 16, 10).cast("double") / float(1 << 32) * F.ceil(F.sqrt("n_docs"))).cast("long")
    rows = materialize(rows.withColumn("part", part), "dealt")
    ahead = Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = rows.groupBy("source", "part").agg(F.sum("size").alias("words")).select(F.col("source").alias("s"), F.col("part").alias("p"), F.coalesce(F.sum("words").over(ahead), F.lit(0)).alias("offset"))
    within = Window.partitionBy("source", "part").orderBy("h", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    placed = rows.withColumn("inner", F.coalesce(F.sum("size").over(within), F.lit(0)))
    placed = placed.join(offsets, placed["source"].eqNullSafe(F.col("s")) & (placed["part"] == F.col("p")))
    return placed.select("doc_id", "source", "size", "source_size", "target", "quantum", (F.col("offset") + F.col("inner")).alias("start"))


def fair_mix(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", weights: Sequence[int] = WEIGHTS, budget: float = 1.0, max_repeats: int = 3) -> DataFrame:
    """What a mix takes of each document: (doc_id, source, size, source_size, target, start, taken).

    Each source's documents queue in the order of a hash of their ids, again and
    again up to ``max_repeats`` times, cut into packets of 256 words, or of a
    hundredth of the source's target where that is less.  A packet's virtual
    finish time is the number of its source's words up to its end, over the
    source's target.  The mix serves the packets of all sources in order of
    finish time, ties by source and place in the queue, until the budget is
    spent; of the packet that crosses it only the words left are taken.  So a
    source misses its target by a packet or so, and reruns agree.

    Virtual time is dealt to ranges; their words, a row for each, tell in which
    of them the budget is spent.  Packets of earlier ranges are served, those of
    later ones are not, and the packets of that range alone are sorted.  Packets
    are arrays within a document's row and are not shuffled.

    A null text counts 0 words.  A null source is a source.  A null id takes
    part under the hash of an empty string.  Repeated rows are documents of
    their own, ties in the hash are ordered by id and size.  An empty table
    gives an empty result; other columns are ignored.
    """
    sized = docs.select(F.col(doc_id).alias("doc_id"), F.col(source).alias("source"), word_count(F.col(text)).alias("size"), F.md5(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")).alias("h"))
    sized = materialize(sized, "sizes")
    targets, total = source_targets(sized, weights, budget, max_repeats)
    placed = materialize(queued(sized, materialize(targets, "targets", by_size=True)), "queued")
    n_ranges = max(1, min(MAX_RANGES, placed.count() // ROWS_PER_RANGE))
    # the budget is spent at about time 1: the last range holds all that ends at 2 or later
    range_of = lambda finish: F.least(F.lit(n_ranges - 1), F.floor(finish * n_ranges / 2)).cast("long")
    served = placed.select("source", "start", F.explode(packets(max_repeats)).alias("p")).select("source", "start", "p.words", "p.upto", "p.finish", range_of(F.col("p.finish")).alias("range"))
    up_to = Window.orderBy("range")  # MAX_RANGES rows at most
    sums = served.groupBy("range").agg(F.sum("words").alias("words")).withColumn("spent", F.sum("words").over(up_to))
    cut = sums.where(F.col("spent") > total).orderBy("range").select("range", (F.col("spent") - F.col("words")).alias("before")).first()
    last, before = (n_ranges, total) if cut is None else (cut["range"], cut["before"])
    in_order = Window.orderBy("finish", F.col("source").asc_nulls_last(), "upto").rowsBetween(Window.unboundedPreceding, -1)  # of one range
    left = F.lit(total - before) - F.coalesce(F.sum("words").over(in_order), F.lit(0))
    crossing = served.where(F.col("range") == last).select("source", "start", F.least(F.col("words"), left).alias("words")).where("words > 0")
    crossing = crossing.groupBy(F.col("source").alias("s"), F.col("start").alias("at")).agg(F.sum("words").alias("more"))
    whole = F.aggregate(packets(max_repeats), F.lit(0).cast("long"), lambda n, p: n + F.when(range_of(p["finish"]) < last, p["words"]).otherwise(F.lit(0)))
    rows = placed.withColumn("whole", whole).join(crossing, placed["source"].eqNullSafe(F.col("s")) & (placed["start"] == F.col("at")) & (placed["size"] > 0), "left")
    return rows.select("doc_id", "source", "size", "source_size", "target", "start", (F.col("whole") + F.coalesce("more", F.lit(0))).alias("taken"))


def served_copies(mix: DataFrame) -> DataFrame:
    """The mix as copies in order of virtual finish time: (doc_id, copy, words, finish), range-sorted.

    A document of which ``n`` times its size and some words more are taken gives
    ``n`` whole copies and one cut short; documents of which nothing is taken,
    null and empty texts among them, give none.  Null ids stay; ties are ordered
    by id and copy.  An empty mix gives no copies.
    """
    copies = mix.where("taken > 0").select("*", F.explode(F.sequence(F.lit(0), F.ceil(F.col("taken") / F.col("size")).cast("int") - 1)).alias("copy"))
    words = F.least(F.col("size"), F.col("taken") - F.col("copy") * F.col("size"))
    finish = (F.col("copy") * F.col("source_size") + F.col("start") + words) / F.col("target")
    return copies.select("doc_id", "copy", words.alias("words"), finish.alias("finish")).orderBy("finish", "doc_id", "copy")


ORACLE_SQL = r"""
WITH d AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS size, md5(coalesce(CAST(doc_id AS VARCHAR), '')) AS h FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (SELECT source, source_size, 3 * source_size AS cap, [5, 2, 1][1 + (row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3] AS weight FROM s),
r AS (SELECT *, row_number() OVER (ORDER BY cap / weight, source ASC NULLS LAST) AS k FROM w),
l AS (SELECT a.source, a.source_size, a.cap, a.weight, a.k,
    CAST((SELECT sum(source_size) FROM r) - coalesce((SELECT sum(cap) FROM r b WHERE b.k < a.k), 0) AS DOUBLE) / CAST((SELECT sum(weight) FROM r b WHERE b.k >= a.k) AS DOUBLE) AS level FROM r a),
v AS (SELECT (SELECT level FROM l WHERE level * weight <= cap ORDER BY k LIMIT 1) AS level),
t AS (SELECT source, source_size, coalesce(least(CAST(cap AS DOUBLE), v.level * weight), CAST(cap AS DOUBLE)) AS target FROM l, v),
q AS MATERIALIZED (SELECT d.doc_id, d.source, d.size, t.source_size, t.target, CAST(greatest(1, least(256, floor(t.target / 100))) AS BIGINT) AS quantum,
    row_number() OVER () AS n, CAST(sum(d.size) OVER (PARTITION BY d.source ORDER BY h, d.doc_id, d.size ROWS UNBOUNDED PRECEDING) AS BIGINT) - d.size AS start
    FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
e AS (SELECT q.*, copy, unnest(range(CAST(ceil(size / quantum) AS BIGINT))) AS piece FROM q, (VALUES (0), (1), (2)) c(copy)),
p AS (SELECT n, source, target, least(size, (piece + 1) * quantum) - piece * quantum AS words, copy * source_size + start + least(size, (piece + 1) * quantum) AS upto FROM e),
f AS (SELECT n, words, coalesce(sum(words) OVER (ORDER BY CAST(upto AS DOUBLE) / target, source ASC NULLS LAST, upto ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS spent FROM p),
g AS (SELECT n, sum(greatest(0, least(words, (SELECT sum(size) FROM d) - spent))) AS taken FROM f GROUP BY n)
SELECT doc_id, CAST(size AS BIGINT) AS size, source_size, target, CAST(coalesce(taken, 0) AS BIGINT) AS taken FROM q LEFT JOIN g USING (n)
"""
