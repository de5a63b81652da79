"""Near-duplicate documents by consistent weighted samples of their word shingles."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from driftview.llm import tokens as tk
from driftview.llm.components import components
from driftview.llm.scratch import columns, materialize
from driftview.llm.settle import settle
from driftview.shipping import ship

#: Counters of the document-frequency table: a fixed size, whatever the corpus.
DF_BITS = 18
#: The ids of so many pairs are sent to every task, 16 MB at most; of more, they are shuffled.
BROADCAST_PAIRS = 1_000_000


def sent(ids: DataFrame) -> DataFrame:
    """A table of one id a row, sent to every task where it is small enough, so that texts are not shuffled to meet it."""
    return F.broadcast(ids) if ids.count() <= 2 * BROADCAST_PAIRS else ids


def document_frequencies(docs: DataFrame, text: str, width: int) -> np.ndarray:
    """Number of documents for each hashed shingle, over all rows, in 2**DF_BITS counters.

    Shingles that share a counter share its count, so a count is never too
    small.  Tasks send sums for each counter, never rows for each shingle.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << DF_BITS, np.int64)
        for batch in batches:
            for part in tk.slices(batch, "text"):
                who, what = tk.shingles(tk.words(part.column("text")), width)
                _, what, _ = tk.distinct(who, what)
                total += np.bincount((what >> np.uint64(64 - DF_BITS)).astype(np.int64), minlength=1 << DF_BITS)
        at = np.flatnonzero(total)
        for i in range(0, len(at), 1 << 16):
            yield pa.RecordBatch.from_arrays([pa.array(at[i : i + (1 << 16)], pa.int32()), pa.array(total[at[i : i + (1 << 16)]])], ["slot", "n"])

    rows = docs.select(F.lower(text).alias("text")).mapInArrow(tk.frugal(count), "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(1 << DF_BITS, np.int64)
    out[rows["slot"].to_numpy()] = rows["n"].to_numpy()
    return out


def idf_table(frequencies: np.ndarray, n_docs: int, spread: float) -> np.ndarray:
    """Weights between 1 (in every document) and 1 + spread (in none)."""
    scale = math.log(n_docs + 1.0) or 1.0
    rare = np.log((n_docs + 1.0) / np.minimum(frequencies + 1.0, n_docs + 1.0)) / scale
    return (1.0 + spread * rare).astype(np.float32)


def weighted_shingles(column: pa.Array, width: int, idf: np.ndarray) -> tuple[tk.Tokens, np.ndarray, np.ndarray, np.ndarray]:
    """Tokens, and owner, hash and TF-IDF weight of each text's distinct shingles."""
    tokens = tk.words(column)
    who, what, tf = tk.distinct(*tk.shingles(tokens, width))
    return tokens, who, what, tf * idf[(what >> np.uint64(64 - DF_BITS)).astype(np.int64)].astype(np.float64)


def consistent_samples(who: np.ndarray, what: np.ndarray, weight: np.ndarray, n_texts: int, bins: int) -> np.ndarray:
    """Improved consistent weighted sampling, one sample in each bin of shingles.

    A shingle's hash deals it to one bin and seeds its Gamma and uniform draws;
    the bin keeps the shingle, with its quantized level, of smallest draw.  A
    bin without shingles borrows from one that the bin's number alone picks.
    Texts without shingles get zeros.
    """
    out = np.zeros((n_texts, bins), np.uint64)
    if not len(who):
        return out
    u = [tk.uniform(tk.mix(what + np.uint64(7919 * k + 1))) for k in range(5)]
    r, c, beta = -np.log(u[0] * u[1]), -np.log(u[2] * u[3]), u[4]
    level = np.floor(np.log(weight) / r + beta)
    draw = np.log(c) - r * (level - beta) - r
    slot = who * bins + (tk.mix(what + np.uint64(0xB1)) % np.uint64(bins)).astype(np.int64)
    order = np.argsort(slot, kind="stable")
    slot, draw = slot[order], draw[order]
    at = np.flatnonzero(np.append(True, slot[1:] != slot[:-1]))
    least = np.minimum.reduceat(draw, at)
    size = np.diff(np.append(at, len(slot)))
    hit = np.flatnonzero(draw == np.repeat(least, size))
    pick = order[hit]
    out.reshape(-1)[slot[hit]] = tk.mix(what[pick] ^ tk.mix(level[pick].astype(np.int64).astype(np.uint64))) | np.uint64(1)
    some = np.zeros(n_texts, bool)
    some[who] = True
    rows, cols = np.nonzero((out == 0) & some[:, None])
    full = out.copy()
    attempt = 1
    while len(rows):
        source = (tk.mix(cols.astype(np.uint64) * np.uint64(1 << 20) + np.uint64(attempt)) % np.uint64(bins)).astype(np.int64)
        got = full[rows, source]
        out[rows, cols] = np.where(got != 0, tk.mix(got + np.uint64(attempt)), 0)
        left = got == 0
        rows, cols = rows[left], cols[left]
        attempt += 1
        if attempt > 40 * bins:
            source = np.argmax(full[rows] != 0, axis=1)
            out[rows, cols] = tk.mix(full[rows, source])
            break
    return out


def band_keys(samples: np.ndarray, rows: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        bands = samples.shape[1] // rows
        parts = samples[:, : bands * rows].reshape(len(samples), bands, rows)
        acc = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64), (len(samples), bands)).copy()
        for k in range(rows):
            acc = tk.mix(acc * np.uint64(0x100000001B3) + parts[:, :, k])
    return acc


def sketches(docs: DataFrame, doc_id: str, text: str, width: int, bins: int, rows: int, idf: np.ndarray) -> DataFrame:
    """(id, d1, d2, n_words, keys): 128 bits of the word sequence, and the band keys; none for texts without words."""
    share = docs.sparkSession.sparkContext.broadcast(idf)

    def sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in tk.slices(batch, "text"):
                words, who, what, weight = weighted_shingles(part.column("text"), width, share.value)
                n = part.num_rows
                d1, d2 = tk.text_digests(words)
                keys = band_keys(consistent_samples(who, what, weight, n, bins), rows)
                sizes = np.where(words.counts > 0, keys.shape[1], 0)
                flat = keys[words.counts > 0].reshape(-1).view(np.int64)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32()), pa.array(flat))
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(d1.view(np.int64)), pa.array(d2.view(np.int64)), pa.array(words.counts), lists], ["id", "d1", "d2", "n_words", "keys"])

    return docs.select(F.col(doc_id).cast("long").alias("id"), F.lower(text).alias("text")).mapInArrow(tk.frugal(sketch), "id long, d1 long, d2 long, n_words long, keys array<long>")


def occurrences(column: pa.Array, width: int, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Owner, hash and weight of each occurrence of a shingle: two texts share as many as the smaller TF, so their weights add up to minima of TF-IDF."""
    who, what, tf = tk.distinct(*tk.shingles(tk.words(column), width))
    turn = np.arange(tf.sum()) - np.repeat(np.cumsum(tf) - tf, tf)
    weight = idf[(what >> np.uint64(64 - DF_BITS)).astype(np.int64)].astype(np.float64)
    again = np.where(turn > 0, tk.mix(turn.astype(np.uint64)), np.uint64(0))
    return np.repeat(who, tf), tk.mix(np.repeat(what, tf) ^ again), np.repeat(weight, tf)


def pair_similarities(pairs: DataFrame, texts: DataFrame, width: int, idf: np.ndarray) -> DataFrame:
    """Weighted Jaccard similarity of the texts of each pair: (a, b, similarity)."""
    share = pairs.sparkSession.sparkContext.broadcast(idf)

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in tk.slices(batch, "text_b", 512 << 10):
                columns = [part.column("text_a").cast(pa.large_string()), part.column("text_b").cast(pa.large_string())]
                n = part.num_rows
                _, who, what, weight = weighted_shingles(pa.concat_arrays(columns), width, share.value)
                order = np.lexsort((what, who % n))
                pair, what, weight = (who % n)[order], what[order], weight[order]
                same = np.flatnonzero((pair[1:] == pair[:-1]) & (what[1:] == what[:-1]))
                total = np.bincount(pair, weight, n)
                shared = np.bincount(pair[same], np.minimum(weight[same], weight[same + 1]), n)
                with np.errstate(invalid="ignore", divide="ignore"):
                    likeness = np.where(total > 0, shared / (total - shared), 1.0)
                yield pa.RecordBatch.from_arrays([part.column("a"), part.column("b"), pa.array(likeness)], ["a", "b", "similarity"])

    ids = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
    wanted = texts.join(F.broadcast(ids), "id", "left_semi") if pairs.count() <= BROADCAST_PAIRS else texts.join(ids, "id", "left_semi")
    with_a = pairs.join(wanted.select(F.col("id").alias("a"), F.col("text").alias("text_a")), "a")
    with_b = with_a.join(wanted.select(F.col("id").alias("b"), F.col("text").alias("text_b")), "b")
    return with_b.select("a", "b", "text_a", "text_b").mapInArrow(tk.frugal(verify), "a long, b long, similarity double")


def near_duplicates(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", threshold: float = 0.8, width: int = 5, bands: int = 20, rows: int = 4, idf_spread: float = 0.1, partner_rounds: int = 3) -> DataFrame:
    """Class of each document: rows (doc_id, class_id, n_copies, n_links), one for each input row.

    Words are runs of ASCII letters and digits and of characters from U+0080,
    in lower case.  Documents with equal word sequences are copies.  Of each set
    of copies one represents the rest; representatives that share a band of
    weighted samples are compared, and linked if their TF-IDF shingles have a
    weighted Jaccard similarity of ``threshold`` or more.  A class is a
    component of links; its id is the smallest document id in it.

    Within a bucket, members are compared with its first and last
    representative, and then, in ``partner_rounds`` rounds or until one brings no
    link, a member of each class in the bucket with one of another class, members
    and neighbours being drawn by a new hash for each bucket and round; pairs that
    were compared are left out.
    These rounds join most of a large group; then all pairs of a bucket whose
    members are not in one class yet are compared (see ``settle``), so no link
    that joins two classes is left out.  ``n_links`` counts the links found on
    the way, which are enough to join a class: pairs of one class are not all
    compared, so it is not the number of all texts that are alike.

    Inverse document frequencies lie between 1 and 1 + ``idf_spread``: without
    that bound the common shingles of a large group of near copies would weigh
    so little that the group's own edits would part it.

    Nulls and empty texts: a null text is an empty one; texts without words are
    copies of each other.  Rows with a null id get a null class.  Repeated rows
    are copies and share an id.  Texts of any length are read in blocks.  An
    empty table gives an empty result; other columns are ignored.
    """
    spark = docs.sparkSession
    ship(spark)
    n_docs = docs.count()
    idf = idf_table(document_frequencies(docs, text, width), n_docs, idf_spread)
    sketched = materialize(sketches(docs, doc_id, text, width, bands * rows, rows, idf), "sketches")
    known = sketched.where("id is not null")
    heads = materialize(known.groupBy("d1", "d2").agg(F.min("id").alias("rep"), F.count("*").alias("n_copies"), F.min_by("keys", "id").alias("keys"), F.max("n_words").alias("n_words")), "heads")
    banded = heads.select("rep", "n_words", F.explode("keys").alias("key"))
    hubs = banded.groupBy("key").agg(F.min("rep").alias("lo"), F.max("rep").alias("hi")).where("lo < hi")
    shared = materialize(banded.join(hubs, "key"), "buckets")
    hub_pairs = shared.select(F.explode(F.array(F.struct(F.col("lo").alias("a"), F.col("rep").alias("b")), F.struct(F.col("rep").alias("a"), F.col("hi").alias("b")))).alias("p")).select("p.*").where("a < b").distinct()
    candidates = materialize(shared.select(F.col("rep").alias("id")).distinct(), "compared", by_size=True)
    source = docs.select(F.col(doc_id).cast("long").alias("id"), F.lower(text).alias("text"))
    # a repeated id could bring in another row's text: the smallest is as good as any, as both are of one document
    texts = materialize(source.join(sent(candidates), "id", "left_semi").groupBy("id").agg(F.min("text").alias("text")), "candidates")
    hub_pairs = materialize(hub_pairs, "tried", by_size=True)
    links = materialize(pair_similarities(hub_pairs, texts, width, idf).where(F.col("similarity") >= threshold).select("a", "b"), "links")
    tried, roots = hub_pairs, components(links)
    open_ = shared.select("key", "rep")
    for turn in range(partner_rounds):
        labelled = open_.join(roots.withColumnRenamed("node", "rep"), "rep", "left").select("key", "rep", F.coalesce("root", "rep").alias("root"))
        chosen = labelled.groupBy("key", "root").agg(F.min_by("rep", F.xxhash64("rep", "key", F.lit(turn))).alias("rep"))
        before = F.lag("rep").over(Window.partitionBy("key").orderBy(F.xxhash64("root", "key", F.lit(turn)), "root"))
        chain = chosen.select("key", "rep", before.alias("before")).where("before is not null")
        chain = materialize(chain.select("key", F.least("rep", "before").alias("a"), F.greatest("rep", "before").alias("b")), "chain", by_size=True)
        steps = materialize(chain.select("a", "b").distinct().join(tried, ["a", "b"], "left_anti"), "steps", by_size=True)
        more = materialize(pair_similarities(steps, texts, width, idf).where(F.col("similarity") >= threshold).select("a", "b"), "links")
        if not more.limit(1).count():
            break
        links, tried = links.unionByName(more), tried.unionByName(steps)
        roots = components(links)
        # classes only grow together: a bucket of one class has nothing left to compare
        open_ = open_.join(chain.select("key").distinct(), "key", "left_semi")
    share = spark.sparkContext.broadcast(idf)
    buckets = shared.select("key", F.col("rep").alias("unit"), F.col("rep").alias("owner"), F.col("n_words").alias("words"))
    links = settle(buckets, links, texts.withColumnRenamed("id", "unit"), lambda column: occurrences(column, width, share.value), threshold)
    roots = components(links)
    degree = links.select(F.explode(F.array("a", "b")).alias("rep")).groupBy("rep").agg(F.count("*").alias("n_links"))
    classes = heads.join(roots.withColumnRenamed("node", "rep"), "rep", "left").join(degree, "rep", "left").select("d1", "d2", F.coalesce("root", "rep").alias("class_id"), "n_copies", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))
    classes = materialize(classes, "classes")
    grouped = known.select("id", "d1", "d2").join(classes, ["d1", "d2"]).select(F.col("id").alias("doc_id"), "class_id", "n_copies", "n_links")
    unknown = sketched.where("id is null").select(F.col("id").alias("doc_id"), F.lit(None).cast("long").alias("class_id"), F.lit(1).cast("long").alias("n_copies"), F.lit(0).cast("long").alias("n_links"))
    return grouped.unionByName(unknown)


def keep_one(docs: DataFrame, classes: DataFrame, doc_id: str = "doc_id") -> DataFrame:
    """The documents without those that another one of their class represents.

    Rows with a null id stay.  Texts without words, null ones among them, are one
    class, of which one stays.  Of repeated rows with one id, one stays: the
    smallest by all columns.  An empty table gives an empty result.
    """
    classes = materialize(classes, "classed", by_size=True)
    dropped = materialize(classes.where("doc_id <> class_id").select(F.col("doc_id").alias(doc_id)).distinct(), "dropped", by_size=True)
    kept = docs.join(sent(dropped), doc_id, "left_anti")
    if classes.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").limit(1).count():
        known = kept.where(F.col(doc_id).isNotNull()).groupBy(doc_id).agg(F.min(F.struct(*columns(docs))).alias("row")).select("row.*")
        kept = known.unionByName(kept.where(F.col(doc_id).isNull()))
    return kept
