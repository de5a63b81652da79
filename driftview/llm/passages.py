"""Passages that repeat across documents, by MinHash bands of paragraphs and of anchored spans."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftview.llm import tokens as tk
from driftview.llm.components import components
from driftview.llm.scratch import columns, fresh, materialize
from driftview.llm.settle import settle
from driftview.shipping import ship

#: Words of an anchored span, and shingles among which an anchor is smallest:
#: any passage of SPAN + REACH - 1 = 50 words holds a span that depends on its words alone.
SPAN, REACH, WIDTH = 30, 21, 5
#: Bands and rows of a paragraph's sketch: two paragraphs of similarity 0.8 share a band with probability 0.998.
BANDS, ROWS = 6, 2
FILTER_BITS = 26


def min_hashes(who: np.ndarray, what: np.ndarray, n: int, bins: int) -> np.ndarray:
    """One-permutation MinHash: each bin's smallest hash; empty bins borrow from one picked by the bin's number."""
    full = np.full((n, bins), np.uint64(0xFFFFFFFFFFFFFFFF))
    if not len(who):
        return full
    slot = who * bins + (what % np.uint64(bins)).astype(np.int64)
    order = np.argsort(slot, kind="stable")
    at = np.flatnonzero(np.append(True, slot[order][1:] != slot[order][:-1]))
    full.reshape(-1)[slot[order][at]] = np.minimum.reduceat(tk.mix(what[order]) >> np.uint64(1), at)
    empty = np.uint64(0xFFFFFFFFFFFFFFFF)
    out = full.copy()
    some = (full != empty).any(1)
    rows, cols = np.nonzero((full == empty) & some[:, None])
    for attempt in range(1, 40 * bins):
        if not len(rows):
            break
        source = (tk.mix(cols.astype(np.uint64) * np.uint64(1 << 20) + np.uint64(attempt)) % np.uint64(bins)).astype(np.int64)
        got = full[rows, source]
        hit = got != empty
        out[rows[hit], cols[hit]] = tk.mix(got[hit] + np.uint64(attempt))
        rows, cols = rows[~hit], cols[~hit]
    return out


def anchors(tokens: tk.Tokens) -> np.ndarray:
    """Words at which spans begin: those whose shingle is the first smallest of REACH consecutive ones of a text."""
    h = tokens.hashes
    n = len(h) - WIDTH + 1
    if n < REACH:
        return np.zeros(0, np.int64)
    with np.errstate(over="ignore"):
        acc = np.zeros(n, np.uint64)
        for k in range(WIDTH):
            acc = acc * np.uint64(0x100000001B3) + h[k : k + n]
    acc = tk.mix(acc)
    owners = tokens.owners()
    least = np.concatenate([np.lib.stride_tricks.sliding_window_view(acc[lo : lo + (1 << 16) + REACH - 1], REACH).argmin(1) + lo + np.arange(min(1 << 16, n - REACH + 1 - lo)) for lo in range(0, n - REACH + 1, 1 << 16)])
    within = owners[: n - REACH + 1] == owners[REACH + WIDTH - 2 :]
    found = np.unique(least[within])
    found = found[found + SPAN <= len(h)]
    return found[owners[found] == owners[found + SPAN - 1]]


def run_hashes(h: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """128 bits of the words from each start to its end."""
    up, down = tk._POWERS.upto(len(h) + 1)
    outs = []
    with np.errstate(over="ignore"):
        for seed in (3, 5):
            sums = np.zeros(len(h) + 1, np.uint64)
            np.add.accumulate(tk.mix(h + np.uint64(seed)) * up[: len(h)], out=sums[1:])
            outs.append(tk.mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64)))
    return outs[0], outs[1]


def units(docs: DataFrame, min_words: int) -> DataFrame:
    """(doc_id, start, n_words, digest, keys): a text's paragraphs of ``min_words`` words or more, with the keys of their bands, and its spans, whose digest is not null."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in tk.slices(batch, "text"):
                tokens = tk.words(part.column("text"))
                at = anchors(tokens)
                first, second = run_hashes(tokens.hashes, at, at + SPAN)
                p_start, p_end = _paragraphs(part.column("text"), tokens)
                long = p_end - p_start >= min_words
                p_start, p_end = p_start[long], p_end[long]
                lines = tk.Tokens(_gather(tokens.hashes, p_start, p_end), np.append(0, np.cumsum(p_end - p_start)))
                who, what = tk.shingles(lines, WIDTH)
                sketch = min_hashes(who, what, len(p_start), BANDS * ROWS)
                keys = np.empty((len(p_start), BANDS), np.uint64)
                for b in range(BANDS):
                    acc = np.full(len(p_start), np.uint64(b + 1))
                    for r in range(ROWS):
                        acc = tk.mix(acc + sketch[:, b * ROWS + r])
                    keys[:, b] = acc
                starts = np.concatenate([at, p_start])
                owner = np.searchsorted(tokens.starts, starts, "right") - 1
                ends = np.append(np.arange(len(at) + 1), len(at) + BANDS * np.arange(1, len(p_start) + 1))
                lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate([first, keys.reshape(-1)]).view(np.int64)))
                digest = pa.array(np.append(second, np.zeros(len(p_start), np.uint64)).view(np.int64), mask=np.arange(len(starts)) >= len(at))
                size = np.append(np.full(len(at), SPAN), p_end - p_start)
                yield pa.RecordBatch.from_arrays([part.column("doc_id").take(pa.array(owner)), pa.array(starts - tokens.starts[owner], pa.int32()), pa.array(size, pa.int32()), digest, lists], ["doc_id", "start", "n_words", "digest", "keys"])

    return docs.mapInArrow(tk.frugal(cut), "doc_id long, start int, n_words int, digest long, keys array<long>")


def _gather(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    sizes = ends - starts
    return values[np.repeat(starts - np.append(0, np.cumsum(sizes)[:-1]), sizes) + np.arange(sizes.sum())] if len(sizes) else values[:0]


def _paragraphs(column: pa.Array, tokens: tk.Tokens) -> tuple[np.ndarray, np.ndarray]:
    """First and last word, plus one, of each line that has words, over all texts."""
    data, offsets = tk.utf8(column)
    cuts = np.union1d(offsets, np.flatnonzero(data[offsets[0] : offsets[-1]] == 10) + offsets[0])
    mask = tk.WORD[data[offsets[0] : offsets[-1]]]
    begin = mask & ~np.append(False, mask[:-1])
    begin[(offsets[:-1] - offsets[0])[offsets[:-1] < offsets[-1]]] |= mask[(offsets[:-1] - offsets[0])[offsets[:-1] < offsets[-1]]]
    words_before = np.append(0, np.cumsum(begin))
    at = words_before[cuts - offsets[0]]
    start, end = at[:-1], at[1:]
    return start[end > start], end[end > start]


def id_filter(ids: DataFrame) -> np.ndarray:
    """A Bloom filter of fixed size over a column ``id``: tasks send words of bits, which are joined by or."""

    def bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            places = filter_places(batch.column("id").to_numpy(zero_copy_only=False)).reshape(-1)
            word, bit = places >> 6, np.uint64(1) << (places & 63).astype(np.uint64)
            order = np.argsort(word, kind="stable")
            at = np.flatnonzero(np.append(True, word[order][1:] != word[order][:-1])) if len(word) else np.zeros(0, np.int64)
            joined = np.bitwise_or.reduceat(bit[order], at) if len(at) else bit
            yield pa.RecordBatch.from_arrays([pa.array(word[order][at], pa.int32()), pa.array(joined.view(np.int64))], ["slot", "bits"])

    rows = ids.select("id").mapInArrow(tk.frugal(bits), "slot int, bits long").groupBy("slot").agg(F.bit_or("bits").alias("bits")).toArrow()
    out = np.zeros(1 << (FILTER_BITS - 6), np.uint64)
    out[rows["slot"].to_numpy()] = rows["bits"].to_numpy().view(np.uint64)
    return out


def filter_places(ids: np.ndarray) -> np.ndarray:
    h = ids.astype(np.int64).view(np.uint64)
    return np.stack([(tk.mix(h + np.uint64(k)) >> np.uint64(64 - FILTER_BITS)).astype(np.int64) for k in (1, 2)])


def passes(filter_: np.ndarray, ids: np.ndarray) -> np.ndarray:
    places = filter_places(ids)
    return ((filter_[places >> 6] >> (places & 63).astype(np.uint64)) & np.uint64(1)).all(0)


def paragraph_texts(docs: DataFrame, wanted: DataFrame, min_words: int) -> DataFrame:
    """(unit, text) of the paragraphs in ``wanted``; a filter keeps other documents' texts out of the shuffle."""
    share = docs.sparkSession.sparkContext.broadcast(id_filter(wanted.select(F.col("unit.doc_id").alias("id"))))

    def pick(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            batch = batch.filter(pa.array(passes(share.value, batch.column("doc_id").to_numpy(zero_copy_only=False))))
            for part in tk.slices(batch, "text"):
                ids, starts, texts = [], [], []
                for doc_id, text in zip(part.column("doc_id").to_pylist(), part.column("text").to_pylist(), strict=True):
                    at = 0
                    for line in (text or "").split("\n"):
                        n = len(_WORDS.findall(line))
                        if n >= min_words:
                            ids.append(doc_id)
                            starts.append(at)
                            texts.append(line)
                        at += n
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(starts, pa.int32()), pa.array(texts, pa.string())], ["doc_id", "start", "text"])

    found = docs.mapInArrow(tk.frugal(pick), "doc_id long, start int, text string").select(F.struct("doc_id", "start").alias("unit"), "text")
    return found.join(wanted, "unit", "left_semi").groupBy("unit").agg(F.min("text").alias("text"))


_WORDS = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")


def jaccard(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """(a, b, similarity) by the exact Jaccard similarity of the texts' distinct shingles."""

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in tk.slices(batch, "text_b", 512 << 10):
                n = part.num_rows
                both = pa.concat_arrays([part.column(c).cast(pa.large_string()) for c in ("text_a", "text_b")])
                who, what, _ = tk.distinct(*tk.shingles(tk.words(both), WIDTH))
                pair, total = who % n, np.bincount(who % n, minlength=n)
                order = np.lexsort((what, pair))
                pair, what = pair[order], what[order]
                same = (pair[1:] == pair[:-1]) & (what[1:] == what[:-1])
                shared = np.bincount(pair[1:][same], minlength=n)
                yield pa.RecordBatch.from_arrays([part.column("a"), part.column("b"), pa.array(shared / np.maximum(1, total - shared))], ["a", "b", "similarity"])

    kind = "struct<doc_id: long, start: int>"
    joined = pairs.join(texts.select(F.col("unit").alias("a"), F.col("text").alias("text_a")), "a").join(texts.select(F.col("unit").alias("b"), F.col("text").alias("text_b")), "b")
    return joined.select("a", "b", "text_a", "text_b").mapInArrow(tk.frugal(verify), f"a {kind}, b {kind}, similarity double")


def _line_features(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    who, what, _ = tk.distinct(*tk.shingles(tk.words(column), WIDTH))
    return who, what, np.ones(len(who))


def repeated_passages(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", threshold: float = 0.8, min_words: int = 32) -> DataFrame:
    """Passages of documents that other documents hold too: (doc_id, start, n_words, first, removed).

    ``first`` is the passage, {doc_id, start}, that the cluster keeps: the
    smallest; all others are ``removed``.  ``start`` counts words from 0.  Words
    are runs of ASCII letters and digits and of characters from U+0080, in lower
    case.

    Paragraphs are lines of ``min_words`` words or more.  Those that share a band
    of their MinHash sketch are one bucket.  Links are pairs of a bucket of an
    exact Jaccard similarity of ``threshold`` or more over five-word shingles, and
    clusters are components of links: a bucket's members are compared with its
    first and last, and then all pairs that are not in one cluster yet (see
    ``settle``).  Two paragraphs at 0.8 that share no band, 2 in 1,000, are not
    compared.  Passages inside
    paragraphs are found by spans of SPAN words that begin at anchors, words
    chosen by the text around them alone; spans are one cluster if equal, by 128
    bits.  A passage of 50 words always holds a span.

    Only repetition across documents counts.  Null and empty texts have no
    passages; rows with a null id are not read.  Rows that repeat an id are one
    document.  Texts of any length are read whole.  Empty tables give an empty
    result; other columns are ignored.
    """
    ship(docs.sparkSession)
    rows = docs.where(F.col(doc_id).isNotNull()).select(F.col(doc_id).cast("long").alias("doc_id"), F.lower(text).alias("text"))
    cut = materialize(units(rows, min_words), "units")
    keyed = cut.select(F.struct("doc_id", "start").alias("unit"), "n_words", "digest", F.explode("keys").alias("key"))
    spread = F.struct(F.min("unit").alias("lo"), F.max("unit").alias("hi"))
    hubs = materialize(keyed.groupBy("key", "digest").agg(spread.alias("h")).where("h.lo.doc_id < h.hi.doc_id").select("key", "digest", "h.lo", "h.hi"), "hubs", by_size=True)
    shared = materialize(keyed.join(hubs.withColumnRenamed("key", "k").withColumnRenamed("digest", "d"), (F.col("key") == F.col("k")) & F.col("digest").eqNullSafe(F.col("d"))).select("key", "unit", "n_words", "digest", "lo", "hi"), "shared")
    spans = shared.where("digest is not null").select("unit", "n_words", F.col("lo").alias("first")).distinct()
    lines = shared.where("digest is null")
    pairs = lines.select(F.explode(F.array(F.struct(F.col("lo").alias("a"), F.col("unit").alias("b")), F.struct(F.col("unit").alias("a"), F.col("hi").alias("b")))).alias("p")).select("p.*").where("a < b and a.doc_id <> b.doc_id").distinct()
    pairs = materialize(pairs, "pairs", by_size=True)
    wanted = pairs.select(F.explode(F.array("a", "b")).alias("unit")).distinct()
    texts = materialize(paragraph_texts(rows, wanted, min_words), "paragraphs")
    links = materialize(jaccard(pairs, texts).where(F.col("similarity") >= threshold).select("a", "b"), "links")
    buckets = lines.select("key", "unit", F.col("unit.doc_id").alias("owner"), F.col("n_words").alias("words"))
    roots = components(settle(buckets, links, texts, _line_features, threshold))
    sizes = lines.groupBy("unit").agg(F.max("n_words").alias("n_words"))
    clustered = roots.select(F.col("node").alias("unit"), F.col("root").alias("first")).join(sizes, "unit").select("unit", "n_words", "first")
    return spans.unionByName(clustered).select("unit.doc_id", "unit.start", "n_words", "first", (F.col("unit") != F.col("first")).alias("removed"))


def passage_report(passages: DataFrame) -> DataFrame:
    """A row for each document with a repeated passage: (doc_id, class_id, n_links, n_passages, n_removed, removed_words).

    Documents that hold the same passages are linked to the one that holds the
    first, and a class is a component of these links, named by its smallest id.
    Documents without a repeated passage, those without text among them, have no
    row; rows that repeat an id are one document; no passages give no rows.
    """
    held = materialize(passages, "passages", by_size=True)
    links = held.select(F.col("first.doc_id").alias("a"), F.col("doc_id").alias("b")).where("a <> b").distinct()
    roots = components(links)
    degree = links.select(F.explode(F.array("a", "b")).alias("doc_id")).groupBy("doc_id").agg(F.count("*").alias("n_links"))
    ends = F.struct(F.col("start").alias("a"), (F.col("start") + F.col("n_words")).alias("b"))
    spans = held.where("removed").groupBy("doc_id").agg(F.sort_array(F.collect_set(ends)).alias("spans"))  # of one text
    union = F.aggregate("spans", F.struct(F.lit(0).alias("total"), F.lit(0).alias("end")), lambda x, s: F.struct((x["total"] + F.greatest(F.lit(0), s["b"] - F.greatest(s["a"], x["end"]))).alias("total"), F.greatest(s["b"], x["end"]).alias("end")))
    spread = spans.select("doc_id", union["total"].alias("removed_words"))
    sums = held.groupBy("doc_id").agg(F.count("*").alias("n_passages"), F.sum(F.col("removed").cast("long")).alias("n_removed"))
    joined = roots.withColumnRenamed("node", "doc_id").join(sums, "doc_id").join(degree, "doc_id").join(spread, "doc_id", "left")
    return joined.select("doc_id", F.col("root").alias("class_id"), "n_links", "n_passages", "n_removed", F.coalesce("removed_words", F.lit(0)).cast("long").alias("removed_words"))


def drop_passages(docs: DataFrame, passages: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents with the words of their removed passages cut out, from the first word's start to the last one's end.

    Passages that overlap are cut as one.  Null and empty texts, rows with a null
    id, and documents without passages stay as they are; rows that repeat an id
    lose the same places; all columns stay.
    """
    ship(docs.sparkSession)
    spans_name, owner = fresh(docs, "__spans"), fresh(docs, "__owner")
    spans = passages.where("removed").groupBy("doc_id").agg(F.collect_set(F.struct("start", "n_words")).alias(spans_name)).withColumnRenamed("doc_id", owner)

    @F.udf(returnType="string", useArrow=True)
    def cut(value, removed):  # noqa: ANN001, ANN202
        if not value or not removed:
            return value
        places = [m.span() for m in _WORDS.finditer(value)]
        out, at, last = [], 0, 0
        for first, n in sorted((r["start"], r["n_words"]) for r in removed):
            a, b = max(first, last), min(first + n, len(places))
            if b > a:
                out.append(value[at : max(at, places[a][0])])
                at, last = places[b - 1][1], b
        return "".join([*out, value[at:]])

    joined = docs.join(spans, docs[doc_id] == spans[owner], "left")
    return joined.withColumn(text, cut(F.col(text), F.col(spans_name))).select(*columns(docs))
