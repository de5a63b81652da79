"""A hidden Markov language model over word classes, and a smoothed unigram base."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftview.llm import tokens as tk
from driftview.llm.scratch import materialize
from driftview.llm.toxicity import fold
from driftview.shipping import ship

#: Words whose counts every task holds: the most frequent ones.  All others are counted as exactly, by a join.
COMMON = 1 << 17
#: Of these, so many are a class each; all other words are classed by their last two bytes.
OWN = 2047
TAIL_BITS = 9
CLASSES = 1 + OWN + (1 << TAIL_BITS)
STATES = 8
BLOCK = 512
SLICE = 4 << 20


def tail_class(tails: np.ndarray) -> np.ndarray:
    return (tk.mix(tails.astype(np.uint64)) >> np.uint64(64 - TAIL_BITS)).astype(np.int32)


class Places:
    """Finds each hash's place in a list of distinct hashes, -1 if it isn't there."""

    BITS = 20

    def __init__(self, listed: np.ndarray) -> None:
        self.listed = listed
        self.tables, rest = [], np.arange(len(listed))
        for shift in (0, self.BITS):
            table = np.full(1 << self.BITS, -1, np.int32)
            slot = self._slot(listed[rest], shift)
            table[slot[::-1]] = rest[::-1]
            self.tables.append(table)
            rest = rest[table[slot] != rest]
        order = np.argsort(listed[rest])
        self.rest, self.rest_at = listed[rest][order], rest[order]

    def _slot(self, h: np.ndarray, shift: int) -> np.ndarray:
        return ((h >> np.uint64(shift)) & np.uint64((1 << self.BITS) - 1)).astype(np.int64)

    def find(self, h: np.ndarray) -> np.ndarray:
        out = np.full(len(h), -1, np.int32)
        if not len(self.listed):
            return out
        open_ = np.arange(len(h))
        for shift, table in zip((0, self.BITS), self.tables, strict=True):
            at = table[self._slot(h[open_], shift)]
            hit = (at >= 0) & (self.listed[np.maximum(at, 0)] == h[open_])
            out[open_[hit]] = at[hit]
            open_ = open_[~hit]
        if len(self.rest):
            k = np.minimum(np.searchsorted(self.rest, h[open_]), len(self.rest) - 1)
            hit = self.rest[k] == h[open_]
            out[open_[hit]] = self.rest_at[k[hit]]
        return out


@dataclass
class Vocabulary:
    """Counts of the training tokens: the common words, and sums for each class."""

    common: np.ndarray
    counts: np.ndarray
    n_tokens: int
    n_types: int
    n_ends: int
    class_tokens: np.ndarray
    class_types: np.ndarray

    def classes(self, tokens: tk.Tokens, at: np.ndarray) -> np.ndarray:
        """Class of each word: 1 to OWN for the most frequent ones; class 0 is the end."""
        return np.where((at >= 0) & (at < OWN), at + 1, 1 + OWN + tail_class(tokens.tails)).astype(np.int32)


@dataclass
class Model:
    start: np.ndarray
    inner: np.ndarray
    move: np.ndarray
    emit: np.ndarray


def count_words(train: DataFrame) -> DataFrame:
    """(word, tail, n): exact counts of the training words; tasks send sums."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in tk.slices(batch, "text", SLICE):
                tokens = tk.words(part.column("text"), tk.GRAPH)
                word, first, n = np.unique(tokens.hashes, return_index=True, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(word.view(np.int64)), pa.array(tail_class(tokens.tails[first])), pa.array(n)], ["word", "tail", "n"])

    return train.mapInArrow(tk.frugal(count), "word long, tail int, n long").groupBy("word").agg(F.min("tail").alias("tail"), F.sum("n").alias("n"))


def vocabulary(counts: DataFrame, n_documents: int) -> Vocabulary:
    common = counts.orderBy(F.desc("n"), "word").limit(COMMON).toArrow()
    words, n, tail = (common[c].to_numpy() for c in ("word", "n", "tail"))
    sums = counts.groupBy("tail").agg(F.sum("n").alias("n"), F.count("*").alias("types")).toArrow()
    tokens, types = np.zeros(CLASSES, np.int64), np.zeros(CLASSES, np.int64)
    at = 1 + OWN + sums["tail"].to_numpy()
    tokens[at], types[at] = sums["n"].to_numpy(), sums["types"].to_numpy()
    total, kinds = int(tokens.sum()) + n_documents, int(types.sum()) + (n_documents > 0)
    own = min(OWN, len(words))
    np.subtract.at(tokens, 1 + OWN + tail[:own], n[:own])
    np.subtract.at(types, 1 + OWN + tail[:own], 1)
    tokens[0], types[0] = n_documents, 1
    tokens[1 : 1 + own], types[1 : 1 + own] = n[:own], 1
    return Vocabulary(words.astype(np.int64).view(np.uint64), n, total, kinds, n_documents, tokens, types)


def class_sequences(column: pa.Array, vocab: Vocabulary, places: Places) -> tuple[tk.Tokens, np.ndarray, np.ndarray, np.ndarray]:
    """Tokens, places of the words, and classes of each text's words and end with where each text begins."""
    tokens = tk.words(column, tk.GRAPH)
    at = places.find(tokens.hashes)
    n = len(column)
    starts = tokens.starts + np.arange(n + 1)
    seq = np.zeros(len(at) + n, np.int32)
    seq[np.arange(len(at)) + tokens.owners()] = vocab.classes(tokens, at)
    return tokens, at, seq, starts


def log_likelihoods(model: Model, seq: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Exact natural log-likelihood of each sequence by the scaled forward recursion, all sequences at once."""
    lengths = np.diff(starts)
    order = np.argsort(-lengths, kind="stable")
    first, lengths = starts[:-1][order], lengths[order]
    emit = np.ascontiguousarray(model.emit.T)
    out = np.zeros(len(order))
    if not len(order):
        return out
    alive = np.searchsorted(-lengths, -np.arange(lengths[0]), "left")  # sequences longer than t
    alpha = model.start * emit[seq[first]]
    for t in range(lengths[0]):
        n = alive[t]
        if t:
            alpha = (alpha[:n] @ model.move) * emit[seq[first[:n] + t]]
        scale = alpha.sum(1)
        alpha /= scale[:, None]
        out[:n] += np.log(scale)
    back = np.empty(len(order))
    back[order] = out
    return back


def expected_counts(model: Model, seq: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, float]:
    """Baum-Welch counts of states begun, moved and emitted, over blocks of at most BLOCK tokens, and their log-likelihood."""
    k = len(model.start)
    lengths = np.diff(starts)
    pieces = -(-lengths // BLOCK)
    owner = np.repeat(np.arange(len(lengths)), pieces)
    nth = np.arange(len(owner)) - np.repeat(np.append(0, np.cumsum(pieces)[:-1]), pieces)
    first = starts[:-1][owner] + nth * BLOCK
    size = np.minimum(BLOCK, lengths[owner] - nth * BLOCK)
    order = np.argsort(-size, kind="stable")
    first, size, head = first[order], size[order], (nth == 0)[order]
    emit = np.ascontiguousarray(model.emit.T)
    start, inner, move, given, total = np.zeros(k), np.zeros(k), np.zeros((k, k)), np.zeros_like(model.emit), 0.0
    for lo in range(0, len(first), 1024):
        f, s, h = first[lo : lo + 1024], size[lo : lo + 1024], head[lo : lo + 1024]
        alive = np.searchsorted(-s, -np.arange(s[0]), "left")
        alphas, scales, likely, seen = [], [], [], []
        for t in range(s[0]):
            n = alive[t]
            obs = seq[f[:n] + t]
            b = emit[obs]
            a = np.where(h[:, None], model.start, model.inner) * b if t == 0 else (alphas[-1][:n] @ model.move) * b
            c = a.sum(1)
            alphas.append(a / c[:, None])
            scales.append(c)
            likely.append(b)
            seen.append(obs)
        beta = np.ones((alive[-1], k))
        gammas = [None] * s[0]
        for t in range(s[0] - 1, -1, -1):
            n = alive[t]
            if t < s[0] - 1:
                m = alive[t + 1]
                next_ = likely[t + 1] * beta / scales[t + 1][:, None]
                move += model.move * (alphas[t][:m].T @ next_)
                beta = np.concatenate([next_ @ model.move.T, np.ones((n - m, k))])
            gammas[t] = alphas[t] * beta
        start += gammas[0][h].sum(0)
        inner += gammas[0][~h].sum(0)
        obs, gamma = np.concatenate(seen), np.concatenate(gammas)
        for state in range(k):
            given[state] += np.bincount(obs, gamma[:, state], model.emit.shape[1])
        total += sum(np.log(c).sum() for c in scales)
    return np.concatenate([start, inner, move.ravel(), given.ravel()]), total


def maximize(sums: np.ndarray, states: int, prior: np.ndarray, weight: float = 20.0) -> Model:
    """The model of largest posterior: classes that a state did not emit get some of ``prior``."""
    start, inner, rest = sums[:states] + 1e-2, sums[states : 2 * states] + 1e-2, sums[2 * states :]
    move = rest[: states * states].reshape(states, states) + 1e-2
    emit = rest[states * states :].reshape(states, -1) + weight * prior
    return Model(start / start.sum(), inner / inner.sum(), move / move.sum(1, keepdims=True), emit / emit.sum(1, keepdims=True))


def class_prior(vocab: Vocabulary) -> np.ndarray:
    p = vocab.class_tokens + 1.0
    return p / p.sum()


def first_model(prior: np.ndarray, states: int, seed: int) -> Model:
    rng = np.random.default_rng(seed)
    emit = prior * rng.gamma(1.0, 1.0, (states, len(prior)))
    move = np.full((states, states), 0.1 / max(1, states - 1))
    np.fill_diagonal(move, 0.9 if states > 1 else 1.0)
    even = np.full(states, 1.0 / states)
    return Model(even, even, move, emit / emit.sum(1, keepdims=True))


def baum_welch(train: DataFrame, vocab: Vocabulary, states: int, rounds: int, sample: int, warm_rounds: int, seed: int, max_bytes: int) -> Model:
    """Rounds over all training texts; they begin from a model fitted to ``sample`` of them, of ``max_bytes`` at most, in one task."""
    prior = class_prior(vocab)
    context = train.sparkSession.sparkContext
    shared = context.broadcast(vocab)

    def sequences(parts: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        places = Places(shared.value.common)
        for part in parts:
            yield class_sequences(part.column("text"), shared.value, places)[2:]

    def warm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        data = list(sequences(tk.within(batches, "text", max_bytes, 2 << 20)))
        model, sums = first_model(prior, states, seed), np.zeros(0)
        for _ in range(warm_rounds):
            sums = sum((expected_counts(model, *x)[0] for x in data), np.zeros(2 * states + states * states + states * CLASSES))
            model = maximize(sums, states, prior)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(sums)), pa.int32()), pa.array(sums)], ["slot", "value"])

    def gather(model_: Model):  # noqa: ANN202
        held = context.broadcast(model_)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums = np.zeros(2 * states + states * states + states * CLASSES)
            for x in sequences(part for batch in batches for part in tk.slices(batch, "text", 2 << 20)):
                sums += expected_counts(held.value, *x)[0]
            at = np.flatnonzero(sums)
            yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(sums[at])], ["slot", "value"])

        return run

    def collected(rows: DataFrame) -> Model:
        got = rows.toArrow()
        sums = np.zeros(2 * states + states * states + states * CLASSES)
        sums[got["slot"].to_numpy()] = got["value"].to_numpy()
        return maximize(sums, states, prior)

    draw = F.xxhash64(F.lit(seed), "doc_id")
    few = train.join(F.broadcast(train.select("doc_id").where("doc_id is not null").orderBy(draw, "doc_id").limit(sample)), "doc_id", "left_semi")
    few = few.repartition(1).sortWithinPartitions(draw, "doc_id", "text")
    model = collected(few.select("text").mapInArrow(tk.frugal(warm), "slot int, value double"))
    for _ in range(rounds):
        sums = train.select("text").mapInArrow(tk.frugal(gather(model)), "slot int, value double")
        model = collected(sums.groupBy("slot").agg(F.sum("value").alias("value")))
    return model


def language_scores(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", folds: int = 7, held_out: int = 2, states: int = STATES, rounds: int = 2, sample: int = 1500, warm_rounds: int = 12, seed: int = 11, max_bytes: int = 32 << 20) -> DataFrame:
    """Log10 probabilities of whole texts: (doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score).

    Words are runs of anything but white space of ASCII, with A-Z in lower case;
    each text ends with one more token.  The model is a hidden Markov model
    over word classes: the most frequent words are a class each, others are
    classed by their last two bytes, and within a class a word has its add-one
    share, with one share more for all unseen words.  The base is an add-one
    unigram model.  Both learn from all documents whose fold is not
    ``held_out``; every count is of all of them.  Training sums run over blocks
    of ``BLOCK`` tokens, scores over whole texts.  The rounds begin from a model
    fitted to ``sample`` documents, of ``max_bytes`` at most, chosen by a hash of
    the id; two ``rounds`` then see every document.

    The commonest words' counts go to every task, in a table of fixed size;
    rarer words, none of which is hot, meet their counts in an equi-join.

    A null or empty text is its end alone.  A null id has fold 0.  Repeated rows
    count and are scored each.  Without training texts the base is 0 for each
    token.  An empty table gives an empty result; other columns are ignored.
    """
    spark = docs.sparkSession
    ship(spark)
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"), (fold(F.col(doc_id), folds) == held_out).alias("held_out"))
    train = rows.where("not held_out").select("doc_id", "text")
    counts = materialize(count_words(train.select("text")), "counts")
    vocab = vocabulary(counts, train.count())
    model = baum_welch(train, vocab, states, rounds, sample, warm_rounds, seed, max_bytes)
    shared = spark.sparkContext.broadcast((vocab, model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocab, model = shared.value
        places, row = Places(vocab.common), TaskContext.get().partitionId() << 40
        slots = np.log10(vocab.n_tokens + vocab.n_types + 1.0)
        share = np.log10(vocab.class_tokens + vocab.class_types + 1.0)
        logs = np.log10(vocab.counts + 1.0)
        for batch in batches:
            for part in tk.slices(batch, "text", SLICE):
                n = part.num_rows
                tokens, at, seq, starts = class_sequences(part.column("text"), vocab, places)
                who, common = tokens.owners(), at >= 0
                own = (at >= 0) & (at < OWN)
                lengths = np.diff(starts)
                base = np.log10(vocab.n_ends + 1.0) - lengths * slots + np.bincount(who[common], logs[at[common]], n)
                score = log_likelihoods(model, seq, starts) / np.log(10.0)
                classes = vocab.classes(tokens, at)
                score -= np.bincount(who[~own], share[classes[~own]], n)
                score += np.bincount(who[common & ~own], logs[at[common & ~own]], n)
                known = np.bincount(who[common], minlength=n) + (vocab.n_ends > 0)
                owner, word, times = tk.distinct(who[~common], tokens.hashes[~common])
                ends = np.append(0, np.cumsum(np.bincount(owner, minlength=n)))
                lists = [pa.ListArray.from_arrays(pa.array(ends, pa.int32()), x) for x in (pa.array(word.view(np.int64)), pa.array(times, pa.int64()))]
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(row, row + n)), part.column("doc_id"), part.column("held_out"), pa.array(lengths), pa.array(known), pa.array(base), pa.array(score), *lists], ["row", "doc_id", "held_out", "n_tokens", "known", "base", "model", "words", "times"])
                row += n

    kind = docs.schema[doc_id].dataType.simpleString()
    scored = materialize(rows.mapInArrow(tk.frugal(run), f"row long, doc_id {kind}, held_out boolean, n_tokens long, known long, base double, model double, words array<long>, times array<long>"), "scored")
    rare = scored.select("row", F.explode(F.arrays_zip("words", "times")).alias("w")).select("row", F.col("w.words").alias("word"), F.col("w.times").alias("times"))
    met = rare.join(counts.select("word", "n"), "word")
    sums = met.groupBy("row").agg(F.sum(F.col("times") * F.log10(F.col("n") + 1.0)).alias("gain"), F.sum("times").alias("met"))
    gain = F.coalesce("gain", F.lit(0.0))
    return scored.drop("words", "times").join(sums, "row", "left").select("doc_id", "held_out", "n_tokens", (F.col("known") + F.coalesce("met", F.lit(0))).alias("n_known"), F.lit(vocab.n_tokens).cast("long").alias("train_tokens"), (F.col("base") + gain).alias("base_score"), (F.col("model") + gain).alias("score"))
