"""Toxicity by learning from confirmed toxic texts and unlabelled texts."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftview.llm import tokens as tk
from driftview.shipping import ship

FEATURE_BITS = 20
#: Besides each word, its first so many bytes: inflected forms share them.
PREFIXES = (4, 5, 6)


def features(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """Row, hashed feature and value of each text's features; a row's values have a Euclidean length of 1."""
    tokens = tk.words(column, heads=PREFIXES)
    n = len(column)
    kinds = [tokens.hashes, *(tk.mix(h ^ np.uint64(11 * k + 3)) for k, h in enumerate(tokens.heads))]
    who = np.concatenate([tokens.owners()] * len(kinds))
    what = np.concatenate(kinds) >> np.uint64(64 - FEATURE_BITS)
    key = who.astype(np.int64) << FEATURE_BITS | what.astype(np.int64)
    key, tf = np.unique(key, return_counts=True)
    who, what = key >> FEATURE_BITS, key & ((1 << FEATURE_BITS) - 1)
    value = np.sqrt(tf.astype(np.float64))
    norm = np.sqrt(np.bincount(who, value * value, n))
    return who, what, value / norm[who], n


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(x, -40, 40)))


@dataclass
class Examples:
    """Sparse rows; ``positive`` marks the confirmed ones, all others are unlabelled."""

    starts: np.ndarray
    index: np.ndarray
    value: np.ndarray
    positive: np.ndarray

    def rows(self, chosen: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        sizes = self.starts[chosen + 1] - self.starts[chosen]
        at = np.repeat(self.starts[chosen] - np.append(0, np.cumsum(sizes)[:-1]), sizes) + np.arange(sizes.sum())
        return np.repeat(np.arange(len(chosen)), sizes), self.index[at], self.value[at]


def fit_nnpu(data: Examples, prior: float, dim: int, epochs: int = 100, batch: int = 512, rate: float = 1.0, beta: float = 0.0, seed: int = 7) -> tuple[np.ndarray, float]:
    """Weights and bias that minimise the non-negative positive-unlabelled risk.

    With logistic loss l, positives P and unlabelled U, the risk is
    prior * mean_P l(+) + max(0, mean_U l(-) - prior * mean_P l(-)).  Where the
    second part of a batch falls below -``beta``, the step goes up that part
    alone.  Steps are scaled by past gradients; batches hold both kinds.
    """
    rng = np.random.default_rng(seed)
    w, b = np.zeros(dim), 0.0
    sum_w, sum_b = np.full(dim, 1e-6), 1e-6
    pos, unl = np.flatnonzero(data.positive), np.flatnonzero(~data.positive)
    if not len(pos) or not len(unl):
        return w, -30.0 if not len(pos) else 30.0
    steps = max(1, -(-len(unl) // batch))
    take = min(len(pos), batch)
    for _ in range(epochs):
        order = rng.permutation(len(unl))
        for k in range(steps):
            u = unl[order[k * batch : (k + 1) * batch]]
            p = pos[rng.choice(len(pos), take, replace=False)]
            row, index, value = data.rows(np.concatenate([p, u]))
            z = np.bincount(row, w[index] * value, len(p) + len(u)) + b
            up = _sigmoid(z)  # slope of l(-); that of l(+) is up - 1
            loss_neg = np.logaddexp(0.0, z)
            rest = loss_neg[len(p) :].mean() - prior * loss_neg[: len(p)].mean()
            g = np.empty(len(z))
            if rest >= -beta:
                g[: len(p)] = prior * ((up[: len(p)] - 1.0) - up[: len(p)]) / len(p)
                g[len(p) :] = up[len(p) :] / len(u)
            else:
                g[: len(p)] = prior * up[: len(p)] / len(p)
                g[len(p) :] = -up[len(p) :] / len(u)
            gw = np.bincount(index, g[row] * value, dim)
            seen = np.flatnonzero(gw)
            step = gw[seen]
            sum_w[seen] += step * step
            w[seen] -= rate * step / np.sqrt(sum_w[seen])
            gb = g.sum()
            sum_b += gb * gb
            b -= 0.1 * rate * gb / np.sqrt(sum_b)
    return w, float(b)


def train(texts: DataFrame, prior: float, max_bytes: int, min_documents: int = 3, lift: float = 4.0) -> tuple[np.ndarray, float]:
    """Fit on a bounded table (id, text, positive) in one task, and return the weights.

    Texts are read in the order of their draw until they make ``max_bytes``.
    Weights go to features in ``min_documents`` confirmed texts or more whose
    share among these is ``lift`` times that among the unlabelled ones or more.
    A feature that only toxic texts have is 1 / prior times as frequent there; so
    where halfway from 1 to that is less than ``lift``, that is asked for instead.
    """

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sizes, index, value, positive = [np.zeros(1, np.int64)], [], [], []
        for part in tk.within(batches, "text", max_bytes):
            who, what, x, n = features(part.column("text"))
            sizes.append(np.bincount(who, minlength=n))
            index.append(what.astype(np.int32))
            value.append(x.astype(np.float32))
            positive.append(part.column("positive").to_numpy(zero_copy_only=False))
        if not index:
            return
        data = Examples(np.cumsum(np.concatenate(sizes)), np.concatenate(index), np.concatenate(value), np.concatenate(positive))
        known = np.repeat(data.positive, np.diff(data.starts))
        n_known = max(1, int(data.positive.sum()))
        within = np.bincount(data.index[known], minlength=1 << FEATURE_BITS)
        without = np.bincount(data.index[~known], minlength=1 << FEATURE_BITS)
        bar = min(lift, (1.0 + 1.0 / prior) / 2.0)
        telling = (within >= min_documents) & (within / n_known >= bar * (without + 1) / max(1, len(data.positive) - n_known))
        names, kept = np.flatnonzero(telling), telling[data.index]
        row = np.repeat(np.arange(len(data.positive)), np.diff(data.starts))[kept]
        starts = np.append(0, np.cumsum(np.bincount(row, minlength=len(data.positive))))
        data = Examples(starts, np.searchsorted(names, data.index[kept]), data.value[kept], data.positive)
        w, b = fit_nnpu(data, prior, len(names))
        yield pa.RecordBatch.from_arrays([pa.array(np.append(names, -1), pa.int32()), pa.array(np.append(w, b))], ["feature", "weight"])

    drawn = texts.repartition(1).sortWithinPartitions(F.xxhash64(F.lit("sample"), "id"), "id", "positive")
    rows = drawn.select("text", "positive").mapInArrow(tk.frugal(fit), "feature int, weight double").toArrow()
    feature, weight = rows["feature"].to_numpy(), rows["weight"].to_numpy()
    w = np.zeros(1 << FEATURE_BITS, np.float32)
    w[feature[feature >= 0]] = weight[feature >= 0]
    return w, float(weight[feature < 0][0]) if len(weight) else 0.0


def score(docs: DataFrame, w: np.ndarray, b: float, doc_id: str, text: str) -> DataFrame:
    share = docs.sparkSession.sparkContext.broadcast(w)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in tk.slices(batch, "text"):
                who, what, x, n = features(part.column("text"))
                z = np.bincount(who, share.value[what] * x, n) + b
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(_sigmoid(z))], ["doc_id", "score"])

    return docs.select(F.col(doc_id).alias("doc_id"), F.lower(text).alias("text")).mapInArrow(tk.frugal(run), f"doc_id {docs.schema[doc_id].dataType.simpleString()}, score double")


def fold(doc_id: Column, modulus: int) -> Column:
    """crc32 of the id as text, modulo ``modulus``; 0 for a null id."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % modulus, F.lit(0)).cast("int")


def toxicity(docs: DataFrame, labels: DataFrame, doc_id: str = "doc_id", text: str = "text", label: str = "toxic", folds: int = 5, max_positive: int = 3000, max_unlabelled: int = 9000, max_bytes: int = 64 << 20) -> DataFrame:
    """Score every text: rows (doc_id, held_out, score, predicted).

    Labels are learned only from ids outside fold 0 of ``folds``.  The
    classifier is fitted on a bounded sample, at most ``max_positive``
    confirmed toxic texts and ``max_unlabelled`` others, chosen by a hash of
    the id, and of these on as many as make ``max_bytes``, in the same order; an
    id gives one text, the smallest of those that repeat it; the class prior is the share of toxic ones among all labels outside
    fold 0.  Unlabelled texts are drawn from all documents outside fold 0,
    labelled or not, and their labels are not read.  Every whole text is scored.

    A null or empty text has no features and gets the bias's score.  A null id
    is held out and never learned from.  Several labels of one id count as
    toxic if one of them is; null labels are ignored.  Repeated rows are scored
    each.  Without toxic labels every score is near 0.  An empty table gives an
    empty result; columns other than the id and the text are never read.
    """
    ship(docs.sparkSession)
    marked = labels.select(F.col(doc_id).alias("id"), F.col(label).alias("y")).where("id is not null and y is not null").groupBy("id").agg(F.max("y").alias("y"))
    marked = marked.where(fold(F.col("id"), folds) != 0)
    n, toxic = marked.agg(F.count("*"), F.coalesce(F.sum((F.col("y") > 0).cast("long")), F.lit(0))).first()
    prior = min(0.9, max(1e-3, toxic / n)) if n else 0.1
    draw = F.xxhash64(F.lit("sample"), "id")
    positives = marked.where("y > 0").orderBy(draw, "id").limit(max_positive).select("id")
    ids = docs.select(F.col(doc_id).alias("id")).where(F.col("id").isNotNull() & (fold(F.col("id"), folds) != 0)).distinct()
    unlabelled = ids.orderBy(draw, "id").limit(max_unlabelled)
    # at most max_positive + max_unlabelled ids: small enough to send to every task
    sample = positives.select("id", F.lit(True).alias("positive")).unionByName(unlabelled.select("id", F.lit(False).alias("positive")))
    texts = docs.select(F.col(doc_id).alias("id"), F.lower(text).alias("text")).join(F.broadcast(sample), "id")
    w, b = train(texts.groupBy("id", "positive").agg(F.min("text").alias("text")), prior, max_bytes)
    scored = score(docs, w, b, doc_id, text)
    return scored.select("doc_id", (fold(F.col("doc_id"), folds) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
