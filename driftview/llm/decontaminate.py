"""Benchmark passages in documents, found by spaced seeds, in built-in functions only."""

from __future__ import annotations

import functools
import itertools
import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftview.llm.scratch import materialize

#: Words that a seed reads at most, the words it may span, and how many masks a length of passage may ask for.
WEIGHT, SPAN, FEW = 6, 12, 3
#: Seeds of benchmarks are sent to every task up to this many, about 100 MB; beyond it they are shuffled.
BROADCAST_SEEDS = 2_000_000


def word_hashes(text: Column) -> Column:
    """A hash of each word in order; words are runs of letters and digits, in lower case."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    return F.transform(words, lambda w: F.xxhash64(w))


@functools.lru_cache(maxsize=256)
def masks_for(n: int, spoilt: int) -> tuple[tuple[int, ...], ...]:
    """Masks, word offsets from 0, of which one somewhere in ``n`` words avoids any ``spoilt`` of them.

    Masks of the largest weight of which few are enough; each is the one that
    saves most of the choices of spoilt words that the ones before don't.
    """
    for weight in range(min(WEIGHT, n - spoilt), 0, -1):
        choices = [frozenset(c) for c in itertools.combinations(range(n), spoilt)]
        saves = {}
        for rest in itertools.combinations(range(1, min(SPAN, n)), weight - 1):
            mask = (0, *rest)
            laid = [{at + o for o in mask} for at in range(n - mask[-1])]
            saves[mask] = {c for c in choices if any(not (c & words) for words in laid)}
        left, chosen = set(choices), []
        while left and len(chosen) < FEW:
            best = max(saves, key=lambda m: (len(saves[m] & left), -m[-1], m))
            left -= saves[best]
            chosen.append(best)
        if not left:
            return tuple(chosen)
    return ((0,),)


def seed_masks(min_words: int, window: int, likeness: float) -> list[tuple[tuple[int, ...], list[int]]]:
    """Each mask with the lengths of items that use it, items of ``window`` words or more counting as such."""
    found: dict[tuple[int, ...], list[int]] = {}
    for n in range(min_words, window + 1):
        for mask in masks_for(n, n - needed(n, likeness)):
            found.setdefault(mask, []).append(n)
    return list(found.items())


def needed(n: int, likeness: float) -> int:
    """Words of ``n`` that must be equal."""
    return math.ceil(n * likeness - 1e-9)


def _seed(hashes: Column, at: Column, masks: dict[int, tuple[int, ...]], number: Column) -> Column:
    """The key of the mask of that number laid on ``hashes`` at ``at``; 0 where it sticks out."""
    key = F
    for own, mask in masks.items():
        value = F.when((at >= 0) & (at + mask[-1] < F.size(hashes)), F.xxhash64(F.lit(own), *[F.get(hashes, at + o) for o in mask]))
        key = key.when(number == own, value)
    return F.coalesce(key, F.lit(0))  # never null: else Spark computes it a second time to filter nulls


def _laid(rows: DataFrame, masks: dict[int, tuple[int, ...]], name: str) -> DataFrame:
    """A row for each mask at each word, with the number of the mask."""
    none, n = F.lit(0).cast("int"), len(masks)
    spread = rows.select("*", F.explode(F.when(F.size("hashes") > 0, F.sequence(none, F.size("hashes") * n - 1)).otherwise(F.array().cast("array<int>"))).alias("j"))
    number = F.element_at(F.array(*map(F.lit, masks)), (F.col("j") % n + 1).cast("int"))
    return spread.withColumn(name, F.expr(f"cast(j div {n} as int)")).withColumn("mask", number).drop("j")


def contamination(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", text: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = 13, likeness: float = 0.8, min_words: int = 5) -> DataFrame:
    """Documents that hold passages of benchmark items: (doc_id, item_id, n_matched, n_item_words, overlap).

    A fixed mask laid on a text hashes some of the words under it and ignores
    the others, so one seed still meets if words it ignores are replaced.
    Equal seeds of a document and an item align the two; the item counts as
    found where, in some ``window`` consecutive words of it, ``likeness`` of the
    words or more, rounded up, equal the document's aligned ones.  Items shorter
    than the window are sought as a whole, by masks of their own.  Masks are
    chosen so that no choice of replaced words that this allows spoils all of
    them: what is alike enough is found.  ``n_matched`` is the largest number of
    equal words over the item's alignments, ``overlap`` that over the item's words.

    Null and empty texts hold nothing.  Items of fewer than ``min_words`` words,
    which have no shingle of five, are not sought.  Rows with a null id are not
    reported.  Rows that repeat an id are read each, documents as well as items;
    a document and an item give one row.  Whole texts are read, whatever their
    length; of a run of hits along one alignment the first is verified.  Empty
    tables give an empty result; other columns are ignored.
    """
    items = benchmark.select(F.col(item_id).alias("item_id"), word_hashes(F.col(item_text)).alias("hashes")).where(F.col("item_id").isNotNull() & (F.size("hashes") >= min_words))
    items = materialize(items.withColumn("item", F.xxhash64("item_id", "hashes")).dropDuplicates(["item"]), "items", by_size=True)
    given = seed_masks(min_words, window, likeness)
    masks = {k: mask for k, (mask, _) in enumerate(given)}
    length = F.least(F.size("hashes"), F.lit(window))
    own = functools.reduce(lambda a, b: a | b, [(F.col("mask") == k) & length.isin(lengths) for k, (_, lengths) in enumerate(given)])
    seeds = _laid(items, masks, "at").where(own).select("item", F.col("at").alias("item_at"), F.col("mask").alias("item_mask"), _seed(F.col("hashes"), F.col("at"), masks, F.col("mask")).alias("item_key"), _seed(F.col("hashes"), F.col("at") - 1, masks, F.col("mask")).alias("item_before"))
    seeds = materialize(seeds.where("item_key <> 0"), "seeds", by_size=True)
    masks = {r[0]: masks[r[0]] for r in seeds.select("item_mask").distinct().orderBy("item_mask").limit(len(masks)).collect()}
    fields = ("doc_id", "item_id", "n_matched", "n_item_words", "overlap")
    if not masks:
        return docs.select(F.col(doc_id).alias("doc_id")).crossJoin(items.select("item_id")).where("false").select("doc_id", "item_id", *[F.lit(0).cast(t).alias(c) for c, t in zip(fields[2:], ("int", "int", "double"), strict=True)])
    words = docs.where(F.col(doc_id).isNotNull()).select(F.col(doc_id).alias("doc_id"), word_hashes(F.col(text)).alias("hashes"))
    laid = _laid(words, masks, "doc_at").withColumn("key", _seed(F.col("hashes"), F.col("doc_at"), masks, F.col("mask")))
    before = _seed(F.col("hashes"), F.col("doc_at") - 1, masks, F.col("mask"))
    # where the same mask meets one word earlier in both texts, the run's first seed stands for this one
    first = lambda x: (F.col("key") == F.col("item_key")) & ((F.col("item_before") == 0) | (F.col("item_before") != x))
    whole = items.select("item", "item_id", F.col("hashes").alias("item_hashes"))
    if seeds.count() <= BROADCAST_SEEDS:
        hits = laid.join(F.broadcast(seeds), first(before)).join(F.broadcast(whole), "item")
    else:
        row = F.xxhash64("hashes").alias("row")  # tells rows of one id apart
        found = laid.where("key <> 0").select("doc_id", row, "key", "doc_at", before.alias("before")).join(seeds, first(F.col("before")))
        ends = found.withColumn("shift", F.col("doc_at") - F.col("item_at")).groupBy("doc_id", "row", "item", "shift").agg(F.min("doc_at").alias("doc_at"))
        hits = words.withColumn("row", row).join(ends, ["doc_id", "row"]).join(whole, "item").withColumn("item_at", F.col("doc_at") - F.col("shift"))
    shift = F.col("doc_at") - F.col("item_at")
    equal = F.transform(F.col("item_hashes"), lambda h, k: F.coalesce(F.when(shift + k >= 0, F.get(F.col("hashes"), shift + k) == h), F.lit(False)).cast("int"))
    hits = hits.select("doc_id", "item_id", equal.alias("equal"))
    width = F.least(F.size("equal"), F.lit(window))
    total = lambda a: F.aggregate(a, F.lit(0), lambda x, y: x + y)
    near = F.exists(F.sequence(F.lit(1), F.size("equal") - width + 1), lambda i: total(F.slice("equal", i, width)) >= F.ceil(width * F.lit(likeness) - F.lit(1e-9)))
    shared = hits.where(near).groupBy("doc_id", "item_id").agg(F.max(total(F.col("equal"))).alias("n_matched"), F.max(F.size("equal")).alias("n_item_words"))
    return shared.withColumn("overlap", F.col("n_matched") / F.col("n_item_words"))


def clean_of(docs: DataFrame, found: DataFrame, doc_id: str = "doc_id") -> DataFrame:
    """The documents without those that ``contamination`` reports; rows with a null id stay."""
    dropped = materialize(found.select(F.col("doc_id").alias(doc_id)).distinct(), "dropped", by_size=True)
    return docs.join(dropped, doc_id, "left_anti")
