"""Links between members of a bucket that no link joins yet: every such pair is compared, in blocks."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftview.llm.components import components
from driftview.llm.scratch import materialize

#: Members of a block, and words: blocks of long texts hold fewer members.
MEMBERS, WORDS = 512, 200_000
#: Features whose columns are dense at one time.
COLUMNS = 1024

#: Owner, hash and weight of the distinct features of each text of a column.
Features = Callable[[pa.Array], tuple[np.ndarray, np.ndarray, np.ndarray]]


def overlaps(who: np.ndarray, what: np.ndarray, weight: np.ndarray, rows: np.ndarray, cols: np.ndarray, n: int) -> np.ndarray:
    """Weight of the features that text ``rows[i]`` shares with text ``cols[j]``."""
    _, name, held = np.unique(what, return_inverse=True, return_counts=True)
    kept = held[name] > 1
    _, name = np.unique(name[kept], return_inverse=True)
    who, weight = who[kept], weight[kept]
    order = np.argsort(name, kind="stable")
    name, who, weight = name[order], who[order], weight[order]
    out = np.zeros((len(rows), len(cols)))
    for lo in range(0, int(name[-1]) + 1 if len(name) else 0, COLUMNS):
        a, b = np.searchsorted(name, [lo, lo + COLUMNS])
        ones, weights = np.zeros((n, COLUMNS)), np.zeros((n, COLUMNS))
        ones[who[a:b], name[a:b] - lo] = 1.0
        weights[who[a:b], name[a:b] - lo] = weight[a:b]
        out += ones[rows] @ weights[cols].T
    return out


def forest(links: np.ndarray, root: np.ndarray, rows: np.ndarray, cols: np.ndarray) -> tuple[list[int], list[int]]:
    """Of links between rows and columns, those that join two classes which no earlier one joins."""
    parent = list(range(int(root.max()) + 1))

    def find(k: int) -> int:
        while parent[k] != k:
            parent[k] = parent[parent[k]]
            k = parent[k]
        return k

    left, right = [], []
    i, j = np.nonzero(links)
    _, first = np.unique(np.stack([root[rows[i]], root[cols[j]]]), axis=1, return_index=True)
    for x, y in zip(rows[i[first]].tolist(), cols[j[first]].tolist(), strict=True):
        a, b = find(int(root[x])), find(int(root[y]))
        if a != b:
            parent[a] = b
            left.append(x)
            right.append(y)
    return left, right


def block_links(groups: DataFrame, features: Features, threshold: float) -> DataFrame:
    """(a, b): links that join the classes of each group (key, lo, hi), between its blocks ``lo`` and ``hi`` or within one."""
    kind = groups.schema["unit"].dataType.simpleString()

    def link(table: pa.Table) -> pa.Table:
        unit = table.column("unit").combine_chunks()
        empty = pa.table({"a": unit[:0], "b": unit[:0]})
        _, root = np.unique(table.column("root").to_numpy(), return_inverse=True)
        block, owner = table.column("block").to_numpy(), table.column("owner").to_numpy()
        lo, hi = table.column("lo")[0].as_py(), table.column("hi")[0].as_py()
        rows, cols = np.flatnonzero(block == lo), np.flatnonzero(block == hi)
        open_ = (root[rows][:, None] != root[cols][None]) & (owner[rows][:, None] != owner[cols][None])
        if not open_.any():
            return empty
        who, what, weight = features(table.column("text").combine_chunks())
        total = np.bincount(who, weight, table.num_rows)
        shared = overlaps(who, what, weight, rows, cols, table.num_rows)
        union = total[rows][:, None] + total[cols][None] - shared
        left, right = forest(open_ & (shared / np.maximum(union, 1e-9) >= threshold), root, rows, cols)
        if not left:
            return empty
        return pa.table({"a": unit.take(pa.array(left)), "b": unit.take(pa.array(right))})

    return groups.groupBy("key", "lo", "hi").applyInArrow(link, f"a {kind}, b {kind}")


def settle(buckets: DataFrame, links: DataFrame, texts: DataFrame, features: Features, threshold: float, label: str = "links") -> DataFrame:
    """``links`` and all that it takes to join, in each bucket, the classes of any two members of ``threshold`` or more.

    ``buckets`` is (key, unit, owner, words), ``texts`` (unit, text); members of
    one owner are not linked.  Buckets of up to three members must be compared
    before.  First the members of a bucket are dealt to blocks by a hash, and
    pairs within a block are compared; that takes work in proportion to the
    bucket, and joins most of a large group.  Then, in buckets of several
    blocks, each member outside the bucket's largest class is compared with all
    members of other classes, a pair of blocks to a task.  Pairs of one class
    are left out, as a link between them joins nothing; no other pair is.
    """
    hashed = F.xxhash64("unit", "key")
    blocks = lambda n, words: F.ceil(F.greatest(n / MEMBERS, words / WORDS)).cast("int")
    several = None
    for within in (True, False):
        roots = components(links).withColumnRenamed("node", "unit")
        held = buckets if several is None else buckets.join(several, "key", "left_semi")
        held = held.join(roots, "unit", "left").withColumn("root", F.coalesce("root", "unit"))
        sizes = held.groupBy("key", "root").agg(F.count("*").alias("n"), F.sum("words").alias("words"))
        whole = sizes.groupBy("key").agg(F.sum("n").alias("n"), F.sum("words").alias("words"), F.count("*").alias("n_roots"), F.max(F.struct("n", "root", "words")).alias("main")).where("n > 3 and n_roots > 1")
        if within:
            plan = materialize(whole.select("key", blocks(F.col("n"), F.col("words")).alias("n_blocks")), "open", by_size=True)
            several = plan.where("n_blocks > 1").select("key")
            dealt = held.join(plan, "key").withColumn("block", F.pmod(hashed, F.col("n_blocks")).cast("int"))
            dealt = dealt.withColumn("lo", F.col("block")).withColumn("hi", F.col("block"))
        else:
            if not several.limit(1).count():
                break
            rest = blocks(F.col("n") - F.col("main.n"), F.col("words") - F.col("main.words"))
            plan = materialize(whole.select("key", F.col("main.root").alias("main"), rest.alias("n_rest"), blocks(F.col("main.n"), F.col("main.words")).alias("n_main")), "open", by_size=True)
            dealt = held.join(plan, "key").withColumn("in_main", F.col("root") == F.col("main"))
            dealt = dealt.withColumn("block", F.when(F.col("in_main"), F.col("n_rest") + F.pmod(hashed, F.col("n_main"))).otherwise(F.pmod(hashed, F.col("n_rest"))).cast("int"))
            dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.when(F.col("in_main"), F.col("n_rest")).otherwise(F.col("n_rest") + F.col("n_main")) - 1)))
            dealt = dealt.withColumn("lo", F.least("block", "other")).withColumn("hi", F.greatest("block", "other"))
        groups = dealt.select("key", "lo", "hi", "block", "unit", "owner", F.col("root").cast("string").alias("root")).join(texts, "unit")
        links = links.unionByName(materialize(block_links(groups, features, threshold), label))
    return links
