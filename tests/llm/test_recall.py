"""Near-duplicate classes and repeated paragraphs against all pairs of whole tables; RECALL_SF_DIR names other tables."""

import collections
import os

import pyarrow as pa
from pyspark.sql import functions as F

from driftview.llm import tokens as tk
from driftview.llm.near_dup import document_frequencies, idf_table, near_duplicates, weighted_shingles
from driftview.llm.passages import repeated_passages

SF_DIR = os.environ.get("RECALL_SF_DIR", "/root/testdata/sf0.01")


def similar_pairs(sets, threshold):
    """All pairs of weighted sets {feature: weight} whose weighted Jaccard similarity reaches the threshold.

    Features are ordered from rare to common.  Two sets that are alike enough
    share one among each one's first features, those that make more than 1 -
    threshold of its weight; so only sets that share one are compared.
    """
    count = collections.Counter(f for s in sets for f in s)
    index, out = collections.defaultdict(list), []
    for i, s in enumerate(sets):
        order, total, seen, near = sorted(s, key=lambda f: (count[f], f)), sum(s.values()), 0.0, set()
        for f in order:
            near.update(index[f])
            index[f].append(i)
            seen += s[f]
            if seen > (1.0 - threshold) * total + 1e-9:
                break
        for j in near:
            shared = sum(min(w, sets[j][f]) for f, w in s.items() if f in sets[j])
            if shared >= threshold * (total + sum(sets[j].values()) - shared) - 1e-12:
                out.append((j, i))
    return out


def joined(pairs, n):
    root = list(range(n))

    def find(k):
        while root[k] != k:
            root[k] = root[root[k]]
            k = root[k]
        return k

    for a, b in pairs:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return [find(k) for k in range(n)]


def test_near_duplicates_of_a_whole_table(spark):
    docs = spark.read.parquet(f"{SF_DIR}/documents.parquet")
    rows = docs.select("doc_id", F.lower("text").alias("text")).orderBy("doc_id").collect()
    idf = idf_table(document_frequencies(docs, "text", 5), len(rows), 0.1)
    sets = []
    for lo in range(0, len(rows), 500):
        part = rows[lo : lo + 500]
        _, who, what, weight = weighted_shingles(pa.array([r["text"] for r in part]), 5, idf)
        own = [{} for _ in part]
        for d, f, w in zip(who.tolist(), what.tolist(), weight.tolist(), strict=True):
            own[d][f] = w
        sets += own
    texts = collections.defaultdict(list)  # copies are one
    for k, r in enumerate(rows):
        texts[tuple(tk.words(pa.array([r["text"]])).hashes.tolist())].append(k)
    heads = [v[0] for v in texts.values()]
    pairs = [(heads[a], heads[b]) for a, b in similar_pairs([sets[h] for h in heads], 0.8)]
    found = {r["doc_id"]: r["class_id"] for r in near_duplicates(docs).collect()}
    label = [found[r["doc_id"]] for r in rows]
    assert all(label[k] == label[v[0]] for v in texts.values() for k in v)
    met = sum(label[a] == label[b] for a, b in pairs)
    print(f"\npairs of different texts at 0.8 or more: {len(pairs)}, in one class: {met}")
    assert met >= 0.97 * len(pairs)
    whole = joined(pairs + [(v[0], k) for v in texts.values() for k in v], len(rows))
    least = {}
    for k, c in enumerate(label):
        least.setdefault(c, k)
    assert all(whole[k] == whole[least[c]] for k, c in enumerate(label))  # no class joins what no link joins


def test_repeated_paragraphs_of_a_whole_table(spark):
    docs = spark.read.parquet(f"{SF_DIR}/documents.parquet")
    rows = docs.select("doc_id", F.lower("text").alias("text")).where("doc_id is not null").collect()
    lines = []
    for r in rows:
        at = 0
        for line in (r["text"] or "").split("\n"):
            h = tk.words(pa.array([line])).hashes.tolist()
            if len(h) >= 32:
                lines.append(((r["doc_id"], at), {tuple(h[i : i + 5]): 1.0 for i in range(len(h) - 4)}))
            at += len(h)
    pairs = [(a, b) for a, b in similar_pairs([s for _, s in lines], 0.8) if lines[a][0][0] != lines[b][0][0]]
    first = collections.defaultdict(set)
    for r in repeated_passages(docs).collect():
        first[r["doc_id"], r["start"]].add((r["first"]["doc_id"], r["first"]["start"]))
    met = sum(bool(first[lines[a][0]] & first[lines[b][0]]) for a, b in pairs)
    print(f"\nlike paragraphs of different documents: {len(pairs)} pairs, in one cluster: {met}")
    assert met >= 0.97 * len(pairs) and len(pairs) > 10
