import random

import numpy as np
import pyarrow as pa

from driftview.llm.near_dup import document_frequencies, idf_table, keep_one, near_duplicates, weighted_shingles
from tests.llm.conftest import words


def edited(base, k, seed):
    rng = random.Random(seed)
    out = list(base)
    for at in rng.sample(range(len(out)), k):
        out[at] = f"e{rng.randrange(10**6)}"
    return out


def classes(df):
    return {r["doc_id"]: r["class_id"] for r in near_duplicates(df).collect()}


def jaccard(a, b):
    sa, sb = ({tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for w in (a, b))
    return len(sa & sb) / len(sa | sb)


def test_copies_near_copies_and_others(frame):
    base = words(1, 200)
    texts = {10: base, 11: list(base), 12: edited(base, 2, 3), 13: words(2, 200), 14: base[:100] + words(4, 100)}
    found = classes(frame([(k, " ".join(v)) for k, v in texts.items()]))
    assert found[10] == found[11] == found[12] == 10
    assert found[13] == 13 and found[14] == 14


def test_against_brute_force(frame):
    texts = {}
    for g in range(12):
        base = words(100 + g, 120)
        texts[g * 10] = base
        for k in range(1, 8):
            texts[g * 10 + k] = edited(base, k, g * 100 + k)
    found = classes(frame([(k, " ".join(v)) for k, v in texts.items()]))
    ids = sorted(texts)
    for i in ids:
        for j in ids:
            if i < j:
                s = jaccard(texts[i], texts[j])
                if s >= 0.85:
                    assert found[i] == found[j], (i, j, s)
                if i // 10 != j // 10:
                    assert found[i] != found[j]


def test_large_group_links_through_edits(frame):
    base = words(7, 150)
    texts = {k: edited(base, 2, k) for k in range(120)}
    root = {k: k for k in texts}

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for i in texts:
        for j in texts:
            if i < j and jaccard(texts[i], texts[j]) >= 0.84:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    found = classes(frame([(k, " ".join(v)) for k, v in texts.items()]))
    lost = sum(found[k] != found[find(k)] for k in texts)
    assert lost == 0


def test_large_group_against_all_pairs_at_the_threshold(frame):
    base = words(7, 150)
    docs = frame([(k, " ".join(edited(base, 2, k))) for k in range(120)])
    idf = idf_table(document_frequencies(docs, "text", 5), 120, 0.1)
    _, who, what, weight = weighted_shingles(pa.array([r["text"] for r in docs.select("doc_id", "text").orderBy("doc_id").collect()]), 5, idf)
    _, name = np.unique(what, return_inverse=True)
    table = np.zeros((120, name.max() + 1))
    table[who, name] = weight
    root = list(range(120))
    for i in range(120):
        for j in range(i):
            if np.minimum(table[i], table[j]).sum() >= 0.8 * np.maximum(table[i], table[j]).sum():
                a, b = sorted((root[i], root[j]))
                root = [a if x == b else x for x in root]
    found = {r["doc_id"]: r["class_id"] for r in near_duplicates(docs).collect()}
    assert [found[k] for k in range(120)] == root


def test_odd_rows(odd, frame):
    rows = near_duplicates(odd).collect()
    assert len(rows) == odd.count()
    found = {r["doc_id"]: r["class_id"] for r in rows}
    assert found[None] is None and found[1] == found[2] == found[5] == 1 and found[3] == 3 and found[4] == 4
    kept = keep_one(odd, near_duplicates(odd))
    assert kept.columns == odd.columns
    assert sorted((r["doc_id"] is None, r["doc_id"]) for r in kept.select("doc_id").collect()) == sorted([(True, None), (False, 1), (False, 3), (False, 4), (False, 6)], key=lambda x: (x[0], x[1] or 0))
    assert near_duplicates(frame([])).collect() == []
