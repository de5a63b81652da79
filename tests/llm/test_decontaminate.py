import itertools
import random

from driftview.llm.decontaminate import clean_of, contamination
from tests.llm.conftest import words


def bench(spark, rows):
    return spark.createDataFrame(rows, "item_id long, text string, doc_id long")


def hits(docs, items):
    return {(r["doc_id"], r["item_id"]) for r in contamination(docs, items).collect()}


def test_exact_substituted_and_clean(spark, frame):
    item = words(1, 40)
    rng = random.Random(2)
    changed = [f"z{rng.randrange(999)}" if k % 9 == 4 else w for k, w in enumerate(item)]
    docs = frame([
        (1, " ".join(words(3, 100) + item + words(4, 50))),
        (2, " ".join(words(5, 100) + changed + words(6, 50))),
        (3, " ".join(words(7, 300))),
        (4, " ".join(words(8, 60) + item[10:26] + words(9, 60))),
        (5, " ".join(item[:6] + words(10, 100) + item[20:26])),
        (6, ", ".join(w.upper() for w in item)),
    ])
    assert hits(docs, bench(spark, [(7, " ".join(item), 1)])) == {(1, 7), (2, 7), (4, 7), (6, 7)}


def test_short_items_are_sought_whole(spark, frame):
    docs = frame([(1, "one two three four five six seven"), (2, "one two three four five x"), (3, "two three four")])
    items = bench(spark, [(1, "Two three four five six!", 0), (2, "two three four", 0), (3, "", 0), (4, None, 0), (None, "one two three four five", 0)])
    assert hits(docs, items) == {(1, 1), (2, 1)}


def test_windows_against_brute_force(spark, frame):
    rng = random.Random(5)
    items = {k: words(50 + k, 30) for k in range(5)}
    docs = {}
    for k in range(40):
        item = items[k % 5]
        noisy = [w if rng.random() > 0.15 else f"n{rng.randrange(999)}" for w in item]
        docs[k] = words(200 + k, 30) + noisy + words(300 + k, 30)
    found = hits(frame([(k, " ".join(v)) for k, v in docs.items()]), bench(spark, [(k, " ".join(v), 0) for k, v in items.items()]))

    truth = set()
    for d, dw in docs.items():
        for b, bw in items.items():
            for shift in range(-len(bw), len(dw)):
                eq = [0 <= shift + k < len(dw) and dw[shift + k] == w for k, w in enumerate(bw)]
                if any(sum(eq[i : i + 13]) >= 11 for i in range(len(bw) - 12)):
                    truth.add((d, b))
    assert found == truth and len(truth) > 15


def test_no_tolerated_substitution_is_missed(spark, frame):
    """Every choice of replaced words that leaves 80 % of an item, for items of 5 to 13 words, beside choices of one more."""
    items, docs, want = [], [], set()
    for n in range(5, 14):
        item = words(n, n)
        items.append((n, " ".join(item), 0))
        allowed = n - -(-n * 8 // 10)
        for spoilt in (allowed, allowed + 1):
            for choice in itertools.combinations(range(n), spoilt):
                if spoilt > allowed and sum(choice) % 7:
                    continue
                docs.append((len(docs), " ".join(["before", *(f"r{k}" if k in choice else w for k, w in enumerate(item)), "after"])))
                if spoilt == allowed:
                    want.add((docs[-1][0], n))
    assert hits(frame(docs), bench(spark, items)) == want


def test_repeated_ids_are_read_each(spark, frame, monkeypatch):
    import driftview.llm.decontaminate as d

    a, b = (" ".join(words(k, 20)) for k in (1, 2))
    docs = frame([(1, a + " x"), (1, b + " y"), (2, " ".join(words(9, 30))), (3, " ".join(["again"] * 4000))])
    items = bench(spark, [(7, a, 0), (7, b, 0), (8, b, 0), (9, " ".join(["again"] * 300), 0)])
    for limit in (10**6, 0):
        monkeypatch.setattr(d, "BROADCAST_SEEDS", limit)
        assert hits(docs, items) == {(1, 7), (1, 8), (3, 9)}


def test_shuffled_path_gives_the_same(spark, frame, monkeypatch):
    import driftview.llm.decontaminate as d

    item = words(1, 30)
    docs = frame([(1, " ".join(words(3, 20) + item)), (2, " ".join(words(4, 50)))])
    monkeypatch.setattr(d, "BROADCAST_SEEDS", 0)
    assert hits(docs, bench(spark, [(7, " ".join(item), 1)])) == {(1, 7)}


def test_odd_rows(spark, odd, frame):
    items = bench(spark, [(1, " ".join(words(5, 60_000)[30_000:30_040]), 0), (1, " ".join(words(5, 60_000)[30_000:30_040]), 0)])
    assert hits(odd, items) == {(3, 1)}
    kept = clean_of(odd, contamination(odd, items))
    assert kept.count() == odd.count() - 1 and set(kept.columns) == set(odd.columns)
    assert hits(frame([]), items) == set() and hits(odd, bench(spark, [])) == set()
