import collections
import itertools
import math
import re
import zlib

import numpy as np
import pytest

import driftview.llm.language_model as lm
from tests.llm.conftest import words

WORD = re.compile("[^\x20\x09-\x0d]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def tokens(text):
    return [*WORD.findall((text or "").translate(LOWER)), None]


def check_base(rows, found):
    counts = collections.Counter()
    for k, t in rows:
        if k is None or zlib.crc32(str(k).encode()) % 7 != 2:
            counts.update(tokens(t))
    n, v = sum(counts.values()), len(counts)
    for (k, t), r in zip(sorted(rows, key=lambda x: (x[0] is not None, x[0] or 0, x[1] or "")), sorted(found, key=lambda r: (r["doc_id"] is not None, r["doc_id"] or 0)), strict=True):
        w = tokens(t)
        assert r["n_tokens"] == len(w) and r["train_tokens"] == n
        assert r["n_known"] == sum(counts[x] > 0 for x in w)
        assert r["base_score"] == pytest.approx(sum(math.log10((counts[x] + 1) / (n + v + 1)) for x in w), rel=1e-9)
        assert r["held_out"] == (k is not None and zlib.crc32(str(k).encode()) % 7 == 2)


@pytest.mark.parametrize("common", [1 << 17, 50])
def test_counts_and_base(frame, monkeypatch, common):
    monkeypatch.setattr(lm, "COMMON", common)
    rows = [(k, " ".join(words(k, 30 + k, 300)) + (" ÀÉ É" if k % 3 else "")) for k in range(60)]
    check_base(rows, lm.language_scores(frame(rows), warm_rounds=3, rounds=1).collect())


def test_model_beats_the_base_on_held_out_texts(frame):
    rows = []
    for k in range(300):
        side = "a" if k % 2 else "b"
        rows.append((k, " ".join(f"{side}{w}" for w in words(k, 80, 60))))
    found = [r for r in lm.language_scores(frame(rows)).collect() if r["held_out"]]
    assert sum(r["score"] for r in found) > sum(r["base_score"] for r in found)


def model(k=3, m=5, seed=1):
    rng = np.random.default_rng(seed)
    norm = lambda x: x / x.sum(-1, keepdims=True)
    return lm.Model(norm(rng.random(k)), norm(rng.random(k)), norm(rng.random((k, k))), norm(rng.random((k, m))))


def test_forward_recursion_sums_over_all_state_paths():
    hmm, seqs = model(), [[0, 3, 2, 4], [1], [2, 2], [4, 0, 1, 3, 3]]
    starts = np.append(0, np.cumsum([len(s) for s in seqs]))
    got = lm.log_likelihoods(hmm, np.array(sum(seqs, [])), starts)
    for s, value in zip(seqs, got, strict=True):
        total = 0.0
        for path in itertools.product(range(3), repeat=len(s)):
            p = hmm.start[path[0]] * hmm.emit[path[0], s[0]]
            for a, b, x in zip(path, path[1:], s[1:], strict=False):
                p *= hmm.move[a, b] * hmm.emit[b, x]
            total += p
        assert value == pytest.approx(math.log(total))


def test_expected_counts_and_rising_likelihood():
    rng = np.random.default_rng(4)
    seq, starts = rng.integers(0, 5, 400), np.array([0, 120, 121, 300, 400])
    hmm, last = model(), -np.inf
    for _ in range(6):
        sums, value = lm.expected_counts(hmm, seq, starts)
        assert sums[:3].sum() == pytest.approx(4) and sums[6 + 9 :].sum() == pytest.approx(400)
        assert value >= last - 1e-9
        last, hmm = value, lm.maximize(sums, 3, np.full(5, 0.2), 1e-9)


def test_places_find_every_word():
    rng = np.random.default_rng(2)
    listed = np.unique(rng.integers(0, 1 << 63, 50_000).astype(np.uint64))
    rng.shuffle(listed)
    places = lm.Places(listed)
    assert (places.find(listed) == np.arange(len(listed))).all()
    assert (places.find(listed ^ np.uint64(1 << 63)) == -1).all()


def test_odd_rows(odd, frame):
    rows = [(r["doc_id"], r["text"]) for r in odd.collect()]
    check_base(rows, lm.language_scores(odd, warm_rounds=2, rounds=1).collect())
    assert lm.language_scores(frame([])).collect() == []
    alone = lm.language_scores(frame([(k, "a b") for k in range(100) if zlib.crc32(str(k).encode()) % 7 == 2][:2])).collect()
    assert all(r["train_tokens"] == 0 and r["n_known"] == 0 and r["base_score"] == 0 for r in alone)
