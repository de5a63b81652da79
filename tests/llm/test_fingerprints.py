import hashlib
import re
import unicodedata

import pytest
from pyspark.sql import functions as F

import driftview.llm.fingerprints as fp
from tests.llm.conftest import words


def canonical(t):
    folded = unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", t or "").casefold())
    return re.sub("[\x09-\x0d\x20\x85\u1680\u2028\u2029]+", " ", folded).strip(" ")


def check(df, rows):
    got = sorted(fp.fingerprint_report(df).collect(), key=lambda r: (r["doc_id"] is not None, r["doc_id"] or 0, r["n_chars"]))
    rows = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, (r[1] or "").encode()))
    digests = {}
    assert len(got) == len(rows)
    by_id = {}
    for k, (key, t) in enumerate(rows):
        t, nxt = t or "", rows[(k + 1) % len(rows)][1] or ""
        cut = len(t) // 4
        edited = t[: len(t) - cut] + nxt[:cut]
        by_id.setdefault(key, []).append((len(t), hashlib.sha256(edited.encode()).hexdigest(), float(canonical(t) == canonical(edited)), float(canonical(t) == canonical(nxt))))
    for r in got:
        assert (r["n_chars"], r["edited_sha256"], r["near_edited"], r["near_next"]) in by_id[r["doc_id"]]
        digests.setdefault(r["fingerprint"], set()).add(r["doc_id"])
    return got


def test_next_texts_across_slots(frame):
    rows = [(k * k + 3, " ".join(words(k, 3 + k % 40)) + "é" * (k % 5)) for k in range(700)]
    check(frame(rows), rows)


def test_equal_texts_have_equal_fingerprints(frame):
    rows = [(1, "ﬁne  Text"), (2, " FINE\ttext\n"), (3, "fine text"), (4, "fine texts"), (5, "Straße"), (6, "STRASSE")]
    got = {r["doc_id"]: r for r in check(frame(rows), rows)}
    assert got[1]["fingerprint"] == got[2]["fingerprint"] == got[3]["fingerprint"] != got[4]["fingerprint"]
    assert got[5]["fingerprint"] == got[6]["fingerprint"]
    assert [got[k]["group_id"] for k in range(1, 7)] == [1, 1, 1, 4, 5, 5] and got[2]["group_size"] == 3


def test_folding_is_composed_again(frame):
    rows = [(1, "\u03aa\u0301"), (2, "\u0390"), (3, "\u03b9\u0308\u0301"), (4, "\u03ca\u0301 "), (5, "\u1680\u0390\u2028"), (6, "\u03ca")]
    got = {r["doc_id"]: r for r in check(frame(rows), rows)}
    assert len({got[k]["fingerprint"] for k in range(1, 6)}) == 1 and got[6]["fingerprint"] != got[1]["fingerprint"]
    assert all(ord(c) < 128 for c in fp.SPACES)


@pytest.mark.parametrize("limit", [0, 10**6])
def test_null_ids_are_counted_in_their_groups(frame, monkeypatch, limit):
    monkeypatch.setattr(fp, "BROADCAST_ROWS", limit)
    rows = [(None, "x y"), (3, "X  y"), (None, "only null"), (None, "only  null"), (8, "x y"), (9, "z")]
    got = sorted((r["doc_id"] or 0, r["group_id"] or 0, r["group_size"]) for r in fp.fingerprint_report(frame(rows)).collect())
    assert got == [(0, 0, 2), (0, 0, 2), (0, 3, 3), (3, 3, 3), (8, 3, 3), (9, 9, 1)]


def test_different_texts_in_one_bucket_are_parted(frame, monkeypatch):
    monkeypatch.setattr(fp, "digest", lambda c: F.lit("0" * 32))
    docs = frame([(1, "a"), (2, "b"), (3, "A"), (4, "c")])
    marked = docs.select("doc_id", F.lit("0" * 32).alias("fingerprint"))
    assert {r["doc_id"]: (r["group_id"], r["group_size"]) for r in fp.equal_groups(marked, docs).collect()} == {1: (1, 2), 2: (2, 1), 3: (1, 2), 4: (4, 1)}


@pytest.mark.parametrize("limit", [0, 10**6])
def test_odd_rows(odd, frame, monkeypatch, limit):
    monkeypatch.setattr(fp, "BROADCAST_ROWS", limit)
    check(odd, [(r["doc_id"], r["text"]) for r in odd.collect()])
    assert fp.fingerprint_report(frame([])).collect() == []
    alone = fp.fingerprint_report(frame([(9, "abcdefgh")])).first()
    assert alone["near_next"] == 1.0 and alone["edited_sha256"] == hashlib.sha256(b"abcdefab").hexdigest()
