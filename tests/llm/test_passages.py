import random

import pytest

from driftview.llm import settle
from driftview.llm.passages import drop_passages, passage_report, repeated_passages
from tests.llm.conftest import words


def found(df):
    return {r["doc_id"]: r for r in passage_report(repeated_passages(df)).collect()}


def test_embedded_passages_of_fifty_words(frame):
    rng, rows, planted = random.Random(1), [], {}
    passages = [words(900 + k, 50 + 5 * k) for k in range(8)]
    for k in range(40):
        w = words(k, rng.randrange(20, 150))
        if k < 24:
            at = rng.randrange(len(w))
            w[at:at] = passages[k % 8]
            planted.setdefault(k % 8, []).append(k)
        rows.append((k, " ".join(w)))
    got = found(frame(rows))
    assert set(got) == set(range(24))
    for ids in planted.values():
        assert len({got[k]["class_id"] for k in ids}) == 1
        assert got[min(ids)]["n_removed"] == 0 and all(got[k]["n_removed"] for k in ids if k != min(ids))


def test_near_equal_paragraphs_and_short_lines(frame):
    base = words(5, 60)
    near = [*base[:30], "edited", *base[31:]]
    short = "a common line of few words"
    rows = [(1, " ".join(words(1, 50)) + "\n" + " ".join(base)), (2, " ".join(near) + "\n" + short), (3, short + "\n" + " ".join(words(3, 50)))]
    got = found(frame(rows))
    assert set(got) == {1, 2} and got[2]["class_id"] == 1


@pytest.mark.parametrize("members", [settle.MEMBERS, 16])
def test_a_large_group_of_near_copies_against_brute_force(frame, monkeypatch, members):
    monkeypatch.setattr(settle, "MEMBERS", members)
    rng, base, texts = random.Random(3), words(11, 150), {}
    for k in range(120):
        w = list(base)
        for at in rng.sample(range(len(w)), 2):
            w[at] = f"e{rng.randrange(10**6)}"
        texts[k] = w
    sets = {k: {tuple(w[i : i + 5]) for i in range(len(w) - 4)} for k, w in texts.items()}
    root = {k: k for k in texts}

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for i in texts:
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    kept = [r for r in repeated_passages(frame([(k, " ".join(w)) for k, w in texts.items()])).collect() if r["n_words"] == 150]
    first = {r["doc_id"]: r["first"]["doc_id"] for r in kept}
    assert {k: first.get(k, k) for k in texts} == {k: find(k) for k in texts}


def test_removal_keeps_the_first_copy_and_the_rest_of_the_text(frame):
    p, own = " ".join(words(7, 80)), [" ".join(words(k, 60)) for k in range(4)]
    docs = frame([(1, f"{own[0]}. {p}. {own[1]}."), (2, f"{own[2]}. {p}. {own[3]}."), (3, None)])
    out = {r["doc_id"]: r["text"] for r in drop_passages(docs, repeated_passages(docs)).collect()}
    assert p in out[1] and out[3] is None
    cut = out[2].removeprefix(f"{own[2]}. ").removesuffix(f". {own[3]}.")
    assert len(cut) < len(out[2]) - 100 and len(cut) < 0.6 * len(p)


def test_a_hot_passage_is_one_class(frame):
    p = " ".join(words(9, 70))
    got = found(frame([(k, " ".join(words(k, 30)) + " " + p) for k in range(50)]))
    assert len(got) == 50 and {r["class_id"] for r in got.values()} == {0} and got[0]["n_links"] == 49


def test_odd_rows(odd, frame):
    assert found(odd) == {} and found(frame([])) == {}
    twice = [(1, " ".join(words(1, 80))), (1, " ".join(words(1, 80))), (None, " ".join(words(1, 80)))]
    assert found(frame(twice)) == {}
    assert drop_passages(odd, repeated_passages(odd)).columns == odd.columns
