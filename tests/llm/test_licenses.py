import random
import re
import time

import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st

from driftview.llm.licenses import BASE, WORDS, base_places, license_scan, rules, scanner

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def brute(text):
    w = WORDS.findall((text or "").translate(LOWER))
    places = [(k, label) for phrase, label in BASE for k in range(len(w)) if w[k : k + len(phrase.split())] == phrase.split()]
    at = [k for k, _ in places]
    return len(w), len(places), min(at, default=None), max(at, default=None), ",".join(sorted({x for _, x in places}))


def test_base_against_brute_force(frame):
    texts = ["CC-BY 4.0; cc by cc by", "GNU General Public License v3\nAll rights reserved.", "all rights are reserved", None, "", "xcc by", "É cc BY é", "General\x00Public\tLicense general public license"]
    found = {r["doc_id"]: r for r in license_scan(frame(list(enumerate(texts)))).collect()}
    for k, t in enumerate(texts):
        r = found[k]
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == brute(t)
        assert 0 <= r["score"] <= 1 and set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(","))


def labels(text):
    return [r.label for *_, r in scanner().detect(f" {' '.join(WORDS.findall(text.translate(LOWER)))} ")]


@pytest.mark.parametrize(("text", "want"), [
    ("licensed under the Apache License, Version 2.0", ["apache-2.0"]),
    ("apache-2.0", ["apache-2.0"]),
    ("released under the terms of the GNU General Public License, version 3 or any later version", ["gpl-3.0-or-later"]),
    ("version 2 of the GNU GPL", ["gpl"]),
    ("GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version", ["gpl-2.0-or-later"]),
    ("SPDX-License-Identifier: GPL-2.0-only", ["gpl-2.0-only"]),
    ("SPDX-License-Identifier: LGPL-2.1-or-later", ["lgpl-2.1-or-later"]),
    ("GPLv3", ["gpl-3.0"]),
    ("MIT license and BSD-3-Clause", ["mit", "bsd-3"]),
    ("We commit to a limit", []),
    ("Creative Commons Attribution-ShareAlike 4.0 International License", ["cc-by-sa-4.0"]),
    ("CC BY-NC-SA 4.0", ["cc-by-nc-sa"]),
    ("https://creativecommons.org/licenses/by/4.0/", ["cc-by-4.0"]),
    ("Copyright (c) 2019 A. Person. No rights reserved.", ["copyright", "no-rights-reserved"]),
    ("Permission is hereby granted, free of charge, to any person obtaining a copy of this software", ["mit"]),
    ("no statement here", []),
])
def test_labels_of_statements(text, want):
    assert labels(text) == want


def test_rules_are_many_and_distinct():
    found = rules()
    assert len(found) == len({r.pattern for r in found}) > 200
    assert all(r.keyword == r.keyword.lower() and r.label and 0 < r.certainty <= 1 for r in found)
    assert base_places(" cc by cc by ") == [(1, "cc-by"), (7, "cc-by")]


def test_keywords_stand_in_all_that_their_rules_match():
    def holds(r):
        @settings(max_examples=25, deadline=None, derandomize=True, database=None, suppress_health_check=list(HealthCheck))
        @given(st.from_regex(re.compile(r.pattern), fullmatch=True, alphabet=st.characters(codec="latin-1")))
        def stands(x):
            assert r.keyword in f" {x} ", (r.label, r.pattern, x)

        stands()

    for r in rules():
        holds(r)


def test_suppression_against_brute_force():
    rng, scan = random.Random(4), scanner()
    parts = ["apache license", "version 2 0", "gnu general public license", "or any later version", "cc by", "sa 4 0", "mit license", "gpl", "3", "all rights reserved", "bsd 3 clause", "word"]
    for _ in range(150):
        text = f" {' '.join(rng.choices(parts, k=rng.randrange(1, 14)))} "
        hits = [(m.start(), m.end(), k, r) for k, r in enumerate(scan_rules) for m in re.finditer(rf"(?<![^ ])(?:{r.pattern})(?![^ ])", text)]
        hits.sort(key=lambda h: (-h[3].priority, h[0] - h[1], h[2], h[0]))
        kept = []
        for a, b, _, r in hits:
            if not any(x <= a and b <= y for x, y, _ in kept):
                kept.append((a, b, r))
        assert scan.detect(text) == sorted(kept, key=lambda h: h[:2])


scan_rules = rules()


def test_a_very_long_text_of_statements(frame):
    one = "licensed under the Apache License, Version 2.0. All rights reserved. CC BY 4.0. GPL v3 or later; MIT License. "
    n = 10_000_000 // len(one)
    began = time.perf_counter()
    row = license_scan(frame([(1, one * n)])).first()
    assert row["n_base"] == 2 * n and len(row["detections"]) == 4 * n and row["last_word"] == len(WORDS.findall(one.lower())) * (n - 1) + 11
    assert time.perf_counter() - began < 120


def test_odd_rows(odd, frame):
    assert license_scan(odd).count() == odd.count() and license_scan(frame([])).collect() == []
