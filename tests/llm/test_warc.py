import base64
import gzip
import hashlib
import os

import pyarrow as pa
import pytest

from driftview.llm.warc import _unindexed_members, _unindexed_records, archive_round_trip, payload_digest, read_records, record, with_revisits, write_pages

SCHEMA = "page_id long, url string, html string, digest string, payload string, n long"


@pytest.fixture(scope="module")
def pages(spark):
    def make(rows):
        return spark.createDataFrame([(k, u, h, "d", "p", 1) for k, u, h in rows], SCHEMA)

    return make


ROWS = [(1, "http://a/é x", "<p>é</p>"), (2, "http://b/%20", "<p>é</p>"), (3, None, None), (4, "http://c\r\nX: y", ""), (5, "", "b" * 300_000), (None, "http://n", "<p>é</p>"), (None, None, "only here"), (7, "http://d", "WARC/1.1\r\n\r\ninside"), (8, "u", "dup"), (8, "u", "dup")]


def test_round_trip_against_brute_force(pages):
    found = archive_round_trip(pages(ROWS)).collect()
    assert len(found) == len(ROWS)
    holder = {}
    for k, _, h in ROWS:
        if k is not None:
            holder[h or ""] = max(holder.get(h or "", k), k)
    want = []
    for k, _, h in ROWS:
        raw = (h or "").encode()
        to = holder.get(h or "")
        revisit = to is not None and to != k
        want.append((k, len(raw), base64.b32encode(hashlib.sha1(raw).digest()).decode(), "revisit" if revisit else "response", to if revisit else None))
    assert sorted(map(str, want)) == sorted(str((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"])) for r in found)
    assert all(r["verified"] for r in found if r["record_type"] == "response")


def test_payloads_urls_and_pushed_filters(spark, pages, tmp_path):
    path = str(tmp_path / "w")
    write_pages(pages(ROWS), path)
    got = read_records(spark, path, "page_id long, url string, record_type string, payload string").where("record_type = 'response'")
    assert "isnotnull(record_type" in got._jdf.queryExecution().executedPlan().toString() and "= response" not in got._jdf.queryExecution().executedPlan().toString()
    rows = {r["page_id"]: r for r in got.collect() if r["page_id"] is not None}
    assert rows[7]["payload"] == "WARC/1.1\r\n\r\ninside" and rows[4]["url"] == "http://c\r\nX: y" and rows[5]["payload"] == "b" * 300_000
    assert read_records(spark, path, "page_id long, record_type string").where("page_id = 2").count() == 1
    assert read_records(spark, path, "page_id long, record_type string").where("record_type in ('revisit')").count() == 3


def test_files_of_failed_attempts_are_not_read(spark, pages, tmp_path):
    path = str(tmp_path / "w")
    write_pages(pages(ROWS[:2]), path)
    (tmp_path / "w" / "pages-stray.warc.gz").write_bytes(gzip.compress(record(99, "u", b"x", None, payload_digest(b"x"))))
    assert {r["page_id"] for r in read_records(spark, path, "page_id long").collect()} == {1, 2}
    write_pages(pages([(50, "u", "later")]), path)
    assert read_records(spark, path, "page_id long").count() == 3


def test_foreign_archives_without_manifest(spark, tmp_path):
    parts = [record(k, f"http://x/{k}", b"body %d" % k, None, payload_digest(b"body %d" % k)) for k in range(5)]
    os.mkdir(tmp_path / "f")
    (tmp_path / "f" / "a.warc.gz").write_bytes(b"".join(gzip.compress(p) for p in parts[:3]))
    (tmp_path / "f" / "b.warc").write_bytes(b"".join(parts[3:]))
    rows = read_records(spark, str(tmp_path / "f"), "page_id long, payload string, verified boolean").collect()
    assert sorted((r["page_id"], r["payload"], r["verified"]) for r in rows) == [(k, f"body {k}", True) for k in range(5)]


@pytest.mark.parametrize("name", ["a.warc", "a.warc.gz"])
def test_unwanted_records_of_foreign_archives_are_stepped_over(spark, tmp_path, name):
    bodies = [os.urandom(300_000 if k % 2 else 10) + b"\r\n\r\nWARC/1.1" for k in range(6)]
    parts = [record(k, f"http://x/{k}", b, None if k % 2 else 3, payload_digest(b)) for k, b in enumerate(bodies)]
    os.mkdir(tmp_path / "f")
    (tmp_path / "f" / name).write_bytes(b"".join(gzip.compress(p) for p in parts) if name.endswith("gz") else b"".join(parts))
    read = lambda: read_records(spark, str(tmp_path / "f"), "page_id long, record_type string, payload_bytes long, verified boolean")
    assert sorted((r["page_id"], r["payload_bytes"], r["verified"]) for r in read().where("record_type = 'response'").collect()) == [(k, len(bodies[k]), True) for k in (1, 3, 5)]
    assert [r["page_id"] for r in read().where("page_id = 2").collect()] == [2] and read().count() == 6
    with open(tmp_path / "f" / name, "rb") as f, pa.PythonFile(f) as file:
        seen = list(_unindexed_records(file, file.size(), lambda raw: False)) if name == "a.warc" else list(_unindexed_members(file, lambda raw: False))
    assert seen == []


def test_small_payloads_and_empty_tables(pages):
    assert with_revisits(pages([(1, "u", "ab"), (2, "u", "ab")]), min_bytes=3).where("refers_to is not null").count() == 0
    assert archive_round_trip(pages([])).collect() == []
