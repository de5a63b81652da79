import hashlib

from pyspark.sql import functions as F

from driftview.llm.lines import drop_shared_lines

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
LONG = "É this line is long enough to be dropped when shared"


def brute(rows):
    where = {}
    key = lambda x: x.strip(" \t\n\x0b\x0c\r").translate(LOWER)
    for k, t in rows:
        for x in (t or "").split("\n"):
            if k is not None and len(key(x)) >= 40:
                where.setdefault(key(x), set()).add(k)
    out = []
    for k, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if k is None or len(where.get(key(x), ())) < 5 or max(where[key(x)]) == k]
        out.append((k, len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return sorted(out, key=str)


def found(df):
    rows = drop_shared_lines(df).select("doc_id", "line_counts.*", F.sha2("text", 256).alias("s"))
    return sorted(map(tuple, rows.collect()), key=str)


def test_against_brute_force(frame):
    rows = [(k, f"own line {k}\n  {LONG.upper() if k % 2 else LONG}\t\nshort\n{LONG}{' x' * (k % 3)}\n") for k in range(9)]
    rows += [(k, f"{'y' * 39}\n{'z' * 40}\r\n") for k in range(20, 26)]
    assert found(frame(rows)) == brute(rows)


def test_repeated_ids_count_once(frame):
    rows = [(1, LONG), (1, LONG), (2, LONG), (3, LONG), (4, LONG)]
    assert found(frame(rows)) == brute(rows)
    rows.append((5, LONG))
    assert found(frame(rows)) == brute(rows) and sum(r[2] for r in brute(rows)) == 5


def test_odd_rows(odd, frame, spark):
    rows = [(r["doc_id"], r["text"]) for r in odd.collect()] + [(None, LONG)] * 6
    assert found(frame(rows)) == brute(rows)
    assert found(frame([])) == []
    clash = spark.createDataFrame([(1, "a\nb", "x", "y")], "doc_id long, text string, line_counts string, `__kept` string")
    out = drop_shared_lines(clash).first()
    assert out["text"] == "a\nb" and out["__kept"] == "y" and out["line_counts"]["n_lines"] == 2
