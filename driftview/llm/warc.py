"""Web archives as a Spark data source, and pages written with revisits of equal payloads.

``format("warc")`` reads and writes folders of gzip-compressed archive files,
each record a member of its own.  Writers finish a file under a name of its
own and report it; the driver lists the reported files in a manifest, so files
of failed attempts are never read.  Beside each file stands an index of its
records' places, which lets readers split files and step over records without
decoding them.
"""

from __future__ import annotations

import base64
import hashlib
import io
import json
import re
import uuid
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from urllib.parse import quote, unquote

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, EqualTo, Filter, In, InputPartition, WriterCommitMessage
from pyspark.sql.types import StructType

from driftview.llm.scratch import materialize, new_path
from driftview.shipping import ship

SCHEMA = "record_id string, page_id long, url string, record_type string, refers_to long, payload_digest string, payload_bytes long, payload string, verified boolean"
WRITE_SCHEMA = "page_id long, url string, payload string, refers_to long"
PUSHABLE = ("record_type", "page_id", "url", "payload_digest")
DATE = "2000-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
SPLIT_BYTES = 16 << 20
BATCH_BYTES = 4 << 20
HEADER_END = b"\r\n\r\n"


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, digest: str) -> bytes:
    """One record, uncompressed; a revisit, if ``refers_to`` is given, has no payload."""
    revisit = refers_to is not None
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d" % len(payload) + HEADER_END
    block = http if revisit else http + payload
    lines = [
        "WARC/1.1",
        f"WARC-Type: {'revisit' if revisit else 'response'}",
        f"WARC-Record-ID: <urn:page:{'none' if page_id is None else page_id}>",
        f"WARC-Date: {DATE}",
        f"WARC-Payload-Digest: sha1:{digest}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if url is not None:
        lines.append(f"WARC-Target-URI: {quote(url, safe=_URI)}")
    if revisit:
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    return "\r\n".join(lines).encode() + HEADER_END + block + HEADER_END


#: All of ASCII that may stand in a header unescaped; the per cent sign may not, so that escapes can be undone.
_URI = "".join(chr(c) for c in range(0x21, 0x7F) if chr(c) != "%")


def headers(block: bytes) -> dict[str, str]:
    lines = block.decode("utf-8", "replace").split("\r\n")
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}


def _page(uri: str | None) -> int | None:
    found = re.fullmatch(r"<urn:page:(-?\d+)>", uri or "")
    return int(found[1]) if found else None


def _open(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (pafs.LocalFileSystem(), path)


@dataclass
class Written(WriterCommitMessage):
    name: str
    size: int
    records: int
    splits: list[int]


class WarcWriter(DataSourceArrowWriter):
    def __init__(self, options: dict[str, str], overwrite: bool) -> None:
        self.path, self.level, self.overwrite = options["path"].rstrip("/"), int(options.get("compresslevel", 4)), overwrite

    def write(self, batches: Iterator[pa.RecordBatch]) -> Written:
        files, root = _open(self.path)
        name = f"pages-{uuid.uuid4().hex}.warc.gz"
        files.create_dir(root, recursive=True)
        at, count, splits, index = 0, 0, [0], io.StringIO()
        with files.open_output_stream(f"{root}/{name}", compression=None) as out:
            for batch in batches:
                columns = [batch.column(x) for x in ("page_id", "url", "payload", "refers_to")]
                for page_id, url, payload, refers_to in zip(*(c.to_pylist() for c in columns), strict=True):
                    raw = (payload or "").encode()
                    digest = payload_digest(raw)
                    packer = zlib.compressobj(self.level, zlib.DEFLATED, 31)
                    member = packer.compress(record(page_id, url, raw, refers_to, digest)) + packer.flush()
                    out.write(member)
                    index.write(f"{at} {len(member)} {'response' if refers_to is None else 'revisit'}\n")
                    at, count = at + len(member), count + 1
                    if at - splits[-1] >= SPLIT_BYTES:
                        splits.append(at)
        with files.open_output_stream(f"{root}/{name}.index", compression=None) as out:
            out.write(index.getvalue().encode())
        return Written(name, at, count, splits)

    def commit(self, messages: list[Written | None]) -> None:
        files, root = _open(self.path)
        files.create_dir(root, recursive=True)
        listed = [] if self.overwrite else (committed(self.path) or [])
        listed += [{"name": m.name, "size": m.size, "records": m.records, "splits": m.splits} for m in messages if m is not None and m.records]
        with files.open_output_stream(f"{root}/_manifest.tmp", compression=None) as out:
            out.write(json.dumps(listed).encode())
        files.move(f"{root}/_manifest.tmp", f"{root}/_manifest.json")

    def abort(self, messages: list[Written | None]) -> None:
        files, root = _open(self.path)
        for m in messages:
            if m is not None:
                for name in (m.name, f"{m.name}.index"):
                    files.delete_file(f"{root}/{name}")


def committed(path: str) -> list[dict] | None:
    files, root = _open(path.rstrip("/"))
    if files.get_file_info(f"{root}/_manifest.json").type != pafs.FileType.File:
        return None
    with files.open_input_stream(f"{root}/_manifest.json", compression=None) as f:
        return json.loads(f.read())


def manifest(path: str) -> list[dict]:
    """The committed files; where there is no manifest, all archive files of the folder, unsplit."""
    if (listed := committed(path)) is not None:
        return listed
    files, root = _open(path.rstrip("/"))
    found = files.get_file_info(pafs.FileSelector(root, allow_not_found=True))
    return [{"name": x.base_name, "size": x.size, "records": -1, "splits": [0]} for x in found if x.base_name.endswith((".warc", ".warc.gz"))]


@dataclass
class Span(InputPartition):
    name: str
    start: int
    stop: int
    indexed: bool


class WarcReader(DataSourceReader):
    def __init__(self, options: dict[str, str], schema: StructType) -> None:
        self.path, self.schema = options["path"].rstrip("/"), schema
        self.wanted: dict[str, set] = {}

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:  # noqa: N802
        for f in filters:
            column = f.attribute[0] if isinstance(f, EqualTo | In) and len(f.attribute) == 1 else None
            if column in PUSHABLE:
                values = {f.value} if isinstance(f, EqualTo) else set(f.value)
                self.wanted[column] = self.wanted.get(column, values) & values
            else:
                yield f

    def partitions(self) -> list[Span]:
        spans = []
        for f in manifest(self.path):
            ends = [*f["splits"][1:], f["size"]]
            spans += [Span(f["name"], a, b, f["records"] >= 0) for a, b in zip(f["splits"], ends, strict=True) if b > a]
        return spans or [Span("", 0, 0, False)]

    def _members(self, span: Span) -> Iterator[bytes | None]:
        """The compressed records of a span that the index does not rule out."""
        files, root = _open(self.path)
        types = self.wanted.get("record_type")
        with files.open_input_file(f"{root}/{span.name}") as f:
            if span.indexed:
                with files.open_input_stream(f"{root}/{span.name}.index", compression=None) as rows:
                    places = [x.split() for x in rows.read().decode().splitlines()]
                chosen = [(int(a), int(n)) for a, n, kind in places if span.start <= int(a) < span.stop and (types is None or kind in types)]
                for a, n in chosen:
                    f.seek(a)
                    yield f.read(n)
            else:
                fits = lambda raw: self._fits(_described(headers(raw)))
                yield from _unindexed_members(f, fits) if span.name.endswith(".gz") else _unindexed_records(f, f.size(), fits)

    def read(self, span: Span) -> Iterator[pa.RecordBatch]:
        names = self.schema.names
        decode = bool({"payload", "verified", "payload_bytes"} & set(names))
        arrow = pa.schema([(n, _ARROW[n]) for n in names])
        rows, held = {n: [] for n in names}, 0
        for member in self._members(span) if span.name else ():
            row, size = self._row(member, decode)
            if row is None:
                continue
            held += size
            for n in names:
                rows[n].append(row[n])
            if held >= BATCH_BYTES or len(rows[names[0]]) >= 4096:
                yield pa.RecordBatch.from_pydict(rows, schema=arrow)
                rows, held = {n: [] for n in names}, 0
        if rows[names[0]]:
            yield pa.RecordBatch.from_pydict(rows, schema=arrow)

    def _fits(self, row: dict) -> bool:
        return all(row[k] in v for k, v in self.wanted.items())

    def _row(self, member: bytes, decode: bool) -> tuple[dict | None, int]:
        """Headers first; the rest is decoded only if they fit the filters and the payload is needed."""
        gz = member[:2] == b"\x1f\x8b"
        unpacker = zlib.decompressobj(31) if gz else None
        head = unpacker.decompress(member, 2048) if gz else member
        while HEADER_END not in head and gz and unpacker.unconsumed_tail:
            head += unpacker.decompress(unpacker.unconsumed_tail, 4096)
        raw, _, rest = head.partition(HEADER_END)
        h = headers(raw)
        row = _described(h)
        if not self._fits(row):
            return None, 0
        if decode and row["record_type"] in ("response", "revisit"):
            block = rest + (unpacker.decompress(unpacker.unconsumed_tail) if gz else b"")
            block = block[: int(h.get("content-length", 0))]
            http, _, payload = block.partition(HEADER_END)
            if row["record_type"] == "response":
                row |= {"payload": payload.decode("utf-8", "replace"), "payload_bytes": len(payload), "verified": payload_digest(payload) == row["payload_digest"]}
            else:
                row["payload_bytes"] = int(headers(http).get("content-length", 0))
            return row, len(payload)
        return row, 0


_ARROW = {"record_id": pa.string(), "page_id": pa.int64(), "url": pa.string(), "record_type": pa.string(), "refers_to": pa.int64(), "payload_digest": pa.string(), "payload_bytes": pa.int64(), "payload": pa.string(), "verified": pa.bool_()}


def _described(h: dict[str, str]) -> dict:
    """A row of what a record's headers say."""
    url = unquote(h["warc-target-uri"]) if "warc-target-uri" in h else None
    digest = h.get("warc-payload-digest", "").removeprefix("sha1:") or None
    return {"record_id": h.get("warc-record-id"), "page_id": _page(h.get("warc-record-id")), "url": url, "record_type": h.get("warc-type"), "refers_to": _page(h.get("warc-refers-to")), "payload_digest": digest, "payload_bytes": None, "payload": None, "verified": None}


def _unindexed_records(f: pa.NativeFile, size: int, fits: Callable[[bytes], bool]) -> Iterator[bytes]:
    """Records one after another: headers are read, and the rest of those that do not fit is stepped over."""
    at = 0
    while at < size:
        f.seek(at)
        head = b""
        while HEADER_END not in head:
            more = f.read(4096)
            if not more:
                return
            head += more
        raw, _, rest = head.partition(HEADER_END)
        n = int(headers(raw).get("content-length", 0))
        if fits(raw):
            yield raw + HEADER_END + rest[:n] + f.read(max(0, n - len(rest)))
        at += len(raw) + 4 + n + 4


def _unindexed_members(f: pa.NativeFile, fits: Callable[[bytes], bool]) -> Iterator[bytes]:
    """Members of gzip, a record each: of one that does not fit, nothing but the headers is kept."""
    rest = b""
    while True:
        unpacker, parts, kept = zlib.decompressobj(31), [b""], None
        while not unpacker.eof:
            rest = rest or f.read(1 << 16)
            if not rest:
                return
            piece = unpacker.decompress(rest, 1 << 16)
            rest = unpacker.unused_data if unpacker.eof else unpacker.unconsumed_tail
            if kept is None:
                parts[0] += piece
                raw, end, _ = parts[0].partition(HEADER_END)
                kept = fits(raw) if end else None
            elif kept:
                parts.append(piece)
        if kept:
            yield b"".join(parts)


class WarcSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema: StructType) -> WarcReader:
        return WarcReader(self.options, schema)

    def writer(self, schema: StructType, overwrite: bool) -> WarcWriter:
        return WarcWriter(self.options, overwrite)


def register(spark: SparkSession) -> None:
    ship(spark)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcSource)


def with_revisits(pages: DataFrame, page_id: str = "page_id", url: str = "url", html: str = "html", min_bytes: int = 0) -> DataFrame:
    """Rows for the writer, (page_id, url, payload, refers_to).

    Of pages whose payloads are equal and have ``min_bytes`` bytes or more, the
    one of largest id holds the payload; the others refer to it.  Payloads are
    compared by SHA-1, which tasks combine before they shuffle; a hot payload's
    pages meet its holder in an equi-join, which adaptive execution splits.  A
    null payload is empty.  Pages with a null id are responses if no equal page
    has an id.  Repeated rows of the holder's id all hold the payload.
    """
    rows = pages.select(F.col(page_id).cast("long").alias("page_id"), F.col(url).cast("string").alias("url"), F.coalesce(F.col(html), F.lit("")).alias("payload"))
    rows = rows.withColumn("digest", F.sha1(F.col("payload").cast("binary")))
    sums = rows.where(F.octet_length("payload") >= min_bytes).groupBy("digest").agg(F.max("page_id").alias("holder"), F.count("*").alias("n"))
    holders = materialize(sums.where("n > 1 and holder is not null").select("digest", "holder"), "holders")
    joined = rows.join(holders, "digest", "left")
    elsewhere = F.col("holder").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("holder"))
    return joined.select("page_id", "url", "payload", F.when(elsewhere, F.col("holder")).alias("refers_to"))


def write_pages(pages: DataFrame, path: str, page_id: str = "page_id", url: str = "url", html: str = "html", min_bytes: int = 0) -> None:
    """Write a record for each page; extra columns are ignored, an empty table leaves an empty manifest."""
    register(pages.sparkSession)
    with_revisits(pages, page_id, url, html, min_bytes).write.format("warc").mode("append").save(path)


def read_records(spark: SparkSession, path: str, columns: str = SCHEMA) -> DataFrame:
    """Records of a folder of archives; payloads are decoded only if ``columns`` asks for what they tell."""
    register(spark)
    return spark.read.format("warc").schema(columns).load(path)


def archive_round_trip(pages: DataFrame) -> DataFrame:
    """Write pages to archives in the shared folder and read back what the records say: a row for each page.

    Null html is an empty payload; ties in equal payloads go to the largest id;
    rows that repeat an id are a record each; null ids stay null; an empty table
    gives an empty result; extra columns are ignored (see ``with_revisits``).
    """
    spark = pages.sparkSession
    path = new_path(spark, "archives")
    write_pages(pages, path)
    return read_records(spark, path, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, verified boolean")
