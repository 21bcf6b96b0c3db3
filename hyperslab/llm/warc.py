"""WARC archives through a table of payload chunks.

A payload never has to be one row: it is a run of rows (record, chunk_no) with the bytes of the chunk, and
each row carries the digest and the length of the payload up to its end. The last row's digest decides which
record of equal payloads is the response and which ones revisit it. Archives are written and read as streams.

Files are WARC/1.1: a warcinfo record first, dates and record ids everywhere, a response as an HTTP message, a revisit
with the id, URL and date of what it refers to. Page ids, and URLs that a header can't hold as they are, have fields of
their own, so reading gives back what was written.

Cases: a null payload is empty; a null page id sorts after all others and is written as an empty header field;
repeated page ids stay separate records (of equal ones, one is the response); an empty table gives no
archive; further columns are ignored; a payload of any size takes the memory of a chunk, apart from the row that
brings it.
"""

from __future__ import annotations

import base64
import datetime
import hashlib
import urllib.parse
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

CHUNKS = "record long, page_id long, url string, chunk_no int, data binary, so_far long, digest string, last boolean"
_CHUNKS = pa.schema([("record", pa.int64()), ("page_id", pa.int64()), ("url", pa.string()), ("chunk_no", pa.int32()), ("data", pa.binary()), ("so_far", pa.int64()), ("digest", pa.string()), ("last", pa.bool_())])
#: Bytes of rows that go to Spark at once.
_FLUSH = 4 << 20


def _base32(sha) -> str:
    return base64.b32encode(sha.copy().digest()).decode()


def _flushed(rows: Iterator[dict], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    held, size = [], 0
    for row in rows:
        held.append(row)
        size += len(row.get("data") or b"") + 64
        if size >= _FLUSH:
            yield pa.RecordBatch.from_pylist(held, schema=schema)
            held, size = [], 0
    if held:
        yield pa.RecordBatch.from_pylist(held, schema=schema)


class Running:
    """The chunk rows of one payload: feed it bytes, in any portions, and end it."""

    def __init__(self, record: int, page_id: int | None, url: str | None, chunk: int):
        self.row, self.chunk = {"record": record, "page_id": page_id, "url": url}, chunk
        self.sha, self.no, self.n, self.held = hashlib.sha1(), 0, 0, b""

    def _put(self, data: bytes, last: bool) -> dict:
        self.sha.update(data)
        self.n += len(data)
        self.no += 1
        return self.row | {"chunk_no": self.no - 1, "data": data, "so_far": self.n, "digest": _base32(self.sha), "last": last}

    def feed(self, data: bytes) -> Iterator[dict]:
        self.held += data
        while len(self.held) > self.chunk:
            yield self._put(self.held[: self.chunk], False)
            self.held = self.held[self.chunk :]

    def end(self) -> Iterator[dict]:
        yield self._put(self.held, True)


def chunk_table(pages: DataFrame, *, chunk: int = 256 << 10, id_column: str = "page_id", url_column: str = "url", payload_column: str = "html") -> DataFrame:
    """Payloads as chunk rows, a written table: record numbers hold however often it is read."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[dict]:
            record = TaskContext.get().partitionId() << 40
            for batch in batches:
                for page_id, url, payload in zip(*(batch.column(k) for k in range(3)), strict=True):
                    running = Running(record, page_id.as_py(), url.as_py(), chunk)
                    record += 1
                    data = payload.as_buffer() if payload.is_valid else pa.py_buffer(b"")
                    for at in range(0, data.size, chunk):
                        yield from running.feed(data[at : at + chunk].to_pybytes())
                    yield from running.end()

        yield from _flushed(rows(), _CHUNKS)

    chosen = pages.select(F.col(id_column).cast("long").alias("page_id"), F.col(url_column).alias("url"), F.encode(F.col(payload_column), "utf-8").alias("payload"))
    return common.written(chosen.mapInArrow(cut, CHUNKS), "warc-chunks")


def decide(chunks: DataFrame, least_bytes: int = 0) -> DataFrame:
    """record, payload_bytes, payload_digest, record_type of every record, and of revisits refers_to (page id), target (record)
    and target_url."""
    whole = chunks.where("last").select("record", "page_id", "url", F.col("so_far").alias("payload_bytes"), F.col("digest").alias("payload_digest"))
    first = (
        whole.where(F.col("payload_bytes") >= least_bytes)
        .groupBy("payload_digest", "payload_bytes")
        .agg(F.min(F.struct(F.col("page_id").isNull().alias("none"), "page_id", "record", "url")).alias("first"))
    )
    joined = whole.join(first, ["payload_digest", "payload_bytes"], "left")
    revisit = F.coalesce(F.col("first.record") != F.col("record"), F.lit(False))
    return joined.select(
        "record",
        "payload_bytes",
        "payload_digest",
        F.when(revisit, "revisit").otherwise("response").alias("record_type"),
        F.when(revisit, F.col("first.page_id")).alias("refers_to"),
        F.when(revisit, F.col("first.record")).alias("target"),
        F.when(revisit, F.col("first.url")).alias("target_url"),
    )


#: Characters that a URL in a header keeps: all of printable ASCII but the space. Fixed value.
_KEPT = "".join(map(chr, range(33, 127)))
_END = "\r\n"


def _uri(url: str | None) -> str:
    """A URL as a header holds it: blanks, control characters and letters beyond ASCII percent-encoded."""
    return urllib.parse.quote(url, safe=_KEPT) if url else "about:blank"


def _fields(*lines: tuple[str, object]) -> bytes:
    return (_END.join(["WARC/1.1", *(f"{k}: {v}" for k, v in lines if v is not None)]) + _END + _END).encode()


def _http(n: int) -> bytes:
    return _END.join(["HTTP/1.1 200 OK", "Content-Type: text/html; charset=utf-8", f"Content-Length: {n}", "", ""]).encode()


def _record_id(run: uuid.UUID, record: object) -> str:
    return f"<urn:uuid:{uuid.uuid5(run, str(record))}>"


def _info(run: uuid.UUID, date: str, name: str) -> bytes:
    body = _END.join([f"filename: {name}", "format: WARC File Format 1.1", ""]).encode()
    return _fields(("WARC-Type", "warcinfo"), ("WARC-Record-ID", _record_id(run, name)), ("WARC-Date", date), ("WARC-Filename", name), ("Content-Type", "application/warc-fields"), ("Content-Length", len(body))) + body


def _header(row: dict, run: uuid.UUID, date: str) -> bytes:
    response, url = row["record_type"] == "response", row["url"]
    exact = None if url and _uri(url) == url else "" if url is None else base64.b64encode(url.encode()).decode() or "="
    http = _http(row["payload_bytes"])
    lines = [
        ("WARC-Type", row["record_type"]), ("WARC-Record-ID", _record_id(run, row["record"])), ("WARC-Date", date), ("WARC-Target-URI", _uri(url)), ("WARC-Page-URI", exact),
        ("WARC-Page-ID", "" if row["page_id"] is None else row["page_id"]), ("WARC-Payload-Digest", f"sha1:{row['payload_digest']}"), ("WARC-Payload-Length", row["payload_bytes"]),
    ]
    if response:
        return _fields(*lines, ("Content-Type", "application/http; msgtype=response"), ("Content-Length", len(http) + row["payload_bytes"])) + http
    lines += [
        ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("WARC-Refers-To", _record_id(run, row["target"])), ("WARC-Refers-To-Target-URI", _uri(row["target_url"])),
        ("WARC-Refers-To-Date", date), ("WARC-Refers-To-Page-ID", "" if row["refers_to"] is None else row["refers_to"]), ("Content-Length", 0),
    ]
    return _fields(*lines)


class _Member:
    """Writes gzip members, one per record, as a stream."""

    def __init__(self, out):
        self.out, self.zip = out, None

    def start(self) -> None:
        self.zip = zlib.compressobj(1, zlib.DEFLATED, 31)

    def write(self, data: bytes) -> None:
        self.out.write(self.zip.compress(data))

    def end(self) -> None:
        self.out.write(self.zip.compress(b"\r\n\r\n") + self.zip.flush())


def write(pages: DataFrame, folder: str, *, least_bytes: int = 0, chunk: int = 256 << 10, id_column: str = "page_id", url_column: str = "url", payload_column: str = "html") -> DataFrame:
    """Write pages as gzip-per-record archives into folder; a row per archive: path, n_records. A written table."""
    run, date = uuid.uuid4(), datetime.datetime.now(datetime.UTC).strftime("%Y-%m-%dT%H:%M:%SZ")
    chunks = chunk_table(pages, chunk=chunk, id_column=id_column, url_column=url_column, payload_column=payload_column)
    decided = decide(chunks, least_bytes)
    body = (F.col("record_type") == "response") | (F.col("chunk_no") == 0)
    rows = (
        chunks.select("record", "page_id", "url", "chunk_no", "data", "last")
        .join(decided, "record")
        .where(body)
        .withColumn("data", F.when(F.col("record_type") == "response", F.col("data")))
        .repartition("record")
        .sortWithinPartitions("record", "chunk_no")
    )

    def archive(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        batch = next(batches, None)
        if batch is None:
            return
        name = f"part-{TaskContext.get().partitionId():06d}.warc.gz"
        uri, n = f"{folder}/{name}", 0
        with common.whole_file(uri) as out:
            member = _Member(out)
            member.start()
            member.write(_info(run, date, name))
            member.end()
            while batch is not None:
                for row in batch.to_pylist():
                    response = row["record_type"] == "response"
                    if row["chunk_no"] == 0:
                        n += 1
                        member.start()
                        member.write(_header(row, run, date))
                    if response:
                        member.write(row["data"])
                    if row["last"] or not response:
                        member.end()
                batch = next(batches, None)
        yield pa.RecordBatch.from_pydict({"path": [uri], "n_records": [n]})

    return common.written(rows.mapInArrow(archive, "path string, n_records long"), "warc-archives")


def _inflated(uri: str) -> Iterator[bytes]:
    where, path = common.open_store(uri)
    with where.open_input_stream(path, compression=None) as file:
        unzip = zlib.decompressobj(31)
        while data := file.read(1 << 20):
            while data:
                yield unzip.decompress(data)
                data = unzip.unused_data
                if unzip.eof:
                    unzip = zlib.decompressobj(31)


class _Stream:
    """Lines and byte counts of a stream of portions."""

    def __init__(self, portions: Iterator[bytes]):
        self.portions, self.held, self.at = portions, b"", 0

    def _more(self) -> bool:
        data = next(self.portions, None)
        if data is None:
            return False
        self.held, self.at = self.held[self.at :] + data, 0
        return True

    def head(self) -> bytes | None:
        while (end := self.held.find(b"\r\n\r\n", self.at)) < 0:
            if not self._more():
                return None
        head, self.at = self.held[self.at : end], end + 4
        return head

    def body(self, n: int) -> Iterator[bytes]:
        while n:
            if self.at == len(self.held) and not self._more():
                raise ValueError("an archive ends within a record")
            data = self.held[self.at : self.at + n]
            self.at += len(data)
            n -= len(data)
            if data:
                yield data


READ = f"{CHUNKS}, record_type string, refers_to long, stated_bytes long, stated_digest string"
_READ = pa.schema([*_CHUNKS, ("record_type", pa.string()), ("refers_to", pa.int64()), ("stated_bytes", pa.int64()), ("stated_digest", pa.string())])


def read(archives: DataFrame, *, chunk: int = 256 << 10, payloads: bool = True) -> DataFrame:
    """The records of those archives as chunk rows, with what their headers state. Without payloads: last rows, data null."""

    def records(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[dict]:
            record = TaskContext.get().partitionId() << 40
            for path in (p for batch in batches for p in batch.column("path").to_pylist()):
                stream = _Stream(_inflated(path))
                while (head := stream.head()) is not None:
                    fields = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in head.decode().lstrip().split(_END)[1:])
                    number = lambda k, of=fields: int(of[k]) if of.get(k) else None
                    left = number("Content-Length")
                    if fields["WARC-Type"] not in ("response", "revisit"):
                        for _ in stream.body(left):
                            pass
                        stream.head()
                        continue
                    exact = fields.get("WARC-Page-URI")
                    url = fields["WARC-Target-URI"] if exact is None else base64.b64decode(exact.strip("=") + "=" * (-len(exact.strip("=")) % 4)).decode() if exact else None
                    more = {"record_type": fields["WARC-Type"], "refers_to": number("WARC-Refers-To-Page-ID"), "stated_bytes": number("WARC-Payload-Length"), "stated_digest": fields["WARC-Payload-Digest"].removeprefix("sha1:")}
                    running = Running(record, number("WARC-Page-ID"), url, chunk)
                    record += 1
                    if left:
                        left -= len(stream.head()) + 4  # of the HTTP message
                    for data in stream.body(left):
                        for row in running.feed(data):
                            if payloads:
                                yield row | more
                    for row in running.end():
                        yield row | more | ({} if payloads else {"data": None})
                    stream.head()  # the empty lines after a record

        yield from _flushed(rows(), _READ)

    many = max(1, 2 * archives.sparkSession.sparkContext.defaultParallelism)
    return archives.repartition(many, "path").mapInArrow(records, READ)


def summary(read_back: DataFrame) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of each record; a response's digest is that of the bytes read."""
    response = F.col("record_type") == "response"
    return read_back.where("last").select(
        "page_id",
        F.when(response, F.col("so_far")).otherwise(F.col("stated_bytes")).alias("payload_bytes"),
        F.when(response, F.col("digest")).otherwise(F.col("stated_digest")).alias("payload_digest"),
        "record_type",
        "refers_to",
    )
