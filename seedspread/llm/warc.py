"""WARC archives as a Spark data source, read and written in Python.

Reading plans one partition per run of archive files, parses the record header first, and asks two things
before anything else of a record is touched: does it meet the pushed-down predicates on record type and
header fields, and does the requested schema want a payload. Where either answer is no the reader skips the
rest of the record, by the skip lengths that the writer leaves in each gzip member's extra field (or, in
archives that lack them, by inflating without decoding).

Writing gives each task its own files of at most about ``roll_bytes``, one gzip member per record. A file
counts only once a commit has listed it in a manifest of its own (overwriting drops the older ones), so what a lost or repeated task left behind is
never read. Paths are in storage that executors share; anything pyarrow has a file system for will do.

Options: ``path``; ``partition_bytes`` (files are packed into partitions up to it); ``roll_bytes``.
Cases: null payloads are empty; null urls give no target header; control characters in header values are
percent-encoded; an empty table gives an archive with no records.
"""

from __future__ import annotations

import gzip
import io
import json
import struct
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, EqualTo, In, InputPartition, WriterCommitMessage

from seedspread.llm.sizes import few

# Fixed values of the WARC/1.1 format.
VERSION = b"WARC/1.1"
IDENTICAL_PAYLOAD = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2000-01-01T00:00:00Z"

FIELDS = {
    "record_type": "WARC-Type",
    "record_id": "WARC-Record-ID",
    "target_uri": "WARC-Target-URI",
    "payload_digest": "WARC-Payload-Digest",
    "refers_to": "WARC-Refers-To",
    "content_type": "Content-Type",
    "date": "WARC-Date",
}
SCHEMA = "record_type string, record_id string, target_uri string, payload_digest string, refers_to string, content_type string, date string, payload_length long, payload binary"
HEAD_BYTES, BATCH_BYTES = 4096, 8 << 20


def filesystem(path: str):
    """(pyarrow file system, path inside it) of a URI or a plain path."""
    from pyarrow import fs

    if path.startswith("file:"):
        return fs.LocalFileSystem(), "/" + path[5:].lstrip("/")
    return fs.FileSystem.from_uri(path) if "://" in path else (fs.LocalFileSystem(), path)


def member(record: bytes) -> bytes:
    """One gzip member whose extra field SL holds its own length and the record's."""
    squeeze = zlib.compressobj(1, zlib.DEFLATED, -15)
    body = squeeze.compress(record) + squeeze.flush()
    total = 12 + 12 + len(body) + 8
    extra = struct.pack("<2sHII", b"SL", 8, total, len(record)) if total < 2**32 and len(record) < 2**32 else struct.pack("<2sH8s", b"XX", 8, b"")
    return struct.pack("<4BIBBH", 0x1F, 0x8B, 8, 4, 0, 0, 255, len(extra)) + extra + body + struct.pack("<II", zlib.crc32(record), len(record) & 0xFFFFFFFF)


def _clean(value: str) -> str:
    return "".join(c if c >= " " and c != "\x7f" else f"%{ord(c):02X}" for c in value)


def record(kind: str, record_id: str, url: str | None, digest: str, payload: bytes | None, length: int, refers_to: str | None) -> bytes:
    """The bytes of a response or revisit record; a revisit keeps the HTTP header and leaves the payload out."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {length}\r\n\r\n".encode()
    block = http + (payload if kind == "response" and payload is not None else b"")
    head = [("WARC-Type", kind), ("WARC-Record-ID", record_id), ("WARC-Date", DATE)]
    if url is not None:
        head.append(("WARC-Target-URI", _clean(url)))
    head.append(("WARC-Payload-Digest", f"sha256:{digest}"))
    if kind == "revisit":
        head += [("WARC-Profile", IDENTICAL_PAYLOAD), ("WARC-Refers-To", refers_to or "")]
    head += [("Content-Type", "application/http; msgtype=response"), ("Content-Length", str(len(block)))]
    return VERSION + b"\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head).encode() + b"\r\n" + block + b"\r\n\r\n"


def parse_header(data: bytes) -> tuple[dict[str, str], int] | None:
    """(lower-cased fields, offset of the block), or None where the header is not complete in ``data``."""
    end = data.find(b"\r\n\r\n")
    if end < 0:
        return None
    lines = data[:end].decode("utf-8", "replace").split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError(f"not a WARC record: {lines[0][:40]!r}")
    fields: dict[str, str] = {}
    last = None
    for line in lines[1:]:
        if line[:1] in (" ", "\t") and last:
            fields[last] += " " + line.strip()
            continue
        name, _, value = line.partition(":")
        last = name.strip().lower()
        fields[last] = value.strip()
    return fields, end + 4


def records(stream, wanted, want_payload: bool) -> Iterator[tuple[dict[str, str], int, bytes | None]]:
    """(header fields, payload length, payload or None) of the records that ``wanted(fields)`` accepts."""
    while True:
        start = stream.tell()
        fixed = stream.read(12)
        if len(fixed) < 12:
            return
        total = None
        if fixed[:2] == b"\x1f\x8b" and fixed[3] & 4:
            extra = stream.read(struct.unpack("<H", fixed[10:12])[0])
            if extra[:2] == b"SL":
                total = struct.unpack("<I", extra[4:8])[0]
        stream.seek(start)
        inflate = zlib.decompressobj(31)
        raw = b""
        head = None
        while head is None and not inflate.eof:
            piece = inflate.unconsumed_tail or stream.read(HEAD_BYTES)
            if not piece:
                raise ValueError("the archive ends inside a record")
            raw += inflate.decompress(piece, HEAD_BYTES)
            head = parse_header(raw)
        if head is None:
            raise ValueError("a record has no complete header")
        fields, at = head
        keep = wanted(fields)

        def rest() -> bytes:
            out = [raw]
            while not inflate.eof:
                piece = inflate.unconsumed_tail or stream.read(1 << 16)
                if not piece:
                    raise ValueError("the archive ends inside a record")
                out.append(inflate.decompress(piece))
            return b"".join(out)

        payload, whole = None, None
        if keep and (want_payload or total is None):
            whole = rest()
        elif total is None:
            rest()
        if keep:
            block = (whole if whole is not None else raw)[at:]
            http_end = block.find(b"\r\n\r\n")
            length = int(fields.get("content-length", 0))
            if "http" in fields.get("content-type", "") and http_end >= 0:
                stated = [x.split(b":", 1)[1] for x in block[:http_end].split(b"\r\n") if x.lower().startswith(b"content-length:")]
                body_length = int(stated[0]) if stated else length - http_end - 4
                body_at = http_end + 4
            else:
                body_length, body_at = length, 0
            if want_payload and fields.get("warc-type") != "revisit":
                payload = block[body_at:length]
            yield fields, body_length, payload
        if total is not None:
            stream.seek(start + total)
        else:
            stream.seek(stream.tell() - len(inflate.unused_data))


class _Files(InputPartition):
    def __init__(self, files: list[str]):
        super().__init__(0)
        self.files = files


class _Reader(DataSourceReader):
    def __init__(self, schema, options):
        self.schema, self.options, self.tests = schema, options, []

    def pushFilters(self, filters):
        """Takes equality and membership tests on header fields; the rest stay with Spark."""
        for f in filters:
            name = f.attribute[0] if isinstance(f, (EqualTo, In)) and len(f.attribute) == 1 else None
            if name in FIELDS:
                self.tests.append((name, {f.value} if isinstance(f, EqualTo) else set(f.value)))
            else:
                yield f

    def partitions(self):
        from pyarrow import fs

        system, root = filesystem(self.options["path"])
        infos = {i.path.rsplit("/", 1)[-1]: i for i in system.get_file_info(fs.FileSelector(root, recursive=False)) if i.is_file}
        if lists := [n for n in infos if _is_manifest(n)]:
            names = sorted({x for n in lists for x in _listed(system, infos[n].path)})
        else:
            names = sorted(n for n in infos if n.endswith((".warc.gz", ".warc")))
        limit, plan, size = int(self.options.get("partition_bytes", 64 << 20)), [], 0
        for name in names:
            if not plan or size + infos[name].size > limit:
                plan.append([])
                size = 0
            plan[-1].append(name)
            size += infos[name].size
        return [_Files(p) for p in plan] or [_Files([])]

    def read(self, partition) -> Iterator[pa.RecordBatch]:
        from pyspark.sql.pandas.types import to_arrow_schema

        schema = to_arrow_schema(self.schema)
        names = schema.names
        tests = self.tests
        value = lambda fields, name: _field(fields, name)
        wanted = lambda fields: all(value(fields, n) in allowed for n, allowed in tests)
        system, root = filesystem(self.options["path"])
        columns: dict[str, list] = {n: [] for n in names}
        held = 0
        for name in partition.files:
            with system.open_input_file(f"{root}/{name}") as f:
                stream = f if name.endswith(".gz") else _squeezed(f)
                for fields, length, payload in records(stream, wanted, "payload" in names):
                    for n in names:
                        columns[n].append(payload if n == "payload" else length if n == "payload_length" else value(fields, n))
                    held += 400 + len(payload or b"")
                    if held > BATCH_BYTES:
                        yield pa.RecordBatch.from_pydict(columns, schema=schema)
                        columns, held = {n: [] for n in names}, 0
        if held:
            yield pa.RecordBatch.from_pydict(columns, schema=schema)


def _squeezed(f) -> io.BytesIO:
    """An archive that is not compressed, as gzip members, so that one reader serves both. Each byte is read once."""
    out, held = io.BytesIO(), b""
    while True:
        while (head := parse_header(held)) is None:
            more = f.read(1 << 16)
            if not more:
                return io.BytesIO(out.getvalue())
            held += more
        end = head[1] + int(head[0]["content-length"]) + 4
        body = [held[:end]]
        missing = end - len(held)
        if missing > 0:
            body.append(f.read(missing))
        out.write(gzip.compress(b"".join(body), 1))
        held = held[end:]


def _is_manifest(name: str) -> bool:
    return name.startswith("_manifest") and name.endswith(".json")


def _listed(system, path: str) -> list[str]:
    with system.open_input_stream(path) as f:
        return json.loads(f.read())["files"]


def _field(fields: dict[str, str], name: str) -> str | None:
    return fields.get(FIELDS[name].lower())


class _Written(WriterCommitMessage):
    def __init__(self, files: list[str]):
        self.files = files


class _Writer(DataSourceArrowWriter):
    def __init__(self, options, overwrite: bool):
        self.options, self.overwrite = options, overwrite

    def write(self, iterator: Iterator[pa.RecordBatch]) -> WriterCommitMessage:
        system, root = filesystem(self.options["path"])
        system.create_dir(root, recursive=True)
        roll, files, out, size = int(self.options.get("roll_bytes", 64 << 20)), [], None, 0
        for batch in iterator:
            for row in batch.to_pylist():
                if out is None or size > roll:
                    if out is not None:
                        out.close()
                    files.append(f"part-{uuid.uuid4().hex}.warc.gz")
                    out, size = system.open_output_stream(f"{root}/{files[-1]}", compression=None), 0
                data = member(record(row["record_type"], row["record_id"], row["target_uri"], row["payload_digest"], row["payload"], row["payload_length"], row["refers_to"]))
                out.write(data)
                size += len(data)
        if out is not None:
            out.close()
        return _Written(files)

    def commit(self, messages):
        from pyarrow import fs

        system, root = filesystem(self.options["path"])
        system.create_dir(root, recursive=True)
        files = sorted(f for m in messages if m is not None for f in m.files)
        older = [i.path for i in system.get_file_info(fs.FileSelector(root, recursive=False)) if i.is_file and _is_manifest(i.path.rsplit("/", 1)[-1])]
        # each commit has a list of its own, so an append leaves the records before it readable
        with system.open_output_stream(f"{root}/_manifest-{uuid.uuid4().hex}.json", compression=None) as f:
            f.write(json.dumps({"files": files}).encode())
        if self.overwrite:
            for path in older:
                gone = _listed(system, path)
                system.delete_file(path)
                for name in gone:
                    system.delete_file(f"{root}/{name}")

    def abort(self, messages):
        system, root = filesystem(self.options["path"])
        for m in messages:
            for f in m.files if m is not None else []:
                system.delete_file(f"{root}/{f}")


class WarcSource(DataSource):
    """``spark.read.format("warc").schema(...)``: name only the columns that are needed; leave ``payload`` out to skip payloads."""

    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return _Reader(schema, dict(self.options))

    def writer(self, schema, overwrite):
        return _Writer(dict(self.options), overwrite)


def register(spark: SparkSession) -> None:
    """Make format ``warc`` known and let Spark push predicates into it."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcSource)


MIN_REVISIT_BYTES = 100
#: Repeated payloads up to which their table is broadcast (about 150 bytes a row); beyond it payloads are shuffled by digest.
MAX_BROADCAST_DIGESTS = 300_000


def page_records(pages: DataFrame) -> DataFrame:
    """``pages(page_id, url, html)`` → one record per row, repeated payloads as revisits of the smallest page_id.

    Rows that share both payload and the smallest page_id are all responses. A null page_id never is the smallest.
    """
    rows = pages.select("page_id", "url", F.coalesce(F.col("html"), F.lit("")).cast("binary").alias("payload"))
    rows = rows.withColumns({"payload_digest": F.sha2("payload", 256), "payload_length": F.octet_length("payload").cast("long")})
    many = F.count("*") > 1
    firsts = (
        rows.filter(F.col("payload_length") >= MIN_REVISIT_BYTES).groupBy("payload_digest").agg(F.min("page_id").alias("first"), many.alias("many"))
        .filter("many and first is not null").select("payload_digest", "first")
    )
    firsts = few(firsts, MAX_BROADCAST_DIGESTS)
    again = F.coalesce(F.col("first") < F.coalesce(F.col("page_id"), F.col("first") + 1), F.lit(False))
    urn = lambda c: F.concat(F.lit("<urn:page:"), c.cast("string"), F.lit(">"))
    return rows.join(firsts, "payload_digest", "left").select(
        F.when(again, F.lit("revisit")).otherwise(F.lit("response")).alias("record_type"), F.coalesce(urn(F.col("page_id")), F.lit("<urn:page:>")).alias("record_id"),
        F.col("url").alias("target_uri"), "payload_digest", F.when(again, urn(F.col("first"))).alias("refers_to"), "payload_length",
        F.when(~again, F.col("payload")).alias("payload"),
    )


def page_id_of(column: Column) -> Column:
    """The page id inside a record id; null where there is none."""
    return F.nullif(F.regexp_extract(column, "^<urn:page:(-?[0-9]+)>$", 1), F.lit("")).cast("long")


def archive(pages: DataFrame, path: str) -> None:
    """Write one WARC record per page under ``path``."""
    register(pages.sparkSession)
    page_records(pages).write.format("warc").mode("append").save(path)


def read_archive(spark: SparkSession, path: str, columns: str = SCHEMA) -> DataFrame:
    """The records under ``path`` with the named columns."""
    register(spark)
    return spark.read.format("warc").schema(columns).load(path)
