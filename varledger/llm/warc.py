"""WARC archives as a Spark data source, and pages written to and read from
them with revisit records for repeated payloads.

Each record of a ``.warc.gz`` file is one gzip member whose extra field gives
its compressed length, so that a reader inflates only the start of a record,
looks at the headers, and passes over a payload that nobody asked for.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import (
    DataSource,
    DataSourceArrowWriter,
    DataSourceReader,
    EqualNullSafe,
    EqualTo,
    In,
    InputPartition,
    WriterCommitMessage,
)

from .common import fresh_path, local_fs

#: Fixed values of the format.
VERSION = b"WARC/1.1"
SAME_PAYLOAD = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_GZIP = struct.Struct("<BBBBIBBHBBHQ")  # header up to the extra field's one value
_MARK = (ord("S"), ord("L"))

FIELDS = {
    "record_type": "WARC-Type",
    "record_id": "WARC-Record-ID",
    "target_uri": "WARC-Target-URI",
    "date": "WARC-Date",
    "payload_digest": "WARC-Payload-Digest",
    "refers_to": "WARC-Refers-To",
}
SCHEMA = (
    "record_type string, record_id string, target_uri string, date string, payload_digest string, "
    "refers_to string, payload_bytes long, payload binary"
)


# -- records --------------------------------------------------------------


def record(row: dict) -> bytes:
    """One record: named headers, then HTTP headers and, unless it is a revisit,
    the payload.  The HTTP length is always that of the full payload."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n"
    http += b"Content-Length: %d\r\n\r\n" % row["payload_bytes"]
    block = http if row["record_type"] == "revisit" else http + (row["payload"] or b"")
    head = [VERSION]
    for field, name in FIELDS.items():
        value = row.get(field)
        if value is not None:
            if field == "payload_digest":
                value = f"sha1:{value}"
            # A line break inside a value would end the header.
            head.append(f"{name}: {value}".replace("\r", "%0D").replace("\n", "%0A").encode())
    if row["record_type"] == "revisit":
        head.append(f"WARC-Profile: {SAME_PAYLOAD}".encode())
    head += [b"Content-Type: application/http; msgtype=response", b"Content-Length: %d" % len(block)]
    return b"\r\n".join(head) + b"\r\n\r\n" + block + b"\r\n\r\n"


def member(raw: bytes, level: int) -> bytes:
    """A gzip member that tells its own length."""
    z = zlib.compressobj(level, zlib.DEFLATED, -15)
    body = z.compress(raw) + z.flush()
    total = _GZIP.size + len(body) + 8
    head = _GZIP.pack(0x1F, 0x8B, 8, 4, 0, 0, 255, 12, *_MARK, 8, total)
    return head + body + struct.pack("<II", zlib.crc32(raw), len(raw) & 0xFFFFFFFF)


def parse_headers(raw: bytes) -> dict[str, str]:
    lines = raw.split(b"\r\n")
    if not lines[0].startswith(b"WARC/"):
        raise ValueError("not a WARC record")
    out = {}
    for line in lines[1:]:
        name, _, value = line.partition(b":")
        out[name.strip().decode().lower()] = value.strip().decode("utf-8", "replace")
    return out


class _Plain:
    """Records of an uncompressed file: the length header tells where each ends."""

    def __init__(self, f):
        self.f, self.at, self.size = f, 0, f.size()

    def __iter__(self):
        while self.at < self.size:
            head = b""
            while b"\r\n\r\n" not in head:
                self.f.seek(self.at + len(head))
                more = self.f.read(4096)
                if not more:
                    raise ValueError("a record is cut short")
                head += more
            cut = head.index(b"\r\n\r\n")
            headers = parse_headers(head[:cut])
            begin, n = self.at + cut + 4, int(headers["content-length"])

            def block(begin=begin, n=n) -> bytes:
                self.f.seek(begin)
                return self.f.read(n)

            yield headers, block
            self.at = begin + n + 4


class _Gzip:
    """Records of a file of gzip members.  A member without the length field
    is inflated to find its end."""

    def __init__(self, f):
        self.f, self.at, self.size = f, 0, f.size()

    def __iter__(self):
        while self.at < self.size:
            self.f.seek(self.at)
            start = self.f.read(4096)
            fields = _GZIP.unpack_from(start) if len(start) >= _GZIP.size else None
            total = fields[-1] if fields and fields[3] & 4 and fields[8:10] == _MARK else None
            z = zlib.decompressobj(31)
            head, read = z.decompress(start), len(start)
            while b"\r\n\r\n" not in head and not z.eof:
                more = self.f.read(4096)
                if not more:
                    raise ValueError("a member is cut short")
                head += z.decompress(more)
                read += len(more)
            cut = head.index(b"\r\n\r\n")
            headers = parse_headers(head[:cut])
            state = {"z": z, "data": head, "read": read}

            def block(at=self.at, total=total, cut=cut, headers=headers, state=state) -> bytes:
                self._rest(at, total, state)
                n = int(headers["content-length"])
                return state["data"][cut + 4 : cut + 4 + n]

            yield headers, block
            if total is None:
                self._rest(self.at, None, state)
                total = state["read"] - len(state["z"].unused_data)
            self.at += total

    def _rest(self, at: int, total: int | None, state: dict) -> None:
        parts = [state["data"]]
        while not state["z"].eof:
            self.f.seek(at + state["read"])
            more = self.f.read((1 << 16) if total is None else max(1, total - state["read"]))
            if not more:
                raise ValueError("a member is cut short")
            parts.append(state["z"].decompress(more))
            state["read"] += len(more)
        state["data"] = b"".join(parts)


# -- the data source ------------------------------------------------------


@dataclass
class _Files(InputPartition):
    paths: tuple[str, ...]

    def __init__(self, paths):
        super().__init__(None)
        self.paths = tuple(paths)


class WarcReader(DataSourceReader):
    """Options: path; payload (default true): false leaves payloads unread;
    partitionBytes: compressed bytes that a task takes, in whole files; with
    the writer's files no task has more than twice that."""

    def __init__(self, options):
        self.path = options["path"]
        self.payload = options.get("payload", "true").lower() != "false"
        self.target = int(options.get("partitionBytes", 32 << 20))
        self.wanted: dict[str, set] = {}

    def pushFilters(self, filters):
        """Equalities on header fields are tested before a payload is read."""
        for f in filters:
            values = None
            if isinstance(f, (EqualTo, EqualNullSafe)) and f.value is not None:
                values = {f.value}
            elif isinstance(f, In):
                values = {v for v in f.value if v is not None}
            if values is not None and len(f.attribute) == 1 and f.attribute[0] in FIELDS:
                name = f.attribute[0]
                self.wanted[name] = self.wanted.get(name, values) & values
            else:
                yield f

    def partitions(self):
        from pyarrow import fs as pafs

        fs, where = local_fs(self.path)
        found = [
            (i.path, i.size)
            for i in fs.get_file_info(pafs.FileSelector(where, recursive=True, allow_not_found=True))
            if i.is_file and i.base_name.endswith((".warc", ".warc.gz")) and i.base_name[0] not in "._"
        ]
        groups, size = [], 0
        for path, n in sorted(found):
            if not groups or size + n > self.target:
                groups.append([])
                size = 0
            groups[-1].append(path)
            size += n
        return [_Files(g) for g in groups] or [_Files(())]

    def read(self, partition):
        fs, _ = local_fs(self.path)
        rows, size = [], 0
        for path in partition.paths:
            with fs.open_input_file(path) as f:
                for headers, block in (_Gzip(f) if path.endswith(".gz") else _Plain(f)):
                    row = {field: headers.get(name.lower()) for field, name in FIELDS.items()}
                    if row["payload_digest"]:
                        row["payload_digest"] = row["payload_digest"].removeprefix("sha1:")
                    if any(row[name] not in values for name, values in self.wanted.items()):
                        continue
                    row["payload_bytes"], row["payload"] = None, None
                    revisit = row["record_type"] == "revisit"
                    if self.payload or revisit:
                        http, _, payload = block().partition(b"\r\n\r\n")
                        if revisit:
                            row["payload_bytes"] = _http_length(http)
                        else:
                            if row["payload_digest"] and hashlib.sha1(payload).hexdigest() != row["payload_digest"]:
                                raise ValueError(f"payload of {row['record_id']} differs from its digest")
                            row["payload_bytes"], row["payload"] = len(payload), payload
                            size += len(payload)
                    rows.append(row)
                    if size > 16 << 20 or len(rows) >= 4096:
                        yield _batch(rows)
                        rows, size = [], 0
        if rows:
            yield _batch(rows)


def _http_length(http: bytes) -> int | None:
    for line in http.split(b"\r\n"):
        name, _, value = line.partition(b":")
        if name.strip().lower() == b"content-length":
            return int(value)
    return None


def _batch(rows: list[dict]) -> pa.RecordBatch:
    kinds = {"payload_bytes": pa.int64(), "payload": pa.binary()}
    names = [f.split()[0] for f in SCHEMA.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([r[n] for r in rows], kinds.get(n, pa.string())) for n in names], names=names)


@dataclass
class _Written(WriterCommitMessage):
    files: tuple[str, ...]


class WarcWriter(DataSourceArrowWriter):
    """Options: path; compression (gzip or none); level; fileBytes: size from
    which a task begins another file.  Files get their names on commit only."""

    def __init__(self, options):
        self.path = options["path"]
        self.gzip = options.get("compression", "gzip") == "gzip"
        self.level = int(options.get("level", 1))
        self.most = int(options.get("fileBytes", 32 << 20))

    def write(self, iterator):
        fs, where = local_fs(self.path)
        fs.create_dir(where, recursive=True)
        context = TaskContext.get()
        out, size, files = None, 0, []
        for batch in iterator:
            names = batch.schema.names
            for lo in range(0, batch.num_rows, 256):
                for values in zip(*(c.to_pylist() for c in batch.slice(lo, 256).columns), strict=True):
                    if out is None:
                        end = ".warc.gz" if self.gzip else ".warc"
                        files.append(f"{where}/.part-{context.partitionId():06d}-{len(files):04d}-{context.taskAttemptId()}{end}")
                        out, size = fs.open_output_stream(files[-1], compression=None), 0
                    raw = record(dict(zip(names, values, strict=True)))
                    raw = member(raw, self.level) if self.gzip else raw
                    out.write(raw)
                    size += len(raw)
                    if size >= self.most:
                        out.close()
                        out = None
        if out is not None:
            out.close()
        return _Written(tuple(files))

    def commit(self, messages):
        fs, _ = local_fs(self.path)
        for message in messages:
            for f in message.files if message else ():
                folder, _, name = f.rpartition("/")
                fs.move(f, f"{folder}/{name.lstrip('.')}")

    def abort(self, messages):
        fs, _ = local_fs(self.path)
        for message in messages:
            for f in message.files if message else ():
                fs.delete_file(f)


class WarcSource(DataSource):
    @classmethod
    def name(cls):
        return "warc"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return WarcReader(self.options)

    def writer(self, schema, overwrite):
        return WarcWriter(self.options)


def read_warc(spark: SparkSession, path: str, *, payload: bool = True) -> DataFrame:
    """Records of all archives under ``path``; equality filters on the header
    columns reach the reader."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcSource)
    return spark.read.format("warc").option("path", path).option("payload", str(payload).lower()).load()


def write_warc(records: DataFrame, path: str, *, compression: str = "gzip") -> None:
    """Write rows with the columns of SCHEMA."""
    records.sparkSession.dataSource.register(WarcSource)
    records.write.format("warc").option("path", path).option("compression", compression).mode("append").save()


# -- pages ----------------------------------------------------------------


def page_records(
    pages: DataFrame, *, id_col: str = "page_id", uri_col: str = "url", html_col: str = "html", least_bytes: int = 1000
) -> DataFrame:
    """A record for each page.  Of equal payloads of ``least_bytes`` and more,
    that with the largest id is the response and the others revisit it.

    Null html is an empty payload.  Rows that repeat the largest id are all
    responses; a null id never is the one that others revisit.
    """
    payload = F.coalesce(F.col(html_col).cast("string"), F.lit("")).cast("binary")
    rows = pages.select(
        F.col(id_col).cast("long").alias("page_id"),
        (F.col(uri_col) if uri_col in pages.columns else F.lit(None)).cast("string").alias("target_uri"),
        payload.alias("payload"),
        F.sha1(payload).alias("payload_digest"),
        F.octet_length(payload).cast("long").alias("payload_bytes"),
    )
    # Only ids and digests are grouped; pages meet the outcome by their id.
    marks = rows.where(F.col("payload_bytes") >= least_bytes).select("page_id", "payload_digest")
    kept = (
        marks.groupBy("payload_digest").agg(F.max("page_id").alias("kept"), F.count("*").alias("n"))
        .where("n > 1 AND kept IS NOT NULL").drop("n")
    )
    again = marks.join(kept, "payload_digest").where("NOT page_id <=> kept").select(
        F.col("page_id").alias("old_id"), F.col("payload_digest").alias("old_digest"), "kept"
    ).distinct()
    both = F.col("page_id").eqNullSafe(F.col("old_id")) & (F.col("payload_digest") == F.col("old_digest"))
    urn = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(c.cast("string"), F.lit("")), F.lit(">"))
    revisit = F.col("kept").isNotNull()
    return rows.join(again, both, "left").select(
        F.when(revisit, "revisit").otherwise("response").alias("record_type"),
        urn(F.col("page_id")).alias("record_id"),
        "target_uri",
        F.lit("2000-01-01T00:00:00Z").alias("date"),
        "payload_digest",
        F.when(revisit, urn(F.col("kept"))).alias("refers_to"),
        "payload_bytes",
        F.when(~revisit, F.col("payload")).alias("payload"),
    )


def page_of(urn) -> F.Column:
    """The id inside a page's record id; null if it has none."""
    return F.expr(f"try_cast(regexp_extract({urn}, '^<urn:page:(-?[0-9]+)>$', 1) AS BIGINT)")


def archive_pages(pages: DataFrame, *, path: str | None = None, id_col: str = "page_id", html_col: str = "html") -> DataFrame:
    """Write all pages and read them back: page_id, payload_bytes,
    payload_digest, record_type and refers_to of each row."""
    spark = pages.sparkSession
    path = path or fresh_path(spark, "warc")
    write_warc(page_records(pages, id_col=id_col, html_col=html_col), path)
    return read_warc(spark, path).select(
        page_of("record_id").alias("page_id"),
        "payload_bytes",
        "payload_digest",
        "record_type",
        page_of("refers_to").alias("refers_to"),
    )
