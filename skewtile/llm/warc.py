"""WARC archives as a PySpark Python data source, written and read.

Writing: each task writes its records as one gzip member each into files of bounded size; only files of
tasks that Spark commits are named in the manifest, so lost executors and repeated tasks leave no
records twice. A member's header carries skip lengths in an "sl" extra field. Reading: files of the
manifest (or, without one, all .warc and .warc.gz files) are packed into partitions by size; each record's headers
are decoded first, record-type and header predicates (options, or filters that Spark pushes down) are
tried on them, and only a wanted payload is read and decoded; others are skipped by their length.

Cases: a null html is an empty payload; a null url gives a record without target URI; line breaks in
a url are percent-encoded; records of one page_id and payload are all responses when that page_id is the
smallest; an empty table gives an archive without records; of the input only page_id, url and html are read.
"""

from __future__ import annotations

import base64
import hashlib
import json
import struct
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, EqualTo, In, InputPartition, WriterCommitMessage

from skewtile.llm.scratch import new_path

# The archive's version line, separators and manifest name.
VERSION, NL, MANIFEST = b"WARC/1.1", b"\r\n", "_records.json"
FILE_BYTES, PART_BYTES = 256 << 20, 128 << 20
READ_SCHEMA = "page_id long, record_type string, target_uri string, refers_to long, payload_digest string, http_length long, payload binary, payload_decoded boolean"
_HEADERS = {"record_type": "warc-type", "target_uri": "warc-target-uri", "payload_digest": "warc-payload-digest"}


def _open(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:/") else (pafs.LocalFileSystem(), path)


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _urn(page_id: int) -> bytes:
    return b"<urn:page:%d>" % page_id


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """One WARC record; with refers_to a revisit, whose block ends after the HTTP headers."""
    http = NL.join([b"HTTP/1.1 200 OK", b"Content-Type: text/html; charset=utf-8", b"Content-Length: %d" % len(payload), b"", b""])
    block = http if refers_to is not None else http + payload
    lines = [VERSION, b"WARC-Type: " + (b"response" if refers_to is None else b"revisit")]
    if page_id is not None:
        lines.append(b"WARC-Record-ID: " + _urn(page_id))
    if url is not None:
        lines.append(b"WARC-Target-URI: " + url.encode("utf-8", "replace").replace(b"\r", b"%0D").replace(b"\n", b"%0A"))
    lines.append(b"WARC-Payload-Digest: sha1:" + digest(payload).encode())
    if refers_to is not None:
        lines += [b"WARC-Refers-To: " + _urn(refers_to), b"WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    lines += [b"Content-Type: application/http; msgtype=response", b"Content-Length: %d" % len(block), b"", b""]
    return NL.join(lines) + block + NL + NL


def member(data: bytes) -> bytes:
    """A gzip member whose extra field "sl" holds its compressed and uncompressed lengths."""
    z = zlib.compressobj(6, zlib.DEFLATED, -15)
    body = z.compress(data) + z.flush()
    size = 10 + 2 + 12 + len(body) + 8
    head = b"\x1f\x8b\x08\x04" + b"\0" * 4 + b"\0\xff" + struct.pack("<H2sHII", 12, b"sl", 8, size, len(data) & 0xFFFFFFFF)
    return head + body + struct.pack("<II", zlib.crc32(data), len(data) & 0xFFFFFFFF)


class _Member:
    """Decodes one gzip member as far as it is asked to, and steps to the next one."""

    def __init__(self, f, start: int):
        self.f, self.start = f, start
        f.seek(start)
        head = f.read(12)
        self.ok = len(head) >= 10
        self.size = None
        if self.ok and head[3] & 4:
            extra = f.read(struct.unpack("<H", head[10:12])[0])
            if extra[:2] == b"sl":
                self.size = struct.unpack("<I", extra[4:8])[0]
        f.seek(start)
        self.z, self.data = zlib.decompressobj(31), b""

    def _more(self) -> bool:
        raw = self.z.unconsumed_tail or self.f.read(1 << 16)
        if not raw or self.z.eof:
            return False
        self.data += self.z.decompress(raw, 1 << 16)
        return True

    def until(self, mark: bytes, start: int = 0) -> int:
        while (at := self.data.find(mark, start)) < 0:
            if not self._more():
                return len(self.data)
        return at

    def take(self, a: int, b: int) -> bytes:
        parts, have = [self.data], len(self.data)
        while have < b:
            raw = self.z.unconsumed_tail or self.f.read(1 << 16)
            if not raw or self.z.eof:
                break
            parts.append(self.z.decompress(raw, 1 << 20))
            have += len(parts[-1])
        self.data = b"".join(parts)
        return self.data[a:b]

    def next_start(self) -> int:
        if self.size:
            return self.start + self.size
        while not self.z.eof and self._more():
            self.data = self.data[-4:]
        return self.f.tell() - len(self.z.unused_data)


class _Plain:
    """The same over a file that isn't compressed: payloads are stepped over by seeking."""

    def __init__(self, f, start: int):
        self.f, self.start, self.end = f, start, start
        f.seek(start)
        self.data = f.read(1 << 12)
        self.ok = bool(self.data)

    def until(self, mark: bytes, start: int = 0) -> int:
        while (at := self.data.find(mark, start)) < 0:
            more = self.f.read(1 << 12)
            if not more:
                return len(self.data)
            self.data += more
        return at

    def take(self, a: int, b: int) -> bytes:
        if len(self.data) < b:
            self.data += self.f.read(b - len(self.data))
        return self.data[a:b]

    def next_start(self) -> int:
        return self.start + self.end


def _fields(head: bytes) -> dict[str, str]:
    out = {}
    for line in head.decode("utf-8", "replace").split("\r\n")[1:]:
        name, _, value = line.partition(":")
        out[name.strip().lower()] = value.strip()
    return out


def _page(urn: str | None) -> int | None:
    number = (urn or "").removeprefix("<urn:page:").removesuffix(">")
    return int(number) if number.removeprefix("-").isdigit() else None


def records(f, compressed: bool, tests: dict[str, frozenset[str]], payload: bool) -> Iterator[tuple]:
    """Rows of READ_SCHEMA from an open archive file; tests: accepted values by column."""
    at = 0
    while True:
        m = (_Member if compressed else _Plain)(f, at)
        if not m.ok:
            return
        end = m.until(NL + NL)
        head = _fields(m.take(0, end))
        length = int(head.get("content-length", 0))
        body = end + 4
        if isinstance(m, _Plain):
            m.end = body + length + 4
        kind, told = head.get("warc-type"), head.get("warc-payload-digest", "").removeprefix("sha1:") or None
        values = {"record_type": kind, "target_uri": head.get("warc-target-uri"), "payload_digest": told}
        if all(values[c] in accepted for c, accepted in tests.items()):
            http_end = min(m.until(NL + NL, body), body + length)
            http = _fields(m.take(body, http_end))
            data = None
            if payload and kind == "response":
                data = m.take(http_end + 4, body + length)
            yield (_page(head.get("warc-record-id")), kind, values["target_uri"], _page(head.get("warc-refers-to")), told, int(http.get("content-length", 0)), data, data is not None)
        at = m.next_start()


class _Files(InputPartition):
    def __init__(self, files: list[str]):
        super().__init__(files)


class WarcReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"].rstrip("/")
        self.payload = options.get("payload", "true").lower() == "true"
        self.part_bytes = int(options.get("partbytes", PART_BYTES))
        self.tests: dict[str, frozenset[str]] = {}
        for column in _HEADERS:
            if column.replace("_", "") in options or column in options:
                said = options.get(column) or options[column.replace("_", "")]
                self.tests[column] = frozenset(said.split(","))

    def partitions(self) -> list[InputPartition]:
        fs, root = _open(self.path)
        manifest = f"{root}/{MANIFEST}"
        if fs.get_file_info(manifest).type == pafs.FileType.File:
            with fs.open_input_stream(manifest) as f:
                files = json.loads(f.read())
        else:
            found = fs.get_file_info(pafs.FileSelector(root, recursive=True))
            files = [[x.path[len(root) + 1 :], x.size] for x in found if x.path.endswith((".warc", ".warc.gz"))]
        packs, size = [[]], 0
        for name, n in sorted(files):
            if packs[-1] and size + n > self.part_bytes:
                packs.append([])
                size = 0
            packs[-1].append(name)
            size += n
        return [_Files(p) for p in packs]

    def read(self, partition) -> Iterator[tuple]:
        fs, root = _open(self.path)
        for name in partition.value:
            with fs.open_input_file(f"{root}/{name}") as f:
                yield from records(f, name.endswith(".gz"), self.tests, self.payload)


class PushdownWarcReader(WarcReader):
    """The reader for sessions in which spark.sql.python.filterPushdown.enabled is true."""

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute[0] in _HEADERS:
                values = frozenset([f.value])
            elif isinstance(f, In) and f.attribute[0] in _HEADERS:
                values = frozenset(f.value)
            else:
                yield f
                continue
            before = self.tests.get(f.attribute[0])
            self.tests[f.attribute[0]] = values if before is None else before & values


class _Written(WriterCommitMessage):
    def __init__(self, files: list[tuple[str, int]]):
        self.files = files


class WarcWriter(DataSourceArrowWriter):
    """Takes rows (page_id, url, html, refers_to)."""

    def __init__(self, options: dict, overwrite: bool):
        self.path, self.overwrite = options["path"].rstrip("/"), overwrite
        self.file_bytes = int(options.get("filebytes", FILE_BYTES))

    def write(self, batches: Iterator[pa.RecordBatch]) -> _Written:
        fs, root = _open(self.path)
        fs.create_dir(root, recursive=True)
        files, out, size, name = [], None, 0, ""
        for b in batches:
            at = {c: b.column(b.schema.get_field_index(c)) for c in ("page_id", "url", "html", "refers_to")}
            for i in range(b.num_rows):
                if out is None:
                    name, size = f"records-{uuid.uuid4().hex}.warc.gz", 0
                    out = fs.open_output_stream(f"{root}/{name}", compression=None)
                page, url, html, ref = (at[c][i].as_py() for c in ("page_id", "url", "html", "refers_to"))
                data = member(record(page, url, (html or "").encode("utf-8", "surrogatepass"), ref))
                out.write(data)
                size += len(data)
                if size >= self.file_bytes:
                    out.close()
                    files.append((name, size))
                    out = None
        if out is not None:
            out.close()
            files.append((name, size))
        return _Written(files)

    def commit(self, messages) -> None:
        fs, root = _open(self.path)
        fs.create_dir(root, recursive=True)
        files = sorted(f for m in messages if m for f in m.files)
        if not self.overwrite and fs.get_file_info(f"{root}/{MANIFEST}").type == pafs.FileType.File:
            with fs.open_input_stream(f"{root}/{MANIFEST}") as f:
                files = sorted([*map(tuple, json.loads(f.read())), *files])
        with fs.open_output_stream(f"{root}/{MANIFEST}", compression=None) as f:
            f.write(json.dumps(files).encode())

    def abort(self, messages) -> None:
        fs, root = _open(self.path)
        for m in messages:
            for name, _ in m.files if m else ():
                fs.delete_file(f"{root}/{name}")


class WarcSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self) -> str:
        return READ_SCHEMA

    def reader(self, schema) -> WarcReader:
        return (PushdownWarcReader if self.options.get("pushdown") == "true" else WarcReader)(self.options)

    def writer(self, schema, overwrite: bool) -> WarcWriter:
        return WarcWriter(self.options, overwrite)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(WarcSource)


def with_revisits(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """page_id, url, html, refers_to: for all but the smallest page_id of equal payloads, that smallest page_id."""
    rows = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    sha = F.sha1(F.encode("html", "UTF-8"))
    light = rows.where(F.octet_length("html") >= least_bytes).select("page_id", sha.alias("_sha"))
    same = light.groupBy(F.col("_sha").alias("_of")).agg(F.min("page_id").alias("_first"), F.count(F.lit(1)).alias("_n")).where("_n > 1").drop("_n")
    again = light.join(same, F.col("_sha") == F.col("_of")).where(~F.col("page_id").eqNullSafe(F.col("_first")) & F.col("_first").isNotNull())
    again = again.select(F.col("page_id").alias("_page"), F.col("_of"), "_first").distinct()
    # pages meet their verdict by page and payload, so the many copies of one payload do not meet in one task
    joined = rows.withColumn("_sha", sha).join(again, F.col("page_id").eqNullSafe(F.col("_page")) & (F.col("_sha") == F.col("_of")), "left")
    return joined.select("page_id", "url", "html", F.col("_first").alias("refers_to"))


def write_archive(pages: DataFrame, path: str, least_bytes: int = 0) -> None:
    register(pages.sparkSession)
    with_revisits(pages, least_bytes).write.format("warc").mode("append").save(path)


def read_archive(spark: SparkSession, path: str, pushdown: bool = False, **options: str) -> DataFrame:
    """READ_SCHEMA. Options: payload ("false": headers only), partBytes, and accepted values, comma-joined, of record_type,
    target_uri, payload_digest. pushdown: also take such predicates from where(); it switches Spark's setting on."""
    register(spark)
    if pushdown:
        spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
        options["pushdown"] = "true"
    return spark.read.format("warc").options(**options).load(path)


def base32(sha1_hex: Column) -> Column:
    """The upper-case base32 form of a hexadecimal SHA-1."""
    eight = lambda i: F.lpad(F.conv(F.substring(sha1_hex, 10 * i + 1, 10), 16, 32), 8, "0")
    return F.translate(F.concat(*(eight(i) for i in range(4))), "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")


def round_trip(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """Writes the pages as an archive in the shared folder and reads it back by two predicates: page_id, payload_bytes, payload_digest, record_type,
    refers_to. Responses tell what their payload as read has; revisits, of which headers alone are decoded, what they state."""
    path = new_path(pages.sparkSession, "warc")
    write_archive(pages, path, least_bytes)
    whole = read_archive(pages.sparkSession, path, record_type="response")
    whole = whole.select("page_id", F.octet_length("payload").cast("long").alias("payload_bytes"), base32(F.sha1("payload")).alias("payload_digest"), "record_type", "refers_to")
    heads = read_archive(pages.sparkSession, path, record_type="revisit", payload="false")
    return whole.unionByName(heads.select("page_id", F.col("http_length").alias("payload_bytes"), "payload_digest", "record_type", "refers_to"))
