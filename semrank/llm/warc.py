"""WARC archives as a Spark data source.

Writing: one record per row, each its own gzip member whose extra field (``sl``, skip lengths) says how many bytes
the member has, packed and unpacked; a payload that another page already holds becomes a revisit record that names
it. A task starts another file every ``ROLL_BYTES``. Files get their final names at commit, so a lost or repeated
task leaves nothing behind that a reader could see.

Reading (``spark.read.format("semrank_warc")``): files are the partitions, packed by size, and are read by ranges, so
a task holds a piece of a file and one payload at a time. Filters on ``record_type``, ``target_uri`` and ``page_id``
are pushed down (record types and a URI prefix also as options): headers are parsed first, and where they rule a
record out, or no payload is asked for, the reader skips to the next member and inflates nothing more. Members of
other writers, which have no skip lengths, are inflated in pieces to find their end.

Cases: null html is an empty payload; a null url gives no target URI; a null page_id is written without an id;
an empty table gives an archive without records; records with equal payloads below ``min_bytes`` are all responses;
repeated page_ids are separate records: a revisit is resolved by page_id and digest, rows that hold the smallest
page_id of a payload are responses each; other columns of the pages are ignored; a page without column url has none.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, EqualTo, Filter, In, InputPartition, StringStartsWith, WriterCommitMessage
from pyspark.sql.types import StructType

from .common import file_system, new_path, only, stored

FORMAT = "semrank_warc"
SCHEMA = "page_id bigint, record_type string, target_uri string, record_id string, refers_to bigint, content_length bigint, payload_digest string, payload binary, file string, offset bigint"
#: Bytes of archives in one read partition, of a file before another one is begun, of one range that is read, and of one piece that is inflated.
PART_BYTES, ROLL_BYTES, RANGE_BYTES, CHUNK = 64 << 20, 64 << 20, 1 << 20, 1 << 14


def _record_id(page_id) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}')}>"


def encode_record(page_id, url, payload: bytes | None, digest: str, refers_to) -> bytes:
    """One record of WARC 1.1 as a gzip member; a revisit has no payload."""
    kind = "response" if refers_to is None else "revisit"
    head = [("WARC-Type", kind), ("WARC-Record-ID", _record_id(page_id)), ("WARC-Date", "2024-01-01T00:00:00Z"), ("WARC-Payload-Digest", f"sha256:{digest}")]
    if page_id is not None:
        head.append(("X-Page-ID", str(page_id)))
    if url:
        head.append(("WARC-Target-URI", url.replace("\r", "%0D").replace("\n", "%0A")))
    if refers_to is not None:
        head += [("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("WARC-Refers-To", _record_id(refers_to)), ("X-Refers-To-Page", str(refers_to))]
    body = b"" if refers_to is not None else payload or b""
    head += [("Content-Type", "text/html; charset=utf-8"), ("Content-Length", str(len(body)))]
    lines = b"".join(f"{k}: {v}\r\n".encode() for k, v in head)
    return gzip_member(b"WARC/1.1\r\n" + lines + b"\r\n" + body + b"\r\n\r\n")


def gzip_member(data: bytes) -> bytes:
    """A gzip member that tells its own packed and unpacked length; one of 4 GB or more tells none."""
    pack = zlib.compressobj(3, zlib.DEFLATED, -15)
    body = pack.compress(data) + pack.flush()
    tail = struct.pack("<II", zlib.crc32(data), len(data) & 0xFFFFFFFF)
    size = 10 + 14 + len(body) + len(tail)
    if max(size, len(data)) >> 32:
        return b"\x1f\x8b\x08\0\0\0\0\0\0\xff" + body + tail
    extra = struct.pack("<H2sHII", 12, b"sl", 8, size, len(data))
    return b"\x1f\x8b\x08\x04\0\0\0\0\0\xff" + extra + body + tail


@dataclass
class Rules:
    """What a record's header must say."""

    types: frozenset[str] | None = None
    uri_prefixes: tuple[str, ...] = ()
    page_ids: frozenset[int] | None = None

    def admit(self, head: dict[str, str]) -> bool:
        if self.types is not None and head.get("warc-type") not in self.types:
            return False
        if any(not head.get("warc-target-uri", "").startswith(p) for p in self.uri_prefixes):
            return False
        return self.page_ids is None or _number(head.get("x-page-id")) in self.page_ids


def _number(text: str | None) -> int | None:
    """None for what isn't a decimal number, as headers of other writers may hold."""
    return int(text) if text and text.removeprefix("-").isdecimal() else None


class Ranges:
    """A file read by ranges: ``at`` gives what lies at a place, as far as one range goes."""

    def __init__(self, file, size: int):
        self.file, self.size, self.start, self.held = file, size, 0, b""

    def at(self, place: int, least: int = 1) -> memoryview:
        if not (self.start <= place and place + least <= self.start + len(self.held)):
            self.start, self.held = place, self.file.read_at(min(max(RANGE_BYTES, least), self.size - place), place)
        return memoryview(self.held)[place - self.start :]


class _Member:
    """Inflates one gzip member piece by piece; ``inflated`` counts all bytes that any member gave."""

    inflated = 0

    def __init__(self, source: Ranges, at: int):
        self.source, self.fed, self.start, self.z = source, at, at, zlib.decompressobj(31)

    def skip_length(self) -> int | None:
        """The member's packed length by its extra field."""
        head = bytes(self.source.at(self.start, min(24, self.source.size - self.start))[:24])
        return struct.unpack("<I", head[16:20])[0] if len(head) == 24 and head[3] & 4 and head[12:16] == b"sl\x08\0" else None

    def read(self, most: int) -> bytes:
        block = self.z.unconsumed_tail
        if not block:
            block = bytes(self.source.at(self.fed)[:CHUNK]) if self.fed < self.source.size else b""
            self.fed += len(block)
        out = self.z.decompress(block, most)
        _Member.inflated += len(out)
        if not len(block) and not out and not self.z.eof:
            raise ValueError(f"the record at byte {self.start} is cut off")
        return out

    def end(self) -> int:
        return self.fed - len(self.z.unused_data)


def records(source: Ranges, rules: Rules, payloads: bool) -> Iterator[tuple[int, dict[str, str], bytes | None]]:
    """(offset, header, payload) of the records that the rules admit. Only headers are parsed of the others."""
    at = 0
    while at < source.size:
        member, text = _Member(source, at), b""
        length = member.skip_length()
        while b"\r\n\r\n" not in text and not member.z.eof:
            text += member.read(1024)
        head, _, body = text.partition(b"\r\n\r\n")
        if not head.startswith(b"WARC/"):
            raise ValueError(f"no WARC record at byte {at}")
        fields = {k.strip().lower(): v.strip() for k, v in (x.split(":", 1) for x in head.decode("utf-8", "replace").split("\r\n")[1:] if ":" in x)}
        admitted = rules.admit(fields)
        parts = [body] if payloads and admitted else None
        while not member.z.eof and (parts is not None or length is None):
            more = member.read(1 << 20)
            if parts is not None:
                parts.append(more)
        if admitted:
            yield at, fields, None if parts is None else b"".join(parts)[: _number(fields.get("content-length")) or 0]
        at = member.end() if length is None else at + length


class _Part(InputPartition):
    def __init__(self, files: list[str]):
        super().__init__(files)
        self.files = files


class _Reader(DataSourceReader):
    def __init__(self, options: dict, schema: StructType):
        self.path, self.names = options["path"], schema.names
        self.rules = Rules(frozenset(options["record_types"].split(",")) if options.get("record_types") else None, (options["uri_prefix"],) if options.get("uri_prefix") else ())

    def pushFilters(self, filters: list[Filter]):  # noqa: N802
        for f in filters:
            name = f.attribute[0] if hasattr(f, "attribute") and len(f.attribute) == 1 else None
            one_of = {f.value} if isinstance(f, EqualTo) else set(f.value) if isinstance(f, In) else None
            if name == "record_type" and one_of is not None:
                self.rules.types = frozenset(one_of if self.rules.types is None else self.rules.types & one_of)
            elif name == "page_id" and one_of is not None:
                self.rules.page_ids = frozenset(one_of if self.rules.page_ids is None else self.rules.page_ids & one_of)
            elif name == "target_uri" and isinstance(f, StringStartsWith):
                self.rules.uri_prefixes += (f.value,)
            else:
                yield f

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        where, path = file_system(self.path)
        files = sorted((x for x in where.get_file_info(fs.FileSelector(path)) if x.base_name.endswith(".warc.gz")), key=lambda x: x.path)
        parts, now, size = [], [], 0
        for x in files:
            if now and size + x.size > PART_BYTES:
                parts.append(_Part(now))
                now, size = [], 0
            now.append(x.path)
            size += x.size
        return [*parts, _Part(now)]

    def read(self, partition: _Part) -> Iterator[tuple]:
        where, _ = file_system(self.path)
        payloads = "payload" in self.names
        for name in partition.files:
            with where.open_input_file(name) as f:
                for at, h, payload in records(Ranges(f, f.size()), self.rules, payloads):
                    whole = {
                        "page_id": _number(h.get("x-page-id")), "record_type": h.get("warc-type"), "target_uri": h.get("warc-target-uri"), "record_id": h.get("warc-record-id"),
                        "refers_to": _number(h.get("x-refers-to-page")), "content_length": _number(h.get("content-length")) or 0,
                        "payload_digest": h.get("warc-payload-digest", "").removeprefix("sha256:"), "payload": payload, "file": name, "offset": at,
                    }
                    yield tuple(whole[n] for n in self.names)


class _Done(WriterCommitMessage):
    def __init__(self, files: list[tuple[str, str]]):
        self.files = files


class _Writer(DataSourceWriter):
    def __init__(self, path: str, roll: int):
        self.path, self.roll = path, roll

    def write(self, rows: Iterator[Row]) -> _Done:
        from pyspark import TaskContext

        where, path = file_system(self.path)
        name, number, out, files = uuid.uuid4().hex, TaskContext.get().partitionId() if TaskContext.get() else 0, None, []
        for r in rows:
            if out is None:
                where.create_dir(path, recursive=True)
                files.append((f"{path}/_open-{name}-{len(files):05}", f"{path}/part-{number:06}-{name}-{len(files):05}.warc.gz"))
                out = where.open_output_stream(files[-1][0])
            payload = bytes(r["payload"]) if r["payload"] is not None else b""
            out.write(encode_record(r["page_id"], r["url"], payload, r["payload_digest"], r["refers_to"]))
            if out.tell() >= self.roll:
                out.close()
                out = None
        if out is not None:
            out.close()
        return _Done(files)

    def commit(self, messages: list[_Done | None]) -> None:
        where, path = file_system(self.path)
        where.create_dir(path, recursive=True)
        for temporary, final in (f for m in messages if m for f in m.files):
            where.move(temporary, final)

    def abort(self, messages: list[_Done | None]) -> None:
        where, _ = file_system(self.path)
        for temporary, _ in (f for m in messages if m for f in m.files):
            where.delete_file(temporary)


class WarcSource(DataSource):
    """Options: path; for reading also record_types (comma-joined) and uri_prefix, for writing roll_bytes."""

    @classmethod
    def name(cls) -> str:
        return FORMAT

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Reader(self.options, schema)

    def writer(self, schema: StructType, overwrite: bool) -> DataSourceWriter:
        return _Writer(self.options["path"], int(self.options.get("roll_bytes", ROLL_BYTES)))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(WarcSource)


def write_archives(pages: DataFrame, path: str, min_bytes: int = 100, roll_bytes: int = ROLL_BYTES) -> None:
    """A record per page. Of equal payloads of at least ``min_bytes`` the smallest page_id's is the response."""
    register(pages.sparkSession)
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary").alias("payload"))
    rows = rows.withColumn("payload_digest", F.sha2("payload", 256))
    seen = rows.filter(F.octet_length("payload") >= min_bytes).groupBy("payload_digest").agg(F.min("page_id").alias("first_id"), F.count("*").alias("n")).filter("n > 1").drop("n")
    again = F.col("first_id").isNotNull() & (~F.col("page_id").eqNullSafe(F.col("first_id")))
    rows = rows.join(seen, "payload_digest", "left").withColumn("refers_to", F.when(again, F.col("first_id"))).drop("first_id")
    rows.select("page_id", "url", "payload", "payload_digest", "refers_to").write.format(FORMAT).mode("append").option("path", path).option("roll_bytes", roll_bytes).save()


def read_archives(spark: SparkSession, path: str, columns: list[str] | None = None, **options: str) -> DataFrame:
    """The records below ``path``. Filters are pushed into the source; the session setting for that is switched on here.

    columns: those wanted, as Spark prunes none for a Python source; without ``payload`` no payload is inflated."""
    register(spark)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    reader = spark.read.format(FORMAT).options(path=path, **options)
    return (reader.schema(", ".join(f for f in SCHEMA.split(", ") if f.split(" ")[0] in columns)) if columns else reader).load()


def round_trip(pages: DataFrame, min_bytes: int = 100) -> DataFrame:
    """Writes archives and reads them back: page_id, payload_bytes, payload_digest, record_type, refers_to, from the records."""
    spark = pages.sparkSession
    path = new_path(spark, "warc")
    write_archives(only_pages(pages), path, min_bytes)
    # one scan of the archives: sizes and digests are taken from the payloads that were read
    told = F.col("payload_digest").alias("told")
    found = stored(read_archives(spark, path).select("page_id", "record_type", "refers_to", told, F.octet_length("payload").cast("long").alias("payload_bytes"), F.sha2("payload", 256).alias("payload_digest")), "warc-read")
    answers, again = found.filter("record_type = 'response'"), found.filter("record_type = 'revisit'").select("page_id", "record_type", "refers_to", "told")
    first = answers.join(again.select(F.col("refers_to").alias("page_id"), "told"), ["page_id", "told"], "left_semi").dropDuplicates(["page_id", "told"])
    resolved = again.join(first.select(F.col("page_id").alias("refers_to"), "told", "payload_bytes", "payload_digest"), ["refers_to", "told"])
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    return answers.select(*names).unionByName(resolved.select(*names))


def only_pages(pages: DataFrame) -> DataFrame:
    return only(pages, "page_id", "html").withColumn("url", F.lit(None).cast("string")) if "url" not in pages.columns else pages.select("page_id", "url", "html")


def payload_digest(payload: bytes) -> str:
    return hashlib.sha256(payload).hexdigest()
