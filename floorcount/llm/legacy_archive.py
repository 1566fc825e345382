"""Legacy ARC archives converted to WARC.

An ARC file starts with a version record that names the fields of its URL record lines: five in version 1, ten in
version 2. Each record is such a line, a block of the declared length and a line end. The converter walks a file by the
declared lengths only, so a block may hold anything. Of each record it makes the WARC equivalents: an identifier
from the archive's name and the record's offset in the unpacked archive, an ISO timestamp from the 14-digit date, a type from
the URL's scheme and the content, and SHA-256 digests of payload and block. A version record becomes a warcinfo; the address
that a page came from is carried as WARC-IP-Address, and what else the line of version 2 says in fields of this module.

Both kinds of archive are written by Spark's text sink, one archive stretch a row: the sink writes a string's bytes as they
are, and the text between rows is an empty gzip member. So every file is a plain sequence of gzip members, one for each record,
on any file system that Spark writes to, committed by its protocol. Files are read whole, as binaryFile, and are small: the writer bounds them.
"""

from __future__ import annotations

import hashlib
import re
import uuid
import zlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from floorcount.llm.scratch import Scratch

FIELDS = {1: "URL IP-address Archive-date Content-type Archive-length", 2: "URL IP-address Archive-date Content-type Result-code Checksum Location Offset Filename Archive-length"}
VERSION_LINE = {1: "1 0 floorcount", 2: "2 0 floorcount"}
LEVEL = 6
#: Bytes of records, not compressed, after which a stretch of an archive ends, and stretches in a file.
STRETCH_BYTES, STRETCHES_A_FILE = 4_000_000, 8
VERSION, VERSION_KEY = re.compile(rb"[12] [0-9]+ [^\n]*"), "version"
NAMESPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")  # the name space of URLs
#: Payloads of at least so many bytes are written once; later ones refer to the first.
REVISIT_BYTES = 100


def member(data: bytes, level: int = LEVEL) -> bytes:
    pack = zlib.compressobj(level, zlib.DEFLATED, 31)
    return pack.compress(data) + pack.flush()


BETWEEN = member(b"").decode("latin-1")


def members(data: bytes, step: int = 1 << 14) -> Iterator[bytes]:
    """The contents of a sequence of gzip members. Each is fed in small steps, so that what follows it isn't copied again and again."""
    view, at = memoryview(data), 0
    while at < len(view):
        unpack, out = zlib.decompressobj(31), []
        while not unpack.eof:
            if at >= len(view):
                raise ValueError("the archive ends within a record")
            out.append(unpack.decompress(view[at : at + step]))
            at += len(view[at : at + step])
        at -= len(unpack.unused_data)
        if whole := b"".join(out):
            yield whole


def write_archive(stretches: DataFrame, path: str) -> None:
    """Writes a table of one binary column."""
    stretches.select(F.col(stretches.columns[0]).cast("string").alias("value")).write.mode("overwrite").option("lineSep", BETWEEN).option("encoding", "ISO-8859-1").option("maxRecordsPerFile", STRETCHES_A_FILE).text(path)


def read_archive(spark: SparkSession, path: str) -> DataFrame:
    """Rows (path, content) of the archive's files."""
    return spark.read.format("binaryFile").load(path).select("path", "content")


def http_block(page_id: int | None, html: bytes | None) -> bytes:
    payload = html or b""
    own = "" if page_id is None else f"X-Page-Id: {page_id}\r\n"
    return f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n{own}Content-Length: {len(payload)}\r\n\r\n".encode() + payload


def arc_record(version: int, url: str | None, date: str, block: bytes, offset: int, name: str) -> bytes:
    """url: null and blanks are written so that the line can still be split from the right."""
    target = (url if url is not None else "-").replace("\r", "%0D").replace("\n", "%0A") or "-"
    fields = [target, "0.0.0.0", date, "text/html"]
    if version == 2:
        fields += ["200", "-", "-", str(offset), name]
    return " ".join([*fields, str(len(block))]).encode("utf-8") + b"\n" + block + b"\n"


def arc_version_record(version: int, name: str, date: str) -> bytes:
    body = f"{VERSION_LINE[version]}\n{FIELDS[version]}\n".encode()
    fields = [f"filedesc://{name}", "0.0.0.0", date, "text/plain", *(["200", "-", "-", "0", name] if version == 2 else []), str(len(body))]
    return " ".join(fields).encode() + b"\n" + body + b"\n"


class _Lines:
    """Reads a sequence of byte strings by lines and lengths, across their borders."""

    def __init__(self, chunks: Iterable[bytes]):
        self.chunks, self.data, self.at, self.gone = iter(chunks), b"", 0, 0

    @property
    def offset(self) -> int:
        """Bytes read so far."""
        return self.gone + self.at

    def _more(self) -> bool:
        chunk = next(self.chunks, None)
        if chunk is None:
            return False
        self.gone += self.at
        self.data, self.at = self.data[self.at :] + chunk, 0
        return True

    def line(self) -> bytes | None:
        while (end := self.data.find(b"\n", self.at)) < 0:
            if not self._more():
                return None
        line, self.at = self.data[self.at : end], end + 1
        return line

    def take(self, n: int) -> bytes:
        while len(self.data) - self.at < n:
            if not self._more():
                raise ValueError("the archive ends within a record")
        out, self.at = self.data[self.at : self.at + n], self.at + n
        return out


def version_fields(body: bytes) -> list[str] | None:
    """The names of the fields that a version block announces; of other blocks, none."""
    head, _, rest = body.partition(b"\n")
    if not VERSION.fullmatch(head.strip()):
        return None
    names = rest.partition(b"\n")[0].decode("utf-8", "replace").split()
    return names if names[:1] == ["URL"] and names[-1:] == ["Archive-length"] else None


def walk_arc(chunks: Iterable[bytes]) -> Iterator[tuple[int, dict[str, str], bytes]]:
    """Offset, header fields and block of each record; VERSION_KEY is among the fields of a version record, which says how many fields follow.

    What makes a version record is its block, not its URL alone: a page may have any URL.
    """
    lines, names = _Lines(chunks), FIELDS[1].split()
    while True:
        offset = lines.offset
        if (line := lines.line()) is None:
            return
        if not line.strip():
            continue
        text = line.decode("utf-8", "replace").rstrip("\r")
        length = text.rsplit(" ", 1)[-1]
        if not (length.isascii() and length.isdigit()):
            raise ValueError("a record line ends without a length")
        block = lines.take(int(length))
        if text.startswith("filedesc://") and (announced := version_fields(block)):
            names = announced
            yield offset, {"URL": text.split(" ", 1)[0], "Archive-date": (text.split(" ") + ["", ""])[2], "Content-type": "text/plain", VERSION_KEY: block.split(b" ", 1)[0].decode()}, block
            continue
        parts = text.rsplit(" ", len(names) - 1)  # a URL may hold blanks
        if len(parts) != len(names):
            raise ValueError(f"a record line has {len(parts)} of {len(names)} fields")
        yield offset, dict(zip(names, parts)), block


def parse_arc(chunks: Iterable[bytes]) -> Iterator[tuple[int, dict[str, str], bytes]]:
    """The records of walk_arc() that aren't version records."""
    return (r for r in walk_arc(chunks) if VERSION_KEY not in r[1])


def split_http(block: bytes) -> tuple[bytes, bytes]:
    """Header, with its empty line, and payload; a block without one is all payload."""
    if block.startswith(b"HTTP/") and (end := block.find(b"\r\n\r\n")) >= 0:
        return block[: end + 4], block[end + 4 :]
    return b"", block


def header_of(block: bytes, name: bytes) -> str | None:
    for line in split_http(block)[0].split(b"\r\n")[1:]:
        key, _, value = line.partition(b":")
        if key.strip().lower() == name.lower():
            return value.strip().decode("utf-8", "replace")
    return None


def warc_time(date: str) -> str:
    d = (date + "00000000000000")[:14]
    return f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z"


def warc_id(archive: str, offset: int) -> str:
    return f"<urn:uuid:{uuid.uuid5(NAMESPACE, f'{archive}#{offset}')}>"


def warc_type(url: str, block: bytes) -> str:
    """response where there is an HTTP header, else resource; metadata for what the archive says about itself."""
    if url.startswith("metadata://"):
        return "metadata"
    return "response" if split_http(block)[0] else "resource"


def warc_record(fields: list[tuple[str, str | None]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in fields if v is not None)
    return f"WARC/1.1\r\n{head}Content-Length: {len(block)}\r\n\r\n".encode() + block + b"\r\n\r\n"


def parse_warc(chunks: Iterable[bytes]) -> Iterator[tuple[dict[str, str], bytes]]:
    lines = _Lines(chunks)
    while (line := lines.line()) is not None:
        if not line.strip():
            continue
        if not line.startswith(b"WARC/"):
            raise ValueError("a WARC record was due")
        fields: dict[str, str] = {}
        while (line := lines.line()) is not None and line.strip():
            key, _, value = line.decode("utf-8", "replace").partition(":")
            fields[key.strip().lower()] = value.strip()
        yield fields, lines.take(int(fields["content-length"]))


def write_arc(pages: DataFrame, path: str, date: str = "20240101000000") -> None:
    """Pages (page_id, url, html) as ARC files, whose version alternates by stretch: a stretch starts with its own version record."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name, part, out, size, count = uuid.uuid4().hex, 0, [], 0, 0
        for batch in batches:
            for page_id, url, html in zip(batch.column("page_id").to_pylist(), batch.column("url").to_pylist(), batch.column("html").cast(pa.binary()).to_pylist()):
                version = 1 + part % 2
                if not out:
                    out.append(member(arc_version_record(version, f"{name}-{part}.arc", date)))
                record = arc_record(version, url, date, http_block(page_id, html), size, f"{name}-{part}.arc")
                out.append(member(record))
                size, count = size + len(record), count + 1
                if size >= STRETCH_BYTES:
                    yield pa.RecordBatch.from_arrays([pa.array([b"".join(out)], pa.binary())], names=["value"])
                    out, size, part = [], 0, part + 1
        if out:
            yield pa.RecordBatch.from_arrays([pa.array([b"".join(out)], pa.binary())], names=["value"])

    write_archive(pages.select("page_id", "url", "html").mapInArrow(run, "value binary"), path)


#: Level of the blocks that a shuffle carries.
CARRIED_LEVEL = 1
RECORD = "archive string, offset long, url string, ip string, date string, content_type string, result_code string, checksum string, location string, page_id long, warc_type string, payload_digest string, payload_bytes long, block binary"


def convert(spark: SparkSession, arc: str, blocks: bool = True) -> DataFrame:
    """The records of ARC files with their WARC equivalents; `block` is the record's block as one gzip member, null if not asked for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, content in zip(batch.column("path").to_pylist(), batch.column("content")):
                archive, rows = path.rsplit("/", 1)[-1], []
                size = 0
                for offset, f, block in walk_arc(members(content.as_py())):
                    about = VERSION_KEY in f
                    if about:
                        block = f"software: floorcount\r\nformat: WARC File Format 1.1\r\nconverted-from: {f['URL']}, ARC version {f[VERSION_KEY]}\r\n".encode()
                    payload = split_http(block)[1]
                    page = None if about else header_of(block, b"X-Page-Id")
                    packed = member(block, CARRIED_LEVEL) if blocks else None
                    said = [None if f.get(k, "-") in ("-", "0.0.0.0") else f[k] for k in ("IP-address", "Result-code", "Checksum", "Location")]
                    kind = "warcinfo" if about else warc_type(f["URL"], block)
                    rows.append((archive, offset, f["URL"], said[0], f["Archive-date"], f["Content-type"], *said[1:], None if page is None else int(page), kind, hashlib.sha256(payload).hexdigest(), len(payload), packed))
                    size += len(packed or b"") + 300
                    if size >= STRETCH_BYTES:
                        yield _rows(rows)
                        rows, size = [], 0
                if rows:
                    yield _rows(rows)

    return read_archive(spark, arc).mapInArrow(run, RECORD)


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    names, types = zip(*(x.split() for x in RECORD.split(", ")))
    kinds = [{"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}[t] for t in types]
    return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows), kinds)], names=list(names))


def with_first(records: DataFrame, digests: DataFrame | None = None) -> DataFrame:
    """records with `first_page`, `first_archive` and `first_offset` of the record that each large payload is kept in.

    The smallest page_id comes first (null last), then archive and offset; counts are made before anything is shuffled by
    digest. Records that can have no equal are dealt by their own place, so that they don't meet in one task; Spark splits
    the tasks of a payload with very many copies.
    """
    large = (F.col("payload_bytes") >= REVISIT_BYTES) & (F.col("warc_type") != "warcinfo")
    first = (records if digests is None else digests).filter(large).groupBy(F.col("payload_digest").alias("digest")).agg(F.min(F.struct(F.col("page_id").isNull().alias("none"), "page_id", "archive", "offset")).alias("first"), F.count(F.lit(1)).alias("copies"))
    again = first.filter(F.col("copies") > 1).select("digest", F.col("first.page_id").alias("first_page"), F.col("first.archive").alias("first_archive"), F.col("first.offset").alias("first_offset"))
    by = F.when(large, F.col("payload_digest")).otherwise(F.concat_ws("#", "archive", "offset"))
    return records.withColumn("by", by).join(again, F.col("by") == F.col("digest"), "left").drop("by", "digest")


def write_warc(records: DataFrame, path: str) -> None:
    """Records of with_first() as WARC files; those that aren't the first of their payload become revisits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, size = [], 0
        for part in (batch.slice(start, 64) for batch in batches for start in range(0, batch.num_rows, 64)):
            for r in part.to_pylist():
                block = b"".join(members(r["block"]))
                kind, refers = r["warc_type"], None
                if r["first_archive"] is not None and (r["first_archive"], r["first_offset"]) != (r["archive"], r["offset"]):
                    kind, refers, block = "revisit", warc_id(r["first_archive"], r["first_offset"]), split_http(block)[0]
                about = kind == "warcinfo"
                content = {"warcinfo": "application/warc-fields", "resource": r["content_type"], "metadata": r["content_type"]}.get(kind, "application/http; msgtype=response")
                fields = [
                    ("WARC-Type", kind), ("WARC-Record-ID", warc_id(r["archive"], r["offset"])), ("WARC-Date", warc_time(r["date"])), ("WARC-Target-URI", None if about or r["url"] == "-" else r["url"]),
                    ("WARC-Filename", r["url"].removeprefix("filedesc://") if about else None), ("Content-Type", content), ("WARC-IP-Address", r["ip"]),
                    ("X-Arc-Result-Code", r["result_code"]), ("X-Arc-Checksum", r["checksum"]), ("X-Arc-Location", r["location"]),
                    ("WARC-Payload-Digest", f"sha256:{r['payload_digest']}"), ("WARC-Block-Digest", f"sha256:{hashlib.sha256(block).hexdigest()}"),
                    ("WARC-Refers-To", refers), ("WARC-Profile", refers and "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"),
                    ("X-Refers-To-Page-Id", None if refers is None or r["first_page"] is None else str(r["first_page"])), ("X-Payload-Length", str(r["payload_bytes"])),
                ]
                record = warc_record(fields, block)
                out.append(member(record))
                size += len(record)
                if size >= STRETCH_BYTES:
                    yield pa.RecordBatch.from_arrays([pa.array([b"".join(out)], pa.binary())], names=["value"])
                    out, size = [], 0
        if out:
            yield pa.RecordBatch.from_arrays([pa.array([b"".join(out)], pa.binary())], names=["value"])

    write_archive(records.mapInArrow(run, "value binary"), path)


WARC_ROW = "record_id string, record_type string, url string, warc_date string, page_id long, payload_digest string, payload_bytes long, refers_to long, refers_to_id string, intact boolean"


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """One row a WARC record, those of type warcinfo too; `intact`: the block, and of responses the payload, have their digests."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.string(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.bool_()]
        names = [x.split()[0] for x in WARC_ROW.split(", ")]
        whole = lambda v: None if v is None else int(v)
        for batch in batches:
            for content in batch.column("content"):
                rows = []
                for f, block in parse_warc(members(content.as_py())):
                    payload, digest = split_http(block)[1], f["warc-payload-digest"].removeprefix("sha256:")
                    revisit = f["warc-type"] == "revisit"
                    intact = hashlib.sha256(block).hexdigest() == f["warc-block-digest"].removeprefix("sha256:") and (revisit or hashlib.sha256(payload).hexdigest() == digest)
                    length = int(f["x-payload-length"]) if revisit else len(payload)
                    rows.append((f["warc-record-id"], f["warc-type"], f.get("warc-target-uri"), f["warc-date"], whole(header_of(block, b"X-Page-Id")), digest, length, whole(f.get("x-refers-to-page-id")), f.get("warc-refers-to"), intact))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows), kinds)], names=names)

    return read_archive(spark, path).mapInArrow(run, WARC_ROW)


def archive_pages(pages: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """Pages written as ARC, converted, written as WARC and read back: the rows of read_warc() but the warcinfo records.

    A null html is an empty payload, a null url is written as "-" and comes back null, a null page_id comes back null and
    never is a reference. Rows repeated as they are become revisits of one of them, if large enough. An empty table gives
    an empty archive and no rows. Other columns of pages are ignored.
    """
    spark = pages.sparkSession
    scratch = scratch or Scratch(spark, "archive")
    write_arc(pages, scratch.path("arc"))
    arc = scratch.path("arc")
    write_warc(with_first(convert(spark, arc), convert(spark, arc, blocks=False)), scratch.path("warc"))
    return read_warc(spark, scratch.path("warc")).filter("record_type <> 'warcinfo'")
