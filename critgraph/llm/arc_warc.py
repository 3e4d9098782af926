"""WARC: converter of legacy ARC archives.

``lay_down`` writes pages as ARC archives of many records, of version 1 and of version 2; an archive is a row that
holds a whole ``.arc.gz`` file (a gzip member a record). ``convert`` parses each archive's records by their declared
lengths and synthesises an equivalent WARC archive: identifier, date, type, target URI, media type and digests. Equal
payloads of at least 100 bytes are kept once, by the record of least page_id; the others become revisits that name it.
Only the digests and places of records are grouped and joined; payloads travel with their archive. ``export`` writes
archives out as files.

Defined results: a null html is an empty payload; a null url is "about:blank", and blanks or
control characters in a URL are percent-encoded; header lines that are not UTF-8 are read byte by byte; repeated rows
give a record each with an identifier of its own, all of the same type; a null page_id counts as the least id; very long pages fill an archive alone; an empty table
gives no record. Extra columns are not read.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from critgraph.runtime import materialise, release, ship

MIN_DUPLICATE = 100
ARC_BYTES = 4 << 20  # an archive is closed when its records have so many
PAGE_FIELD = "X-Page-Id"  # of a record's HTTP message: carries the page's id through both formats
ARC_FIELDS = {1: ("url", "ip", "date", "type", "length"), 2: ("url", "ip", "date", "type", "code", "checksum", "location", "offset", "file", "length")}
_EPOCH = "20200101000000"


def safe_url(url: str | None) -> str:
    """A URL without white space or control characters, as ARC header lines need it."""
    return "".join(c if c > " " and c != "\x7f" and not c.isspace() else "".join(f"%{b:02X}" for b in c.encode()) for c in url or "") or "about:blank"


def arc_head(version: int) -> bytes:
    """The version block an ARC file starts with: it tells how header lines are to be read."""
    fields = b" ".join({"url": b"URL", "ip": b"IP-address", "date": b"Archive-date", "type": b"Content-type", "length": b"Archive-length", "code": b"Result-code", "checksum": b"Checksum", "location": b"Location", "offset": b"Offset", "file": b"Filename"}[f] for f in ARC_FIELDS[version])
    body = b"%d 0 critgraph\n%s\n" % (version, fields)
    line = b"filedesc://pages.arc 0.0.0.0 " + _EPOCH.encode() + b" text/plain "
    return line + (b"" if version == 1 else b"200 - - 0 pages.arc ") + b"%d\n" % len(body) + body + b"\n"


def arc_record(version: int, url: str, payload: bytes, checksum: str = "-", page: int | None = None) -> bytes:
    """Header line, HTTP message, newline."""
    own = b"" if page is None else b"%s: %d\r\n" % (PAGE_FIELD.encode(), page)
    body = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n%s\r\n" % (len(payload), own) + payload
    line = f"{safe_url(url)} 0.0.0.0 {_EPOCH} text/html " + ("" if version == 1 else f"200 {checksum} - 0 pages.arc ") + f"{len(body)}\n"
    return line.encode() + body + b"\n"


def header_text(raw: bytes) -> str:
    """A header line of a legacy archive; one that is not UTF-8 is taken byte by byte."""
    try:
        return raw.decode()
    except UnicodeDecodeError:
        return raw.decode("latin-1")


def http_fields(body: bytes) -> dict[str, str]:
    return dict(x.split(": ", 1) for x in header_text(body.partition(b"\r\n\r\n")[0]).split("\r\n")[1:] if ": " in x)


def members_of(data: bytes) -> bytes:
    """The records of a gzip file of many members, read as a stream: decompressing it at once copies the rest of the file for each member."""
    with gzip.GzipFile(fileobj=io.BytesIO(data)) as f:
        return f.read()


def page_of(body: bytes) -> int | None:
    own = http_fields(body).get(PAGE_FIELD)
    return None if own is None else int(own)


def parse_arc(data: bytes) -> Iterator[dict]:
    """The records after the version block: a field each, ``body`` and ``payload``. Bad lengths raise ValueError."""
    at, version = 0, None
    while at < len(data):
        stop = data.index(b"\n", at)
        line = header_text(data[at:stop]).split(" ")
        size = int(line[-1])
        body = data[stop + 1 : stop + 1 + size]
        if size < 0 or len(body) != size or data[stop + 1 + size : stop + 2 + size] != b"\n":
            raise ValueError(f"record at {at}: declared length {size} does not fit")
        at = stop + 2 + size
        if line[0].startswith("filedesc://"):
            version = int(body.split(b" ", 1)[0])
            continue
        fields = ARC_FIELDS[version or (1 if len(line) == 5 else 2)]
        if len(line) != len(fields):
            raise ValueError(f"{len(line)} fields in a version {version} header")
        yield dict(zip(fields, line)) | {"body": body, "payload": body.partition(b"\r\n\r\n")[2]}


def warc_record(kind: str, record_id: str, arc: dict, fields: dict[str, str]) -> bytes:
    d = arc["date"]
    body = arc["body"] if kind == "response" else arc["body"][: len(arc["body"]) - len(arc["payload"])]
    head = {
        "WARC-Type": kind, "WARC-Record-ID": f"<{record_id}>", "WARC-Date": f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z",
        "WARC-Target-URI": arc["url"], "WARC-IP-Address": arc["ip"], "Content-Type": "application/http; msgtype=response",
        "WARC-Block-Digest": "sha1:" + base64.b32encode(hashlib.sha1(body).digest()).decode(),
    } | fields | {"Content-Length": str(len(body))}
    return b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head.items()).encode() + b"\r\n" + body + b"\r\n\r\n"


def parse_warc(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(header fields, block) of each record."""
    at = 0
    while at < len(data):
        stop = data.index(b"\r\n\r\n", at)
        first, *lines = data[at:stop].decode().split("\r\n")
        if not first.startswith("WARC/"):
            raise ValueError(f"no record at {at}")
        head = dict(x.split(": ", 1) for x in lines)
        size = int(head["Content-Length"])
        yield head, data[stop + 4 : stop + 4 + size]
        at = stop + 8 + size


def record_urn(archive: str, place: int) -> str:
    return "urn:uuid:" + str(uuid.uuid5(uuid.NAMESPACE_URL, f"{archive}#{place}"))


def warc_info(archive: str) -> bytes:
    body = f"software: critgraph\r\nformat: WARC File Format 1.1\r\nconverted-from: {archive}\r\n".encode()
    e = _EPOCH
    head = f"WARC/1.1\r\nWARC-Type: warcinfo\r\nWARC-Record-ID: <{record_urn(archive, -1)}>\r\nWARC-Date: {e[:4]}-{e[4:6]}-{e[6:8]}T00:00:00Z\r\nContent-Type: application/warc-fields\r\nContent-Length: {len(body)}\r\n\r\n"
    return head.encode() + body + b"\r\n\r\n"


def lay_down(pages: DataFrame, arc_bytes: int = ARC_BYTES) -> DataFrame:
    """Legacy archives of the pages: archive (name), data (a .arc.gz file)."""
    ship(pages.sparkSession)

    def run(batches):
        task, made, size, members = TaskContext.get().partitionId(), 0, 0, []

        def closed():
            head = gzip.compress(arc_head(made % 2 + 1), 1, mtime=0)
            return pa.record_batch([pa.array([f"pages-{task:06d}-{made:06d}.arc.gz"]), pa.array([head + b"".join(members)], pa.binary())], names=["archive", "data"])

        for b in batches:
            for k in range(b.num_rows):
                page, url, html = (b.column(i)[k].as_py() for i in range(3))
                payload = (html or "").encode()
                record = arc_record(made % 2 + 1, url, payload, hashlib.sha1(payload).hexdigest(), page)
                members.append(gzip.compress(record, 1, mtime=0))
                size += len(record)
                if size >= arc_bytes:
                    yield closed()
                    made, size, members = made + 1, 0, []
        if members:
            yield closed()

    return pages.select(F.col("page_id").cast("bigint"), F.col("url").cast("string"), F.col("html").cast("string")).mapInArrow(run, "archive string, data binary")


def index(legacy: DataFrame) -> DataFrame:
    """Per record of the archives: archive, place, page_id, payload_digest, payload_bytes, target_uri."""
    ship(legacy.sparkSession)
    schema = "archive string, place bigint, page_id bigint, payload_digest string, payload_bytes bigint, target_uri string"

    def run(batches):
        for b in batches:
            for k in range(b.num_rows):
                name = b.column(0)[k].as_py()
                rows = [(name, i, page_of(x["body"]), hashlib.sha256(x["payload"]).hexdigest(), len(x["payload"]), x["url"]) for i, x in enumerate(parse_arc(members_of(b.column(1)[k].as_py())))]
                kinds = [pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string()]
                yield pa.record_batch([pa.array(c, kind) for c, kind in zip(list(zip(*rows)) or [[]] * 6, kinds)], names=[x.split()[0] for x in schema.split(", ")])

    return legacy.mapInArrow(run, schema)


def revisits(found: DataFrame) -> DataFrame:
    """Per archive that has revisits: archive, them (place, and archive, place and URI of the record that each refers to).

    Digests that occur once go no further; the first record of a digest is found with map-side minima. An archive's
    list is bounded by the records it holds.
    """
    first = F.min(F.struct("page_id", "archive", "place", "target_uri")).alias("first")
    again = found.where(F.col("payload_bytes") >= MIN_DUPLICATE).groupBy("payload_digest").agg(first, F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    # records of the first's own page repeat it: responses too
    to = found.where(F.col("payload_bytes") >= MIN_DUPLICATE).join(again, "payload_digest").where(~F.col("page_id").eqNullSafe(F.col("first.page_id")))
    return to.groupBy("archive").agg(F.collect_list(F.struct("place", F.col("first.archive").alias("archive"), F.col("first.place").alias("at"), F.col("first.target_uri").alias("uri"))).alias("them"))


def convert(legacy: DataFrame) -> DataFrame:
    """WARC archives of legacy ones: archive (name), data (a .warc.gz file)."""
    ship(legacy.sparkSession)

    def run(batches):
        for b in batches:
            for k in range(b.num_rows):
                name, data = b.column(0)[k].as_py(), b.column(1)[k].as_py()
                to = {x["place"]: x for x in b.column(2)[k].as_py() or ()}
                members = [gzip.compress(warc_info(name), 1, mtime=0)]
                for i, arc in enumerate(parse_arc(members_of(data))):
                    fields = {"WARC-Payload-Digest": f"sha256:{hashlib.sha256(arc['payload']).hexdigest()}"}
                    if x := to.get(i):
                        fields |= {
                            "WARC-Profile": "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest",
                            "WARC-Refers-To": f"<{record_urn(x['archive'], x['at'])}>", "WARC-Refers-To-Target-URI": x["uri"],
                        }
                    members.append(gzip.compress(warc_record("revisit" if x else "response", record_urn(name, i), arc, fields), 1, mtime=0))
                yield pa.record_batch([pa.array([name.replace(".arc.gz", ".warc.gz")]), pa.array([b"".join(members)], pa.binary())], names=["archive", "data"])

    them = revisits(materialise(index(legacy), "index"))
    return legacy.join(them, "archive", "left").select("archive", "data", "them").mapInArrow(run, "archive string, data binary")


def read_back(archives: DataFrame) -> DataFrame:
    """Per record: page_id, payload_bytes, payload_digest, record_type, refers_to, target_uri, record_id.

    A response's size and digest are taken from its block, a revisit's from its header fields and HTTP message; the page
    that a revisit refers to is that of the record it names.
    """
    ship(archives.sparkSession)
    schema = "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to_id string, target_uri string, record_id string"

    def run(batches):
        for b in batches:
            for k in range(b.num_rows):
                rows = []
                for head, block in parse_warc(members_of(b.column(0)[k].as_py())):
                    if (kind := head["WARC-Type"]) not in ("response", "revisit"):
                        continue
                    payload, declared = block.partition(b"\r\n\r\n")[2], head["WARC-Payload-Digest"].partition(":")[2]
                    digest, size = (hashlib.sha256(payload).hexdigest(), len(payload)) if kind == "response" else (declared, int(http_fields(block)["Content-Length"]))
                    if digest != declared:
                        raise ValueError(f"digest of {head['WARC-Record-ID']} differs")
                    rows.append((page_of(block), size, digest, kind, head.get("WARC-Refers-To"), head["WARC-Target-URI"], head["WARC-Record-ID"]))
                kinds = [pa.int64(), pa.int64(), *[pa.string()] * 5]
                yield pa.record_batch([pa.array(c, kind) for c, kind in zip(list(zip(*rows)) or [[]] * 7, kinds)], names=[x.split()[0] for x in schema.split(", ")])

    found = materialise(archives.select("data").mapInArrow(run, schema), "records")
    named = found.select(F.col("record_id").alias("refers_to_id"), F.col("page_id").alias("refers_to")).join(found.select("refers_to_id").where("refers_to_id is not null").distinct(), "refers_to_id", "left_semi")
    return found.join(named, "refers_to_id", "left").select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "target_uri", "record_id")


def round_trip(pages: DataFrame) -> DataFrame:
    """Lay all pages down as ARC archives, convert these to WARC archives and read the archives."""
    # members are compressed already
    legacy = materialise(lay_down(pages), "arc", "uncompressed")
    archives = materialise(convert(legacy), "warc", "uncompressed")
    release(legacy)
    return read_back(archives)


def export(archives: DataFrame, folder: str) -> None:
    """Write each archive as a file (on storage that the workers mount)."""

    def write(batches):
        for b in batches:
            for name, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                with open(f"{folder}/{name}", "wb") as f:
                    f.write(data)
            yield b.select([0])

    archives.select("archive", "data").mapInArrow(write, "archive string").count()
