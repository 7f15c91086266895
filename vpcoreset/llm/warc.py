"""Web archives in ZIP packages: writing, and reading by ranges without extraction.

A package is a ZIP file of stored members: ``archive/data.warc.gz`` (one gzip member a record),
``indexes/index.cdxj`` (a line a record: page, offset and length inside the archive member) and ``datapackage.json``.
The reader finds the end-of-directory record at the file's tail, follows ZIP64 records where
sizes or counts overflow, parses the central directory, locates the stored members, reads the index,
and then reads each record as a byte range of the file. Nothing is unpacked to disk.

Files are written and read through ``pyarrow.fs`` by the executors, in the shared folder. A writer task
names its file after the attempt and only files named by committed tasks are read, so lost executors and
speculative attempts leave unread files at worst.

Duplicates: of pages with equal payloads of at least ``least`` bytes the one with the largest id is the
response, the others are revisit records without payload that name it.

Defined results: a null payload is empty; smaller payloads are always responses; pages that repeat id and
payload are written and returned each, those of the response as responses;
a page without an id is a response, and read back without one; an empty table writes no file and gives no row; columns other than id, url and html are ignored.
"""

from __future__ import annotations

import gzip
import hashlib
import json
import struct
import uuid
import zlib
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpcoreset.llm.common import scratch, stored

# Signatures and field sizes of the ZIP format.
LOCAL, CENTRAL, END, END64, LOCATOR64 = b"PK\x03\x04", b"PK\x01\x02", b"PK\x05\x06", b"PK\x06\x06", b"PK\x06\x07"
FULL16, FULL32 = 0xFFFF, 0xFFFFFFFF
ARCHIVE, INDEX, PACKAGE = "archive/data.warc.gz", "indexes/index.cdxj", "datapackage.json"
DATE = "2024-01-01T00:00:00Z"


def open_path(path: str):
    """(file system, path inside it) of a URI or plain path."""
    from pyarrow import fs

    if "://" not in path:
        path = "file://" + path.removeprefix("file:")
    return fs.FileSystem.from_uri(path)


# ---- writing


class PackageWriter:
    """Streams records into a stored archive member; the index follows it."""

    def __init__(self, out, force64: bool = False):
        self.out, self.force64, self.at, self.members, self.index = out, force64, 0, [], []
        self._begin(ARCHIVE)

    def _put(self, data: bytes) -> None:
        self.out.write(data)
        self.at += len(data)

    def _begin(self, name: str) -> None:
        self.open = [name, self.at, 0, 0]  # crc and size follow in a descriptor
        raw = name.encode()
        self._put(LOCAL + struct.pack("<HHHHHIIIHH", 45, 0x0808, 0, 0, 33, 0, 0, 0, len(raw), 0) + raw)
        self.start = self.at

    def write(self, data: bytes) -> None:
        self.open[2] = zlib.crc32(data, self.open[2])
        self.open[3] += len(data)
        self._put(data)

    def _end(self) -> None:
        name, at, crc, size = self.open
        wide = self.force64 or size >= FULL32
        self._put(b"PK\x07\x08" + struct.pack("<IQQ" if wide else "<III", crc, size, size))
        self.members.append(self.open)

    def record(self, page_id: str, url: str, kind: str, payload: bytes, digest: str, length: int, refers_to: str | None) -> None:
        block = b"" if kind == "revisit" else payload
        http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {length}\r\n\r\n".encode()
        head = {
            "WARC-Type": kind, "WARC-Target-URI": url.replace("\r", "%0D").replace("\n", "%0A"), "WARC-Date": DATE, "WARC-Record-ID": f"<urn:page:{page_id}>",
            "WARC-Payload-Digest": f"sha1:{digest}", "X-Payload-Length": str(length), "Content-Type": "application/http; msgtype=response",
        }
        if kind == "revisit":
            head |= {"WARC-Profile": "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", "WARC-Refers-To": f"<urn:page:{refers_to}>"}
        head["Content-Length"] = str(len(http) + len(block))
        lines = "".join(f"{k}: {v}\r\n" for k, v in head.items())
        data = gzip.compress(f"WARC/1.1\r\n{lines}\r\n".encode("utf-8", "surrogatepass") + http + block + b"\r\n\r\n", 4, mtime=0)
        self.index.append((page_id, self.at - self.start, len(data)))
        self.write(data)

    def close(self) -> None:
        self._end()
        self._begin(INDEX)
        for page, offset, length in self.index:
            self.write((json.dumps({"page": page, "offset": offset, "length": length}) + "\n").encode())
        self._end()
        self._begin(PACKAGE)
        self.write(json.dumps({"profile": "data-package", "resources": [{"path": ARCHIVE, "records": len(self.index)}, {"path": INDEX}]}).encode())
        self._end()
        directory = self.at
        for name, at, crc, size in self.members:
            wide = self.force64 or size >= FULL32 or at >= FULL32
            raw, extra = name.encode(), struct.pack("<HHQQQ", 1, 24, size, size, at) if wide else b""
            shown = FULL32 if wide else size
            self._put(CENTRAL + struct.pack("<HHHHHHIIIHHHHHII", 45, 45, 0x0808, 0, 0, 33, crc, shown, shown, len(raw), len(extra), 0, 0, 0, 0, FULL32 if wide else at) + raw + extra)
        size, n = self.at - directory, len(self.members)
        wide = self.force64 or directory >= FULL32
        if wide:
            at = self.at
            self._put(END64 + struct.pack("<QHHIIQQQQ", 44, 45, 45, 0, 0, n, n, size, directory) + LOCATOR64 + struct.pack("<IQI", 0, at, 1))
        self._put(END + struct.pack("<HHHHIIH", 0, 0, FULL16 if wide else n, FULL16 if wide else n, FULL32 if wide else size, FULL32 if wide else directory, 0))


def write_packages(records: DataFrame, folder: str) -> DataFrame:
    """Writes (page_id, url, payload, payload_digest, payload_bytes, record_type, refers_to) rows, a package a task; (path, records) of the files written."""

    def write(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        out = None
        for batch in batches:
            for r in batch.itertuples(index=False):
                if out is None:
                    path = f"{folder}/{uuid.uuid4().hex}.wacz"
                    system, inner = open_path(path)
                    system.create_dir(inner.rsplit("/", 1)[0], recursive=True)
                    stream = system.open_output_stream(inner)
                    out = PackageWriter(stream)
                out.record(r.page_id, r.url or "", r.record_type, bytes(r.payload), r.payload_digest, int(r.payload_bytes), r.refers_to)
        if out is not None:
            out.close()
            stream.close()
            yield pd.DataFrame({"path": [path], "records": [len(out.index)]})

    return stored(records.mapInPandas(write, "path string, records long"), "warc-manifest")


# ---- reading


def _zip64(extra: bytes, fields: list[int]) -> list[int]:
    """Fills the fields that are all ones from the ZIP64 extra field, in order."""
    at = 0
    while at + 4 <= len(extra):
        tag, size = struct.unpack_from("<HH", extra, at)
        if tag == 1:
            wide = at + 4
            for i, v in enumerate(fields):
                if v == FULL32 and wide + 8 <= at + 4 + size:
                    fields[i] = struct.unpack_from("<Q", extra, wide)[0]
                    wide += 8
        at += 4 + size
    return fields


def directory(source) -> dict[str, tuple[int, int, int]]:
    """Members of a ZIP file opened for random access: name -> (offset of its data, stored size, method)."""
    size = source.size()
    tail_at = max(0, size - (22 + 65535))
    tail = source.read_at(size - tail_at, tail_at)
    end = tail.rfind(END)
    if end < 0:
        raise ValueError("no end of central directory")
    n, length, start = struct.unpack_from("<HII", tail, end + 10)
    if FULL32 in (length, start) or n == FULL16:
        at = tail_at + end - 20
        locator = source.read_at(20, at)
        if locator[:4] == LOCATOR64:
            at64 = struct.unpack_from("<Q", locator, 8)[0]
            head = source.read_at(56, at64)
            if head[:4] != END64:
                raise ValueError("no ZIP64 end of central directory")
            n, length, start = struct.unpack_from("<QQQ", head, 32)
    raw, at, found = source.read_at(length, start), 0, {}
    for _ in range(n):
        if raw[at : at + 4] != CENTRAL:
            raise ValueError("broken central directory")
        method, = struct.unpack_from("<H", raw, at + 10)
        packed, full, names, extras, notes = struct.unpack_from("<IIHHH", raw, at + 20)
        offset, = struct.unpack_from("<I", raw, at + 42)
        name = raw[at + 46 : at + 46 + names].decode()
        full, packed, offset = _zip64(raw[at + 46 + names : at + 46 + names + extras], [full, packed, offset])
        head = source.read_at(30, offset)
        if head[:4] != LOCAL:
            raise ValueError("broken local header")
        a, b = struct.unpack_from("<HH", head, 26)
        found[name] = (offset + 30 + a + b, packed, method)
        at += 46 + names + extras + notes
    return found


def index_ranges(source) -> Iterator[tuple[int, int]]:
    """(offset, length) in the file of every record, from the index; the members must be stored."""
    members = directory(source)
    archives = [m for name, m in members.items() if name.startswith("archive/")]
    for name, (at, size, method) in members.items():
        if not name.startswith("indexes/"):
            continue
        if method or any(m[2] for m in archives):
            raise ValueError("a member is not stored")
        left, rest = size, b""
        while left or rest:
            step = min(left, 1 << 20)
            lines = (rest + source.read_at(step, at)).split(b"\n")
            at, left, rest = at + step, left - step, lines.pop()
            if not left and rest:
                lines, rest = [*lines, rest], b""
            for line in filter(None, lines):
                entry = json.loads(line)
                yield archives[0][0] + entry["offset"], entry["length"]


def parse_record(data: bytes) -> tuple[dict[str, str], bytes]:
    """Header fields and HTTP payload of one gzip member."""
    raw = gzip.decompress(data)
    head, _, block = raw.partition(b"\r\n\r\n")
    fields = dict(line.split(": ", 1) for line in head.decode("utf-8", "surrogatepass").split("\r\n")[1:])
    block = block[: int(fields["Content-Length"])]
    return fields, block.partition(b"\r\n\r\n")[2]


RECORD = "page_id string, url string, payload binary, payload_bytes long, payload_digest string, record_type string, refers_to string, sound boolean"


def read_packages(manifest: DataFrame, *, chunk: int = 256, payloads: bool = True) -> DataFrame:
    """Records of the packages in the manifest's ``path``; read in ranges of up to ``chunk`` records, by many tasks a file."""

    def ranges(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for path in batch["path"]:
                system, inner = open_path(path)
                with system.open_input_file(inner) as source:
                    held: list[tuple[int, int]] = []
                    for r in index_ranges(source):
                        held.append(r)
                        if len(held) == chunk:
                            yield pd.DataFrame({"path": [path], "at": [[a for a, _ in held]], "size": [[s for _, s in held]]})
                            held = []
                    if held:
                        yield pd.DataFrame({"path": [path], "at": [[a for a, _ in held]], "size": [[s for _, s in held]]})

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for row in batch.itertuples(index=False):
                system, inner = open_path(row.path)
                out = []
                with system.open_input_file(inner) as source:
                    for a, s in zip(row.at, row.size, strict=True):
                        fields, payload = parse_record(source.read_at(int(s), int(a)))
                        page = lambda k: x if (x := fields.get(k, "").removeprefix("<urn:page:").rstrip(">")) not in ("", "none") else None
                        digest, kind = fields["WARC-Payload-Digest"].removeprefix("sha1:"), fields["WARC-Type"]
                        sound = kind == "revisit" or (hashlib.sha1(payload).hexdigest() == digest and len(payload) == int(fields["X-Payload-Length"]))
                        out.append((page("WARC-Record-ID"), fields["WARC-Target-URI"], payload if payloads else None, int(fields["X-Payload-Length"]), digest, kind, page("WARC-Refers-To"), sound))
                yield pd.DataFrame(out, columns=[x.split()[0] for x in RECORD.split(", ")])

    # Counts are given, since ranges are a few bytes a record and would be coalesced into one task, which then reads all archives.
    size = manifest.agg(F.count(F.lit(1)).alias("files"), F.coalesce(F.sum("records"), F.lit(0)).alias("records")).collect()[0]
    files, tasks = min(size["files"], 4096) or 1, min(-(-size["records"] // (8 * chunk)), 65_536) or 1
    spans = manifest.select("path").repartition(files, "path").mapInPandas(ranges, "path string, at array<long>, size array<long>")
    return spans.repartition(tasks, "path", F.element_at("at", 1)).mapInPandas(read, RECORD).withColumns({k: F.col(k).cast("long") for k in ("page_id", "refers_to")})


def plan_records(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", text_col: str = "html", least: int = 1000) -> DataFrame:
    """Each page with its payload and the kind of record it gets."""
    payload = F.encode(F.coalesce(F.col(text_col), F.lit("")), "UTF-8")
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"), payload.alias("payload"))
    rows = rows.withColumns({"payload_digest": F.sha1("payload"), "payload_bytes": F.octet_length("payload").cast("long")})
    # Decided on digests and ids alone; payloads meet only the rows that are to be revisits, by id and digest.
    told = rows.where((F.col("payload_bytes") >= least) & F.col("page_id").isNotNull()).select("page_id", "payload_digest")
    best = told.groupBy("payload_digest").agg(F.max("page_id").alias("best"), F.min("page_id").alias("other")).where("best <> other").drop("other")
    revisits = told.join(best, "payload_digest").where(F.col("page_id") != F.col("best")).distinct()
    rows = rows.join(revisits, ["page_id", "payload_digest"], "left")
    revisit = F.col("best").isNotNull()
    return rows.select(
        F.coalesce(F.col("page_id").cast("string"), F.lit("none")).alias("page_id"), "url", "payload", "payload_digest", "payload_bytes",
        F.when(revisit, "revisit").otherwise("response").alias("record_type"), F.when(revisit, F.col("best").cast("string")).alias("refers_to"))


def archive_round_trip(pages: DataFrame, folder: str | None = None, **names) -> DataFrame:
    """Writes the pages to packages in a shared folder and returns what reading them gives."""
    folder = folder or scratch(pages.sparkSession, "warc")
    manifest = write_packages(plan_records(pages, **names), folder)
    return read_packages(manifest, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "sound")


WARC_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html, sha1(coalesce(html, '')) AS payload_digest, CAST(octet_length(encode(coalesce(html, ''))) AS BIGINT) AS payload_bytes FROM pages),
b AS (SELECT payload_digest, max(page_id) AS best FROM p WHERE payload_bytes >= 1000 GROUP BY 1)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN best <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN best <> page_id THEN best END AS refers_to, true AS sound FROM p LEFT JOIN b USING (payload_digest)
"""
