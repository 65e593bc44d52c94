"""Web archives packaged in ZIP files: writer and reader.

A package holds stored (not compressed) members: `archive/data.warc.gz`, one gzip member per WARC record, and `indexes/index.cdxj`,
a sorted line per record with its offset and length. The reader opens a package by its tail: end record, ZIP64 end record where
the plain fields overflow, central directory, local header; then it reads the index member and fetches records by byte
range inside the stored archive. Nothing is extracted, and a package is split into ranges of index lines for parallel reading.

Packages go to and come from any store that pyarrow's file systems open, in the folder that all executors share.

Defined results: a null html is an empty payload; payloads under `least_bytes` are always responses; of equal longer payloads
the one of the largest page_id is the response (rows that repeat that id are all responses) and the others revisit it; a null
page_id counts as smaller than any; null urls are recorded as `urn:page:<id>`; other columns are ignored.
"""

from __future__ import annotations

import gzip
import hashlib
import json
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from datetime import UTC, datetime

import pyarrow as pa
import xxhash
from pyarrow import fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from labelflow.llm.common import binary_text, join_groups, materialise, new_path

#: Signatures and sizes of the ZIP format, and the WARC version line: fixed values.
LOCAL, CENTRAL, END, END64, LOCATOR64 = b"PK\x03\x04", b"PK\x01\x02", b"PK\x05\x06", b"PK\x06\x06", b"PK\x06\x07"
LOCAL_FIELDS, CENTRAL_FIELDS, END_FIELDS = "<4s5H3I2H", "<4s6H3I5H2I", "<4s4H2IH"
END64_FIELDS, LOCATOR64_FIELDS = "<4sQ2H2I4Q", "<4sIQI"
WARC_VERSION = b"WARC/1.1\r\n"
FULL16, FULL32 = 0xFFFF, 0xFFFFFFFF
DATA, INDEX = "archive/data.warc.gz", "indexes/index.cdxj"
#: Packages are closed at about this many bytes.
PACKAGE_BYTES = 256 << 20
LINES_PER_SPLIT = 2_000
LEAST_BYTES = 1000
_WHEN = datetime(2024, 1, 1, tzinfo=UTC).strftime("%Y-%m-%dT%H:%M:%SZ")


# ---- ZIP ------------------------------------------------------------------------------------------------------------


@dataclass
class Member:
    name: str
    size: int
    crc: int
    header_at: int
    method: int = 0


class PackageWriter:
    """Writes stored members to a stream one after another; sizes need not be known, as a descriptor follows each member."""

    def __init__(self, stream, zip64: bool = False):
        self.stream, self.at, self.members, self.zip64 = stream, 0, [], zip64

    def _put(self, data: bytes) -> None:
        self.stream.write(data)
        self.at += len(data)

    def begin(self, name: str) -> None:
        raw = name.encode()
        self.members.append(Member(name, 0, 0, self.at))
        self._put(struct.pack(LOCAL_FIELDS, LOCAL, 45, 0x0808, 0, 0, 0x5821, 0, 0, 0, len(raw), 0) + raw)

    def write(self, data: bytes) -> int:
        """Appends to the open member; returns the offset inside it."""
        m = self.members[-1]
        offset = m.size
        self._put(data)
        m.size += len(data)
        m.crc = zlib.crc32(data, m.crc)
        return offset

    def end(self) -> None:
        m = self.members[-1]
        big = self.zip64 or m.size >= FULL32
        self._put(struct.pack("<4sI" + ("2Q" if big else "2I"), b"PK\x07\x08", m.crc, m.size, m.size))

    def close(self) -> None:
        start = self.at
        for m in self.members:
            raw = m.name.encode()
            big = self.zip64 or m.size >= FULL32 or m.header_at >= FULL32
            extra = struct.pack("<2H3Q", 1, 24, m.size, m.size, m.header_at) if big else b""
            size, at = (FULL32, FULL32) if big else (m.size, m.header_at)
            self._put(struct.pack(CENTRAL_FIELDS, CENTRAL, 45, 45, 0x0808, 0, 0, 0x5821, m.crc, size, size, len(raw), len(extra), 0, 0, 0, 0, at) + raw + extra)
        length, n = self.at - start, len(self.members)
        if self.zip64 or start >= FULL32 or length >= FULL32 or n >= FULL16:
            here = self.at
            self._put(struct.pack(END64_FIELDS, END64, 44, 45, 45, 0, 0, n, n, length, start))
            self._put(struct.pack(LOCATOR64_FIELDS, LOCATOR64, 0, here, 1))
            n, length, start = FULL16, FULL32, FULL32
        self._put(struct.pack(END_FIELDS, END, 0, 0, n, n, length, start, 0))


class PackageReader:
    """Directory and byte ranges of a package; reads only what is asked for."""

    def __init__(self, file, size: int):
        self.file, self.size = file, size
        self.members = {m.name: m for m in self._directory()}

    def _range(self, at: int, n: int) -> bytes:
        self.file.seek(at)
        return self.file.read(n)

    def _directory(self) -> Iterator[Member]:
        tail_at = max(0, self.size - (FULL16 + struct.calcsize(END_FIELDS)))
        tail = self._range(tail_at, self.size - tail_at)
        spot = tail.rfind(END)
        if spot < 0:
            raise ValueError("not a ZIP package: no end record")
        _, _, _, _, n, length, start, _ = struct.unpack_from(END_FIELDS, tail, spot)
        if n == FULL16 or length == FULL32 or start == FULL32:
            locator = self._range(tail_at + spot - struct.calcsize(LOCATOR64_FIELDS), struct.calcsize(LOCATOR64_FIELDS))
            sign, _, end64_at, _ = struct.unpack(LOCATOR64_FIELDS, locator)
            if sign != LOCATOR64:
                raise ValueError("ZIP64 locator missing")
            fields = struct.unpack(END64_FIELDS, self._range(end64_at, struct.calcsize(END64_FIELDS)))
            n, length, start = fields[7], fields[8], fields[9]
        raw, at, head = self._range(start, length), 0, struct.calcsize(CENTRAL_FIELDS)
        for _ in range(n):
            f = struct.unpack_from(CENTRAL_FIELDS, raw, at)
            if f[0] != CENTRAL:
                raise ValueError("central directory damaged")
            method, crc, packed, size, name_n, extra_n, note_n, header_at = f[4], f[7], f[8], f[9], f[10], f[11], f[12], f[16]
            name = raw[at + head : at + head + name_n].decode()
            extra = raw[at + head + name_n : at + head + name_n + extra_n]
            while len(extra) >= 4:
                kind, n_bytes = struct.unpack_from("<2H", extra)
                if kind == 1:  # the wide fields, present for those that overflow, in this order
                    wide = list(struct.unpack_from(f"<{n_bytes // 8}Q", extra, 4))
                    size = wide.pop(0) if size == FULL32 else size
                    packed = wide.pop(0) if packed == FULL32 else packed
                    header_at = wide.pop(0) if header_at == FULL32 else header_at
                extra = extra[4 + n_bytes :]
            yield Member(name, size, crc, header_at, method)
            at += head + name_n + extra_n + note_n

    def data_at(self, name: str) -> int:
        """Offset in the package of a stored member's first byte."""
        m = self.members[name]
        if m.method:
            raise ValueError(f"{name} is compressed, not stored")
        f = struct.unpack(LOCAL_FIELDS, self._range(m.header_at, struct.calcsize(LOCAL_FIELDS)))
        if f[0] != LOCAL:
            raise ValueError("local header damaged")
        return m.header_at + struct.calcsize(LOCAL_FIELDS) + f[9] + f[10]

    def read(self, name: str, at: int = 0, n: int | None = None) -> bytes:
        """Bytes of a stored member, without the rest of it."""
        m = self.members[name]
        return self._range(self.data_at(name) + at, m.size - at if n is None else n)


# ---- WARC -----------------------------------------------------------------------------------------------------------


def warc_record(page_id: int | None, url: str, digest: str, size: int, kind: str, refers_to: int | None, payload: bytes) -> bytes:
    """One record as a gzip member; a revisit carries headers and no payload."""
    body = payload if kind == "response" else b""
    head = {
        "WARC-Type": kind,
        "WARC-Record-ID": f"<urn:page:{page_id}>",
        "WARC-Date": _WHEN,
        "WARC-Target-URI": url,
        "WARC-Payload-Digest": f"sha1:{digest}",
        "Content-Type": "application/http; msgtype=response",
    }
    if kind == "revisit":
        head |= {"WARC-Profile": "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", "WARC-Refers-To": f"<urn:page:{refers_to}>"}
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {size}\r\n\r\n".encode()
    head["Content-Length"] = str(len(http) + len(body))
    lines = "".join(f"{k}: {v.replace(chr(13), '%0D').replace(chr(10), '%0A')}\r\n" for k, v in head.items()).encode()
    return gzip.compress(WARC_VERSION + lines + b"\r\n" + http + body + b"\r\n\r\n", compresslevel=5, mtime=0)


def parse_record(raw: bytes) -> tuple[dict[str, str], dict[str, str], bytes]:
    """WARC headers, HTTP headers and payload of one gzip member."""
    data = gzip.decompress(raw)
    if not data.startswith(WARC_VERSION):
        raise ValueError("not a WARC record")
    head, _, rest = data.partition(b"\r\n\r\n")
    headers = dict(x.split(": ", 1) for x in head.decode().split("\r\n")[1:])
    block = rest[: int(headers["Content-Length"])]
    http, _, body = block.partition(b"\r\n\r\n")
    return headers, dict(x.split(": ", 1) for x in http.decode().split("\r\n")[1:]), body


def _page_of(urn: str) -> int | None:
    found = urn.removeprefix("<urn:page:").removesuffix(">")
    return None if found == "None" else int(found)


# ---- Spark ----------------------------------------------------------------------------------------------------------


def plan_records(pages: DataFrame, least_bytes: int = LEAST_BYTES) -> DataFrame:
    """page_id, url, payload, payload_bytes, payload_digest, record_type, refers_to. Only repeated payloads take part in the
    lookup, and the pages of a payload that many share are dealt over tasks."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.coalesce(F.col("url"), F.concat(F.lit("urn:page:"), F.coalesce(F.col("page_id").cast("string"), F.lit("None")))).alias("url"), binary_text("html").alias("payload"))
    rows = rows.withColumn("payload_bytes", F.length("payload").cast("long")).withColumn("payload_digest", F.sha1("payload"))
    long_enough = F.col("payload_bytes") >= least_bytes
    keys = rows.filter(long_enough).groupBy("payload_digest", "payload_bytes").agg(F.max("page_id").alias("first_id"), F.count("*").alias("copies")).filter("copies > 1")
    out = join_groups(rows, keys, ["payload_digest", "payload_bytes"], "copies", ["page_id", "url"])
    revisit = F.col("first_id").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first_id"))
    return out.select("page_id", "url", "payload", "payload_bytes", "payload_digest", F.when(revisit, F.lit("revisit")).otherwise(F.lit("response")).alias("record_type"), F.when(revisit, F.col("first_id")).alias("refers_to"))


def _write_packages(folder: str, package_bytes: int, zip64: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = pafs.FileSystem.from_uri(folder)
        store.create_dir(root, recursive=True)
        open_now = None

        def start():
            name = xxhash.xxh64_hexdigest(__import__("os").urandom(16))
            stream = store.open_output_stream(f"{root}/.{name}.part")
            writer = PackageWriter(stream, zip64)
            writer.begin(DATA)
            return name, stream, writer, []

        def finish(name, stream, writer, lines) -> pa.RecordBatch:
            writer.end()
            writer.begin(INDEX)
            writer.write("".join(sorted(lines)).encode())
            writer.end()
            writer.close()
            stream.close()
            store.move(f"{root}/.{name}.part", f"{root}/{name}.wacz")
            return pa.RecordBatch.from_arrays([pa.array([f"{folder}/{name}.wacz"]), pa.array([len(lines)], pa.int64()), pa.array([writer.at], pa.int64())], names=["path", "n_records", "size"])

        for batch in batches:
            cols = [batch.column(i).to_pylist() for i in range(7)]
            for page_id, url, payload, size, digest, kind, refers_to in zip(*cols, strict=True):
                if open_now is None:
                    open_now = start()
                raw = warc_record(page_id, url, digest, size, kind, refers_to, payload)
                at = open_now[2].write(raw)
                entry = {"url": url, "digest": f"sha1:{digest}", "offset": at, "length": len(raw), "filename": DATA}
                open_now[3].append(f"{url.split('#')[0].lower().replace(' ', '%20').replace(chr(10), '%0A')} {page_id} {json.dumps(entry)}\n")
                if open_now[2].at >= package_bytes:
                    yield finish(*open_now)
                    open_now = None
        if open_now is not None:
            yield finish(*open_now)

    return run


def write_packages(records: DataFrame, folder: str, package_bytes: int = PACKAGE_BYTES, zip64: bool = False) -> DataFrame:
    """Writes planned records as packages under the folder; returns the manifest (path, n_records, size). The manifest names the
    packages of tasks that succeeded; what a failed attempt left is not in it."""
    cols = records.select("page_id", "url", "payload", "payload_bytes", "payload_digest", "record_type", "refers_to")
    return materialise(cols.mapInArrow(_write_packages(folder, package_bytes, zip64), "path string, n_records long, size long"), "packages")


def _read_splits(lines_each: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, size, first in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                store, where = pafs.FileSystem.from_uri(path)
                with store.open_input_file(where) as f:
                    package = PackageReader(f, size)
                    lines = package.read(INDEX).splitlines()[first : first + lines_each]
                    base = package.data_at(DATA)
                    rows = []
                    for line in lines:
                        entry = json.loads(line[line.index(b"{") :])
                        headers, http, body = parse_record(package._range(base + entry["offset"], entry["length"]))
                        kind = headers["WARC-Type"]
                        digest = hashlib.sha1(body).hexdigest() if kind == "response" else headers["WARC-Payload-Digest"].removeprefix("sha1:")
                        n = len(body) if kind == "response" else int(http["Content-Length"])
                        rows.append((_page_of(headers["WARC-Record-ID"]), headers["WARC-Target-URI"], n, digest, kind, _page_of(headers["WARC-Refers-To"]) if kind == "revisit" else None, body))
                kinds = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"])

    return run


def read_packages(manifest: DataFrame, lines_each: int = LINES_PER_SPLIT) -> DataFrame:
    """Records of all packages of a manifest (path, n_records, size): ranges of index lines are dealt over tasks."""
    splits = manifest.filter("n_records > 0").select("path", "size", F.explode(F.expr(f"sequence(0L, n_records - 1, {lines_each}L)")).alias("first"))
    spread = splits.repartition(max(1, int(splits.sparkSession.conf.get("spark.sql.shuffle.partitions"))), "path", "first")
    return spread.mapInArrow(_read_splits(lines_each), "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary")


def round_trip(pages: DataFrame) -> DataFrame:
    """Writes the pages' archives to the shared folder and reads them back."""
    folder = new_path(pages.sparkSession, "archives")
    return read_packages(write_packages(plan_records(pages), folder))
