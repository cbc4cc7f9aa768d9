"""WARC records in ZIP packages: writing them, and reading records by range without extraction.

A package is a ZIP archive with two stored members: ``archive/data.warc.gz``, records that are each
a gzip member of their own, and ``indexes/index.cdxj``, a line for each record with its offset and
length.  The reader looks at the end of the package for the central directory (the ZIP64 one where
counts or offsets need it), finds both members there, and reads single records by their ranges.
"""

from __future__ import annotations

import base64
import hashlib
import json
import os
import struct
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from urllib.parse import unquote, urlparse

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.storage import fresh_path

LEAST_REVISIT = 1000
PACKAGE_BYTES = 64 << 20
_DATA, _INDEX = "archive/data.warc.gz", "indexes/index.cdxj"
# Fixed values of the ZIP and WARC formats.
_LOCAL, _CENTRAL, _END, _END64, _LOCATOR64 = b"PK\x03\x04", b"PK\x01\x02", b"PK\x05\x06", b"PK\x06\x06", b"PK\x06\x07"
_LIMIT16, _LIMIT32, _EXTRA64 = 0xFFFF, 0xFFFFFFFF, 1
_DOS_DATE = 0x21
_DATE = "2000-01-01T00:00:00Z"
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


# ---- records -------------------------------------------------------------------------------------


def record_bytes(page_id: int | None, url: str | None, kind: str, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One WARC/1.1 record as a gzip member.  A revisit carries no payload, its headers describe the full one."""
    head = [
        "WARC/1.1",
        f"WARC-Type: {kind}",
        f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>",
        f"WARC-Date: {_DATE}",
        f"WARC-Payload-Digest: sha1:{base64.b32encode(bytes.fromhex(digest)).decode()}",
        f"X-Payload-Length: {len(payload)}",
    ]
    if url is not None:
        head.append("WARC-Target-URI: " + url.replace("\r", "%0D").replace("\n", "%0A"))
    if kind == "revisit":
        head += [f"WARC-Refers-To: <urn:page:{refers_to}>", f"WARC-Profile: {_PROFILE}"]
    status = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
    body = status if kind == "revisit" else status + payload
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(body)}"]
    squeeze = zlib.compressobj(4, zlib.DEFLATED, 31)
    return squeeze.compress("\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n") + squeeze.flush()


def parse_record(member: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and payload of one gzip member."""
    raw = zlib.decompressobj(31).decompress(member)
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    headers = dict(x.split(": ", 1) for x in lines[1:])
    body = rest[: int(headers["Content-Length"])]
    return headers, body.partition(b"\r\n\r\n")[2]


# ---- packages ------------------------------------------------------------------------------------


def build_package(members: list[tuple[str, list[bytes]]], force64: bool = False) -> Iterator[bytes]:
    """Bytes of a ZIP archive of stored members, each given as a list of chunks; ZIP64 where it is needed."""
    at, central = 0, []
    for name, chunks in members:
        size, crc, encoded = sum(map(len, chunks)), 0, name.encode()
        for c in chunks:
            crc = zlib.crc32(c, crc)
        big = force64 or size >= _LIMIT32 or at >= _LIMIT32
        shown = _LIMIT32 if big else size
        extra = struct.pack("<HHQQ", _EXTRA64, 16, size, size) if big else b""
        version = 45 if big else 20
        local = struct.pack("<4sHHHHHIIIHH", _LOCAL, version, 0x800, 0, 0, _DOS_DATE, crc, shown, shown, len(encoded), len(extra)) + encoded + extra
        central_extra = struct.pack("<HHQQQ", _EXTRA64, 24, size, size, at) if big else b""
        central.append(
            struct.pack("<4sHHHHHHIIIHHHHHII", _CENTRAL, version, version, 0x800, 0, 0, _DOS_DATE, crc, shown, shown, len(encoded), len(central_extra), 0, 0, 0, 0, _LIMIT32 if big else at)
            + encoded
            + central_extra
        )
        yield local
        yield from chunks
        at += len(local) + size
    directory = b"".join(central)
    n, big = len(members), force64 or at >= _LIMIT32 or len(members) >= _LIMIT16
    if big:
        directory += struct.pack("<4sQHHIIQQQQ", _END64, 44, 45, 45, 0, 0, n, n, len(directory), at) + struct.pack("<4sIQI", _LOCATOR64, 0, at + len(b"".join(central)), 1)
    yield directory
    yield struct.pack("<4sHHHHIIH", _END, 0, 0, min(n, _LIMIT16), min(n, _LIMIT16), min(len(b"".join(central)), _LIMIT32), _LIMIT32 if big else at, 0)


@dataclass(frozen=True)
class Member:
    """A stored member: where its bytes begin and how many there are."""

    begin: int
    size: int
    crc: int


def read_directory(read: Callable[[int, int], bytes], size: int) -> dict[str, Member]:
    """Members by name, from the central directory; ``read(offset, length)`` gives a range of the package."""
    tail_at = max(0, size - (22 + _LIMIT16))
    tail = read(tail_at, size - tail_at)
    end = tail.rfind(_END)
    while end >= 0 and (len(tail) < end + 22 or end + 22 + struct.unpack_from("<H", tail, end + 20)[0] != len(tail)):
        end = tail.rfind(_END, 0, end)
    if end < 0:
        raise ValueError("not a ZIP package: no end of central directory")
    count, length, start = struct.unpack_from("<HII", tail, end + 10)
    if _LIMIT16 == count or _LIMIT32 in (length, start):
        at = tail_at + end - 20
        mark, _, where, _ = struct.unpack("<4sIQI", read(at, 20))
        if mark != _LOCATOR64:
            raise ValueError("ZIP64 locator is missing")
        record = read(where, 56)
        if record[:4] != _END64:
            raise ValueError("ZIP64 end of central directory is missing")
        count, length, start = struct.unpack_from("<QQQ", record, 32)
    directory, at, out = read(start, length), 0, {}
    for _ in range(count):
        if directory[at : at + 4] != _CENTRAL:
            raise ValueError("central directory is damaged")
        method, = struct.unpack_from("<H", directory, at + 10)
        crc, packed, plain, n_name, n_extra, n_comment = struct.unpack_from("<IIIHHH", directory, at + 16)
        offset, = struct.unpack_from("<I", directory, at + 42)
        name = directory[at + 46 : at + 46 + n_name].decode()
        extra = directory[at + 46 + n_name : at + 46 + n_name + n_extra]
        wide = _wide_values(extra)
        plain = wide.pop(0) if plain == _LIMIT32 else plain
        packed = wide.pop(0) if packed == _LIMIT32 else packed
        offset = wide.pop(0) if offset == _LIMIT32 else offset
        if method == 0:
            if packed != plain:
                raise ValueError(f"{name}: a stored member's sizes differ")
            head = read(offset, 30)
            if head[:4] != _LOCAL:
                raise ValueError(f"{name}: local header is missing")
            skip = sum(struct.unpack_from("<HH", head, 26))
            out[name] = Member(offset + 30 + skip, plain, crc)
        at += 46 + n_name + n_extra + n_comment
    return out


def _wide_values(extra: bytes) -> list[int]:
    at = 0
    while at + 4 <= len(extra):
        kind, n = struct.unpack_from("<HH", extra, at)
        if kind == _EXTRA64:
            return list(struct.unpack_from(f"<{n // 8}Q", extra, at + 4))
        at += 4 + n
    return []


def read_records(read: Callable[[int, int], bytes], size: int) -> Iterator[tuple[dict[str, str], bytes]]:
    """All records of a package, each by the range that the index names."""
    members = read_directory(read, size)
    data, index = members[_DATA], members[_INDEX]
    listing = read(index.begin, index.size)
    if zlib.crc32(listing) != index.crc:
        raise ValueError("the index is damaged")
    for line in listing.decode().splitlines():
        entry = json.loads(line.split(" ", 2)[2])
        offset, length = int(entry["offset"]), int(entry["length"])
        if not 0 <= offset <= offset + length <= data.size:
            raise ValueError("the index points outside its member")
        yield parse_record(read(data.begin + offset, length))


# ---- Spark ---------------------------------------------------------------------------------------


def plan_records(pages: DataFrame, least: int = LEAST_REVISIT) -> DataFrame:
    """``page_id, url, payload, payload_digest, record_type, refers_to`` for every row of pages.

    Of rows with equal payloads of at least ``least`` bytes the one with the largest page_id is the
    response, the others are revisits of it; rows that repeat that page_id are responses too.
    """
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    rows = pages.select("page_id", "url", payload.alias("payload")).withColumn("payload_digest", F.sha1("payload"))
    keys = pages.select("page_id", F.sha1(payload).alias("payload_digest"), F.octet_length(payload).alias("n")).where(F.col("n") >= least)
    shared = keys.groupBy("payload_digest").agg(F.max("page_id").alias("__largest"), F.count("*").alias("__n")).where("__n > 1").drop("__n")
    joined = rows.join(shared, "payload_digest", "left")
    again = (F.col("__largest").isNotNull()) & ~F.col("page_id").eqNullSafe(F.col("__largest"))
    return joined.select(
        "page_id", "url", "payload", "payload_digest", F.when(again, "revisit").otherwise("response").alias("record_type"), F.when(again, F.col("__largest")).alias("refers_to")
    )


def _local_path(folder: str) -> str | None:
    """The path of a folder that executors reach as files, else None."""
    parts = urlparse(folder)
    return unquote(parts.path) if parts.scheme in ("", "file") else None


def write_packages(records: DataFrame, folder: str, package_bytes: int = PACKAGE_BYTES) -> DataFrame:
    """Write packages of records and return ``package, n_records, n_bytes`` and, if they are not files, ``content``.

    Each task writes packages of about ``package_bytes`` into ``folder``: a file appears under its
    final name only when it is whole, so a task that runs again replaces what its lost copy left.
    Where executors cannot open the folder as files, packages are rows with their bytes instead.
    """
    path = _local_path(folder)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, serial, members, index, held = TaskContext.get().partitionId(), 0, [], [], 0

        def close() -> pa.RecordBatch:
            nonlocal serial, members, index, held
            name = f"pages-{part:06d}-{serial:05d}.zip"
            chunks = build_package([(_DATA, members), (_INDEX, [("\n".join(index) + "\n").encode()])])
            content, size = None, 0
            if path is None:
                content = b"".join(chunks)
                size = len(content)
            else:
                os.makedirs(path, exist_ok=True)
                draft = f"{path}/.{name}.{os.getpid()}.{TaskContext.get().taskAttemptId()}"
                with open(draft, "wb") as f:
                    for c in chunks:
                        size += f.write(c)
                os.replace(draft, f"{path}/{name}")
            out = pa.RecordBatch.from_arrays([pa.array([name]), pa.array([len(index)], pa.int64()), pa.array([size], pa.int64()), pa.array([content], pa.binary())], names=["package", "n_records", "n_bytes", "content"])
            serial, members, index, held = serial + 1, [], [], 0
            return out

        for batch in batches:
            columns = [batch.column(c) for c in ("page_id", "url", "payload", "payload_digest", "record_type", "refers_to")]
            for i in range(batch.num_rows):
                page_id, url, payload, digest, kind, refers_to = (c[i].as_py() for c in columns)
                member = record_bytes(page_id, url, kind, payload, digest, refers_to)
                place = (url or "-").replace(" ", "%20").replace("\n", "%0A").replace("\r", "%0D")
                index.append(f"{place} {_DATE} " + json.dumps({"offset": str(held), "length": str(len(member)), "digest": digest}))
                members.append(member)
                held += len(member)
                if held >= package_bytes:
                    yield close()
        if members:
            yield close()

    return records.select("page_id", "url", "payload", "payload_digest", "record_type", "refers_to").mapInArrow(run, "package string, n_records long, n_bytes long, content binary")


def read_packages(packages: DataFrame, folder: str) -> DataFrame:
    """A row for each record of the listed packages: ``page_id, url, payload_bytes, payload_digest, record_type, refers_to, payload``.

    A response's length and digest are computed from the payload that was read and must agree with
    its headers; a revisit's are those of its headers, which describe the full payload.
    """
    path = _local_path(folder)

    def records(package: str, size: int, content: bytes | None) -> Iterator[tuple[dict[str, str], bytes]]:
        if content is not None:
            yield from read_records(lambda at, n: content[at : at + n], size)
            return
        with open(f"{path}/{package}", "rb") as f:
            def read(at: int, n: int) -> bytes:
                f.seek(at)
                return f.read(n)

            yield from read_records(read, size)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                out, held = [], 0
                for headers, payload in records(row["package"], row["n_bytes"], row["content"]):
                    out.append(_described(headers, payload))
                    held += len(payload)
                    if len(out) >= 1000 or held >= _BATCH_BYTES:
                        yield pa.RecordBatch.from_pylist(out, schema=_ROWS)
                        out, held = [], 0
                if out:
                    yield pa.RecordBatch.from_pylist(out, schema=_ROWS)

    return packages.mapInArrow(run, "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary")


#: Payload bytes after which a batch of records goes on, so that very long pages do not gather in a worker.
_BATCH_BYTES = 16 << 20
_ROWS = pa.schema(
    [("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())]
)


def _described(headers: dict[str, str], payload: bytes) -> dict:
    number = lambda x: int(x) if (x := x.removeprefix("<urn:page:").removesuffix(">")) else None
    kind, size = headers["WARC-Type"], int(headers["X-Payload-Length"])
    digest = base64.b32decode(headers["WARC-Payload-Digest"].removeprefix("sha1:")).hex()
    if kind == "response" and (len(payload) != size or hashlib.sha1(payload).hexdigest() != digest):
        raise ValueError("a record's payload does not match its headers")
    return {
        "page_id": number(headers["WARC-Record-ID"]),
        "url": headers.get("WARC-Target-URI"),
        "payload_bytes": size,
        "payload_digest": digest,
        "record_type": kind,
        "refers_to": number(headers["WARC-Refers-To"]) if kind == "revisit" else None,
        "payload": payload if kind == "response" else None,
    }


def round_trip(pages: DataFrame, package_bytes: int = PACKAGE_BYTES) -> DataFrame:
    """Write a record for every row of ``pages``, then read all packages back.

    A null html is an empty payload; a null url or page_id is left out of the record; repeated rows
    are records each; an empty table gives no package and no row; other columns are not written.
    The list of packages is itself written to the shared folder, so reading starts from whole files.
    """
    spark = pages.sparkSession
    folder = fresh_path(spark, "warc")
    listing = f"{folder}-list"
    write_packages(plan_records(pages), folder, package_bytes).write.parquet(listing)
    packages = spark.read.schema("package string, n_records long, n_bytes long, content binary").parquet(listing)
    return read_packages(packages.repartition(max(1, spark.sparkContext.defaultParallelism)), folder)
