"""WARC records in ZIP packages: writer, directory parser, range reader.

A package is a ZIP archive of stored members: archive/data.warc.gz (a gzip member per record, so that each can be read alone)
and indexes/index.cdxj (offset and length of each record). The reader takes the end record, the ZIP64 records where there are
any, and the central directory from the archive's tail, finds the stored members, reads the index and then only the byte ranges
of records; nothing is extracted. Packages live in a folder that all executors reach by a pyarrow file system URI (file, s3,
gs, hdfs). A writer task gives its package a fresh name and returns it; only packages of successful tasks are in the manifest,
so a task may be lost and run again.

Defined cases: null html is an empty payload; equal payloads below the limit are all responses; among equal larger payloads the
largest page_id is the response (all rows that have it, if repeated; null counts as least); empty tables give no package; extra
columns are ignored; a package without the members, or with compressed ones, raises ValueError.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import json
import re
import struct
import uuid
import zipfile
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import fresh_dir, materialise

DATA, INDEX = "archive/data.warc.gz", "indexes/index.cdxj"
#: Payloads from this size are stored once; a package ends after so many bytes; a read covers at most so many.
DEDUP_BYTES, PACKAGE_BYTES, READ_BYTES = 1000, 128 << 20, 4 << 20
DATE = "1970-01-01T00:00:00Z"
#: Fixed values of the ZIP format.
END, END64, LOCATOR64, ENTRY, LOCAL = b"PK\5\6", b"PK\6\6", b"PK\6\7", b"PK\1\2", b"PK\3\4"
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


# ---- records

def record_bytes(page_id, url: str | None, payload: bytes, refers_to=None, revisit: bool = False) -> bytes:
    """One gzip member with a response record, or a revisit that names the record with the payload."""
    text = lambda x: "" if x is None else re.sub(r"[\r\n]", " ", str(x))
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    digest = base64.b32encode(hashlib.sha1(payload).digest()).decode()
    head = {"WARC-Type": "revisit" if revisit else "response", "WARC-Record-ID": f"<urn:page:{text(page_id)}>", "WARC-Date": DATE, "WARC-Target-URI": text(url)}
    if revisit:
        head |= {"WARC-Refers-To": f"<urn:page:{text(refers_to)}>", "WARC-Profile": _PROFILE}
    block = http if revisit else http + payload
    head |= {"WARC-Payload-Digest": f"sha1:{digest}", "Content-Type": "application/http; msgtype=response", "Content-Length": str(len(block))}
    lines = "".join(f"{k}: {v}\r\n" for k, v in head.items()).encode("utf-8", "surrogatepass")
    return gzip.compress(b"WARC/1.1\r\n" + lines + b"\r\n" + block + b"\r\n\r\n", 5, mtime=0)


@dataclass
class Record:
    kind: str
    record_id: str
    refers_to: str | None
    url: str
    payload: bytes | None
    payload_bytes: int
    payload_digest: str


def parse_record(raw: bytes) -> Record:
    """A record from its gzip member; the digest of a response is checked against its payload."""
    data = gzip.decompress(raw)
    head, _, rest = data.partition(b"\r\n\r\n")
    first, *lines = head.decode("utf-8", "surrogatepass").split("\r\n")
    if not first.startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines)
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    size = int(re.search(rb"\r\nContent-Length: (\d+)", http)[1])
    digest = base64.b32decode(fields["WARC-Payload-Digest"].removeprefix("sha1:")).hex()
    kind, ident = fields["WARC-Type"], lambda x: x[len("<urn:page:") : -1]
    if kind == "response" and (len(payload) != size or hashlib.sha1(payload).hexdigest() != digest):
        raise ValueError(f"{fields['WARC-Record-ID']}: payload and digest differ")
    refers = ident(fields["WARC-Refers-To"]) if kind == "revisit" else None
    return Record(kind, ident(fields["WARC-Record-ID"]), refers, fields.get("WARC-Target-URI", ""), payload if kind == "response" else None, size, digest)


# ---- packages

class PackageWriter:
    """Streams records into a ZIP package; needs no seek on the output. force_zip64 writes the large-file records always."""

    def __init__(self, out, force_zip64: bool = True):
        self.zip = zipfile.ZipFile(out, "w", zipfile.ZIP_STORED)
        self.member = self.zip.open(zipfile.ZipInfo(DATA), "w", force_zip64=force_zip64)
        self.index, self.at = io.BytesIO(), 0

    def add(self, key: str, kind: str, raw: bytes) -> None:
        line = json.dumps({"filename": "data.warc.gz", "offset": self.at, "length": len(raw), "type": kind})
        self.index.write(f"{key} {DATE} {line}\n".encode("utf-8", "surrogatepass"))
        self.member.write(raw)
        self.at += len(raw)

    def close(self) -> None:
        self.member.close()
        self.zip.writestr(zipfile.ZipInfo(INDEX), self.index.getvalue())
        self.zip.close()


@dataclass
class Member:
    name: str
    method: int
    size: int
    header_at: int


class PackageReader:
    """Directory and members of a ZIP package over range reads. source: read_at(length, offset), and its size."""

    def __init__(self, read_at, size: int):
        self.read_at, self.size = read_at, size
        self.members = {m.name: m for m in self._directory()}

    def _directory(self) -> Iterator[Member]:
        tail_at = max(0, self.size - (1 << 16) - 22)
        tail = self.read_at(self.size - tail_at, tail_at)
        at = tail.rfind(END)
        while at >= 0 and at + 22 + struct.unpack_from("<H", tail, at + 20)[0] != len(tail):
            at = tail.rfind(END, 0, at)  # those bytes stood in a comment
        if at < 0:
            raise ValueError("no end of central directory")
        count, length, start = struct.unpack_from("<H2L", tail, at + 10)
        if 0xFFFF == count or 0xFFFFFFFF in (length, start):
            locator = self.read_at(20, tail_at + at - 20)
            if locator[:4] != LOCATOR64:
                raise ValueError("no ZIP64 locator")
            end = self.read_at(56, struct.unpack_from("<Q", locator, 8)[0])
            if end[:4] != END64:
                raise ValueError("no ZIP64 end record")
            count, length, start = struct.unpack_from("<3Q", end, 32)
        data, at = self.read_at(length, start), 0
        for _ in range(count):
            if data[at : at + 4] != ENTRY:
                raise ValueError("broken central directory")
            flags, method = struct.unpack_from("<2H", data, at + 8)
            packed, plain = struct.unpack_from("<2L", data, at + 20)
            n_name, n_extra, n_note = struct.unpack_from("<3H", data, at + 28)
            header_at = struct.unpack_from("<L", data, at + 42)[0]
            name = data[at + 46 : at + 46 + n_name].decode("utf-8" if flags & 0x800 else "cp437")
            extra = data[at + 46 + n_name : at + 46 + n_name + n_extra]
            plain, packed, header_at = self._wide(extra, [plain, packed, header_at])
            yield Member(name, method, plain, header_at)
            at += 46 + n_name + n_extra + n_note

    @staticmethod
    def _wide(extra: bytes, values: list[int]) -> list[int]:
        """Values of all ones are replaced, in order, by those of the ZIP64 extra field."""
        at = 0
        while at + 4 <= len(extra):
            tag, n = struct.unpack_from("<2H", extra, at)
            if tag == 1:
                wide = iter(struct.unpack_from(f"<{n // 8}Q", extra, at + 4))
                return [next(wide) if v == 0xFFFFFFFF else v for v in values]
            at += 4 + n
        return values

    def data_at(self, name: str) -> tuple[int, int]:
        """Offset in the archive and length of a stored member's bytes."""
        m = self.members.get(name)
        if m is None or m.method != 0:
            raise ValueError(f"no stored member {name}")
        head = self.read_at(30, m.header_at)
        if head[:4] != LOCAL:
            raise ValueError(f"broken header of {name}")
        n_name, n_extra = struct.unpack_from("<2H", head, 26)
        return m.header_at + 30 + n_name + n_extra, m.size

    def index(self) -> list[tuple[int, int]]:
        """Offset and length in the archive of each record, from the index member."""
        at, n = self.data_at(INDEX)
        base, _ = self.data_at(DATA)
        rows = [json.loads(x.split(b" ", 2)[2]) for x in self.read_at(n, at).splitlines()]
        return [(base + r["offset"], r["length"]) for r in rows]


def open_package(uri: str) -> PackageReader:
    from pyarrow import fs

    system, path = fs.FileSystem.from_uri(uri)
    file = system.open_input_file(path)
    return PackageReader(lambda n, at: file.read_at(n, at), file.size())


# ---- Spark

def with_roles(pages: DataFrame, least_bytes: int = DEDUP_BYTES) -> DataFrame:
    """page_id, url, html, revisit, refers_to. Payloads are grouped by two hashes and length, combined before the shuffle."""
    html = F.coalesce(F.col("html"), F.lit(""))
    rows = pages.select("page_id", "url", html.alias("html"))
    key = [F.sha1(html).alias("k1"), F.xxhash64(html).alias("k2"), F.octet_length(html).alias("k3")]
    groups = pages.select("page_id", *key).where(F.col("k3") >= least_bytes).groupBy("k1", "k2", "k3")
    twins = groups.agg(F.max("page_id").alias("target"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    joined = rows.withColumns({"r1": F.sha1("html"), "r2": F.xxhash64("html"), "r3": F.octet_length("html")})
    joined = joined.join(twins, (F.col("r1") == F.col("k1")) & (F.col("r2") == F.col("k2")) & (F.col("r3") == F.col("k3")), "left")
    revisit = F.col("k1").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("target"))
    return joined.select("page_id", "url", "html", revisit.alias("revisit"), F.when(revisit, F.col("target")).alias("refers_to"))


def write_packages(pages: DataFrame, folder: str, least_bytes: int = DEDUP_BYTES, package_bytes: int = PACKAGE_BYTES) -> DataFrame:
    """Writes all pages; the manifest (path, records, bytes) has a row per package."""

    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        system, root = fs.FileSystem.from_uri(folder)
        done, writer, out = [], None, None

        def close() -> None:
            nonlocal writer
            writer.close()
            out.close()
            done[-1][1:] = [done[-1][1], writer.at]
            writer = None

        for b in it:
            for page_id, url, html, revisit, refers in zip(*(b.column(c) for c in ("page_id", "url", "html", "revisit", "refers_to"))):
                if writer is None:
                    system.create_dir(root, recursive=True)
                    name = f"pages-{uuid.uuid4().hex}.wacz"
                    out = system.open_output_stream(f"{root}/{name}")
                    writer = PackageWriter(out)
                    done.append([f"{folder}/{name}", 0, 0])
                raw = record_bytes(page_id.as_py(), url.as_py(), html.as_py().encode("utf-8", "surrogatepass"), refers.as_py(), revisit.as_py())
                writer.add(str(done[-1][1]), "revisit" if revisit.as_py() else "response", raw)
                done[-1][1] += 1
                if writer.at >= package_bytes:
                    close()
        if writer is not None:
            close()
        yield pa.RecordBatch.from_arrays([pa.array([d[i] for d in done], t) for i, t in enumerate((pa.string(), pa.int64(), pa.int64()))], names=["path", "records", "bytes"])

    return materialise(with_roles(pages, least_bytes).mapInArrow(batches, "path string, records bigint, bytes bigint"), "warc-manifest")


def read_packages(manifest: DataFrame, id_type: str = "bigint") -> DataFrame:
    """A row per record of the packages: page_id, payload_bytes, payload_digest, record_type, refers_to, url, html, path, offset.

    The first step reads directories and indexes and lists byte ranges of at most READ_BYTES; these are dealt out anew, so a
    large package is read by many tasks.
    """

    def ranges(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for path in b.column("path").to_pylist():
                rows, group, start = [], [], 0
                for at, n in open_package(path).index():
                    if group and at + n - start > READ_BYTES:
                        rows.append(group)
                        group = []
                    start = at if not group else start
                    group.append((at, n))
                rows += [group] if group else []
                yield pa.RecordBatch.from_arrays([pa.array([path] * len(rows), pa.string()), *(pa.array([[x[i] for x in r] for r in rows], pa.list_(pa.int64())) for i in (0, 1))], names=["path", "ats", "ns"])

    def records(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for path, ats, ns in zip(b.column("path").to_pylist(), b.column("ats").to_pylist(), b.column("ns").to_pylist()):
                data = open_package_file(path, ats[0], ats[-1] + ns[-1] - ats[0])
                got = [parse_record(data[a - ats[0] : a - ats[0] + n]) for a, n in zip(ats, ns)]
                text = lambda xs: pa.array(xs, pa.string())
                yield pa.RecordBatch.from_arrays(
                    [text([r.record_id or None for r in got]), pa.array([r.payload_bytes for r in got], pa.int64()), text([r.payload_digest for r in got]), text([r.kind for r in got]), text([r.refers_to for r in got]), text([r.url for r in got]),
                     text([None if r.payload is None else r.payload.decode("utf-8", "replace") for r in got]), text([path] * len(got)), pa.array(ats, pa.int64())],
                    names=["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url", "html", "path", "offset"],
                )

    n = manifest.sparkSession.sparkContext.defaultParallelism
    todo = manifest.repartition("path").mapInArrow(ranges, "path string, ats array<bigint>, ns array<bigint>").repartition(4 * n)
    rows = todo.mapInArrow(records, "page_id string, payload_bytes bigint, payload_digest string, record_type string, refers_to string, url string, html string, path string, offset bigint")
    return rows.withColumn("page_id", F.col("page_id").cast(id_type)).withColumn("refers_to", F.col("refers_to").cast(id_type))


def open_package_file(uri: str, at: int, n: int) -> bytes:
    from pyarrow import fs

    system, path = fs.FileSystem.from_uri(uri)
    with system.open_input_file(path) as file:
        return file.read_at(n, at)


def op1_warc(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    manifest = write_packages(pages, fresh_dir(spark, "warc"))
    return read_packages(manifest, pages.schema["page_id"].dataType.simpleString()).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
m AS (SELECT *, max(page_id) OVER (PARTITION BY h) AS last FROM p)
SELECT page_id, octet_length(encode(h))::BIGINT AS payload_bytes, sha1(h) AS payload_digest,
  CASE WHEN octet_length(encode(h)) >= 1000 AND page_id IS DISTINCT FROM last THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN octet_length(encode(h)) >= 1000 AND page_id IS DISTINCT FROM last THEN last END AS refers_to
FROM m
"""
