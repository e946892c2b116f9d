"""WARC records in ZIP packages, read by range without extraction.

A package is a ZIP file whose members are stored, not deflated: ``archive/data.warc`` with one
record after the other and ``indexes/index.cdx`` with one line for each record (id, offset,
length). The reader fetches the tail of the file, finds the end record (ZIP64 where sizes,
offsets or counts need it), walks the central directory, resolves each member's local header,
and then reads single records by byte range.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
import zlib

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import materialize, new_folder

# Signatures of the ZIP format.
LOCAL, CENTRAL, END, END64, LOCATOR64 = 0x04034B50, 0x02014B50, 0x06054B50, 0x06064B50, 0x07064B50
WARC_MEMBER, INDEX_MEMBER = "archive/data.warc", "indexes/index.cdx"
SMALLEST_REVISIT = 1000
DATE = "2024-01-01T00:00:00Z"


class StoredZipWriter:
    """Writes stored members front to back; every member gets ZIP64 fields when ``zip64`` or a size asks for it."""

    def __init__(self, sink, zip64: bool = False):
        self.sink, self.zip64, self.at, self.members = sink, zip64, 0, []

    def _put(self, data: bytes) -> None:
        self.sink.write(data)
        self.at += len(data)

    def begin(self, name: str) -> None:
        raw = name.encode()
        self.open = [raw, self.at, 0, 0]
        self._put(struct.pack("<IHHHHHIIIHH", LOCAL, 45, 0x0808, 0, 0, 0x21, 0, 0, 0, len(raw), 0) + raw)

    def write(self, data: bytes) -> int:
        """Adds to the open member; the offset within it at which ``data`` begins."""
        start = self.open[3]
        self._put(data)
        self.open[2], self.open[3] = zlib.crc32(data, self.open[2]), start + len(data)
        return start

    def end(self) -> None:
        _, _, crc, size = self.open
        self._put(struct.pack("<IIQQ" if self._large(size) else "<IIII", 0x08074B50, crc, size, size))
        self.members.append(self.open)

    def _large(self, value: int) -> bool:
        return self.zip64 or value >= 0xFFFFFFFF

    def close(self) -> None:
        start = self.at
        for raw, at, crc, size in self.members:
            extra, size32, at32 = b"", size, at
            if self._large(size):
                extra, size32 = struct.pack("<QQ", size, size), 0xFFFFFFFF
            if self._large(at):
                extra, at32 = extra + struct.pack("<Q", at), 0xFFFFFFFF
            extra = struct.pack("<HH", 1, len(extra)) + extra if extra else b""
            self._put(
                struct.pack("<IHHHHHHIIIHHHHHII", CENTRAL, 45, 45, 0x0808, 0, 0, 0x21, crc, size32, size32, len(raw), len(extra), 0, 0, 0, 0, at32) + raw + extra
            )
        size, count, cut = self.at - start, len(self.members), self.at
        if self._large(start) or self._large(size) or count >= 0xFFFF:
            self._put(struct.pack("<IQHHIIQQQQ", END64, 44, 45, 45, 0, 0, count, count, size, start) + struct.pack("<IIQI", LOCATOR64, 0, cut, 1))
            count, size, start = 0xFFFF, 0xFFFFFFFF, 0xFFFFFFFF
        self._put(struct.pack("<IHHHHIIH", END, 0, 0, count, count, size, start, 0))


class ZipRangeReader:
    """``read(offset, length)`` is all that it needs of a file."""

    def __init__(self, read, size: int):
        self.read, self.size = read, size
        tail_at = max(0, size - 22 - 0xFFFF)
        tail = read(tail_at, size - tail_at)
        at = tail.rfind(struct.pack("<I", END))
        if at < 0:
            raise ValueError("no end of central directory: not a ZIP package")
        count, length, start = struct.unpack_from("<HII", tail, at + 10)
        if (count == 0xFFFF or 0xFFFFFFFF in (length, start)) and tail_at + at >= 20:
            where = read(tail_at + at - 20, 20)
            if struct.unpack_from("<I", where)[0] == LOCATOR64:
                end64 = read(struct.unpack_from("<Q", where, 8)[0], 56)
                if struct.unpack_from("<I", end64)[0] != END64:
                    raise ValueError("broken ZIP64 end record")
                count, length, start = struct.unpack_from("<QQQ", end64, 32)
        self.members = self._directory(read(start, length), count)

    @staticmethod
    def _directory(data: bytes, count: int) -> dict[str, tuple[int, int, int]]:
        """name -> (method, local header offset, size)"""
        found, at = {}, 0
        for _ in range(count):
            if struct.unpack_from("<I", data, at)[0] != CENTRAL:
                raise ValueError("broken central directory")
            method, packed, full, n, m, c, offset = (
                *struct.unpack_from("<H", data, at + 10), *struct.unpack_from("<II", data, at + 20), *struct.unpack_from("<HHH", data, at + 28), *struct.unpack_from("<I", data, at + 42),
            )
            name, extra = data[at + 46 : at + 46 + n].decode(), data[at + 46 + n : at + 46 + n + m]
            k = 0
            while k + 4 <= len(extra):
                kind, size = struct.unpack_from("<HH", extra, k)
                if kind == 1:
                    wide = [x[0] for x in struct.iter_unpack("<Q", extra[k + 4 : k + 4 + size // 8 * 8])]
                    full = wide.pop(0) if full == 0xFFFFFFFF else full
                    packed = wide.pop(0) if packed == 0xFFFFFFFF else packed
                    offset = wide.pop(0) if offset == 0xFFFFFFFF else offset
                k += 4 + size
            found[name] = (method, offset, packed)
            at += 46 + n + m + c
        return found

    def locate(self, name: str) -> tuple[int, int]:
        """Offset and size of a stored member's bytes."""
        method, offset, size = self.members[name]
        if method != 0:
            raise ValueError(f"{name} is compressed, so it can't be read by range")
        head = self.read(offset, 30)
        if struct.unpack_from("<I", head)[0] != LOCAL:
            raise ValueError("broken local header")
        n, m = struct.unpack_from("<HH", head, 26)
        return offset + 30 + n + m, size


def warc_record(page_id, url: str | None, payload: bytes, digest: str, refers_to=None) -> bytes:
    """A response with the payload, or a revisit that names the page whose payload it shares.

    The HTTP header of either gives the length of the full payload.
    """
    kind = "response" if refers_to is None else "revisit"
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http + payload if refers_to is None else http
    uri = "".join(c for c in url or "" if c >= " " and c != "\x7f")
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{page_id}>", f"WARC-Target-URI: {uri}", f"WARC-Date: {DATE}", f"WARC-Payload-Digest: sha1:{digest}"]
    if refers_to is not None:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse_record(data: bytes) -> dict:
    """``page_id, record_type, refers_to, payload, payload_bytes, payload_digest`` of one record."""
    head, _, rest = data.partition(b"\r\n\r\n")
    fields = dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:])
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    length = next(int(x.split(b":")[1]) for x in http.split(b"\r\n") if x.lower().startswith(b"content-length:"))
    named = lambda key: (lambda x: None if x in (None, "None") else int(x))(fields[key][len("<urn:page:") : -1] if key in fields else None)
    digest, stated = fields["WARC-Payload-Digest"].split(":")[1], fields["WARC-Type"]
    if stated == "response":
        if hashlib.sha1(payload).hexdigest() != digest or len(payload) != length:
            raise ValueError(f"payload of record {fields['WARC-Record-ID']} is damaged")
    return {"page_id": named("WARC-Record-ID"), "record_type": stated, "refers_to": named("WARC-Refers-To"), "payload": payload, "payload_bytes": length, "payload_digest": digest}


def _file_system(uri: str):
    return pafs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri}")


def plan_records(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``(page_id, url, payload, digest, refers_to)``: who revisits whom, by digest and length of the payload."""
    payload = F.coalesce(F.col(html_col).cast("binary"), F.lit(b""))
    held = pages.select(F.col(id_col).cast("bigint").alias("page_id"), F.col(url_col).alias("url"), payload.alias("payload"))
    held = held.withColumn("digest", F.sha1("payload")).withColumn("n", F.octet_length("payload"))
    shared = held.where(F.col("n") >= SMALLEST_REVISIT).groupBy("digest", "n").agg(F.max("page_id").alias("first"), F.count(F.lit(1)).alias("copies"))
    shared = materialize(shared.where("copies > 1").drop("copies"), "shared")
    refers = F.when(~F.col("page_id").eqNullSafe(F.col("first")), F.col("first"))
    return held.join(shared, ["digest", "n"], "left").select("page_id", "url", "payload", "digest", refers.alias("refers_to"))


def write_packages(records: DataFrame, folder: str, most_bytes: int = 256 << 20, zip64: bool = False) -> DataFrame:
    """Writes packages of about ``most_bytes`` at most under ``folder``; returns their manifest ``(uri, size, n)``.

    Names are new for every attempt and only what a finished task names is in the manifest, so a
    repeated task leaves a stray file at worst.
    """

    def kernel(batches):
        system, root = _file_system(folder)
        system.create_dir(root, recursive=True)
        done, state = [], None

        def opened():
            name = f"{root}/{uuid.uuid4().hex}.wacz"
            sink = system.open_output_stream(name)
            zipped = StoredZipWriter(sink, zip64)
            zipped.begin(WARC_MEMBER)
            return [name, sink, zipped, []]

        def closed(state):
            name, sink, zipped, lines = state
            zipped.end()
            zipped.begin(INDEX_MEMBER)
            zipped.write("".join(lines).encode())
            zipped.end()
            zipped.close()
            sink.close()
            done.append((name, zipped.at, len(lines)))

        for batch in batches:
            for page_id, url, payload, digest, refers in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                state = state or opened()
                data = warc_record(page_id, url, payload, digest, refers)
                at = state[2].write(data)
                state[3].append(f"{page_id} {at} {len(data)}\n")
                if state[2].at >= most_bytes:
                    closed(state)
                    state = None
        if state:
            closed(state)
        if done:
            yield pa.RecordBatch.from_arrays([pa.array([d[i] for d in done]) for i in range(3)], ["uri", "size", "n"])

    return records.mapInArrow(kernel, "uri string, size bigint, n bigint")


def read_packages(manifest: DataFrame, folder: str, with_payload: bool = False) -> DataFrame:
    """One row for each record of the packages: ``page_id, payload_bytes, payload_digest, record_type, refers_to[, payload]``."""
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"] + ["payload"] * with_payload
    kinds = {"page_id": pa.int64(), "payload_bytes": pa.int64(), "refers_to": pa.int64(), "payload": pa.binary()}

    def kernel(batches):
        system, _ = _file_system(folder)
        for batch in batches:
            for name in batch.column(0).to_pylist():
                with system.open_input_file(name) as f:
                    package = ZipRangeReader(lambda at, n: f.read_at(n, at), f.size())  # noqa: B023
                    data_at, _ = package.locate(WARC_MEMBER)
                    index_at, index_size = package.locate(INDEX_MEMBER)
                    held = []
                    for line in f.read_at(index_size, index_at).decode().splitlines():
                        _, at, size = line.split(" ")
                        held.append(parse_record(f.read_at(int(size), data_at + int(at))))
                        if len(held) >= 500:
                            yield packed(held)
                            held = []
                    if held:
                        yield packed(held)

    def packed(held):
        return pa.RecordBatch.from_arrays([pa.array([r[c] for r in held], kinds.get(c, pa.string())) for c in names], names)

    schema = "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint" + ", payload binary" * with_payload
    return manifest.select("uri").mapInArrow(kernel, schema)


def archive_pages(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", with_payload: bool = False, most_bytes: int = 256 << 20) -> DataFrame:
    """Writes every page to packages in the shared folder and reads all records back.

    Null html is an empty payload; a null id is written as such and read back as null; rows that repeat the largest id
    of a group are responses each; an empty table writes nothing and gives an empty result. Other columns are ignored.
    """
    spark = pages.sparkSession
    folder = new_folder(spark, "packages")
    manifest = materialize(write_packages(plan_records(pages, id_col, url_col, html_col), folder, most_bytes), "manifest")
    spread = manifest.repartition(max(1, spark.sparkContext.defaultParallelism))
    return read_packages(spread, folder, with_payload)


def op8_warc(spark, sf_dir: str) -> DataFrame:
    return archive_pages(spark.read.parquet(f"{sf_dir}/pages.parquet"))


OP8_SQL = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS b FROM pages),
d AS (SELECT page_id, octet_length(b) AS n, sha1(b) AS digest FROM p),
m AS (SELECT *, max(page_id) OVER (PARTITION BY digest, n) AS top FROM d)
SELECT page_id, n AS payload_bytes, digest AS payload_digest,
       CASE WHEN n >= 1000 AND page_id <> top THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 1000 AND page_id <> top THEN top END AS refers_to
FROM m
"""
