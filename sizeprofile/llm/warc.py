"""WARC archives: a writer that dedups payloads and a reader that splits compressed files at any byte.

Every record is a gzip member of its own. A reading task gets a byte range; it looks for the gzip magic, decodes each
candidate's headers to tell members from chance matches, and owns the records that start inside its range.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from urllib.parse import quote

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batches_of, file_store, put_file, rows_of, work_path, written

FILE_BYTES, SPLIT_BYTES = 128 << 20, 8 << 20
_MAGIC = b"\x1f\x8b\x08"
_HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n"
_REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_READ_BYTES = 1 << 20
#: Left as they are in a target URI; white space and controls are percent-encoded.
_URI_SAFE = "".join(map(chr, range(0x21, 0x7F)))


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """One record; a revisit carries the HTTP header of the full payload but not the payload."""
    block = _HTTP % len(payload)
    head = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", "WARC-Date: 1970-01-01T00:00:00Z"]
    if url is not None:
        head.append(f"WARC-Target-URI: {quote(url, safe=_URI_SAFE)}")
    head.append(f"WARC-Payload-Digest: sha1:{payload_digest(payload)}")
    if refers_to is None:
        block += payload
    else:
        head += [f"WARC-Profile: {_REVISIT_PROFILE}", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


_FILES = pa.schema([("path", pa.string()), ("n_records", pa.int64()), ("n_bytes", pa.int64())])


def with_first_copies(pages: DataFrame, min_bytes: int = 0, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html") -> DataFrame:
    """id, url, payload (bytes; null is empty) and refers_to: the smallest id with an equal payload, null for that page itself.

    Rows that tie on the smallest id are all responses; so are payloads under `min_bytes`, and groups without any id.
    Payloads are compared by SHA-256. The smallest id is aggregated before anything is shuffled, so a payload that a
    third of all pages share costs one row a task there. The payloads found twice are written before the join: it
    is a broadcast if their measured size allows, and otherwise AQE splits the pages of a hot payload.
    """
    raw = F.coalesce(F.col(f"`{payload_col}`"), F.lit("")).cast("binary")
    keyed = rows_of(pages, id=F.col(f"`{id_col}`").cast("long"), url=url_col, payload=raw).withColumn("key", F.when(F.octet_length("payload") >= min_bytes, F.unhex(F.sha2("payload", 256))))
    first = keyed.where(F.col("key").isNotNull()).groupBy("key").agg(F.min("id").alias("first"), F.count(F.lit(1)).alias("n")).where((F.col("n") > 1) & F.col("first").isNotNull()).select("key", "first")
    first = written(first, "first-copies")
    other = F.col("id").isNull() | (F.col("first") < F.col("id"))
    return keyed.join(first, "key", "left").select("id", "url", "payload", F.when(F.col("first").isNotNull() & other, F.col("first")).alias("refers_to"))


def write_warc(pages: DataFrame, folder: str, min_bytes: int = 0, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", file_bytes: int = FILE_BYTES) -> DataFrame:
    """Write one record for each row; return the list of files (path, n_records, n_bytes).

    A task streams its rows into files of about `file_bytes`; they are renamed into place when complete, and only
    those of the attempt that succeeded are listed. An empty table gives an empty list.
    """

    def write(batches):
        def one():
            rows = (r for b in batches for r in zip(*(c.to_pylist() for c in b.columns)))
            row = next(rows, None)
            while row:
                done = None

                def body(out):
                    nonlocal row, done
                    n = size = 0
                    while row and size < file_bytes:
                        pack = zlib.compressobj(6, zlib.DEFLATED, 31)
                        raw = pack.compress(record(row[0], row[1], row[2], row[3])) + pack.flush()
                        out.write(raw)
                        n, size = n + 1, size + len(raw)
                        row = next(rows, None)
                    done = (n, size)

                path = put_file(folder, f"pages-{uuid.uuid4().hex}.warc.gz", body)
                yield (path, *done)

        yield from batches_of(_FILES, one())

    marked = with_first_copies(pages, min_bytes, id_col, url_col, payload_col)
    return written(marked.mapInArrow(write, "path string, n_records long, n_bytes long"), "warc-files")


class _Bytes:
    """Random reads of a file with one chunk kept."""

    def __init__(self, path: str):
        store, at = file_store(path)
        self.f = store.open_input_file(at)
        self.size, self.begin, self.chunk = self.f.size(), 0, b""

    def read(self, at: int, least: int = 1, most: int = 16 << 10) -> memoryview:
        """Bytes from `at` on: `least` unless the file ends, `most` if they are at hand."""
        if not (self.begin <= at and at + least <= self.begin + len(self.chunk)):
            self.f.seek(at)
            self.begin, self.chunk = at, self.f.read(max(_READ_BYTES, least))
        return memoryview(self.chunk)[at - self.begin :][:most]

    def find_magic(self, at: int, end: int) -> int:
        """First place of the magic that starts in [at, end), or -1."""
        while at < end:
            self.read(at, len(_MAGIC))
            k = self.chunk.find(_MAGIC, at - self.begin, end - self.begin + len(_MAGIC) - 1)
            if k >= 0:
                return self.begin + k
            if self.begin + len(self.chunk) >= min(self.size, end + len(_MAGIC) - 1):
                return -1
            at = self.begin + len(self.chunk) - len(_MAGIC) + 1
        return -1


def _fields(block: bytes) -> tuple[str, dict[str, str]] | None:
    lines = block.decode("utf-8", "replace").split("\r\n")
    got = dict(x.split(":", 1) for x in lines[1:] if ":" in x)
    return lines[0], {k.strip().lower(): v.strip() for k, v in got.items()}


def _starts_record(file: _Bytes, at: int) -> bool:
    """Whether a gzip member that decodes to WARC headers starts here (or the file ends here)."""
    if at >= file.size:
        return True
    unpack, got, ends = zlib.decompressobj(31), bytearray(), -1
    try:
        while ends < 0 and not unpack.eof:
            part = file.read(at, 1)
            if not part:
                return False
            looked = max(0, len(got) - 3)
            got += unpack.decompress(part[:1024])
            ends = got.find(b"\r\n\r\n", looked)
            at += min(1024, len(part))
            if len(got) >= 6 and not got.startswith(b"WARC/1"):
                return False
    except zlib.error:
        return False
    head = bytes(got[: max(0, ends)]).lower()
    return head.startswith(b"warc/1") and b"content-length:" in head and b"warc-type:" in head


def _member(file: _Bytes, at: int) -> tuple[bytes, int] | None:
    """(record, offset after the member), or None if this is no whole member with a right checksum."""
    unpack, out = zlib.decompressobj(31), []
    try:
        while not unpack.eof:
            part = file.read(at, 1)
            if not part:
                return None
            out.append(unpack.decompress(part))
            at += len(part)
    except zlib.error:
        return None
    return b"".join(out), at - len(unpack.unused_data)


def _record(file: _Bytes, at: int):
    """(fields, HTTP fields, payload, offset after the record) of a whole record, or None."""
    got = _member(file, at) if _starts_record(file, at) else None
    if not got:
        return None
    head, _, rest = got[0].partition(b"\r\n\r\n")
    fields = _fields(head)[1]
    n = fields.get("content-length", "")
    if not (n.isdigit() and len(rest) == int(n) + 4 and rest.endswith(b"\r\n\r\n") and _starts_record(file, got[1])):
        return None
    http, _, payload = rest[:-4].partition(b"\r\n\r\n")
    return fields, _fields(http)[1], payload, got[1]


def records_in(path: str, begin: int, end: int, size: int | None = None, skip_damaged: bool = False):
    """(fields, HTTP fields, payload) of the records that start in [begin, end).

    A match of the magic counts as a record if its headers decode as WARC, its member ends with a right checksum, its
    length agrees, and the file ends or another record starts right behind it.

    No record is lost unseen: a file that is not of the listed size, does not begin with a record, or has anything but
    a whole record right behind a record is an error. A range also verifies the record behind its last one, where the next
    range with a record begins. With `skip_damaged` what cannot be read is passed over.
    """
    file = _Bytes(path)
    if size is not None and size != file.size and not skip_damaged:
        raise ValueError(f"{path}: {file.size} bytes, but {size} are listed")
    at, sure = begin, begin == 0
    while at < min(end, file.size):
        if not sure:
            at = file.find_magic(at, end)
            if at < 0:
                return
        if got := _record(file, at):
            yield got[:3]
            at, sure = got[3], True
        elif sure and not skip_damaged:
            raise ValueError(f"{path}: no whole record at byte {at}")
        else:
            at, sure = at + 1, False
    if sure and at < file.size and not skip_damaged and not _record(file, at):
        raise ValueError(f"{path}: no whole record at byte {at}")


def _page(urn: str | None) -> int | None:
    tail = (urn or "").removesuffix(">").rpartition(":")[2]
    return int(tail) if tail.lstrip("-").isdigit() else None


def read_warc(files: DataFrame, split_bytes: int = SPLIT_BYTES, skip_damaged: bool = False) -> DataFrame:
    """page_id, url, record_type, payload_bytes and payload_digest (both of the full payload), refers_to, payload (null in a revisit).

    `files` lists paths and sizes. Each split of `split_bytes` is a task's row. A payload that does not match its digest
    is an error, and so is a damaged, cut-off or missing record; `skip_damaged` reads on behind it instead.
    """
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("record_type", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())])

    def read(batches):
        def rows():
            for b in batches:
                for path, n_bytes, begin in zip(*(c.to_pylist() for c in b.columns)):
                    for fields, http, payload in records_in(path, begin, begin + split_bytes, n_bytes, skip_damaged):
                        kind, digest = fields["warc-type"], fields["warc-payload-digest"].removeprefix("sha1:")
                        if kind == "response" and payload_digest(payload) != digest:
                            raise ValueError(f"{path}: payload of {fields.get('warc-record-id')} does not match its digest")
                        size = len(payload) if kind == "response" else int(http["content-length"])
                        yield _page(fields.get("warc-record-id")), fields.get("warc-target-uri"), kind, size, digest, _page(fields.get("warc-refers-to")), payload if kind == "response" else None

        yield from batches_of(schema, rows(), weigh=lambda r: len(r[-1] or b""))

    splits = files.select("path", "n_bytes", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.col("n_bytes") - 1, F.lit(0)), F.lit(split_bytes).cast("long"))).alias("begin"))
    n = files.agg(F.sum(F.ceil(F.col("n_bytes") / split_bytes))).first()[0] or 1
    return splits.repartition(max(1, min(int(n), 100_000))).mapInArrow(read, "page_id long, url string, record_type string, payload_bytes long, payload_digest string, refers_to long, payload binary")


def op4_warc(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    files = write_warc(pages, work_path(spark, "warc"))
    return read_warc(files).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP4_SQL = r"""
with p as (
  select page_id, encode(coalesce(html, '')) as payload from pages
), d as (
  select page_id, octet_length(payload)::bigint as payload_bytes, sha1(payload) as hex, min(page_id) over (partition by payload) as first from p
), bits as (
  select page_id, payload_bytes, first, ('0x' || substr(hex, 10 * k + 1, 10))::bigint as part, k from d, range(4) t(k)
), letters as (
  select page_id, payload_bytes, first, k,
         string_agg(substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + ((part >> (35 - 5 * j)) & 31)::int, 1), '' order by j) as piece
  from bits, range(8) s(j) group by all
), digests as (
  select page_id, payload_bytes, first, string_agg(piece, '' order by k) as payload_digest from letters group by all
)
select page_id, payload_bytes, payload_digest, case when first = page_id then 'response' else 'revisit' end as record_type,
       case when first <> page_id then first end as refers_to
from digests
"""
