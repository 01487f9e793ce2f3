"""WARC archives written and read as a chunked record table.

Writing streams each payload into its record piece by piece, one gzip member a record; records whose
payload has been stored by another are revisits without payload. Reading parses the archives as
streams and yields rows (record, chunk number): a payload of any size becomes as many rows as it has
chunks of CHUNK bytes, each with the SHA-1 of the payload up to its end, so neither side ever holds a
whole record and the last row of a record has its digest.

Cases. A null html is an empty payload. Of equal payloads of at least least_bytes the largest page_id
is the response (nulls lose; several rows with that id are all responses), the others revisit it.
Line breaks and blanks in urls are percent-encoded, a null url is left out. Repeated page_ids are
records of their own. Empty tables write nothing and read as empty. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, fresh_dir, sized, table
from .files import create, new_name, open_at

CHUNK = 1 << 16
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
DATE = "2024-01-01T00:00:00Z"
REVISIT = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
CHUNK_ROWS = "page_id long, record_id string, record_type string, refers_to long, chunk_no long, n_bytes long, total_bytes long, running_sha1 string, last boolean, data binary"


def planned(pages: DataFrame, least_bytes: int = 1000) -> DataFrame:
    """page_id, url, payload, payload_bytes, payload_digest, refers_to (null for responses)."""
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    d = pages.select("page_id", "url", payload.alias("payload"))
    d = d.withColumns({"payload_bytes": F.octet_length("payload").cast("long"), "payload_digest": F.sha1("payload")})
    again = d.where(F.col("payload_bytes") >= least_bytes).groupBy("payload_digest").agg(F.max("page_id").alias("keeper"), F.count("*").alias("n"))
    d = d.join(sized(again.where("n > 1").drop("n")), "payload_digest", "left")
    other = F.col("keeper").isNotNull() & (F.col("page_id").isNull() | (F.col("page_id") != F.col("keeper")))
    return d.select("page_id", "url", "payload", "payload_bytes", "payload_digest", F.when(other, F.col("keeper")).alias("refers_to"))


def record_name(page_id: int | None) -> str:
    return f"<urn:page:{'none' if page_id is None else page_id}>"


def header(page_id: int | None, url: str | None, size: int, digest: str, refers_to: int | None) -> bytes:
    lines = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {record_name(page_id)}", f"WARC-Date: {DATE}"]
    if url is not None:
        lines.append(f"WARC-Target-URI: {quote(url, safe=''':/?#[]@!$&'()*+,;=%-._~''')}")
    lines += ["Content-Type: application/http;msgtype=response", f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {size}"]
    if refers_to is not None:
        lines += [f"WARC-Profile: {REVISIT}", f"WARC-Refers-To: {record_name(refers_to)}"]
    block = len(HTTP) + (size if refers_to is None else 0)
    return "\r\n".join([*lines, f"Content-Length: {block}", "", ""]).encode()


def write_archives(records: DataFrame, folder: str) -> DataFrame:
    """Write planned records into archives of the folder, one a task; returns (path, n_records), written down at once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, n, path = None, 0, new_name(folder, "warc.gz")
        for batch in batches:
            columns = [batch.column(c) for c in ("page_id", "url", "payload", "payload_bytes", "payload_digest", "refers_to")]
            for i in range(batch.num_rows):
                page_id, url, _, size, digest, refers_to = (None if k == 2 else c[i].as_py() for k, c in enumerate(columns))
                out = out or create(path)
                gz = zlib.compressobj(6, zlib.DEFLATED, 31)
                out.write(gz.compress(header(page_id, url, size, digest, refers_to) + HTTP))
                if refers_to is None:
                    data = memoryview(columns[2][i].as_buffer())
                    for a in range(0, size, CHUNK):
                        out.write(gz.compress(data[a : a + CHUNK]))
                out.write(gz.compress(b"\r\n\r\n") + gz.flush())
                n += 1
        if out is not None:
            out.close()
            yield pa.RecordBatch.from_arrays([pa.array([path]), pa.array([n], pa.int64())], ["path", "n_records"])

    return cut(records.select("page_id", "url", "payload", "payload_bytes", "payload_digest", "refers_to").mapInArrow(run, "path string, n_records long"))


class Stream:
    """Bytes of an archive of gzip members (or plain), taken in pieces."""

    def __init__(self, path: str):
        self.file, self.have = open_at(path), bytearray()
        start = self.file.read(2)
        self.plain, self.raw, self.engine = start != b"\x1f\x8b", start, zlib.decompressobj(31)

    def _more(self) -> bool:
        while True:
            if not self.raw:
                # All input can be taken in while output is still waiting.
                if not self.plain and not self.engine.eof and (got := self.engine.decompress(b"", CHUNK)):
                    self.have += got
                    return True
                self.raw = self.file.read(CHUNK)
                if not self.raw:
                    return False
            if self.plain:
                self.have += self.raw
                self.raw = b""
                return True
            if self.engine.eof:
                self.engine = zlib.decompressobj(31)
            got = self.engine.decompress(self.raw, CHUNK)
            self.raw = self.engine.unused_data if self.engine.eof else self.engine.unconsumed_tail
            if got:
                self.have += got
                return True

    def until(self, mark: bytes) -> bytes | None:
        """Up to and without the mark; None at the end of the archive."""
        at = self.have.find(mark)
        while at < 0:
            if not self._more():
                if self.have.strip():
                    raise ValueError("the archive ends inside a record")
                return None
            at = self.have.find(mark)
        out = bytes(self.have[:at])
        del self.have[: at + len(mark)]
        return out

    def take(self, n: int) -> Iterator[bytes]:
        """n bytes, in pieces of at most CHUNK."""
        while n:
            while len(self.have) < min(n, CHUNK):
                if not self._more():
                    raise ValueError("the archive ends inside a record")
            piece = bytes(self.have[: min(n, CHUNK)])
            del self.have[: len(piece)]
            n -= len(piece)
            yield piece


def read_records(path: str) -> Iterator[tuple[dict[str, str], Iterator[bytes]]]:
    """(header fields, pieces of the payload) of each record; the pieces are to be used up before the next."""
    stream = Stream(path)
    while (head := stream.until(b"\r\n\r\n")) is not None:
        lines = head.decode().split("\r\n")
        if lines[0] not in ("WARC/1.0", "WARC/1.1"):
            raise ValueError(f"not a WARC record: {lines[0][:40]}")
        fields = {k.lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        size = int(fields["content-length"])
        if fields.get("content-type", "").startswith("application/http"):
            size -= len(stream.until(b"\r\n\r\n")) + 4
        yield fields, stream.take(size)
        if b"".join(stream.take(4)) != b"\r\n\r\n":
            raise ValueError("a record is not closed")


def _page(name: str | None) -> int | None:
    m = re.fullmatch(r"<urn:page:(-?\d+)>", name or "")
    return int(m[1]) if m else None


def read_chunks(files: DataFrame, data: bool = True) -> DataFrame:
    """The chunked record table (CHUNK_ROWS) of the archives; data=False leaves the bytes themselves out.

    A revisit has one row without bytes, with the length and digest of the payload it stands for.
    """

    def rows(path: str) -> Iterator[tuple]:
        for fields, pieces in read_records(path):
            own = (_page(fields["warc-record-id"]), fields["warc-record-id"], fields["warc-type"], _page(fields.get("warc-refers-to")))
            said, length = fields["warc-payload-digest"].removeprefix("sha1:"), int(fields["x-payload-length"])
            if own[2] == "revisit":
                for _ in pieces:
                    raise ValueError("a revisit has a payload")
                yield *own, 0, 0, length, said, True, None
                continue
            sha, total, no = hashlib.sha1(), 0, 0
            for piece in pieces:
                sha.update(piece)
                total += len(piece)
                yield *own, no, len(piece), total, sha.hexdigest(), total == length, piece if data else None
                no += 1
            if not length:
                yield *own, 0, 0, 0, sha.hexdigest(), True, b"" if data else None
            if total != length or sha.hexdigest() != said:
                raise ValueError(f"{own[1]}: the payload is not what its header says")

    kinds = (pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.bool_(), pa.binary())
    names = [x.split()[0] for x in CHUNK_ROWS.split(", ")]

    def packed(part: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*part, strict=True), kinds, strict=True)], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path in batch.column(0).to_pylist():
                part: list[tuple] = []
                for row in rows(path):
                    part.append(row)
                    if len(part) >= (64 if data else 4096):
                        yield packed(part)
                        part = []
                if part:
                    yield packed(part)

    # One task an archive, as AQE would put short lists of long archives into one task.
    return files.select("path").repartition(max(1, files.count()), "path").mapInArrow(run, CHUNK_ROWS)


def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    files = write_archives(planned(table(spark, sf_dir, "pages")), fresh_dir(spark, "warc"))
    return read_chunks(files, data=False).where("last").select("page_id", F.col("total_bytes").alias("payload_bytes"), F.col("running_sha1").alias("payload_digest"), "record_type", "refers_to")


#: DuckDB SQL for op7.
OP7_SQL = """
WITH p AS (SELECT page_id, strlen(coalesce(html, '')) AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest FROM pages),
k AS (SELECT payload_digest, max(page_id) AS keeper FROM p WHERE payload_bytes >= 1000 GROUP BY 1 HAVING count(*) > 1)
SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes, payload_digest,
  CASE WHEN keeper IS NOT NULL AND page_id IS DISTINCT FROM keeper THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN keeper IS NOT NULL AND page_id IS DISTINCT FROM keeper THEN keeper END AS refers_to
FROM p LEFT JOIN k USING (payload_digest)
"""
