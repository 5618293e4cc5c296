"""WARC archives: written one gzip member a record, read sequentially.

The reader takes a file in chunks, ends a record with its gzip member, frames the header and the block by
Content-Length, and verifies the digests of block and payload; it never holds more than a chunk and a record.
"""

from __future__ import annotations

import base64
import hashlib
import posixpath
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from urllib.parse import quote, unquote, urlsplit

import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erfocus.operators.durable import cut, shared_path, sized

MIN_SHARED = 1000
FILE_BYTES = 1 << 30
CHUNK = 1 << 16
DATE = "2024-01-01T00:00:00Z"
#: Fixed values of the format.
VERSION = b"WARC/1.1"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


class DamagedRecord(ValueError):
    pass


@dataclass
class Record:
    headers: dict[str, str]
    block: bytes

    @property
    def kind(self) -> str:
        return self.headers["WARC-Type"]

    def http(self) -> tuple[dict[str, str], bytes]:
        """Headers of the response in the block, and its payload."""
        head, _, payload = self.block.partition(b"\r\n\r\n")
        return _fields(head.split(b"\r\n")[1:]), payload


def _fields(lines: list[bytes]) -> dict[str, str]:
    return {k.decode(): v.strip().decode() for k, _, v in (x.partition(b":") for x in lines if x)}


def _digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data, usedforsecurity=False).digest()).decode()


def hex_digest(field: str) -> str:
    return base64.b32decode(field.partition(":")[2]).hex()


def _urn(page_id, payload: bytes) -> str:
    """A record's id: the page's, quoted, and the payload's digest, so that records of one page id differ unless they are alike."""
    return f"<urn:page:{'-' if page_id is None else '=' + quote(str(page_id), safe='', errors='surrogatepass')}:{hashlib.sha1(payload, usedforsecurity=False).hexdigest()}>"


def page_of(urn: str):
    """The page id in a record's id."""
    name = urn.removeprefix("<urn:page:").rpartition(":")[0]
    return unquote(name[1:], errors="surrogatepass") if name.startswith("=") else None


def member(page_id, url: str | None, payload: bytes, refers_to=None, revisit: bool = False) -> bytes:
    """A record as a gzip member.  A revisit has the response's headers, with the payload's length, but no payload."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if revisit else http + payload
    fields = {
        "WARC-Type": "revisit" if revisit else "response",
        "WARC-Record-ID": _urn(page_id, payload),
        "WARC-Date": DATE,
        "WARC-Target-URI": " ".join((url or "").split()),
        "WARC-Payload-Digest": _digest(payload),
        "WARC-Block-Digest": _digest(block),
        "Content-Type": "application/http; msgtype=response",
        "Content-Length": str(len(block)),
    }
    if revisit:
        fields |= {"WARC-Profile": REVISIT_PROFILE, "WARC-Refers-To": _urn(refers_to, payload)}
    head = VERSION + b"\r\n" + b"".join(f"{k}: {v}\r\n".encode("utf-8", "surrogatepass") for k, v in fields.items())
    z = zlib.compressobj(6, zlib.DEFLATED, 31)
    return z.compress(head + b"\r\n" + block + b"\r\n\r\n") + z.flush()


def members(chunks: Iterator[bytes]) -> Iterator[bytes]:
    """The uncompressed content of each gzip member."""
    z, parts = zlib.decompressobj(31), []
    begun = False
    for chunk in chunks:
        while chunk:
            begun = True
            parts.append(z.decompress(chunk))
            if not z.eof:
                break
            yield b"".join(parts)
            chunk, z, parts, begun = z.unused_data, zlib.decompressobj(31), [], False
    if begun:
        raise DamagedRecord("the file ends inside a record")


def records(chunks: Iterator[bytes]) -> Iterator[Record]:
    """Framed and verified records; raises DamagedRecord on any that is not whole."""
    for data in members(chunks):
        head, found, rest = data.partition(b"\r\n\r\n")
        first, *lines = head.split(b"\r\n")
        if not found or not first.startswith(b"WARC/"):
            raise DamagedRecord("no WARC header")
        fields = _fields(lines)
        size = int(fields.get("Content-Length", -1))
        if size < 0 or rest[size:] != b"\r\n\r\n":
            raise DamagedRecord("the block's length is not the stated one")
        record = Record(fields, rest[:size])
        if "WARC-Block-Digest" in fields and _digest(record.block) != fields["WARC-Block-Digest"]:
            raise DamagedRecord("the block's digest is not the stated one")
        if record.kind == "response" and "WARC-Payload-Digest" in fields and _digest(record.http()[1]) != fields["WARC-Payload-Digest"]:
            raise DamagedRecord("the payload's digest is not the stated one")
        yield record


def _store(uri: str):
    """(file system, path) of a folder or file: local, or any store that Arrow reaches."""
    from pyarrow import fs

    parts = urlsplit(uri)
    if parts.scheme in ("", "file"):
        return fs.LocalFileSystem(), parts.path
    return fs.FileSystem.from_uri(uri)


def planned(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", min_shared: int = MIN_SHARED) -> DataFrame:
    """(page_id, url, html, response): the id of the response that a row revisits, else null.

    Of equal payloads of at least min_shared bytes those of the largest id are responses, as are all if
    every id is null; a null id is less than any.
    """
    rows = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.coalesce(F.col(html_col), F.lit("")).alias("html"))
    digest = F.sha1(F.col("html").cast("binary"))
    long = F.octet_length("html") >= min_shared
    shared = rows.where(long).select(digest.alias("__digest"), "page_id").groupBy("__digest").agg(F.max("page_id").alias("__last"), F.count(F.lit(1)).alias("n")).where("n > 1")
    shared = sized(cut(shared.select("__digest", "__last")), 200_000)
    joined = rows.join(shared, long & (digest == F.col("__digest")), "left")
    return joined.select("page_id", "url", "html", F.when(~F.col("page_id").eqNullSafe(F.col("__last")), F.col("__last")).alias("response"))


def write(pages: DataFrame, folder: str, file_bytes: int = FILE_BYTES, **columns) -> DataFrame:
    """Write archives of at most about file_bytes to a folder; returns (path, records), the archives' list.

    A file is written under a name of the attempt's own and renamed when whole, so tasks may be retried.
    """
    plan = planned(pages, **columns)

    def run(batches):
        fs, top = _store(folder)
        fs.create_dir(top, recursive=True)
        context = TaskContext.get()
        out, n, size, k = None, 0, 0, 0
        own = f"{top.rstrip('/')}/part-{context.partitionId():05d}"
        done = []

        def close():
            out.close()
            fs.move(f"{own}-{k:04d}.{context.taskAttemptId()}", f"{own}-{k:04d}.warc.gz")
            done.append((posixpath.join(folder.rstrip("/"), f"part-{context.partitionId():05d}-{k:04d}.warc.gz"), n))

        for pdf in batches:
            for page_id, url, html, response in zip(pdf["page_id"], pdf["url"], pdf["html"], pdf["response"], strict=True):
                if out is None:
                    out, n, size = fs.open_output_stream(f"{own}-{k:04d}.{context.taskAttemptId()}", compression=None), 0, 0
                data = member(page_id, url, html.encode("utf-8", "surrogatepass"), response, response is not None)
                out.write(data)
                n, size = n + 1, size + len(data)
                if size >= file_bytes:
                    close()
                    out, k = None, k + 1
        if out is not None:
            close()
        if done:
            yield pd.DataFrame({"path": [p for p, _ in done], "records": [c for _, c in done]})

    plan = plan.withColumn("page_id", F.col("page_id").cast("string")).withColumn("response", F.col("response").cast("string"))
    return cut(plan.mapInPandas(run, "path string, records long"))


def read(archives: DataFrame, with_payload: bool = False) -> DataFrame:
    """Records of archives listed in a column path, a task a file: what the headers and blocks say."""
    n = max(1, min(10_000, archives.count()))

    def run(batches):
        for pdf in batches:
            for path in pdf["path"]:
                fs, at = _store(path)
                with fs.open_input_stream(at, compression=None) as f:
                    rows, held = [], 0
                    for r in records(iter(lambda f=f: f.read(CHUNK), b"")):
                        http, payload = r.http()
                        rows.append((page_of(r.headers["WARC-Record-ID"]), r.headers["WARC-Target-URI"], int(http["Content-Length"]), hex_digest(r.headers["WARC-Payload-Digest"]), r.kind, page_of(r.headers.get("WARC-Refers-To", "")), payload if with_payload else None))
                        held += len(payload) if with_payload else 100
                        if held > 16 << 20:
                            yield _frame(rows)
                            rows, held = [], 0
                    if rows:
                        yield _frame(rows)

    return archives.select("path").repartition(n, "path").mapInPandas(run, "page_id string, url string, payload_bytes long, payload_digest string, record_type string, refers_to string, payload binary")


def _frame(rows: list) -> pd.DataFrame:
    return pd.DataFrame(rows, columns=["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"], dtype=object).astype({"payload_bytes": "int64"})


def round_trip(pages: DataFrame, folder: str | None = None, id_col: str = "page_id") -> DataFrame:
    """Write every row to archives and read them back: a row per record.

    Null html is the empty payload.  Repeated rows are a record each; ids of any text, also with line breaks, come
    back as they were; a null id is kept; an empty table gives no row; extra columns are not read.
    """
    kind = pages.schema[id_col].dataType
    found = read(write(pages, folder or shared_path(pages.sparkSession, "warc"), id_col=id_col))
    return found.select(F.col("page_id").cast(kind).alias("page_id"), "payload_bytes", "payload_digest", "record_type", F.col("refers_to").cast(kind).alias("refers_to"))


ROUND_TRIP_SQL = f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
d AS (SELECT page_id, octet_length(encode(html)) AS n, sha1(html) AS digest FROM p),
m AS (SELECT *, max(page_id) OVER (PARTITION BY digest) AS last FROM d)
SELECT page_id, n::BIGINT AS payload_bytes, digest AS payload_digest,
  CASE WHEN n >= {MIN_SHARED} AND page_id IS DISTINCT FROM last THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN n >= {MIN_SHARED} AND page_id IS DISTINCT FROM last THEN last END AS refers_to
FROM m
"""
