"""WARC archives: a writer, and a sequential reader that needs no index.

Each record is a gzip member of its own. The reader inflates a stream of chunks step by step, cuts records by their content
length, and compares block and payload digests. Archives are kept as rows (archive, part, content) so that Spark can write
and read them in any store; `export_files` writes the same bytes as .warc.gz files where a local path is at hand.

A payload that other records of the table repeat is stored once, with the largest page_id; the others are revisits that
refer to it. Payloads shorter than `least` bytes are always stored. Digests are counted by partial aggregation, and only
rows of repeated payloads are matched with their digests, salted, so a payload that a third of all rows share is dealt out.

Edge cases: a null html is an empty payload; repeated rows (same page_id, same payload) are each a response if theirs is the
largest id; a row without page_id is a response; an empty table gives no archives and no rows; other columns aren't looked at.
"""

from __future__ import annotations

import base64
import hashlib
import os
import zlib
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

CRLF = b"\r\n"
SALTS = 32


def _digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def _hex(digest: str) -> str:
    return base64.b32decode(digest.partition(":")[2]).hex()


def _urn(page_id: int | None) -> str:
    return f"<urn:page:{'none' if page_id is None else page_id}>"


def _page(urn: str | None) -> int | None:
    last = (urn or "").strip("<>").rpartition(":")[2]
    return int(last) if last.lstrip("-").isdigit() else None


@dataclass
class Record:
    headers: dict[str, str]
    http: dict[str, str] = field(default_factory=dict)
    payload: bytes = b""

    @property
    def kind(self) -> str:
        return self.headers["WARC-Type"]


def _lines(pairs: dict[str, str]) -> bytes:
    return b"".join(f"{k}: {v}".encode() + CRLF for k, v in pairs.items())


def encode(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, date: str = "1970-01-01T00:00:00Z", level: int = 6) -> bytes:
    """One gzip member: a response, or a revisit without its payload if it refers to another page."""
    digest = _digest(payload)
    block = b"HTTP/1.1 200 OK" + CRLF + _lines({"Content-Type": "text/html; charset=utf-8", "Content-Length": str(len(payload))}) + CRLF
    head = {"WARC-Type": "response" if refers_to is None else "revisit", "WARC-Record-ID": _urn(page_id), "WARC-Date": date, "WARC-Payload-Digest": digest}
    if url:
        head["WARC-Target-URI"] = "".join(url.splitlines())
    if refers_to is None:
        block += payload
    else:
        head |= {"WARC-Refers-To": _urn(refers_to), "WARC-Profile": "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"}
    head |= {"WARC-Block-Digest": _digest(block), "Content-Type": "application/http; msgtype=response", "Content-Length": str(len(block))}
    pack = zlib.compressobj(level, zlib.DEFLATED, 31)
    return pack.compress(b"WARC/1.1" + CRLF + _lines(head) + CRLF + block + CRLF + CRLF) + pack.flush()


def _parsed(lines: bytes) -> dict[str, str]:
    pairs = (x.decode("utf-8", "replace").partition(":") for x in lines.split(CRLF) if x)
    return {k.strip(): v.strip() for k, _, v in pairs}


def _inflated(chunks: Iterable[bytes], step: int = 1 << 16) -> Iterator[tuple[bytes, bool]]:
    """(bytes, True at a member's end) of a stream of gzip members, at most `step` bytes at once."""
    unpack, fresh = zlib.decompressobj(31), True
    for chunk in chunks:
        while chunk:
            fresh = False
            data = unpack.decompress(chunk, step)
            chunk = unpack.unconsumed_tail
            ended = unpack.eof
            yield data, ended
            if ended:
                chunk, unpack, fresh = unpack.unused_data, zlib.decompressobj(31), True
    if not fresh:
        raise ValueError("the archive ends within a member")


def read(chunks: Iterable[bytes]) -> Iterator[Record]:
    """Records in order; a broken frame or a digest that doesn't match raises ValueError."""
    held = bytearray()
    for data, ended in _inflated(chunks):
        held += data
        if ended:
            yield _record(bytes(held))
            held.clear()


def _record(member: bytes) -> Record:
    head, _, rest = member.partition(CRLF + CRLF)
    version, _, lines = head.partition(CRLF)
    headers = _parsed(lines)
    if not version.startswith(b"WARC/") or "Content-Length" not in headers:
        raise ValueError("no WARC record")
    size = int(headers["Content-Length"])
    block = rest[:size]
    if len(block) != size or rest[size:] != CRLF + CRLF:
        raise ValueError(f"content length {size} doesn't fit {headers.get('WARC-Record-ID')}")
    if "WARC-Block-Digest" in headers and headers["WARC-Block-Digest"] != _digest(block):
        raise ValueError(f"block digest of {headers.get('WARC-Record-ID')}")
    top, _, payload = block.partition(CRLF + CRLF)
    http = _parsed(top.partition(CRLF)[2])
    if headers["WARC-Type"] == "response" and headers.get("WARC-Payload-Digest") != _digest(payload):
        raise ValueError(f"payload digest of {headers.get('WARC-Record-ID')}")
    return Record(headers, http, payload)


def with_references(pages: DataFrame, least: int = 1000, key: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """(page_id, url, html as bytes, refers_to): refers_to is null for responses."""
    p = pages.select(
        F.col(key).cast("long").alias("page_id"),
        (F.col(url) if url in pages.columns else F.lit(None)).cast("string").alias("url"),
        F.encode(F.coalesce(F.col(html).cast("string"), F.lit("")), "UTF-8").alias("payload"),
    )
    keyed = p.select("*", F.when(F.octet_length("payload") >= least, F.sha1("payload")).alias("digest"), F.pmod(F.xxhash64("page_id"), F.lit(SALTS)).alias("salt"))
    repeated = keyed.where("digest is not null").groupBy("digest").agg(F.count("*").alias("n"), F.max("page_id").alias("first")).where("n > 1")
    dealt = repeated.select("digest", "first", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))).alias("salt"))
    # Rows whose payload isn't long enough for a revisit skip the join.
    known = keyed.where("digest is not null").join(dealt, ["digest", "salt"], "left")
    refers = F.when(F.col("page_id") != F.col("first"), F.col("first"))
    return known.select("page_id", "url", "payload", refers.alias("refers_to")).union(keyed.where("digest is null").select("page_id", "url", "payload", F.lit(None).cast("long")))


def write(pages: DataFrame, path: str, least: int = 1000, part_bytes: int = 8 << 20, **columns: str) -> None:
    """Archives of the pages, one for each task, written as Parquet rows (archive, part, content)."""

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        archive, part, held = TaskContext.get().partitionId(), 0, bytearray()
        row = lambda: pa.RecordBatch.from_arrays([pa.array([archive], pa.int64()), pa.array([part], pa.int64()), pa.array([bytes(held)], pa.binary())], names=["archive", "part", "content"])
        for b in batches:
            for page_id, url, payload, refers_to in zip(*(b.column(i) for i in range(4)), strict=True):
                held += encode(page_id.as_py(), url.as_py(), payload.as_py(), refers_to.as_py())
                if len(held) >= part_bytes:
                    yield row()
                    part, held = part + 1, bytearray()
        if held:
            yield row()

    with_references(pages, least, **columns).mapInArrow(of, "archive long, part long, content binary").write.mode("overwrite").parquet(path)


RECORD = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long"


def read_back(archives: DataFrame, payloads: bool = False) -> DataFrame:
    """One row a record of rows (archive, part, content), as in RECORD, and its payload if asked for.

    Parts hold whole members, so a part can be read alone and large archives are read by many tasks.
    """
    types = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64()] + [pa.binary()] * payloads
    names = [x.split()[0] for x in RECORD.split(", ")] + ["payload"] * payloads

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for content in b.column(0):
                rows, held = [], 0
                for r in read([content.as_py()]):
                    size = int(r.http.get("Content-Length", len(r.payload)))
                    row = (_page(r.headers["WARC-Record-ID"]), r.headers.get("WARC-Target-URI"), size, _hex(r.headers["WARC-Payload-Digest"]), r.kind, _page(r.headers.get("WARC-Refers-To")))
                    rows.append(row + (r.payload,) * payloads)
                    held += len(r.payload) * payloads
                    if len(rows) >= 4096 or held >= 8 << 20:
                        yield _batch(rows, types, names)
                        rows, held = [], 0
                if rows:
                    yield _batch(rows, types, names)

    return archives.select("content").mapInArrow(of, RECORD + ", payload binary" * payloads)


def _batch(rows: list[tuple], types: list[pa.DataType], names: list[str]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)


def export_files(archives: DataFrame, folder: str) -> list[str]:
    """Write each archive as a .warc.gz file into a folder that all executors can write; a lost task's file is written anew."""

    def of(key: tuple, table: pa.Table) -> pa.Table:
        path = os.path.join(folder, f"part-{key[0].as_py():05d}.warc.gz")
        with open(path + ".tmp", "wb") as f:
            for content in table.sort_by("part").column("content"):
                f.write(content.as_py())
        os.replace(path + ".tmp", path)
        return pa.table({"path": [path]})

    os.makedirs(folder, exist_ok=True)
    return sorted(r[0] for r in archives.groupBy("archive").applyInArrow(of, "path string").collect())


def file_chunks(path: str, step: int = 1 << 16, opener: Callable = open) -> Iterator[bytes]:
    with opener(path, "rb") as f:
        while chunk := f.read(step):
            yield chunk
