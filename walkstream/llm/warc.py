"""WARC 1.1 archives: one gzip member per record, written per page, and a sequential reader.

Archives are bounded byte strings (about `archive_bytes` of payload each) kept as rows of a table in the shared folder, which
any store of Spark can hold, each with a name of its own (partition and number); `export` writes them as files, `read_files`
reads files of any store, each as one cell, and `read_mounted` streams files of any size from a mounted folder. The reader
works through an archive in order: it inflates members piece by piece, frames blocks by Content-Length and checks block and
payload digests, holding one record at a time. `unmatched_revisits` lists revisits whose response isn't there.

Duplicates: of records with equal payloads of at least `min_bytes` bytes, that with the smallest page id is the response; the
others are revisits without payload that name it. Equal payloads are found by their SHA-1; a group may be any size, since
digests are reduced to a minimum first and those of large groups are dealt out by salt.

Defined cases: a null payload is empty; rows with a null page id are responses; rows that share the smallest id of a group
are all responses; an empty table writes no archive; other columns of the input are ignored; a damaged record raises
ValueError.
"""

from __future__ import annotations

import base64
import hashlib
import zlib
from collections.abc import Callable, Iterator
from urllib.parse import unquote, urlparse

import pandas as pd
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace

CRLF = b"\r\n"
PIECE = 1 << 16
#: Date and profile of written records (fixed values).
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def base32_sha1(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def record(page_id: str, url: str, payload: bytes, refers_to: str | None, digest: str) -> bytes:
    """One gzip member with a response or revisit record."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if refers_to is not None else http + payload
    head = [("WARC-Type", "response" if refers_to is None else "revisit"), ("WARC-Record-ID", f"<urn:page:{page_id}>"), ("WARC-Date", DATE), ("WARC-Target-URI", url.replace("\r", "%0D").replace("\n", "%0A"))]
    if refers_to is not None:
        head += [("WARC-Profile", PROFILE), ("WARC-Refers-To", f"<urn:page:{refers_to}>")]
    head += [("WARC-Payload-Digest", f"sha1:{digest}"), ("WARC-Block-Digest", f"sha1:{base32_sha1(block)}"), ("Content-Type", "application/http; msgtype=response"), ("Content-Length", str(len(block)))]
    raw = b"WARC/1.1\r\n" + b"".join(f"{k}: {v}\r\n".encode() for k, v in head) + CRLF + block + CRLF + CRLF
    z = zlib.compressobj(6, zlib.DEFLATED, 31)
    return z.compress(raw) + z.flush()


def pieces_of(archive: bytes) -> Callable[[], bytes]:
    """Reads an archive held in memory piece by piece."""
    view, at = memoryview(archive), 0

    def read() -> bytes:
        nonlocal at
        at += PIECE
        return bytes(view[at - PIECE : at])

    return read


def members(read: Callable[[], bytes]) -> Iterator[bytes]:
    """The inflated gzip members, in order. read gives the next piece of the archive, empty at its end."""
    rest = read()
    while rest:
        z, out = zlib.decompressobj(31), []
        while not z.eof:
            if not rest:
                raise ValueError("the archive ends within a member")
            try:
                out.append(z.decompress(rest))
            except zlib.error as e:
                raise ValueError(f"bad member: {e}") from e
            rest = z.unused_data if z.eof else read()
        yield b"".join(out)
        rest = rest or read()


def read_archive(archive: bytes | Callable[[], bytes]) -> Iterator[dict]:
    """Header fields (lower-case names), payload, payload length and digest of every record; digests are checked."""
    for raw in members(archive if callable(archive) else pieces_of(archive)):
        cut = raw.find(CRLF + CRLF)
        lines = raw[: max(cut, 0)].split(CRLF)
        if cut < 0 or not lines[0].startswith(b"WARC/"):
            raise ValueError("no record header")
        head = {k.strip().lower(): v.strip() for k, _, v in (x.decode().partition(":") for x in lines[1:])}
        size = int(head["content-length"])
        block = raw[cut + 4 : cut + 4 + size]
        if len(block) != size or raw[cut + 4 + size :] != CRLF + CRLF:
            raise ValueError("the block doesn't have its length")
        if "warc-block-digest" in head and head["warc-block-digest"] != f"sha1:{base32_sha1(block)}":
            raise ValueError("block digest differs")
        payload, length = block, size
        if head.get("content-type", "").startswith("application/http"):
            end = block.find(CRLF + CRLF)
            fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(b":") for x in block[: max(end, 0)].split(CRLF)[1:])}
            payload = block[end + 4 :] if end >= 0 else b""
            length = int(fields.get(b"content-length", len(payload)))
        if head.get("warc-type") != "revisit":
            if length != len(payload) or ("warc-payload-digest" in head and head["warc-payload-digest"] != f"sha1:{base32_sha1(payload)}"):
                raise ValueError("payload differs from its digest or length")
        yield head | {"payload": payload, "payload_length": length}


def mark_duplicates(pages: DataFrame, page_id: str, digest: Column, size: Column, min_bytes: int = 0, salts: int = 64) -> DataFrame:
    """Add refers_to: the smallest page id with an equal payload if that is another one, else null."""
    own = pages.withColumn("_d", digest).withColumn("_n", size).withColumn("_salt", F.pmod(F.xxhash64(page_id), F.lit(salts)).cast("int"))
    keyed = own.where(F.col("_n") >= min_bytes).select("_d", "_salt", F.col(page_id).alias("_id"))
    least = keyed.groupBy("_d", "_salt").agg(F.min("_id").alias("_least"), F.count("*").alias("_k")).groupBy("_d").agg(F.min("_least").alias("_least"), F.sum("_k").alias("_k")).where("_k > 1")
    dealt = least.select("_d", "_least", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("_salt"))
    out = own.join(dealt, ["_d", "_salt"], "left")
    differs = (F.col(page_id) != F.col("_least")) & (F.col("_n") >= min_bytes)
    return out.withColumn("refers_to", F.when(differs, F.col("_least"))).drop("_d", "_n", "_salt", "_least", "_k")


def write_archives(pages: DataFrame, workspace: Workspace, page_id: str = "page_id", url: str = "url", html: str = "html", min_bytes: int = 0, archive_bytes: int = 8 << 20) -> DataFrame:
    """Write all pages; returns the table of archives: name, body."""
    own = pages.select(F.col(page_id).cast("long").alias("page_id"), F.coalesce(F.col(url), F.lit("")).alias("url"), F.coalesce(F.encode(F.col(html), "utf-8"), F.lit(b"")).alias("payload"))
    marked = mark_duplicates(own, "page_id", F.sha1("payload"), F.octet_length("payload"), min_bytes)

    def write(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        part, number, records, size = TaskContext.get().partitionId(), 0, [], 0

        def archive() -> pd.DataFrame:
            return pd.DataFrame({"name": [f"pages-{part:06d}-{number:06d}.warc.gz"], "body": [b"".join(records)]})

        for pdf in batches:
            refers = pdf["refers_to"].astype("Int64")
            for i, u, p, r in zip(pdf["page_id"].astype("Int64"), pdf["url"], pdf["payload"], refers, strict=True):
                p = bytes(p)
                records.append(record("null" if pd.isna(i) else str(i), u, p, None if pd.isna(r) else str(r), base32_sha1(p)))
                size += len(p) + 512
                if size >= archive_bytes:
                    yield archive()
                    number, records, size = number + 1, [], 0
        if records:
            yield archive()

    return workspace.write(marked.mapInPandas(write, "name string, body binary"), "archives")


def _number(urn: str | None) -> int | None:
    tail = (urn or "").strip("<>").rpartition(":")[2]
    return int(tail) if tail.lstrip("-").isdigit() else None


def _schema(with_payload: bool) -> str:
    return "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string" + ", payload binary" * with_payload


def _rows(records: Iterator[dict], with_payload: bool, most_bytes: int = 8 << 20) -> Iterator[pd.DataFrame]:
    """Frames of records, of about most_bytes payload each."""
    names, rows, size = [x.split()[0] for x in _schema(with_payload).split(", ")], [], 0

    def frame() -> pd.DataFrame:
        return pd.DataFrame(rows, columns=names).astype({"page_id": "Int64", "refers_to": "Int64", "payload_bytes": "Int64"})

    for r in records:
        row = (_number(r.get("warc-record-id")), r.get("warc-target-uri"), r.get("warc-type"), _number(r.get("warc-refers-to")), r["payload_length"], r.get("warc-payload-digest", "").partition(":")[2])
        rows.append((*row, r["payload"]) if with_payload else row)
        size += (len(r["payload"]) if with_payload else 0) + 256
        if size >= most_bytes:
            yield frame()
            rows, size = [], 0
    if rows:
        yield frame()


def read_archives(archives: DataFrame, body: str = "body", with_payload: bool = False) -> DataFrame:
    """One row for each record: page_id, url, record_type, refers_to, payload_bytes, payload_digest (and payload)."""

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for archive in pdf.iloc[:, 0]:
                yield from _rows(read_archive(bytes(archive)), with_payload)

    return archives.select(body).mapInPandas(read, _schema(with_payload))


def unmatched_revisits(read: DataFrame) -> DataFrame:
    """Revisits that name no response of the same digest and length."""
    gone = read.where("record_type = 'revisit'")
    have = read.where("record_type = 'response'").select(F.col("page_id").alias("refers_to"), "payload_digest", "payload_bytes").distinct()
    return gone.join(have, ["refers_to", "payload_digest", "payload_bytes"], "left_anti")


def read_mounted(spark: SparkSession, folder: str, with_payload: bool = True) -> DataFrame:
    """Records of the .warc.gz files of a folder mounted at all executors, streamed: a file is never held as a whole."""
    names = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.gz").load(f"file://{folder}").select("path")

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for path in pdf["path"]:
                with open(unquote(urlparse(path).path), "rb") as f:
                    yield from _rows(read_archive(lambda f=f: f.read(PIECE)), with_payload)

    return names.mapInPandas(read, _schema(with_payload))


def read_files(spark: SparkSession, path: str, with_payload: bool = True) -> DataFrame:
    """Records of .warc.gz files in any store."""
    return read_archives(spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.gz").load(path), "content", with_payload)


def export(archives: DataFrame, folder: str) -> DataFrame:
    """Write archives as files into a mounted folder that all executors share; returns name and size."""
    def put(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import os

        for pdf in batches:
            for name, body in zip(pdf["name"], pdf["body"], strict=True):
                partial = os.path.join(folder, f".{name}.{os.getpid()}")
                with open(partial, "wb") as f:
                    f.write(body)
                os.replace(partial, os.path.join(folder, name))  # a repeated task writes the same bytes
                yield pd.DataFrame({"name": [name], "size": [len(body)]})

    return archives.mapInPandas(put, "name string, size long")
