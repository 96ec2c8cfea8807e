"""WARC archives: a writer that shares payloads between equal records, and a sequential reader.

Each record is one gzip member. The writer stores a payload once: of records with equal payloads of at least
`least` bytes the one with the smallest id is a response, the others are revisit records that refer to it. The reader
goes through a file once, in blocks: it inflates member after member, frames each record by its content length and
compares the payload's SHA-256 with the digest in its header, and a revisit's digest with that of the response it refers to.

Tasks write to names of their own and move the finished file, so a task that runs twice leaves one archive. Paths are
URIs of any file system that pyarrow opens; every executor must see them.

Nulls and odd input: a null payload is empty. A null id is written without a number, read back as null, and is
the response only where all ids of equal payloads are null. Rows that repeat the id and payload of a response are
responses too. URLs are written percent-encoded where they hold blanks or control characters. An empty table makes no
archive.
"""

from __future__ import annotations

import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator
from typing import NamedTuple
from urllib.parse import quote

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .kernel import released
from .tables import BROADCAST_ROWS, keep

from ..shipping import cut, work_dir
VERSION, DATE, BLOCK, SALTS = "WARC/1.1", "2000-01-01T00:00:00Z", 1 << 16, 16
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
READ = "page_id long, url string, payload binary, payload_bytes long, payload_digest string, record_type string, refers_to long, verified boolean"


class Record(NamedTuple):
    headers: dict[str, str]
    block: bytes


def record_bytes(headers: dict[str, str], block: bytes) -> bytes:
    """One record as a gzip member."""
    lines = [VERSION, *(f"{k}: {v}" for k, v in headers.items()), f"Content-Length: {len(block)}", "", ""]
    squeeze = zlib.compressobj(6, zlib.DEFLATED, 31)
    return squeeze.compress("\r\n".join(lines).encode() + block + b"\r\n\r\n") + squeeze.flush()


def inflated(read, size: int = BLOCK) -> Iterator[bytes]:
    """Pieces of a file of gzip members as it is read; `read(n)` gives at most n bytes."""
    open_, begun = zlib.decompressobj(31), False
    while data := read(size):
        while data:
            begun = True
            yield open_.decompress(data)
            data = open_.unused_data
            if open_.eof:
                open_, begun = zlib.decompressobj(31), False
    if begun:
        raise ValueError("the archive ends inside a gzip member")


def records(read) -> Iterator[Record]:
    """The records of an archive in order."""
    buffer, source = bytearray(), inflated(read)

    def fill(least: int) -> bool:
        while len(buffer) < least:
            more = next(source, None)
            if more is None:
                return False
            buffer.extend(more)
        return True

    while True:
        seen = 0
        while (end := buffer.find(b"\r\n\r\n", max(0, seen - 3))) < 0:
            seen = len(buffer)
            if not fill(seen + 1):
                if buffer:
                    raise ValueError("the archive ends inside a header")
                return
        first, *lines = bytes(buffer[:end]).decode().split("\r\n")
        if not first.startswith("WARC/"):
            raise ValueError(f"not a record: {first[:40]!r}")
        headers = dict(x.split(": ", 1) for x in lines)
        size = int(headers["Content-Length"])
        if not fill(end + 4 + size + 4):
            raise ValueError("the archive ends inside a record")
        yield Record(headers, bytes(buffer[end + 4 : end + 4 + size]))
        del buffer[: end + 4 + size + 4]


def _urn(page_id) -> str:
    return f"<urn:page:{'' if page_id is None else page_id}>"


def _page(urn: str | None) -> int | None:
    found = re.fullmatch(r"<urn:page:(-?\d+)>", urn or "")
    return int(found[1]) if found else None


def with_decisions(pages: DataFrame, id_col: str = "page_id", payload: str = "html", url: str = "url", least: int = 100) -> DataFrame:
    """id, url, payload, n_bytes, digest and refers_to (null for responses). Only digests and ids are aggregated. Digests that occur more than once meet the rows by a checked broadcast; if they are too many, by a join in which each digest has SALTS parts, so that the rows of a frequent one are dealt out."""
    body = F.coalesce(F.col(payload).cast("string"), F.lit(""))
    rows = pages.select(F.col(id_col).cast("long").alias("id"), F.col(url).cast("string").alias("url"), body.alias("payload")).withColumns(
        {"digest": F.sha2(F.col("payload"), 256), "n_bytes": F.octet_length("payload").cast("long")}
    )
    firsts = keep(rows.where(F.col("n_bytes") >= least).groupBy("digest").agg(F.min("id").alias("first"), F.count("*").alias("n")).where("n > 1").drop("n"))
    refers = F.when((F.col("n_bytes") >= least) & F.col("first").isNotNull() & ~F.col("id").eqNullSafe(F.col("first")), F.col("first"))
    return met(rows, firsts, "digest", "id").select("id", "url", "payload", "n_bytes", "digest", refers.alias("refers_to"))


def met(rows: DataFrame, few: DataFrame, key: str, by: str, most: int = BROADCAST_ROWS) -> DataFrame:
    """rows left joined with a kept table of one row for each key: by a checked broadcast, else salted by the column `by`."""
    if few.count() <= most:
        return rows.join(F.broadcast(few), key, "left")
    salt = F.pmod(F.xxhash64(by), F.lit(SALTS)).cast("int")
    dealt = few.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return rows.withColumn("__salt", salt).join(dealt, [key, "__salt"], "left").drop("__salt")


def write(decided: DataFrame, to: str) -> DataFrame:
    """Writes an archive for each partition; gives path and n_records of each. The result is a checkpoint: reading it writes nothing again."""

    @released
    def run(batches):
        out = None
        for batch in batches:
            for page_id, url, payload, size, digest, refers in zip(*(batch.column(c).to_pylist() for c in ("id", "url", "payload", "n_bytes", "digest", "refers_to")), strict=True):
                if out is None:
                    fs, base = pafs.FileSystem.from_uri(to)
                    fs.create_dir(base, recursive=True)
                    task = TaskContext.get()
                    name = f"{base}/records-{task.partitionId():06d}.warc.gz"
                    part, n = f"{name}.{task.taskAttemptId()}.part", 0
                    out = fs.open_output_stream(part, compression=None)
                    out.write(record_bytes({"WARC-Type": "warcinfo", "WARC-Date": DATE, "WARC-Record-ID": f"<urn:archive:{task.partitionId()}>", "Content-Type": "application/warc-fields"}, b"format: WARC File Format 1.1\r\n"))
                head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {size}\r\n\r\n".encode()
                headers = {"WARC-Type": "response" if refers is None else "revisit", "WARC-Date": DATE, "WARC-Record-ID": _urn(page_id)}
                if url is not None:
                    headers["WARC-Target-URI"] = quote(url, safe="%/:=&?~#+!$,;'@()*[]")
                headers |= {"WARC-Payload-Digest": f"sha256:{digest}", "Content-Type": "application/http; msgtype=response"}
                if refers is None:
                    head += payload.encode()
                else:
                    headers |= {"WARC-Profile": PROFILE, "WARC-Refers-To": _urn(refers)}
                out.write(record_bytes(headers, head))
                n += 1
        if out is not None:
            out.close()
            fs.move(part, name)
            yield pa.RecordBatch.from_arrays([pa.array([f"{to}/{name.rpartition('/')[2]}"]), pa.array([n], pa.int64())], ["path", "n_records"])

    return cut(decided.mapInArrow(run, "path string, n_records long"))


def parse(rec: Record) -> tuple | None:
    """A response or revisit as a row of READ, None for other records."""
    kind = rec.headers.get("WARC-Type")
    if kind not in ("response", "revisit"):
        return None
    head, _, payload = rec.block.partition(b"\r\n\r\n")
    size = next(int(x.split(b":")[1]) for x in head.split(b"\r\n") if x.lower().startswith(b"content-length:"))
    digest = rec.headers["WARC-Payload-Digest"].removeprefix("sha256:")
    fine = kind == "revisit" or (len(payload) == size and hashlib.sha256(payload).hexdigest() == digest)
    return (_page(rec.headers["WARC-Record-ID"]), rec.headers.get("WARC-Target-URI"), None if kind == "revisit" else payload, size, digest, kind, _page(rec.headers.get("WARC-Refers-To")), fine)


def read(archives: DataFrame, path: str = "path", strict: bool = True, payloads: bool = True) -> DataFrame:
    """The response and revisit records of the archives at the given paths, as READ says. strict: a payload that doesn't fit its digest ends the job, and so does an archive without as many records as its row's n_records says, if there is that column; else `verified` tells. Whether a revisit's digest is that of the response it refers to is not known here, see `linked`. payloads: False leaves them null once verified."""
    counted = "n_records" in archives.columns

    @released
    def run(batches):
        names = [x.split()[0] for x in READ.split(", ")]
        types = [pa.int64(), pa.string(), pa.binary(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.bool_()]

        def out(rows):
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), types, strict=True)], names)

        for batch in batches:
            for uri, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist() if counted else [None] * batch.num_rows, strict=True):
                fs, at = pafs.FileSystem.from_uri(uri)
                rows, held, found = [], 0, 0
                with fs.open_input_stream(at, compression=None) as f:
                    for rec in records(f.read):
                        row = parse(rec)
                        if row is None:
                            continue
                        if strict and not row[-1]:
                            raise ValueError(f"a payload of {uri} doesn't fit its digest: {rec.headers['WARC-Record-ID']}")
                        found += 1
                        held += len(row[2] or b"") * payloads
                        rows.append(row if payloads else (*row[:2], None, *row[3:]))
                        if held >= 4 << 20 or len(rows) >= 10_000:
                            yield out(rows)
                            rows, held = [], 0
                if rows:
                    yield out(rows)
                if strict and n is not None and n != found:
                    raise ValueError(f"{uri} has {found} records of {n}")

    return archives.select(path, *(["n_records"] if counted else [])).mapInArrow(run, READ)


def linked(found: DataFrame, among: DataFrame | None = None) -> DataFrame:
    """found, where a revisit is `verified` if a response of the page that it refers to has its digest and size. among: where the responses are, by default found itself; of them only ids, digests and sizes are read."""
    own = (found if among is None else among).where("record_type = 'response' and page_id is not null").select(F.col("page_id").alias("refers_to"), F.struct(F.col("payload_digest").alias("d"), F.col("payload_bytes").alias("n")).alias("__x"))
    wanted = keep(found.where("record_type = 'revisit'").select("refers_to").distinct())
    own = own.join(F.broadcast(wanted) if wanted.count() <= BROADCAST_ROWS else wanted, "refers_to", "left_semi")
    there = keep(own.groupBy("refers_to").agg(F.collect_set("__x").alias("__there")))
    fits = F.exists("__there", lambda x: (x["d"] == F.col("payload_digest")) & (x["n"] == F.col("payload_bytes")))
    both = met(found, there, "refers_to", "page_id")
    return both.withColumn("verified", F.when(F.col("record_type") == "revisit", F.coalesce(fits, F.lit(False))).otherwise(F.col("verified"))).select(*found.columns)


def round_trip(pages: DataFrame, to: str | None = None, id_col: str = "page_id", payload: str = "html", url: str = "url", payloads: bool = True) -> DataFrame:
    """Writes pages to archives in `to`, by default a new folder in the shared one, and reads them back."""
    spark: SparkSession = pages.sparkSession
    to = to or f"{work_dir(spark)}/warc-{uuid.uuid4().hex}"
    archives = write(with_decisions(pages, id_col, payload, url), to)
    if not payloads:
        return linked(keep(read(archives, payloads=False)))
    return linked(read(archives), keep(read(archives, payloads=False)))
