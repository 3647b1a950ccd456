"""WARC archives written and read as a chunked record table.

A payload travels as rows (record, chunk number, bytes) of at most CHUNK bytes. The writer streams the rows of a record
into one gzip member; the reader inflates a member piece by piece and returns rows again. Both carry a running SHA-1, so
neither holds a whole record of an oversized payload; chunks are cut from the column one at a time, and no array of them is
built. Of equal payloads the smallest id is a response record, the others are revisit records that name it; what is read
of a revisit is held against the response that it names.

Defined cases: a null payload is empty; a null or unprintable URL is written as urn:page:<id>; a null id is written as an
empty field and read as null, and is the smallest only among nulls; rows that repeat an id and payload are all responses;
an empty table gives no archive and no row; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import file_system, join_unique, materialise, scratch, slices

CHUNK = 1 << 20
#: An archive is closed once it has this many bytes.
FILE_BYTES = 1 << 30


def dedupe(pages: DataFrame, id_col: str, payload_col: str, url_col: str, min_bytes: int) -> DataFrame:
    """id, url, body, size, sha (hex), first: the id of the response with an equal payload if the row is a revisit, else null."""
    body = F.coalesce(F.col(payload_col).cast("binary"), F.lit(b""))
    rows = pages.select(F.col(id_col).cast("long").alias("id"), F.col(url_col).cast("string").alias("url"), body.alias("body")).withColumn("size", F.octet_length("body").cast("long")).withColumn("sha", F.sha1("body"))
    groups = rows.select("id", "sha", "size").groupBy("sha", "size").agg(F.min("id").alias("first"), F.count(F.lit(1)).alias("n"))
    groups = materialise(groups.where((F.col("n") > 1) & (F.col("size") >= min_bytes)), "groups")
    total = groups.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    out = join_unique(rows, groups, ["sha", "size"], "n", total, hint="shuffle_hash")
    return out.withColumn("first", F.when(~F.col("first").eqNullSafe(F.col("id")), F.col("first")))


def chunked(rows: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """One row a chunk, in order within its task; a revisit has one empty chunk."""
    n = F.when(F.col("first").isNotNull(), 1).otherwise(F.greatest(F.lit(1), F.ceil(F.col("size") / chunk))).cast("int")
    numbered = rows.withColumn("n", n).withColumn("no", F.explode(F.sequence(F.lit(0), n - 1)))
    return numbered.select("id", "url", "size", "sha", "first", "n", "no", F.when(F.col("first").isNotNull(), F.lit(b"")).otherwise(F.substring("body", F.col("no") * chunk + 1, F.lit(chunk))).alias("bytes"))


def _head(id_, url, size, sha, first) -> bytes:
    name = "" if id_ is None else str(id_)
    url = url if url and re.fullmatch(r"[!-~]+", url) else f"urn:page:{name}"
    digest = base64.b32encode(bytes.fromhex(sha)).decode()
    uid = lambda i: uuid.UUID(bytes=hashlib.md5(f"{i}:{sha}".encode()).digest())
    http = b"" if first is not None else f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {size}\r\n\r\n".encode()
    lines = ["WARC/1.1", f"WARC-Type: {'response' if first is None else 'revisit'}", f"WARC-Record-ID: <urn:uuid:{uid(name)}>", "WARC-Date: 1970-01-01T00:00:00Z", f"WARC-Target-URI: {url}", f"WARC-Payload-Digest: sha1:{digest}", f"X-Page-Id: {name}", f"X-Payload-Length: {size}"]
    if first is not None:
        lines += [f"WARC-Refers-To: <urn:uuid:{uid(first)}>", f"X-Refers-To-Page: {first}", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(http) + (size if first is None else 0)}"]
    return ("\r\n".join(lines) + "\r\n\r\n").encode() + http


def write_archives(pages: DataFrame, folder: str, id_col: str = "page_id", payload_col: str = "html", url_col: str = "url", min_bytes: int = 0, chunk: int = CHUNK, level: int = 1) -> DataFrame:
    """Write pages as .warc.gz files in folder (any store); returns their manifest (path in that store, records, bytes).

    Each try of a task writes files of its own names, and only those in the manifest count, so retries leave no doubles.
    """

    def run(batches):
        fs, at = file_system(folder)
        fs.create_dir(at, recursive=True)
        out, path, made, sent, z, sha = None, "", 0, 0, None, None
        for b in slices(batches, 64):
            for r in b.to_pylist():
                if out is None:
                    name, made, sent = f"{uuid.uuid4().hex}.warc.gz", 0, 0
                    path, out = f"{folder.rstrip('/')}/{name}", fs.open_output_stream(f"{at}/{name}")
                if r["no"] == 0:
                    z, sha = zlib.compressobj(level, zlib.DEFLATED, 31), hashlib.sha1()
                    sent += out.write(z.compress(_head(r["id"], r["url"], r["size"], r["sha"], r["first"])))
                sha.update(r["bytes"])
                sent += out.write(z.compress(r["bytes"]))
                if r["no"] == r["n"] - 1:
                    if r["first"] is None and sha.hexdigest() != r["sha"]:
                        raise ValueError(f"record {r['id']}: its chunks don't make up its payload")
                    sent += out.write(z.compress(b"\r\n\r\n") + z.flush())
                    made += 1
                    if sent >= FILE_BYTES:
                        out.close()
                        yield pa.RecordBatch.from_pydict({"path": [path], "records": [made], "bytes": [sent]})
                        out = None
        if out is not None:
            out.close()
            yield pa.RecordBatch.from_pydict({"path": [path], "records": [made], "bytes": [sent]})

    rows = chunked(dedupe(pages, id_col, payload_col, url_col, min_bytes), chunk)
    return materialise(rows.mapInArrow(run, "path string, records long, bytes long"), "manifest")


def _inflated(file, size: int):
    """Pieces of a file of gzip members."""
    z = zlib.decompressobj(31)
    while data := file.read(size):
        while data:
            yield z.decompress(data, size)
            data = z.unconsumed_tail
            if z.eof:
                data, z = z.unused_data, zlib.decompressobj(31)
    yield z.flush()


def records(file, chunk: int = CHUNK):
    """(headers, chunk number, bytes, running sha1, last) of each chunk of each record's payload."""
    source, held = _inflated(file, chunk), b""
    while True:
        while (cut := held.find(b"\r\n\r\n")) < 0:
            if (more := next(source, None)) is None:
                return
            held += more
        head = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in held[:cut].decode().split("\r\n")[1:])}
        left, held = int(head["content-length"]), held[cut + 4 :]
        if left and head.get("content-type", "").startswith("application/http"):
            while (cut := held.find(b"\r\n\r\n")) < 0:
                held += next(source)
            left, held = left - cut - 4, held[cut + 4 :]
        sha, no = hashlib.sha1(), 0
        while True:
            while len(held) < min(left, chunk):
                held += next(source)
            part, held = held[: min(left, chunk)], held[min(left, chunk) :]
            left -= len(part)
            sha.update(part)
            yield head, no, part, sha, left == 0
            no += 1
            if not left:
                break
        while len(held) < 4:
            held += next(source)
        held = held[4:]


def read_archives(manifest: DataFrame, chunk: int = CHUNK, payload: bool = True) -> DataFrame:
    """The record table of the archives: page_id, record_type, refers_to, chunk_no, chunk_bytes, bytes, digest (of the payload so far), declared_bytes, declared_digest, last."""
    fields = "page_id long, record_type string, refers_to long, chunk_no int, chunk_bytes long, bytes binary, digest string, declared_bytes long, declared_digest string, last boolean"
    names = [f.split()[0] for f in fields.split(", ")]
    kinds = [pa.int64(), pa.string(), pa.int64(), pa.int32(), pa.int64(), pa.binary(), pa.string(), pa.int64(), pa.string(), pa.bool_()]
    def run(batches):
        for b in batches:
            for path in b.column(0).to_pylist():
                fs, at = file_system(path)
                with fs.open_input_stream(at) as f:
                    held, weight = [], 0
                    for h, no, part, sha, last in records(f, chunk):
                        number = lambda k: int(h[k]) if h.get(k) else None  # noqa: E731, B023
                        held.append((number("x-page-id"), h["warc-type"], number("x-refers-to-page"), no, len(part), part if payload else None, base64.b32encode(sha.digest()).decode(), number("x-payload-length"), h["warc-payload-digest"].partition(":")[2], last))
                        weight += len(part) * payload
                        if len(held) >= 4096 or weight > 8 * chunk:
                            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*held, strict=True), kinds, strict=True)], names)
                            held, weight = [], 0
                    if held:
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*held, strict=True), kinds, strict=True)], names)

    n = max(1, manifest.count())
    return manifest.select("path").repartitionByRange(n, "path").mapInArrow(run, fields)


def round_trip(pages: DataFrame, folder: str | None = None, **kind) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to: as read back from the archives of pages."""
    manifest = write_archives(pages, folder or scratch(pages.sparkSession, "warc"), **kind)
    read = read_archives(manifest, payload=False).where("last")
    size = F.col("chunk_no") * F.lit(CHUNK).cast("long") + F.col("chunk_bytes")
    whole = materialise(read.select("page_id", "record_type", "refers_to", size.alias("size"), "digest", "declared_bytes", "declared_digest"), "records")
    own = whole.where("record_type = 'response'")
    revisits = whole.where("record_type = 'revisit'").select("page_id", "record_type", "refers_to", F.col("declared_bytes").alias("told"), F.col("declared_digest").alias("sha"))
    # the responses that revisits name, with how many name them: a page's payload is what was read of its response
    named = revisits.groupBy("refers_to", "sha").agg(F.count(F.lit(1)).alias("n"))
    held = own.select(F.col("page_id").alias("refers_to"), F.col("digest").alias("sha"), "size").groupBy("refers_to", "sha").agg(F.max("size").alias("size"))
    held = materialise(named.join(held, ["refers_to", "sha"], "left"), "named")
    total = held.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    met = join_unique(revisits, held, ["refers_to", "sha"], "n", total)
    wrong = F.raise_error(F.concat(F.lit("no response with the payload of the revisit of page "), F.coalesce(F.col("page_id").cast("string"), F.lit("null"))))
    checked = F.when(F.col("size") == F.col("told"), F.col("size")).otherwise(wrong.cast("long"))
    there = own.select("page_id", F.col("size").alias("payload_bytes"), F.col("digest").alias("payload_digest"), "record_type", "refers_to")
    return there.unionByName(met.select("page_id", checked.alias("payload_bytes"), F.col("sha").alias("payload_digest"), "record_type", "refers_to"))
