"""WARC archives: writing, normalising monolithic gzip files, indexed reading.

`write_monolithic` writes every partition's records as one gzip stream a file, as many crawlers do. `normalise` inflates
such a file once, front to back, writes each record as a gzip member of its own and a sidecar index of (offset, length).
`read_records` then fetches any record by one seek. Files go to a folder that all executors share; a task names its files
afresh at every attempt and reports them when they are complete, so retries leave no half-written file in the result.

Defined results: a null payload counts as empty; a null url is left out of the header; a null id has the record id
``urn:page:null``. Of records with equal payloads of at least `least_bytes` bytes, those with the largest id are responses
and the others revisit it (a null id revisits; where all ids are null, all are responses). An empty table gives no file.
"""

from __future__ import annotations

import base64
import hashlib
import json
import uuid
import zlib

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, functions as F

from .common import bounded_batches, maybe_broadcast, new_folder, packed, stash

CHUNK = 1 << 20
HTTP_HEAD = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=UTF-8\r\nContent-Length: %d\r\n\r\n"
FILE_SCHEMA = "path string, records long"
INDEX_SCHEMA = "path string, offset long, length long"
RECORD_SCHEMA = "record_id string, page_id long, url string, record_type string, refers_to long, payload binary, payload_bytes long, payload_digest string"


def _open(folder: str):
    return pafs.FileSystem.from_uri(folder)


def _urn(page_id) -> str:
    return f"<urn:page:{'null' if page_id is None else page_id}>"


def _page(urn: str | None) -> int | None:
    tail = (urn or "").rstrip(">").rpartition(":")[2]
    return int(tail) if tail.lstrip("-").isdigit() else None


def _oneline(s: str) -> str:
    return s.replace("\r", "%0D").replace("\n", "%0A")


def build_record(page_id, url, payload: bytes, digest: str, refers_to, revisit: bool, date: str) -> bytes:
    """One WARC/1.1 record; a revisit holds the headers only."""
    head = HTTP_HEAD % len(payload)
    block = head if revisit else head + payload
    lines = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: {_urn(page_id)}", f"WARC-Date: {date}"]
    if url is not None:
        lines.append(f"WARC-Target-URI: {_oneline(url)}")
    lines += [f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Bytes: {len(payload)}"]
    if revisit:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {_urn(refers_to)}"]
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}", "", ""]
    return "\r\n".join(lines).encode() + block + b"\r\n\r\n"


def parse_headers(head: bytes) -> dict[str, str]:
    out = {}
    for line in head.decode("utf-8", "replace").split("\r\n")[1:]:
        name, _, value = line.partition(":")
        out[name.strip().lower()] = value.strip()
    return out


def mark_revisits(pages: DataFrame, ident: str, payload: str, least_bytes: int = 0) -> DataFrame:
    """`_row, _id, _text, _sha, _keep`: `_keep` is the id of the response that a row revisits, else null."""
    rows = packed(pages, payload, ident).withColumn("_text", F.coalesce("_text", F.lit("")).cast("binary"))
    rows = rows.withColumn("_sha", F.sha1("_text"))
    large = rows.where(F.octet_length("_text") >= least_bytes).groupBy("_sha").agg(F.max("_id").alias("_keep"), F.count("*").alias("_n"))
    again = maybe_broadcast(stash(large.where("_n > 1 and _keep is not null").select("_sha", "_keep"), "payloads"), 64)
    keep = F.when(F.col("_id").eqNullSafe(F.col("_keep")) | (F.octet_length("_text") < least_bytes), None).otherwise(F.col("_keep"))
    return rows.join(again, "_sha", "left").withColumn("_keep", keep)


def _writer(folder: str, level: int, roll_bytes: int, date: str):
    def run(batches):
        fs, base = _open(folder)
        out = None
        for b in batches:
            for pid, url, data, sha, keep in zip(*(c.to_pylist() for c in b.columns)):
                if out is None:
                    path = f"{base}/{uuid.uuid4().hex}.warc.gz"
                    out, gz, size, n = fs.open_output_stream(path, compression=None), zlib.compressobj(level, wbits=31), 0, 0
                digest = base64.b32encode(bytes.fromhex(sha)).decode()
                record = build_record(pid, url, data, digest, keep, keep is not None, date)
                out.write(gz.compress(record))
                size, n = size + len(record), n + 1
                if size >= roll_bytes:
                    out.write(gz.flush())
                    out.close()
                    yield pa.RecordBatch.from_pydict({"path": [path], "records": [n]})
                    out = None
        if out is not None:
            out.write(gz.flush())
            out.close()
            yield pa.RecordBatch.from_pydict({"path": [path], "records": [n]})

    return run


def write_monolithic(
    pages: DataFrame, folder: str, ident: str = "page_id", url: str = "url", payload: str = "html",
    least_bytes: int = 0, level: int = 1, roll_bytes: int = 128 << 20, date: str = "2024-01-01T00:00:00Z",
) -> DataFrame:
    """Write all rows as whole-file gzip streams; returns (path, records) of the files, already written."""
    fs, base = _open(folder)
    fs.create_dir(base, recursive=True)
    rows = mark_revisits(pages, ident, payload, least_bytes).select(F.col("_id").cast("long"), F.col("_row")[url].alias("_url"), "_text", "_sha", F.col("_keep").cast("long"))
    return stash(rows.mapInArrow(_writer(folder, level, roll_bytes, date), FILE_SCHEMA), "warc-files")


def inflate(stream):
    """Chunks of the inflated bytes of a gzip stream with one member or many."""
    gz, started = zlib.decompressobj(wbits=31), False
    while data := stream.read(CHUNK):
        while data:
            started = True
            yield gz.decompress(data, 4 * CHUNK)
            while gz.unconsumed_tail:
                yield gz.decompress(gz.unconsumed_tail, 4 * CHUNK)
            data = gz.unused_data
            if gz.eof:
                gz, started = zlib.decompressobj(wbits=31), False
    if started and not gz.eof:
        raise ValueError("gzip stream ends early")


def split_records(chunks):
    """From inflated chunks: ("head", bytes) at each record's start, then ("body", bytes) pieces; holds one chunk at a time."""
    buf, at, left = b"", 0, 0
    for chunk in chunks:
        buf, at = buf[at:] + chunk, 0
        while at < len(buf):
            if left:
                piece = buf[at: at + left]
                at, left = at + len(piece), left - len(piece)
                yield "body", piece
                continue
            end = buf.find(b"\r\n\r\n", at)
            if end < 0:
                break
            head, at = buf[at: end + 4], end + 4
            left = int(parse_headers(head)["content-length"]) + 4
            yield "head", head
    if left or buf[at:].strip():
        raise ValueError("WARC record is cut off")


def _normaliser(folder: str, level: int):
    def run(batches):
        fs, base = _open(folder)
        for b in batches:
            for source in b.column(0).to_pylist():
                target = f"{base}/{uuid.uuid4().hex}.warc.gz"
                index, at, gz = [], 0, None
                with fs.open_input_stream(source, compression=None) as stream, fs.open_output_stream(target, compression=None) as out:

                    def put(data):
                        out.write(data)
                        return len(data)

                    for kind, piece in split_records(inflate(stream)):
                        if kind == "head":
                            if gz is not None:
                                at += put(gz.flush())
                                index.append((start, at - start, meta))
                            gz, start = zlib.compressobj(level, wbits=31), at
                            h = parse_headers(piece)
                            meta = {"id": h["warc-record-id"], "type": h["warc-type"], "url": h.get("warc-target-uri")}
                        at += put(gz.compress(piece))
                    if gz is not None:
                        at += put(gz.flush())
                        index.append((start, at - start, meta))
                with fs.open_output_stream(f"{target}.idx", compression=None) as side:
                    side.write("".join(json.dumps({"offset": o, "length": n} | m) + "\n" for o, n, m in index).encode())
                yield pa.RecordBatch.from_pydict({"path": [target] * len(index), "offset": [o for o, _, _ in index], "length": [n for _, n, _ in index]},
                                                 schema=pa.schema([("path", pa.string()), ("offset", pa.int64()), ("length", pa.int64())]))

    return run


def normalise(files: DataFrame, folder: str, level: int = 1) -> DataFrame:
    """Rewrite each file of `files` (column path) record by record; returns the index (path, offset, length) of the new files."""
    fs, base = _open(folder)
    fs.create_dir(base, recursive=True)
    spread = files.select("path").repartition(max(1, min(files.count(), 10_000)))
    return stash(spread.mapInArrow(_normaliser(folder, level), INDEX_SCHEMA), "warc-index")


def _reader(folder: str):
    def run(batches):
        fs, _ = _open(folder)
        name, file = None, None
        names = [f.split()[0] for f in RECORD_SCHEMA.split(", ")]
        types = [{"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}[f.split()[1]] for f in RECORD_SCHEMA.split(", ")]

        def batch(rows):
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names)

        for b in batches:
            rows, size = [], 0
            for path, offset, length in zip(*(c.to_pylist() for c in b.columns)):
                if path != name:
                    name, file = path, fs.open_input_file(path)
                file.seek(offset)
                record = zlib.decompress(file.read(length), wbits=31)
                head, _, rest = record.partition(b"\r\n\r\n")
                h = parse_headers(head)
                block = rest[: int(h["content-length"])]
                payload = block.partition(b"\r\n\r\n")[2]
                revisit = h["warc-type"] == "revisit"
                declared = h["warc-payload-digest"].partition(":")[2]
                if not revisit and base64.b32encode(hashlib.sha1(payload).digest()).decode() != declared:
                    raise ValueError(f"payload of {h['warc-record-id']} does not have its digest")
                rows.append((h["warc-record-id"].strip("<>"), _page(h["warc-record-id"]), h.get("warc-target-uri"), h["warc-type"],
                             _page(h.get("warc-refers-to")), None if revisit else payload, int(h["x-payload-bytes"]), declared))
                size += len(payload)
                if size >= 16 * CHUNK:
                    yield batch(rows)
                    rows, size = [], 0
            if rows:
                yield batch(rows)

    return run


def read_records(index: DataFrame, folder: str) -> DataFrame:
    """Every record that the index lists, by random access; a revisit has a null payload. Checks each payload's digest."""
    return index.select("path", "offset", "length").mapInArrow(_reader(folder), RECORD_SCHEMA)


def archive_round_trip(pages: DataFrame, **options) -> DataFrame:
    """Write `pages` as monolithic archives, normalise them, and read every record back through the index."""
    spark = pages.sparkSession
    bounded_batches(spark)
    whole, single = new_folder(spark, "warc-whole"), new_folder(spark, "warc-records")
    return read_records(normalise(write_monolithic(pages, whole, **options), single), single)
