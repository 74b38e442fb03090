"""WARC archives: one gzip member for each record, a sidecar offset index, revisits of equal payloads.

A crawler's archive is often one gzip stream over the whole file, which cannot be entered in
the middle. The normaliser inflates such a stream once, front to back, and writes each
record as a member of its own, with its offset and length in a JSON-lines index.
"""

from __future__ import annotations

import hashlib
import json
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridchain.llm.shared import scratch_path, small_batches, tidy

#: Payloads below this size are always stored in full.
LEAST_REVISIT = 100
#: Bytes of one archive file before the next is begun, about.
ROLL_BYTES = 64 << 20
CHUNK = 1 << 18
#: Header names and profile of the format's version 1.1.
VERSION = b"WARC/1.1"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def _open(uri: str):
    """File system and path of a URI; plain paths are local."""
    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


def record_bytes(kind: str, record_id: str, fields: dict[str, str], payload: bytes) -> bytes:
    head = [f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:uuid:{record_id}>", "WARC-Date: 1970-01-01T00:00:00Z", "Content-Type: application/octet-stream"]
    head += [f"{k}: {v}" for k, v in fields.items()] + [f"Content-Length: {len(payload)}"]
    return VERSION + b"\r\n" + "\r\n".join(head).encode() + b"\r\n\r\n" + payload + b"\r\n\r\n"


def split_records(chunks: Iterator[bytes]) -> Iterator[tuple[dict[str, str], bytes, bytes]]:
    """(headers, payload, whole record) of a stream of plain record bytes; holds one record at a time."""
    held, done = bytearray(), False

    def more() -> bool:
        nonlocal done
        part = next(chunks, None)
        if part is None:
            done = True
            return False
        held.extend(part)
        return True

    while True:
        while (at := held.find(b"\r\n\r\n")) < 0 and more():
            pass
        if at < 0:
            if held.strip():
                raise ValueError("a WARC record is cut off in its header")
            return
        lines = bytes(held[:at]).decode("utf-8").split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"not a WARC record: {lines[0][:40]!r}")
        headers = dict(line.split(": ", 1) for line in lines[1:])
        end = at + 4 + int(headers["Content-Length"])
        while len(held) < end + 4 and more():
            pass
        if len(held) < end:
            raise ValueError("a WARC record is shorter than its Content-Length")
        yield headers, bytes(held[at + 4 : end]), bytes(held[: end + 4])
        del held[: end + 4]


def inflate(source) -> Iterator[bytes]:
    """Plain bytes of a gzip file of one or many members, in chunks."""
    engine = zlib.decompressobj(31)
    while block := source.read(CHUNK):
        while block:
            out = engine.decompress(block, CHUNK)
            while out:
                yield out
                # output can be pending when all input is taken
                out = b"" if engine.eof else engine.decompress(engine.unconsumed_tail, CHUNK)
            block = engine.unused_data
            if engine.eof:
                engine = zlib.decompressobj(31)
            else:
                block = b""
    if tail := engine.flush():
        yield tail


def normalise(source: str, target: str, level: int = 6) -> int:
    """Rewrite a gzip archive with a member for each record, and `target`.index beside it. Returns the records."""
    (system, path), (out_system, out_path) = _open(source), _open(target)
    at = count = 0
    with system.open_input_stream(path, compression=None) as stream, out_system.open_output_stream(out_path, compression=None) as out, out_system.open_output_stream(f"{out_path}.index", compression=None) as index:
        for headers, _, whole in split_records(inflate(stream)):
            engine = zlib.compressobj(level, zlib.DEFLATED, 31)
            member = engine.compress(whole) + engine.flush()
            out.write(member)
            index.write(json.dumps({"record_id": headers["WARC-Record-ID"], "type": headers["WARC-Type"], "offset": at, "length": len(member)}).encode() + b"\n")
            at, count = at + len(member), count + 1
    return count


def read_member(uri: str, offset: int, length: int) -> tuple[dict[str, str], bytes]:
    """One record by its place in a normalised archive, without reading the rest."""
    system, path = _open(uri)
    with system.open_input_file(path) as file:
        headers, payload, _ = next(split_records(iter([zlib.decompress(file.read_at(length, offset), 31)])))
    return headers, payload


def _write_monolith(folder: str, roll: int, level: int):
    """Write records of a task to gzip files of one stream each; returns the files."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, path = _open(folder)
        system.create_dir(path, recursive=True)
        out = engine = None
        names, held = [], 0

        def close():
            if out is not None:
                out.write(engine.flush())
                out.close()

        for batch in batches:
            for row in batch.to_pylist():
                if out is None or held > roll:
                    close()
                    names.append(f"{uuid.uuid4().hex}.warc.gz")
                    out, engine, held = system.open_output_stream(f"{path}/{names[-1]}", compression=None), zlib.compressobj(level, zlib.DEFLATED, 31), 0
                payload = (row["html"] or "").encode()
                fields = {"X-Page-ID": "" if row["page_id"] is None else str(row["page_id"]), "WARC-Target-URI": (row["url"] or "urn:none").replace("\r", "").replace("\n", ""), "WARC-Payload-Digest": f"sha256:{row['payload_digest']}", "X-Payload-Length": str(len(payload))}
                if row["refers_to"] is not None:
                    fields |= {"WARC-Profile": REVISIT_PROFILE, "WARC-Refers-To": f"<urn:page:{row['refers_to']}>"}
                body = b"" if row["refers_to"] is not None else payload
                out.write(engine.compress(record_bytes("response" if row["refers_to"] is None else "revisit", str(uuid.uuid4()), fields, body)))
                held += len(body) + 500
        close()
        yield pa.RecordBatch.from_arrays([pa.array([f"{folder}/{n}" for n in names], pa.string())], ["file"])

    return tidy(run)


def _normalise_files(folder: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, path = _open(folder)
        system.create_dir(path, recursive=True)
        for batch in batches:
            for source in batch.column("file").to_pylist():
                target = f"{folder}/{uuid.uuid4().hex}.warc.gz"
                count = normalise(source, target)
                yield pa.RecordBatch.from_arrays([pa.array([source]), pa.array([target]), pa.array([count], pa.int64())], ["source", "file", "records"])

    return tidy(run)


def read_archives(files: DataFrame) -> DataFrame:
    """Records of archives (column file) as page_id, url, record_type, payload, payload_bytes, payload_digest, refers_to."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["page_id", "url", "record_type", "payload", "payload_bytes", "payload_digest", "refers_to"]
        kinds = [pa.int64(), pa.string(), pa.string(), pa.binary(), pa.int64(), pa.string(), pa.int64()]
        for batch in batches:
            for uri in batch.column("file").to_pylist():
                system, path = _open(uri)
                with system.open_input_stream(path, compression=None) as stream:
                    rows, held = [], 0
                    for h, payload, _ in split_records(inflate(stream)):
                        refers = h.get("WARC-Refers-To")
                        if refers is None:  # of a response the payload itself is measured
                            size, digest = len(payload), hashlib.sha256(payload).hexdigest()
                            if digest != h["WARC-Payload-Digest"][7:]:
                                raise ValueError(f"the payload of page {h['X-Page-ID']} doesn't match its digest")
                        else:
                            size, digest = int(h["X-Payload-Length"]), h["WARC-Payload-Digest"][7:]
                        rows.append((int(h["X-Page-ID"]) if h["X-Page-ID"] else None, h["WARC-Target-URI"], h["WARC-Type"], payload, size, digest, refers and int(refers[10:-1])))
                        held += len(payload)
                        if held > 1 << 22:
                            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names)
                            rows, held = [], 0
                    if rows:
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names)

    return files.select("file").mapInArrow(run, "page_id long, url string, record_type string, payload binary, payload_bytes long, payload_digest string, refers_to long")


def with_revisits(pages: DataFrame, least: int = LEAST_REVISIT) -> DataFrame:
    """page_id, url, html, payload_digest, refers_to (the first page with an equal payload, else null).

    Groups of equal payloads are summed up to their smallest page_id before the shuffle. A
    null page_id is never the first of a group that has another.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce("html", F.lit("")).alias("html"))
    rows = rows.withColumn("payload_digest", F.sha2(F.encode("html", "UTF-8"), 256)).withColumn("large", F.octet_length("html") >= least)
    firsts = rows.filter("large").groupBy("payload_digest").agg(F.min("page_id").alias("first_page"), F.count(F.lit(1)).alias("pages")).filter("pages > 1").drop("pages")
    later = rows.filter("large").select("page_id", "payload_digest").join(firsts, "payload_digest").filter(F.coalesce(F.col("page_id") != F.col("first_page"), F.lit(True)))
    later = later.select(F.col("page_id").alias("later"), F.col("payload_digest").alias("later_digest"), F.col("first_page").alias("refers_to")).distinct()
    same = F.col("page_id").eqNullSafe(F.col("later")) & (F.col("payload_digest") == F.col("later_digest")) & F.col("large")
    return rows.join(later, same, "left").select("page_id", "url", "html", "payload_digest", "refers_to")


def archive_pages(pages: DataFrame, folder: str | None = None, roll: int = ROLL_BYTES) -> DataFrame:
    """Write pages as whole-file gzip archives, normalise them, and return the files.

    Returns source (removed after it was rewritten is left to the caller), file, records.
    The folder must be one that all executors reach; by default the shared scratch folder.
    """
    spark: SparkSession = pages.sparkSession
    folder = folder or scratch_path(spark, "warc")
    small_batches(spark)
    written = with_revisits(pages).mapInArrow(_write_monolith(f"{folder}/monolith", roll, 6), "file string")
    written.write.parquet(f"{folder}/written")
    files = spark.read.schema("file string").parquet(f"{folder}/written")
    files.repartition(max(1, files.count())).mapInArrow(_normalise_files(f"{folder}/records"), "source string, file string, records long").write.parquet(f"{folder}/files")
    return spark.read.schema("source string, file string, records long").parquet(f"{folder}/files")


def page_records(pages: DataFrame, folder: str | None = None) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of each page, read back from its archive.

    Null html is an empty payload. Rows that repeat a page_id each give a record; when they
    are the smallest of a group of equal payloads they are all responses. An empty table
    gives no rows; other columns are ignored.
    """
    files = archive_pages(pages, folder)
    files = files.repartition(max(1, files.count()), F.xxhash64("file"))
    return read_archives(files).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
