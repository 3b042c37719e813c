"""WARC archives compressed record by record with a trained Zstandard dictionary.

A file begins with a skippable frame (magic 0x184D2A5D) that holds the dictionary, as the WARC-Zstandard
convention has it; each record is a frame of its own, so a reader can begin at any record. The dictionary
is trained on whole records of a bounded sample of the input (``sample_bytes``, a parameter of this fit; pages of over 16 times
the mean size are not taken for it); every record is archived.

Of the pages with one payload the smallest page_id is a ``response``; the others are ``revisit`` records
that name it and have no payload, but its length and digest. A task writes its file under a name of
its own attempt and then gives it its final name, so a task that runs again leaves one whole file.

Defined results: a null html is an empty payload; pages with equal payloads revisit the first, empty ones too
if ``min_revisit`` is 0; rows that repeat a page_id are archived each (equal rows among them
are responses both if theirs is the smallest id); an empty table makes no file; extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenbox.llm.scratch import Scratch, small_batches

#: fixed values of the WARC-Zstandard convention
DICTIONARY_FRAME = 0x184D2A5D
DICTIONARY_BYTES = 64 << 10
SAMPLE_BYTES = 4 << 20
LEVEL = 3
#: payload bytes after which a task begins its next file
FILE_BYTES = 256 << 20
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_SPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page_id: int | None) -> str:
    return f"<urn:uuid:{uuid.uuid5(_SPACE, f'page-{page_id}')}>"


def make_record(page_id: int | None, url: str | None, payload: bytes, response: int | None, date: str) -> bytes:
    """One record; ``response`` is the page that a revisit refers to, or None."""
    revisit = response is not None
    digest = payload_digest(payload)
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if revisit else http + payload
    target = (url or "").replace("\r", "%0D").replace("\n", "%0A")
    fields = [("WARC-Type", "revisit" if revisit else "response"), ("WARC-Record-ID", record_id(page_id)), ("WARC-Date", date), ("WARC-Target-URI", target)]
    fields += [("WARC-Page-ID", page_id)] if page_id is not None else []
    fields += [("WARC-Profile", _PROFILE), ("WARC-Refers-To", record_id(response)), ("WARC-Refers-To-Page-ID", response)] if revisit else []
    fields += [("WARC-Payload-Digest", f"sha1:{digest}"), ("Content-Type", "application/http; msgtype=response"), ("Content-Length", len(block))]
    head = "".join(f"{k}: {v}\r\n" for k, v in fields)
    return f"WARC/1.1\r\n{head}\r\n".encode() + block + b"\r\n\r\n"


def parse_record(record: bytes) -> tuple[dict[str, str], bytes, bytes]:
    """(WARC fields, HTTP head, payload) of a record, lengths checked."""
    head, _, rest = record.partition(b"\r\n\r\n")
    version, *lines = head.decode().split("\r\n")
    fields = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in lines)
    size = int(fields["Content-Length"])
    if version != "WARC/1.1" or rest[size:] != b"\r\n\r\n":
        raise ValueError("not a WARC record")
    http, _, payload = rest[:size].partition(b"\r\n\r\n")
    return fields, http, payload


def train_dictionary(samples: list[bytes], size: int = DICTIONARY_BYTES) -> bytes:
    """A dictionary of the samples; their own bytes where there are too few to train on."""
    import zstandard

    try:
        return zstandard.train_dictionary(size, samples, k=256, d=8).as_bytes()
    except zstandard.ZstdError:
        return b"".join(samples)[:size]


def _file_system(root: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(root) if "://" in root else (fs.LocalFileSystem(), root.removeprefix("file:"))


def mark_revisits(pages: DataFrame, min_revisit: int = 0) -> DataFrame:
    """page_id, digest and response (the smallest page_id of that payload) of the pages that are not that one."""
    payload = F.coalesce("html", F.lit(""))
    named = pages.where(F.octet_length(payload) >= min_revisit).select("page_id", F.unhex(F.sha1(payload)).alias("digest"))
    firsts = named.groupBy("digest").agg(F.min("page_id").alias("response"), F.max("page_id").alias("last")).where("response < last").drop("last")
    return named.join(firsts, "digest").where("page_id > response").select("page_id", "digest", "response").distinct()


def write_archives(pages: DataFrame, root: str, scratch: Scratch, min_revisit: int = 0, date: str = "2024-01-01T00:00:00Z", sample_bytes: int = SAMPLE_BYTES, file_bytes: int = FILE_BYTES) -> DataFrame:
    """Archive ``pages`` (page_id, url, html) below ``root``; (path, records) of the files written."""
    pages = pages.select("page_id", "url", "html")
    size = F.octet_length(F.coalesce("html", F.lit("")))
    mean, rows = pages.agg(F.coalesce(F.avg(size), F.lit(0.0)), F.count("*")).first()
    count = max(16, int(sample_bytes / max(mean, 1)))
    # twice the wanted pages by their hash, so that tasks together hand over a bounded number of bytes
    share = F.pmod(F.xxhash64("page_id"), F.lit(1 << 30)) < int(min(1.0, 2 * count / max(rows, 1)) * (1 << 30))
    sample = pages.where(share & (size <= 16 * max(mean, 1))).orderBy(F.xxhash64("page_id"), "page_id").limit(count).collect()
    records = [make_record(r["page_id"], r["url"], (r["html"] or "").encode(), None, date) for r in sample]
    dictionary = pages.sparkSession.sparkContext.broadcast(train_dictionary(records) if records else b"")
    revisits = scratch.write(mark_revisits(pages, min_revisit), "revisits").withColumnsRenamed({"page_id": "again", "digest": "payload"})
    digest = F.unhex(F.sha1(F.coalesce(pages["html"], F.lit(""))))
    marked = pages.join(revisits, (pages["page_id"] == revisits["again"]) & (digest == revisits["payload"]), "left").select("page_id", "url", F.coalesce("html", F.lit("")).alias("html"), "response")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard
        from pyspark import TaskContext

        files, base = _file_system(root)
        files.create_dir(base, recursive=True)
        task, made = TaskContext.get(), []
        raw = dictionary.value
        press = zstandard.ZstdCompressor(level=LEVEL, dict_data=zstandard.ZstdCompressionDict(raw, dict_type=zstandard.DICT_TYPE_AUTO))
        out, name, n, filled = None, "", 0, 0

        def close():
            nonlocal out
            out.close()
            files.move(f"{base}/.{name}.{task.taskAttemptId()}", f"{base}/{name}")
            made.append((name, n))
            out = None

        for batch in batches:
            for i in range(batch.num_rows):
                page_id, url, html, response = (c[i].as_py() for c in batch.columns)
                if out is None:
                    name, n, filled = f"part-{task.partitionId():06d}-{len(made):04d}.warc.zst", 0, 0
                    out = files.open_output_stream(f"{base}/.{name}.{task.taskAttemptId()}", compression=None)
                    out.write(struct.pack("<II", DICTIONARY_FRAME, len(raw)) + raw)
                payload = html.encode()
                out.write(press.compress(make_record(page_id, url, payload, response, date)))
                n, filled = n + 1, filled + len(payload)
                if filled >= file_bytes:
                    close()
        if out is not None:
            close()
        yield pa.RecordBatch.from_arrays([pa.array([f"{root}/{m}" for m, _ in made], pa.string()), pa.array([k for _, k in made], pa.int64())], ["path", "records"])

    return scratch.write(marked.mapInArrow(run, "path string, records long"), "files")


def archive_records(stream, chunk: int = 1 << 20) -> Iterator[bytes]:
    """The records of an open archive, one frame at a time."""
    import zstandard

    magic, size = struct.unpack("<II", stream.read(8))
    if magic != DICTIONARY_FRAME:
        raise ValueError("the archive does not begin with its dictionary")
    raw = stream.read(size)
    context = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(raw, dict_type=zstandard.DICT_TYPE_AUTO))
    rest = b""
    while True:
        if not rest:
            rest = stream.read(chunk)
            if not rest:
                return
        frame, parts = context.decompressobj(), []
        while not frame.eof:
            if not rest:
                rest = stream.read(chunk)
                if not rest:
                    raise ValueError("the archive ends inside a record")
            parts.append(frame.decompress(rest))
            rest = frame.unused_data if frame.eof else b""
        yield b"".join(parts)


def read_archives(spark: SparkSession, files: DataFrame) -> DataFrame:
    """page_id, record_type, payload_bytes, payload_digest, refers_to, target, payload length stored."""
    schema = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, target string, stored_bytes long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in schema.split(", ")]
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64()]

        def made(rows):
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)

        for batch in batches:
            for path in batch.column(0).to_pylist():
                system, place = _file_system(path)
                rows = []
                with system.open_input_stream(place, compression=None) as stream:
                    for record in archive_records(stream):
                        fields, http, payload = parse_record(record)
                        length = int(http.rpartition(b"Content-Length: ")[2])
                        kind, digest = fields["WARC-Type"], fields["WARC-Payload-Digest"].removeprefix("sha1:")
                        if kind == "response" and (len(payload) != length or payload_digest(payload) != digest):
                            raise ValueError("a payload differs from its digest")
                        page, refers = fields.get("WARC-Page-ID"), fields.get("WARC-Refers-To-Page-ID")
                        rows.append((page and int(page), length, digest, kind, refers and int(refers), fields["WARC-Target-URI"], len(payload)))
                        if len(rows) == 4096:
                            yield made(rows)
                            rows = []
                if rows:
                    yield made(rows)

    return files.select("path").repartition(max(1, files.count())).mapInArrow(run, schema)


def archive_digest(pages: DataFrame, min_revisit: int = 0) -> DataFrame:
    """Write the archives, read them back: a row for each page."""
    scratch = Scratch(pages.sparkSession, "warc")
    files = write_archives(pages, scratch.at("archives"), scratch, min_revisit)
    with small_batches(pages.sparkSession):
        return read_archives(pages.sparkSession, files).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
