"""Web archives in WARC 1.1, compressed by Zstandard with a dictionary of their own.

Each archive starts with a skippable frame that holds a dictionary trained on records of
that archive; every record is a frame of its own, compressed with it. A payload that several
pages have is stored once, under the smallest page_id; the others are revisit records, which
are made from its digest and length: their payloads go nowhere.

Tasks write archives under names that are never used twice and report them in a manifest.
Only what a finished task reported is read, so lost executors and repeated tasks leave
nothing but unread files.
"""

from __future__ import annotations

import base64
import hashlib
import io
import re
import struct
import uuid

import pyarrow as pa
import zstandard
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codematch.llm.joins import left_join
from codematch.llm.workers import released
from codematch.sources.io import discard, materialize, scratch_path

# Fixed values of the formats.
DICTIONARY_MAGIC = 0x184D2A5D
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"

#: Bytes of payload in one archive, of its dictionary, and of the records that it is trained on.
ARCHIVE_BYTES, DICTIONARY_BYTES, TRAINING_BYTES = 16 << 20, 32 << 10, 1 << 20
LEVEL = 3
_MANIFEST = pa.schema([("path", pa.string()), ("n_records", pa.int64()), ("n_bytes", pa.int64()), ("dictionary_bytes", pa.int64())])
_RECORDS = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())])


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page_id: int | None) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_OID, f'page {page_id}') if page_id is not None else uuid.uuid4()}>"


def record(page_id: int | None, url: str | None, payload: bytes | None, refers_to: int | None, date: str, length: int, digest: str) -> bytes:
    """One WARC record; a revisit, without payload, if refers_to is given. A header's control characters are percent-encoded."""
    revisit = refers_to is not None
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % length
    block = http if revisit else http + payload
    fields = [("WARC-Type", "revisit" if revisit else "response"), ("WARC-Record-ID", record_id(page_id)), ("WARC-Date", date), ("Content-Type", "application/http; msgtype=response"), ("WARC-Payload-Digest", f"sha1:{digest}"), ("X-Payload-Length", str(length))]
    if page_id is not None:
        fields.append(("X-Page-ID", str(page_id)))
    if url is not None:
        fields.append(("WARC-Target-URI", re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url)))
    if revisit:
        fields += [("WARC-Profile", PROFILE), ("WARC-Refers-To", record_id(refers_to)), ("X-Refers-To-Page-ID", str(refers_to))]
    fields.append(("Content-Length", str(len(block))))
    return b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields).encode("utf-8", "surrogatepass") + b"\r\n" + block + b"\r\n\r\n"


def archive(records: list[bytes]) -> tuple[bytes, int]:
    """The bytes of an archive, and of its dictionary (0 where the records are too few or too even to train one)."""
    sample, size = [], 0
    step = max(1, sum(map(len, records)) // TRAINING_BYTES)
    for r in records[::step]:
        sample.append(r[: 128 << 10])
        size += len(sample[-1])
        if size >= TRAINING_BYTES:
            break
    trained = None
    if len(sample) >= 8 and size >= 4 * 1024:
        try:
            trained = zstandard.train_dictionary(min(DICTIONARY_BYTES, size // 4), sample, k=256, d=8)
        except zstandard.ZstdError:
            trained = None
    out = io.BytesIO()
    if trained:
        content = zstandard.ZstdCompressor(level=LEVEL).compress(trained.as_bytes())
        out.write(struct.pack("<II", DICTIONARY_MAGIC, len(content)) + content)
    press = zstandard.ZstdCompressor(level=LEVEL, dict_data=trained, write_checksum=True) if trained else zstandard.ZstdCompressor(level=LEVEL, write_checksum=True)
    for r in records:
        out.write(press.compress(r))
    return out.getvalue(), len(trained.as_bytes()) if trained else 0


def records_of(stream):
    """Yields (headers, block) of each record of an open archive."""
    head = stream.read(8)
    trained, start = None, head
    if len(head) == 8 and struct.unpack("<I", head[:4])[0] == DICTIONARY_MAGIC:
        content = stream.read(struct.unpack("<I", head[4:])[0])
        plain = zstandard.ZstdDecompressor().decompress(content, max_output_size=1 << 26) if content[:4] == struct.pack("<I", zstandard.MAGIC_NUMBER) else content
        trained, start = zstandard.ZstdCompressionDict(plain), b""
    rest = io.BytesIO(start + stream.read())
    press = zstandard.ZstdDecompressor(dict_data=trained) if trained else zstandard.ZstdDecompressor()
    lines = io.BufferedReader(press.stream_reader(rest, read_across_frames=True), 1 << 20)
    while first := lines.readline():
        if not first.startswith(b"WARC/"):
            raise ValueError("not at the start of a WARC record")
        headers = {}
        while (line := lines.readline()) not in (b"\r\n", b""):
            k, _, v = line.rstrip(b"\r\n").partition(b": ")
            headers[k.decode().lower()] = v.decode("utf-8", "surrogatepass")
        block = lines.read(int(headers["content-length"]))
        if lines.read(4) != b"\r\n\r\n":
            raise ValueError("a WARC record is cut short")
        yield headers, block


def _write(folder: str, date: str, archive_bytes: int):
    def run(batches):
        store, root = fs.FileSystem.from_uri(folder)
        store.create_dir(root, recursive=True)
        records, size = [], 0

        def close():
            data, dictionary = archive(records)
            path = f"{root}/{uuid.uuid4().hex}.warc.zst"
            with store.open_output_stream(path) as f:
                f.write(data)
            return pa.RecordBatch.from_pydict({"path": [path], "n_records": [len(records)], "n_bytes": [len(data)], "dictionary_bytes": [dictionary]}, _MANIFEST)

        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                part = batch.slice(at, 64)
                for page_id, url, refers_to, length, sha1, html in zip(*(part.column(i).to_pylist() for i in range(5)), part.column(5).cast(pa.binary()).to_pylist(), strict=True):
                    digest = base64.b32encode(bytes.fromhex(sha1)).decode()
                    records.append(record(page_id, url, html, refers_to, date, length, digest))
                    size += len(records[-1])
                    if size >= archive_bytes:
                        yield close()
                        records, size = [], 0
        if records:
            yield close()

    return run


def write_archives(pages: DataFrame, folder: str, least_bytes: int = 0, date: str = "2000-01-01T00:00:00Z", archive_bytes: int = ARCHIVE_BYTES, limits: dict | None = None) -> DataFrame:
    """Writes a record per row of pages(page_id BIGINT, url, html) under folder; returns the manifest.

    Of rows with equal payloads of least_bytes or more, those with the smallest page_id are
    responses and the others revisit it. Null html is an empty payload, a null url is left
    out. A row without page_id revisits if an equal payload has one; else it is a response.
    Repeated rows with the smallest page_id are responses each. Other columns are ignored.
    Pages are written where they lie: only digests are shuffled, and the list of repeated ones
    is joined to the pages (limits: those of joins.left_join). The manifest is written before
    this returns.
    """
    html = F.coalesce(F.col("html").cast("string"), F.lit(""))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), html.alias("html"))
    rows = rows.withColumns({"n_bytes": F.octet_length("html").cast("long"), "sha1": F.sha1(F.col("html").cast("binary"))})
    copied = rows.where(F.col("n_bytes") >= least_bytes).groupBy(F.col("sha1").alias("same")).agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("copies"))
    copied = materialize(copied.where("copies > 1 AND first IS NOT NULL"), "copied")
    ready = left_join(rows, copied, {"sha1": "same"}, size="copies", found="first", **(limits or {}))
    revisit = F.when(~F.col("page_id").eqNullSafe(F.col("first")), F.col("first"))
    ready = ready.select("page_id", "url", revisit.alias("refers_to"), "n_bytes", "sha1", F.when(revisit.isNull(), F.col("html")).alias("html"))
    manifest = materialize(ready.mapInArrow(released(_write(folder, date, archive_bytes)), "path string, n_records long, n_bytes long, dictionary_bytes long"), "manifest")
    discard(copied)
    return manifest


def _read(folder: str, payloads: bool):
    def run(batches):
        store, _ = fs.FileSystem.from_uri(folder)
        for batch in batches:
            for path in batch.column(0).to_pylist():
                with store.open_input_stream(path) as f:
                    out, size = [], 0
                    for h, block in records_of(f):
                        number = lambda k: int(h[k]) if k in h else None  # noqa: B023, E731
                        digest, length, payload = h["warc-payload-digest"].removeprefix("sha1:"), number("x-payload-length"), None
                        if h["warc-type"] == "response":
                            payload = block.partition(b"\r\n\r\n")[2]
                            if base32_sha1(payload) != digest or len(payload) != length:
                                raise ValueError(f"payload of page {h.get('x-page-id')} doesn't match its digest")
                        out.append((number("x-page-id"), h.get("warc-target-uri"), length, digest, h["warc-type"], number("x-refers-to-page-id"), payload if payloads else None))
                        size += len(block)
                        if size > 8 << 20:
                            yield _batch(out)
                            out, size = [], 0
                    if out:
                        yield _batch(out)

    return run


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _RECORDS, strict=True)], schema=_RECORDS)


def read_archives(manifest: DataFrame, folder: str, payloads: bool = True) -> DataFrame:
    """The records of the archives that a manifest lists; payload is null for revisits. A record that doesn't match its digest is an error."""
    spark = manifest.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return manifest.select("path").repartition(n, "path").mapInArrow(released(_read(folder, payloads)), "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary")


def archived_pages(pages: DataFrame) -> DataFrame:
    """Writes the pages, reads the archives back: page_id, payload_bytes, payload_digest, record_type, refers_to."""
    folder = scratch_path(pages.sparkSession, "warc")
    return read_archives(write_archives(pages, folder), folder, payloads=False).drop("payload", "url")
