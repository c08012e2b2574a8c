import base64
import hashlib
import io
import struct

import zstandard

from codematch.llm import warc


def test_archive_round_trip():
    payloads = [f"<p>{'same words ' * 30}{i}</p>".encode() for i in range(200)]
    records = [warc.record(i, f"http://h/{i}\n x", p, None, "2000-01-01T00:00:00Z", len(p), warc.base32_sha1(p)) for i, p in enumerate(payloads)]
    data, size = warc.archive(records)
    assert size > 0 and struct.unpack("<I", data[:4])[0] == warc.DICTIONARY_MAGIC
    length = struct.unpack("<I", data[4:8])[0]
    trained = zstandard.ZstdCompressionDict(zstandard.ZstdDecompressor().decompress(data[8 : 8 + length]))
    first = zstandard.ZstdDecompressor(dict_data=trained).decompressobj().decompress(data[8 + length :])
    assert first == records[0]  # a record is a frame of its own
    back = list(warc.records_of(io.BytesIO(data)))
    assert [h["x-page-id"] for h, _ in back] == [str(i) for i in range(200)]
    assert back[7][1].endswith(b"7</p>")
    few, none = warc.archive(records[:2])
    assert none == 0 and len(list(warc.records_of(io.BytesIO(few)))) == 2


def test_pages_round_trip(spark, tmp_path):
    rows = [(1, "http://a/", "x" * 10, 0), (2, None, None, 0), (3, "u", "x" * 10, 0), (4, "u", "", 0), (5, "u\r\nX: y", "é\r\n\r\nWARC/1.1 z", 0), (None, "n", "x" * 10, 0), (None, "n", "alone", 0), (5, "u", "é\r\n\r\nWARC/1.1 z", 0), (9, "long", "ab" * 200_000, 0)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, payload int")
    folder = f"file://{tmp_path}/w"
    got = warc.read_archives(warc.write_archives(pages, folder, archive_bytes=1000), folder).collect()
    assert len(got) == len(rows)
    first = {}
    for i, _, h, _ in rows:
        if i is not None:
            first[h or ""] = min(i, first.get(h or "", i))
    want = []
    for i, _, h, _ in rows:
        b = (h or "").encode()
        least = first.get(h or "")
        refers = None if least is None or least == i else least
        want.append((i, len(b), base64.b32encode(hashlib.sha1(b).digest()).decode(), "response" if refers is None else "revisit", refers, b if refers is None else None))
    key = lambda r: tuple(map(repr, r))
    assert sorted(((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to, None if r.payload is None else bytes(r.payload)) for r in got), key=key) == sorted(want, key=key)
    small = warc.read_archives(warc.write_archives(pages, folder, least_bytes=11), folder).collect()
    assert sum(r.record_type == "revisit" for r in small) == 0
    assert warc.archived_pages(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_many_copies_of_a_page_are_not_gathered(spark, tmp_path):
    rows = [(i, "u", "hot" if i % 2 else f"page {i % 20}") for i in range(400)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    want = sorted(map(repr, warc.archived_pages(pages).collect()))
    folder = f"file://{tmp_path}/w"
    got = warc.read_archives(warc.write_archives(pages, folder, limits={"most": 3, "heavy": 3}), folder, payloads=False).drop("payload", "url")
    assert sorted(map(repr, got.collect())) == want and sum("response" in w for w in want) == 11


def test_contract_on_pages(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    got = {r.page_id: r for r in warc.archived_pages(pages).collect()}
    rows = {r.page_id: (r.html or "").encode() for r in pages.collect()}
    assert got.keys() == rows.keys()
    for i, b in rows.items():
        least = min(j for j, c in rows.items() if c == b)
        assert tuple(got[i]) == (i, len(b), base64.b32encode(hashlib.sha1(b).digest()).decode(), "response" if least == i else "revisit", None if least == i else least)
