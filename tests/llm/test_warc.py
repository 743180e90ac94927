import base64
import glob
import hashlib

import pytest
import zstandard

from detectlab.llm import warc


def brute(rows):
    least = {}
    for i, _, h in rows:
        p = (h or "").encode()
        k = least.get(p)
        least[p] = i if k is None else k if i is None else min(k, i)
    out = []
    for i, _, h in rows:
        p = (h or "").encode()
        first = least[p]
        again = i != first
        out.append((i, len(p), base64.b32encode(hashlib.sha1(p).digest()).decode(), "revisit" if again else "response", first if again else None))
    return out


def order(rows):
    return sorted(rows, key=lambda r: tuple((x is None, x) for x in r))


COLUMNS = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]


def test_round_trip(spark):
    rows = [(r.page_id, r.url, r.html) for r in spark.read.parquet("/root/testdata/sf0.001/pages.parquet").collect()]
    rows += [(1000 + k, f"http://a/{k}", rows[k % 3][2]) for k in range(20)]
    rows += [(2000, None, None), (2001, "x\r\nWARC-Type: evil y", ""), (2002, "é ü", "<p>é\r\n\r\n</p>"), (None, "u", "only here"), (None, "u", rows[0][2]), (7, "dup", rows[7][2]), (3000, "long", "ab" * 500000)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 as key", "2 as rank")
    manifest, records = warc.archive(df)
    got = [tuple(r) for r in records.select(*COLUMNS).collect()]
    assert order(got) == order(brute(rows))
    assert sum(r.records for r in manifest.collect()) == len(rows)
    full = {r.page_id: r.payload for r in warc.read_archives(manifest).where("record_type = 'response' and page_id is not null").collect()}
    assert all(full[i] == (h or "").encode() for i, _, h in rows if i in full and i != 7)


def test_archive_format(spark, tmp_path):
    pages = spark.read.parquet("/root/testdata/sf0.001/pages.parquet")
    dictionary = warc.train_dictionary(pages, size=4096)
    assert dictionary
    warc.write_archives(warc.plan_records(pages), f"file://{tmp_path}", dictionary, archive_bytes=20_000).collect()
    files = glob.glob(f"{tmp_path}/*.warc.zst")
    assert len(files) > 1
    data = open(files[0], "rb").read()
    assert data[:4] == (0x184D2A5D).to_bytes(4, "little")
    size = int.from_bytes(data[4:8], "little")
    shared = zstandard.ZstdDecompressor().decompress(data[8 : 8 + size], max_output_size=1 << 20)
    assert shared == dictionary
    records = list(warc.frames(data))
    assert all(r.startswith(b"WARC/1.1\r\n") for r in records)
    plain = warc.DICT_FRAME.to_bytes(4, "little") + len(shared).to_bytes(4, "little") + shared + data[8 + size :]
    assert list(warc.frames(plain)) == records


def test_what_is_wrong_is_told(spark, tmp_path):
    good = warc.record(1, "http://a", b"hello", None, False)
    assert warc.parse(good)["payload"] == b"hello"
    for bad in (good[:-1], good + b"x", good.replace(b"hello", b"hellO"), good.replace(b"WARC/1.1", b"WARC/9"), good.replace(b"WARC-Date", b"WARC-Dare"), b"", good.replace(b"Content-Length: ", b"Content-Length: 1", 1)):
        with pytest.raises(ValueError):
            warc.parse(bad)
    pack = zstandard.ZstdCompressor().compress
    path = tmp_path / "a.warc.zst"
    path.write_bytes(pack(good) + pack(good.replace(b"hello", b"hellO")) + pack(good)[:-3])
    m = spark.createDataFrame([(f"file://{path}",)], "uri string")
    got = [(r.page_id, r.error is not None) for r in warc.read_archives(m, on_error="report").collect()]
    assert got == [(1, False), (None, True), (None, True)]
    with pytest.raises(Exception, match="digest"):
        warc.read_archives(m).collect()


def test_empty(spark):
    manifest, records = warc.archive(spark.createDataFrame([], "page_id long, url string, html string"))
    assert manifest.count() == 0 and records.count() == 0
