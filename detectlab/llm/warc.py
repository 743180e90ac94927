"""WARC archives compressed with Zstandard: one frame per record, dictionary first.

An archive starts with a skippable frame that holds the dictionary (itself
plain or Zstandard-compressed), then has one frame per record. Records are WARC/1.1:
the page with the smallest id among equal payloads is a response, the others are
revisits that refer to it.

Archives are written by the executors into a folder all machines share; a task
writes under names of its own and its manifest row alone makes a file count, so
a task that runs again leaves nothing half-written to be read.
"""

from __future__ import annotations

import base64
import hashlib
import os
import re
import uuid
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detectlab.llm.frames import cut, shared_dir

#: Fixed values of the formats.
DICT_FRAME = 0x184D2A5D
ZSTD_FRAME = 0xFD2FB528
DICT_MAGIC = 0xEC30A437
REVISIT = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "1970-01-01T00:00:00Z"
_LAST = 9223372036854775807


def sha1_base32(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def train_dictionary(pages: DataFrame, *, samples: int = 256, sample_chars: int = 16384, size: int = 32768) -> bytes:
    """A dictionary from a bounded sample: one page in each of ``samples`` buckets of ids, ``sample_chars`` of each. b'' if there is too little."""
    bucket, order = F.pmod(F.xxhash64("page_id"), F.lit(samples)), F.xxhash64(F.lit(1), "page_id")
    least = pages.where("html is not null and page_id is not null").groupBy(bucket.alias("bucket")).agg(F.min(F.struct(order.alias("order"), "page_id")).alias("p")).select("p.page_id")
    texts = pages.join(F.broadcast(least), "page_id").groupBy("page_id").agg(F.first(F.substring("html", 1, sample_chars)).alias("html"))  # least has at most samples rows
    picked = sorted(texts.collect(), key=lambda r: r.page_id)
    try:
        return zstandard.train_dictionary(size, [r.html.encode() for r in picked if r.html]).as_bytes()
    except (zstandard.ZstdError, ValueError):
        return b""


def _ref(page_id: int | None) -> str:
    return f"<urn:page:{'none' if page_id is None else page_id}>"


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, revisit: bool) -> bytes:
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if revisit else http + payload
    target = re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url) if url else "urn:unknown"
    head = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: {_ref(page_id)}", f"WARC-Date: {DATE}", f"WARC-Target-URI: {target}"]
    if revisit:
        head += [f"WARC-Profile: {REVISIT}", f"WARC-Refers-To: {_ref(refers_to)}"]
    head += ["Content-Type: application/http; msgtype=response", f"WARC-Block-Digest: sha1:{sha1_base32(block)}", f"WARC-Payload-Digest: sha1:{sha1_base32(payload)}", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def dictionary_frame(dictionary: bytes) -> bytes:
    body = zstandard.ZstdCompressor(level=3).compress(dictionary)
    return DICT_FRAME.to_bytes(4, "little") + len(body).to_bytes(4, "little") + body


def frame_end(data: bytes, at: int) -> int:
    """Where the Zstandard frame at this place ends, from its header and block headers."""
    if int.from_bytes(data[at : at + 4], "little") != ZSTD_FRAME:
        raise ValueError(f"no Zstandard frame at byte {at}")
    flags = data[at + 4]
    single, size = flags >> 5 & 1, (0, 2, 4, 8)[flags >> 6]
    at += 5 + (not single) + (0, 1, 2, 4)[flags & 3] + (1 if single and not size else size)
    while True:
        if at + 3 > len(data):
            raise ValueError("the archive ends inside a frame")
        head = int.from_bytes(data[at : at + 3], "little")
        at += 3 + (1 if head >> 1 & 3 == 1 else head >> 3)
        if head & 1:
            end = at + 4 * (flags >> 2 & 1)
            if end > len(data):
                raise ValueError("the archive ends inside a frame")
            return end


def frames(data: bytes) -> Iterator[bytes]:
    """The records of an archive. Skippable frames other than the dictionary are passed over."""
    at, codec = 0, zstandard.ZstdDecompressor()
    while at < len(data):
        magic = int.from_bytes(data[at : at + 4], "little")
        if magic & 0xFFFFFFF0 == 0x184D2A50:
            size = int.from_bytes(data[at + 4 : at + 8], "little")
            body = data[at + 8 : at + 8 + size]
            if len(body) < size:
                raise ValueError("the archive ends inside a frame")
            if magic == DICT_FRAME and at == 0:
                if int.from_bytes(body[:4], "little") != DICT_MAGIC:
                    body = zstandard.ZstdDecompressor().decompressobj().decompress(body)
                codec = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(body))
            at += 8 + size
        else:
            end = frame_end(data, at)
            yield codec.decompressobj().decompress(data[at:end])
            at = end


def parse(data: bytes) -> dict:
    """One record, checked: version line, needed headers, lengths, digests, and that nothing follows."""
    head, mark, rest = data.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not mark or not re.fullmatch(r"WARC/1\.[01]", lines[0]):
        raise ValueError(f"not a WARC record: {lines[0][:40]!r}")
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    if missing := {"warc-type", "warc-record-id", "warc-date", "content-length"} - fields.keys():
        raise ValueError(f"headers missing: {sorted(missing)}")
    size = int(fields["content-length"])
    if len(rest) != size + 4 or rest[size:] != b"\r\n\r\n":
        raise ValueError(f"Content-Length {size} but the record holds {len(rest) - 4} bytes")
    block = rest[:size]
    if "warc-block-digest" in fields and fields["warc-block-digest"] != f"sha1:{sha1_base32(block)}":
        raise ValueError("block digest differs")
    http, _, payload = block.partition(b"\r\n\r\n")
    length = re.search(rb"(?im)^content-length:\s*(\d+)\s*$", http.replace(b"\r\n", b"\n"))
    digest = fields.get("warc-payload-digest", "")
    if fields["warc-type"] == "response":
        if digest and digest != f"sha1:{sha1_base32(payload)}":
            raise ValueError("payload digest differs")
        if length and int(length[1]) != len(payload):
            raise ValueError("HTTP length differs")
    elif fields["warc-type"] == "revisit" and "warc-refers-to" not in fields:
        raise ValueError("revisit without WARC-Refers-To")
    number = lambda ref: int(m[1]) if (m := re.fullmatch(r"<urn:page:(-?\d+)>", ref or "")) else None
    return {
        "page_id": number(fields["warc-record-id"]), "url": fields.get("warc-target-uri"), "record_type": fields["warc-type"],
        "payload_bytes": int(length[1]) if length else len(payload), "payload_digest": digest.removeprefix("sha1:"),
        "refers_to": number(fields.get("warc-refers-to")), "payload": payload if fields["warc-type"] == "response" else None,
    }


def _open(uri: str, mode: str):
    """A file in the shared folder: local paths directly, other stores through Arrow's file systems."""
    if ":" not in uri or uri.startswith("file:"):
        path = re.sub("^file:/*", "/", uri)
        if mode == "wb":
            os.makedirs(os.path.dirname(path), exist_ok=True)
        return open(path, mode)
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(uri)
    if mode == "wb":
        store.create_dir(path.rpartition("/")[0])
        return store.open_output_stream(path)
    return store.open_input_file(path)




def plan_records(pages: DataFrame, min_bytes: int = 0, *, broadcast_rows: int = 100_000, salts: int = 64) -> DataFrame:
    """page_id, url, html, first (the response's page_id, or null if the page is the response itself).

    broadcast_rows: payloads of several pages (100 bytes each) up to which they are broadcast, so that no html is
    shuffled. More are joined by payload and one of ``salts`` numbers of the page, as one payload may be that of many pages.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    rows = rows.withColumn("key", F.sha2("html", 256)).withColumn("rank", F.coalesce("page_id", F.lit(_LAST)))
    least = rows.where(F.octet_length("html") >= min_bytes).groupBy("key").agg(F.min("rank").alias("least"), F.count("*").alias("n")).where("n > 1").drop("n")
    least = cut(least.withColumnRenamed("key", "k"))
    if least.count() <= broadcast_rows:
        joined = rows.join(F.broadcast(least), F.col("key") == F.col("k"), "left")
    else:
        least = least.withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
        rows = rows.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(salts)).cast("int"))
        joined = rows.join(least, (F.col("key") == F.col("k")) & (F.col("salt") == F.col("s")), "left")
    return joined.select("page_id", "url", "html", F.when(F.col("rank") > F.col("least"), F.col("least")).alias("first"))


def write_archives(planned: DataFrame, folder: str, dictionary: bytes = b"", *, archive_bytes: int = 32 << 20, level: int = 3) -> DataFrame:
    """Writes archives of about archive_bytes before compression; returns their manifest: uri, records, bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shared = zstandard.ZstdCompressionDict(dictionary) if dictionary else None
        codec = zstandard.ZstdCompressor(level=level, dict_data=shared) if shared else zstandard.ZstdCompressor(level=level)
        done, out, raw, count, total = [], None, 0, 0, 0

        def close():
            if out is not None:
                out.close()
                done.append((uri, count, total))

        for batch in batches:
            for page_id, url, html, first in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                if out is None or raw >= archive_bytes:
                    close()
                    uri, raw, count, total = f"{folder}/{uuid.uuid4().hex}.warc.zst", 0, 0, 0
                    out = _open(uri, "wb")
                    if dictionary:
                        total += out.write(dictionary_frame(dictionary))
                data = record(page_id, url, html.encode(), first, first is not None)
                total += out.write(codec.compress(data))
                raw, count = raw + len(data), count + 1
        close()
        yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*done, strict=True) if done else ((), (), ()), (pa.string(), pa.int64(), pa.int64()), strict=True)], ["uri", "records", "bytes"])

    return cut(planned.mapInArrow(run, "uri string, records long, bytes long"))


_READ = {"page_id": pa.int64(), "url": pa.string(), "record_type": pa.string(), "payload_bytes": pa.int64(), "payload_digest": pa.string(), "refers_to": pa.int64(), "payload": pa.binary(), "error": pa.string()}


def read_archives(manifest: DataFrame, *, payloads: bool = True, on_error: str = "fail") -> DataFrame:
    """One row per record of the archives in the column uri.

    on_error: 'fail' raises on a record that isn't valid, 'report' returns it with
    its error and nulls; an archive that is cut off ends with such a row.
    """
    if on_error not in ("fail", "report"):
        raise ValueError(on_error)

    def table(rows: list[dict]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([r.get(c) for r in rows], t) for c, t in _READ.items()], list(_READ))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for uri in batch.column(0).to_pylist():
                with _open(uri, "rb") as f:
                    data = f.read()
                rows, held, walk = [], 0, frames(data)
                while True:
                    try:
                        raw = next(walk, None)
                        if raw is None:
                            break
                        got = parse(raw)
                        got = got if payloads else got | {"payload": None}
                        rows.append(got)
                        held += len(got["payload"] or b"")
                    except (ValueError, zstandard.ZstdError) as e:
                        if on_error == "fail":
                            raise ValueError(f"{uri}: {e}") from e
                        rows.append({"error": str(e)})
                        if "archive ends" in str(e) or "no Zstandard" in str(e):
                            break
                    if held >= 8 << 20 or len(rows) >= 5000:
                        yield table(rows)
                        rows, held = [], 0
                yield table(rows)

    kinds = {pa.int64(): "long", pa.string(): "string", pa.binary(): "binary"}
    tasks = max(1, min(manifest.count(), 100_000))  # named: a list of archives is few bytes, what they hold is not
    return manifest.select("uri").repartition(tasks, "uri").mapInArrow(run, ", ".join(f"{c} {kinds[t]}" for c, t in _READ.items()))


def archive(pages: DataFrame, *, min_bytes: int = 0) -> tuple[DataFrame, DataFrame]:
    """Writes all pages; returns (manifest, records read back and checked).

    Null html is an empty payload, null url 'urn:unknown'. Rows without page_id
    come last among equal payloads. Rows with the smallest page_id of a payload are
    all responses, repeated or not. An empty table writes no archive and gives no rows.
    """
    folder = f"{shared_dir(pages.sparkSession)}/warc-{uuid.uuid4().hex}"
    manifest = write_archives(plan_records(pages, min_bytes), folder, train_dictionary(pages))
    return manifest, read_archives(manifest, payloads=False)
