"""WARC archives with one Zstandard frame per record and a shared dictionary in the leading skippable frame.

An archive is one byte string: a skippable frame (magic 0x184D2A5D) that holds the dictionary, then a frame for the
warcinfo record and for each record. Archives are rows of a Parquet table in the shared folder (``archive_id``,
``content``): any store that Spark writes can hold them, a task that is repeated replaces its rows, and the size of an
archive is bounded. ``export_archives`` puts them out as .warc.zst files, ``read_archive_files`` reads such files.

Records of equal payloads: the one with the largest page_id is a response, the others are revisits of it. Equal
payloads are found by digest; the winner per digest is pre-aggregated before any row moves, and large groups of equal
digests are split by Spark's adaptive join.

Archives of other writers are read as well: frames without a content size (decoded up to MAX_RECORD bytes), no dictionary or
one stored plain, any record identifier, all record types, header lines that go on in the next line, HTTP messages without a
length. Blocks of the type application/http give the bytes behind the HTTP head as payload, all others the whole block.
Digests in SHA-1, SHA-256 or MD5, as base32 or hex, are checked where they are given; others are handed on unchecked.

Defined results: a null html is an empty payload; rows with the same page_id that share a payload are all responses if
it is the largest page_id; a null page_id loses to any other and is never referred to unless alone; damaged frames
or records that break a rule of the format come back with ``error`` set instead of stopping the job; identifiers that no
page of ours has give a null page_id and stand in ``record_id`` and ``refers_to_id``.
"""

from __future__ import annotations

import base64
import hashlib
import os
import re
import struct
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

# fixed values of the container formats
DICTIONARY_FRAME = 0x184D2A5D
ZSTD_MAGIC = 0xFD2FB528
SKIPPABLE = range(0x184D2A50, 0x184D2A60)
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"

#: Payload bytes after which an archive is closed, and bytes of the dictionary.
ARCHIVE_BYTES = 8_000_000
DICTIONARY_BYTES = 32_768
#: Bytes of a dictionary that a reader accepts.
MAX_DICTIONARY = 1 << 24
RECORD_DATE = "2024-01-01T00:00:00Z"
#: Bytes of one record that a reader decodes at most; a larger one gives an error row.
MAX_RECORD = 1 << 30
FIELDS = (
    "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary, "
    "record_id string, refers_to_id string, content_type string, date string, error string"
)


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _uri(page_id: int | None) -> str:
    return f"<urn:page:{'none' if page_id is None else page_id}>"


def _page(uri: str | None) -> int | None:
    """The page of an identifier of ours, null for any other."""
    found = re.fullmatch(r"<urn:page:(-?[0-9]{1,19})>", uri or "")
    return int(found[1]) if found else None


def _clean(value: str) -> str:
    """A header value on one line; characters that would break it are percent-encoded."""
    return "".join(c if c.isprintable() and c not in "%" else "".join(f"%{b:02X}" for b in c.encode()) for c in value)


def record_bytes(kind: str, headers: list[tuple[str, str]], block: bytes) -> bytes:
    lines = ["WARC/1.1", f"WARC-Type: {kind}", *(f"{k}: {v}" for k, v in headers), f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def page_record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """refers_to: page_id of the response with this payload, or None if this is the response."""
    headers = [
        ("WARC-Record-ID", _uri(page_id)),
        ("WARC-Date", RECORD_DATE),
        ("WARC-Payload-Digest", f"sha1:{payload_digest(payload)}"),
    ]
    if url is not None:
        headers.insert(1, ("WARC-Target-URI", _clean(url)))
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    headers.append(("Content-Type", "application/http;msgtype=response"))
    if refers_to is None:
        return record_bytes("response", headers, http + payload)
    headers += [("WARC-Refers-To", _uri(refers_to)), ("WARC-Profile", REVISIT_PROFILE)]
    return record_bytes("revisit", headers, http)  # the head alone: its Content-Length still tells the payload's size


def train_dictionary(samples: list[bytes], size: int = DICTIONARY_BYTES) -> bytes:
    """A dictionary from some records of the archive; raw content where there is too little to train on."""
    picked = samples[:: max(1, len(samples) // 128)][:160]
    try:
        if len(picked) >= 16:
            return zstandard.train_dictionary(size, [s[:8192] for s in picked], k=256, d=8).as_bytes()
    except zstandard.ZstdError:
        pass
    return b"".join(s[:2048] for s in picked)[:size] or b"WARC/1.1\r\nWARC-Type: response\r\nContent-Length: "


def archive_bytes(records: list[bytes]) -> bytes:
    dictionary = train_dictionary(records)
    packer = zstandard.ZstdCompressor(
        level=3, dict_data=zstandard.ZstdCompressionDict(dictionary), write_checksum=True, write_content_size=True
    )
    info = record_bytes("warcinfo", [("WARC-Record-ID", "<urn:page:none>"), ("WARC-Date", RECORD_DATE)], b"format: WARC/1.1\r\n")
    stored = zstandard.ZstdCompressor(level=9).compress(dictionary)
    head = struct.pack("<II", DICTIONARY_FRAME, len(stored)) + stored
    return head + b"".join(packer.compress(r) for r in [info, *records])


# ---- reading -------------------------------------------------------------------------------------------------------


def frame_end(data: bytes, at: int) -> int:
    """End of the Zstandard frame that begins at ``at``, from its headers alone (public frame format)."""
    if len(data) < at + 5:
        raise ValueError("truncated frame header")
    descriptor = data[at + 4]
    single = descriptor >> 5 & 1
    pos = at + 5 + (not single) + (0, 1, 2, 4)[descriptor & 3] + (single, 2, 4, 8)[descriptor >> 6]
    while True:
        if len(data) < pos + 3:
            raise ValueError("truncated block header")
        head = int.from_bytes(data[pos : pos + 3], "little")
        kind, size = head >> 1 & 3, head >> 3
        if kind == 3:
            raise ValueError("reserved block type")
        pos += 3 + (1 if kind == 1 else size)
        if head & 1:
            break
    pos += 4 * (descriptor >> 2 & 1)
    if pos > len(data):
        raise ValueError("truncated frame")
    return pos


def load_dictionary(data: bytes) -> tuple[zstandard.ZstdCompressionDict | None, int]:
    """The dictionary of the leading skippable frame, if there is one, and where the records begin."""
    if len(data) >= 8:
        magic, size = struct.unpack_from("<II", data)
        if magic == DICTIONARY_FRAME:
            raw = data[8 : 8 + size]
            if len(raw) < size:
                raise ValueError("truncated dictionary")
            if raw[:4] == struct.pack("<I", ZSTD_MAGIC):
                raw = _decoded(zstandard.ZstdDecompressor(), raw, MAX_DICTIONARY)
            return zstandard.ZstdCompressionDict(raw), 8 + size
    return None, 0


def _fields(lines: list[str]) -> dict[str, str]:
    """Header lines by lower-case name; a line that begins with white space goes on with the one before."""
    out: dict[str, str] = {}
    last = None
    for line in lines:
        if line[:1] in (" ", "\t") and last:
            out[last] += " " + line.strip()
            continue
        name, colon, value = line.partition(":")
        if not colon or not name or name != name.strip():
            raise ValueError("malformed header line")
        last = name.lower()
        out[last] = value.strip()
    return out


def _check_digest(told: str, data: bytes) -> str:
    """The bare digest; raises if it can be checked and is wrong."""
    name, colon, digest = told.partition(":")
    if not colon or not digest:
        raise ValueError("malformed digest")
    if name.lower().replace("-", "") in ("sha1", "sha256", "md5"):
        own = hashlib.new(name.lower().replace("-", ""), data).digest()
        if digest.upper().rstrip("=") != base64.b32encode(own).decode().rstrip("=") and digest.lower() != own.hex():
            raise ValueError("payload does not match its length or digest")
    return digest


def _http(block: bytes) -> tuple[bytes, int | None]:
    """The body of an HTTP message, and the length that its head tells, if any."""
    head, mark, body = block.partition(b"\r\n\r\n")
    if not mark:
        raise ValueError("malformed HTTP head")
    told = {}
    for line in head.split(b"\r\n")[1:]:
        name, _, value = line.partition(b":")
        told[name.strip().lower()] = value.strip()
    length = told.get(b"content-length", b"")
    return body, int(length) if length.isdigit() and b"transfer-encoding" not in told else None


def parse_record(raw: bytes) -> dict:
    """One record, validated: version, header lines, Content-Length, end marks, HTTP length and digests."""
    head, mark, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode("utf-8").split("\r\n")
    if not mark or lines[0] not in ("WARC/1.0", "WARC/1.1"):
        raise ValueError("no WARC version line")
    fields = _fields(lines[1:])
    for name in ("warc-type", "warc-record-id", "warc-date", "content-length"):
        if name not in fields:
            raise ValueError(f"no {name}")
    if not re.fullmatch("[0-9]+", fields["content-length"]):
        raise ValueError("malformed Content-Length")
    size = int(fields["content-length"])
    if len(rest) != size + 4 or rest[size:] != b"\r\n\r\n":
        raise ValueError("Content-Length does not match")
    kind, block = fields["warc-type"], rest[:size]
    if told := fields.get("warc-block-digest"):
        _check_digest(told, block)
    url = fields.get("warc-target-uri")
    out = {
        "record_type": kind,
        "record_id": fields["warc-record-id"],
        "page_id": _page(fields["warc-record-id"]),
        "url": url.strip("<>") if url else url,
        "refers_to_id": fields.get("warc-refers-to"),
        "refers_to": _page(fields.get("warc-refers-to")),
        "content_type": fields.get("content-type"),
        "date": fields["warc-date"],
    }
    payload, length = block, None
    if (out["content_type"] or "").replace(" ", "").lower().startswith("application/http") and (block or kind != "revisit"):
        payload, length = _http(block)
    told = fields.get("warc-payload-digest")
    if kind == "revisit":
        if payload or not (out["refers_to_id"] or fields.get("warc-refers-to-target-uri") or told):
            raise ValueError("malformed revisit")
        return out | {"payload_bytes": length, "payload_digest": told.partition(":")[2] if told else None}
    if kind == "response" and length not in (None, len(payload)) and "warc-truncated" not in fields:
        raise ValueError("payload does not match its length or digest")
    digest = None
    if told:
        digest = _check_digest(told, payload) if "warc-truncated" not in fields else told.partition(":")[2]
    return out | {"payload_bytes": len(payload), "payload_digest": digest, "payload": payload}


def _decoded(reader: zstandard.ZstdDecompressor, frame: bytes, most: int) -> bytes:
    """The content of one frame, with or without a content size in its header."""
    with reader.stream_reader(frame) as stream:
        out = stream.read(most + 1)
    if len(out) > most:
        raise ValueError(f"a record of over {most} bytes")
    return out


def read_records(data: bytes, most: int | None = None) -> Iterator[dict]:
    """Every record of an archive; a damaged frame gives a row with ``error``, a lost frame border ends the archive."""
    try:
        dictionary, at = load_dictionary(data)
    except (ValueError, zstandard.ZstdError) as e:
        yield {"error": str(e)}
        return
    reader = zstandard.ZstdDecompressor(dict_data=dictionary) if dictionary else zstandard.ZstdDecompressor()
    while at < len(data):
        try:
            (magic,) = struct.unpack_from("<I", data, at)
            if magic in SKIPPABLE:
                size = struct.unpack_from("<I", data, at + 4)[0]
                if at + 8 + size > len(data):
                    raise ValueError("truncated skippable frame")
                at += 8 + size
                continue
            if magic != ZSTD_MAGIC:
                raise ValueError("no frame where one should begin")
            end = frame_end(data, at)
        except (ValueError, struct.error) as e:
            yield {"error": f"at byte {at}: {e}"}
            return
        try:
            yield parse_record(_decoded(reader, data[at:end], MAX_RECORD if most is None else most))
        except (ValueError, UnicodeDecodeError, zstandard.ZstdError) as e:
            yield {"error": f"at byte {at}: {e}"}
        at = end


# ---- on Spark --------------------------------------------------------------------------------------------------------


def mark_revisits(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """pages (page_id, url, html) -> page_id, url, payload, response_id: the response's page_id for revisits."""
    rows = pages.select("page_id", "url", F.encode(F.coalesce("html", F.lit("")), "UTF-8").alias("payload"))
    rows = rows.withColumn("digest", F.unhex(F.sha1("payload")))
    owner = (
        rows.filter(F.octet_length("payload") >= least_bytes)
        .groupBy(F.col("digest").alias("key"))
        .agg(F.max("page_id").alias("owner"))
    )
    joined = rows.join(owner, F.col("digest") == F.col("key"), "left")
    other = F.when(~F.col("page_id").eqNullSafe(F.col("owner")), F.col("owner"))
    return joined.select("page_id", "url", "payload", other.alias("response_id"))


def write_archives(pages: DataFrame, least_bytes: int = 0, archive_bytes_limit: int = ARCHIVE_BYTES) -> DataFrame:
    """A durable table of archives (archive_id, content) that hold one record per row of pages."""

    def run(batches):
        records: list[bytes] = []
        size = number = 0

        def close():
            nonlocal records, size, number
            content = archive_bytes(records)
            records, size = [], 0
            number += 1
            return pa.RecordBatch.from_arrays([pa.array([number]), pa.array([content], type=pa.binary())], names=["number", "content"])

        for b in batches:
            for page, url, payload, other in zip(*(c.to_pylist() for c in b.columns), strict=True):
                records.append(page_record(page, url, payload, other))
                size += len(records[-1])
                if size >= archive_bytes_limit:
                    yield close()
        if records:
            yield close()

    made = common.map_arrow(mark_revisits(pages, least_bytes), run, "number long, content binary")
    name = F.concat_ws("-", F.lit("part"), F.spark_partition_id(), F.col("number"))
    return common.materialise(made.select(name.alias("archive_id"), "content"), "warc")


def read_archives(archives: DataFrame, info: bool = False) -> DataFrame:
    """archives (archive_id, content) -> archive_id and the columns of FIELDS, one row per record; records about the
    archive itself (warcinfo) only with ``info``."""
    names = [x.split()[0] for x in FIELDS.split(", ")]
    types = {"page_id": pa.int64(), "payload_bytes": pa.int64(), "refers_to": pa.int64(), "payload": pa.binary()}

    def run(batches):
        for b in batches:
            for name, content in zip(*(c.to_pylist() for c in b.columns), strict=True):
                rows: list[dict] = []
                size = 0

                def out(rows=rows, name=name):
                    cols = [pa.array([r.get(n) for r in rows], type=types.get(n, pa.string())) for n in names]
                    return pa.RecordBatch.from_arrays([pa.array([name] * len(rows), type=pa.string()), *cols], names=["archive_id", *names])

                for r in read_records(content):
                    if r.get("record_type") == "warcinfo" and not info:
                        continue
                    rows.append(r)
                    size += len(r.get("payload") or b"")
                    if size > 4_000_000:
                        yield out()
                        rows.clear()
                        size = 0
                if rows:
                    yield out()

    return common.map_arrow(archives.select("archive_id", "content"), run, f"archive_id string, {FIELDS}")


def export_archives(archives: DataFrame, folder: str) -> DataFrame:
    """Write each archive as FOLDER/archive_id.warc.zst, a folder that all executors mount; returns the paths."""

    def run(batches):
        os.makedirs(folder, exist_ok=True)
        for b in batches:
            paths = []
            for name, content in zip(*(c.to_pylist() for c in b.columns), strict=True):
                paths.append(f"{folder}/{name}.warc.zst")
                part = f"{paths[-1]}.{os.getpid()}.part"
                with open(part, "wb") as f:
                    f.write(content)
                os.replace(part, paths[-1])  # whole or not at all, also when a task is repeated
            yield pa.RecordBatch.from_arrays([pa.array(paths)], names=["path"])

    return common.map_arrow(archives.select("archive_id", "content"), run, "path string")


def read_archive_files(spark, glob: str) -> DataFrame:
    """.warc.zst files of any store that Spark reads, as archives (archive_id, content)."""
    return spark.read.format("binaryFile").load(glob).select(F.col("path").alias("archive_id"), "content")
