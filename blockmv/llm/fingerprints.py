"""Document fingerprints by content-defined chunking.

A gear hash over the last 16 bytes marks chunk boundaries by content, so an insertion moves the boundaries around it
only. Chunk sizes are normalised: before NORMAL bytes a boundary needs more zero bits than after it. A fingerprint is
the set of chunk digests with the bytes that each one covers; the containment of a text in another is the share of its
bytes whose chunks the other has too.

The successor of a document is the one with the next larger doc_id, that of the last is the first. The table is
range-partitioned by doc_id once; inside a partition successors are neighbours, and the first row of each partition is
also sent to the partition before it.

Defined results: a null text is empty; an empty text has the empty fingerprint, which contains and is contained in
empty ones only (likeness 1); a single document is its own successor; rows of equal doc_id come in the order of a
hash of their texts; a null doc_id sorts first; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

NORMAL = 32
LEAST = 8
MOST = 128
#: Zero bits at the top of the 16-bit hash that make a boundary: before NORMAL bytes, and after.
HARD, EASY = 6, 4
_SPAN = 16
#: A random 16-bit word per byte value, from a rule.
_GEAR = np.array([xxhash.xxh32_intdigest(bytes([b]), 1) >> 16 for b in range(256)], dtype=np.uint16)
NULL_ID = -(1 << 63)


def gear_hashes(data: bytes) -> np.ndarray:
    """h[i]: sum over the last 16 bytes up to i of gear[byte] << age, by doubling the span."""
    h = _GEAR[np.frombuffer(data, dtype=np.uint8)]
    span = 1
    while span < _SPAN:
        older = np.zeros_like(h)
        older[span:] = h[:-span] << np.uint16(span)
        h = h + older
        span *= 2
    return h


def chunk_edges(data: bytes) -> list[int]:
    """0, the end of each chunk, ..., len(data)."""
    n = len(data)
    if n <= LEAST:
        return [0, n] if n else [0]
    h = gear_hashes(data)
    at = np.flatnonzero(h < np.uint16(1 << (16 - EASY)))
    hard = (h[at] < np.uint16(1 << (16 - HARD))).tolist()
    edges = [0]
    begin = 0
    for end, strong in zip((at + 1).tolist(), hard, strict=True):
        while end - begin > MOST:
            begin += MOST
            edges.append(begin)
        size = end - begin
        if size >= NORMAL or (strong and size >= LEAST):
            begin = end
            edges.append(end)
    while n - begin > MOST:
        begin += MOST
        edges.append(begin)
    if begin < n:
        edges.append(n)
    return edges


Fingerprint = dict[str, int]


def fingerprint(text: str | None) -> Fingerprint:
    """Chunk digest (16 hex digits) -> bytes that chunks of this digest cover."""
    data = (text or "").encode()
    edges = chunk_edges(data)
    out: Fingerprint = {}
    digest = xxhash.xxh3_64_hexdigest
    for a, b in zip(edges, edges[1:], strict=False):
        d = digest(data[a:b])
        out[d] = out.get(d, 0) + b - a
    return out


def to_string(f: Fingerprint) -> str:
    return ",".join(f"{d}:{n}" for d, n in sorted(f.items()))


def from_string(s: str) -> Fingerprint:
    return {d: int(n) for d, n in (x.split(":") for x in s.split(","))} if s else {}


def containment(a: Fingerprint, b: Fingerprint) -> float:
    """Share of a's bytes in chunks that b has as well."""
    total = sum(a.values())
    if not total:
        return 0.0 if b else 1.0
    return sum(min(n, b[d]) for d, n in a.items() if d in b) / total


def with_fingerprints(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with the column ``fingerprint`` appended."""

    def f(texts: list) -> list[pa.Array]:
        return [pa.array([to_string(fingerprint(t)) for t in texts], type=pa.string())]

    return common.map_texts(docs, text, "fingerprint string", lambda: f)


def edited(text: str, following: str) -> str:
    """text with its last quarter replaced by the first as many characters of the following text."""
    k = len(text) // 4
    return text[: len(text) - k] + following[:k]


_COLUMNS = {
    "doc_id": pa.int64(),
    "n_chars": pa.int64(),
    "edited_sha256": pa.string(),
    "fingerprint": pa.string(),
    "edited_fingerprint": pa.string(),
    "near_edited": pa.float64(),
    "near_next": pa.float64(),
}
_DDL = (
    "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, "
    "near_edited double, near_next double"
)


def _compared(doc_id: int | None, text: str, own: Fingerprint, following: str, other: Fingerprint) -> tuple:
    changed = edited(text, following)
    after = own if changed == text else fingerprint(changed)
    return (
        doc_id,
        len(text),
        hashlib.sha256(changed.encode()).hexdigest(),
        to_string(own),
        to_string(after),
        containment(own, after),
        containment(own, other),
    )


def _record(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [()] * len(_COLUMNS)
    made = [pa.array(c, type=t) for c, t in zip(cols, _COLUMNS.values(), strict=True)]
    return pa.RecordBatch.from_arrays(made, names=list(_COLUMNS))


def _neighbours(batches) -> Iterator[pa.RecordBatch]:
    """Rows (doc_id, text, guest) of one partition in order, then guests: the first row of the next partition."""
    held = None
    for b in (b.slice(x, y - x) for b in batches for x, y in common.text_runs(b.column(1))):
        rows, size = [], 0
        for doc_id, text, guest in zip(*(c.to_pylist() for c in b.columns[:3]), strict=True):
            if guest and held is None:
                break  # guests that share the first one's doc_id
            text = text or ""
            own = fingerprint(text)
            if held is not None:
                rows.append(_compared(*held, text, own))
            held = None if guest else (doc_id, text, own)
            size += len(text)
            if size > common.SLICE_CHARS:
                yield _record(rows)
                rows, size = [], 0
        if rows:
            yield _record(rows)


def _dealt(batches, cuts: np.ndarray, heads: dict[int, int]) -> Iterator[pa.RecordBatch]:
    """Rows with their partition; a row that is the first of a partition also goes to the one before, as a guest."""
    firsts = np.array(sorted(heads), dtype=np.int64)
    for b in batches:
        key = b.column(2).to_numpy()
        part = np.searchsorted(cuts, key, side="right")
        copies = np.flatnonzero(np.isin(key, firsts))
        guests = b.take(pa.array(copies))
        to = [heads[k] for k in key[copies].tolist()]
        for rows, place, guest in ((b, part, False), (guests, to, True)):
            if rows.num_rows:
                made = [pa.array([guest] * rows.num_rows), rows.column(2), rows.column(3), pa.array(np.asarray(place, dtype=np.int32))]
                yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(1), *made], names=["doc_id", "text", "guest", "key", "tie", "part"])


def compare_with_next(docs: DataFrame, partitions: int | None = None) -> DataFrame:
    """docs (doc_id, text) -> one row per row with the fingerprints of the text, of its edited text, and likenesses.

    Two passes over the ids alone give the cuts and the first doc_id of each partition: two numbers per partition reach
    the driver and the tasks. The texts then move once.
    """
    spark = docs.sparkSession
    n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    key = F.coalesce("doc_id", F.lit(NULL_ID))
    shares = [k / n for k in range(1, n)] or [0.5]
    found = docs.select(key.alias("key")).agg(F.percentile_approx("key", shares, 100 * n).alias("cuts")).first()["cuts"]
    cuts = np.unique(np.array(found if n > 1 and found else [], dtype=np.int64))

    def lowest(batches):
        least: dict[int, int] = {}
        for b in batches:
            values = b.column(0).to_numpy()
            part = np.searchsorted(cuts, values, side="right")
            for p in np.unique(part).tolist():
                least[p] = min(int(values[part == p].min()), least.get(p, 1 << 63))
        yield pa.RecordBatch.from_arrays([pa.array(list(least), type=pa.int32()), pa.array(list(least.values()), type=pa.int64())], names=["part", "least"])

    ids = common.map_arrow(docs.select(key.alias("key")), lowest, "part int, least long")
    least = {r["part"]: r["least"] for r in ids.groupBy("part").agg(F.min("least").alias("least")).collect()}
    order = sorted(least)
    heads = {least[p]: order[k - 1] for k, p in enumerate(order)}  # the first of all follows the last of all
    rows = docs.select("doc_id", "text", key.alias("key"), F.xxhash64("text").alias("tie"))
    ddl = "doc_id long, text string, guest boolean, key long, tie long, part int"
    dealt = common.map_arrow(rows, lambda b: _dealt(b, cuts, heads), ddl).repartitionById(len(cuts) + 1, "part")
    ordered = dealt.select("doc_id", "text", "guest", "key", "tie").sortWithinPartitions("guest", "key", "tie")
    return common.map_arrow(ordered, _neighbours, _DDL)
