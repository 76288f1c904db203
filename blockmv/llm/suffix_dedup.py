"""Removal of repeated passages: every byte inside a string of WIDTH bytes that also starts earlier is removed.

"Earlier" means in a document of smaller doc_id, or further ahead in the same document; matches never cross documents
and are judged on the input. Sorting every suffix of the corpus would move many times its size, so suffixes are sorted
in two rounds that together decide every WIDTH-byte string exactly.

Round 1, anchored suffixes. Each string of WIDTH bytes is assigned the position of the smallest hash among its GRAM-byte
substrings. Equal strings have equal anchors, so strings of one anchor are compared with each other only. The strings
of one anchor start at consecutive positions and form a span; there is one span for about every 35 bytes. Spans are
ordered by the suffix at their anchor - its 8 leading bytes, then a hash of GRAM bytes - then by a 128-bit digest of the
whole span, by document and position. Splitters sampled from the corpus range-partition them by these keys, also inside
a run of equal spans, so a passage that stands in a third of all documents is dealt over as many tasks as its share. Each
bucket is sorted by multikey quicksort. All but the first of a run of equal spans are removed whole; that two spans are
equal is told by their digests. Different spans with the same anchor, and those at the edges of a bucket, go to round 2.

Round 2, full suffixes. The remaining spans are shipped with their bytes, range-partitioned by the keys of their single
strings with splitters sampled anew, and expanded: every start in the span is a suffix. A bucket sorts them by multikey
quicksort over the anchor's keys, then over the suffixes' own bytes, WORDS words of 8 bytes that cover WIDTH bytes, then by
document and position. Neighbours with equal bytes form a run; all but its first are removed. The first suffix of a bucket,
in the order of the splitters, is compared with the last one of the bucket before, which settles runs that go over a
boundary.

A bucket holds about BUCKET_BYTES of text, whatever the size of the corpus: there are as many as that takes.

Defined results: null and empty texts, and texts under WIDTH bytes, lose nothing; rows that repeat a doc_id and its text
are one document and get equal results; differing texts of one doc_id, or without doc_id, are documents of their own, in
the order of their SHA-256; a null doc_id sorts before all others; an empty table gives no rows. Memory of a task: its bucket, and one portion of texts.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_right
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common

WIDTH = 100
GRAM = 32
_REACH = WIDTH - GRAM + 1
#: Bytes handled at once; positions inside such a portion take 24 bits.
PORTION = 1_000_000
_POSITION = np.uint64((1 << 24) - 1)
#: Spans held by a task before they are handed on, and documents sampled per bucket for the splitters.
HELD_SPANS = 400_000
SAMPLED_DOCS = 16
SAMPLED_ROWS = 64
#: Text of a bucket, which bounds the memory of a task; there are spark.sql.shuffle.partitions buckets at least.
BUCKET_BYTES = 12_000_000
#: 8-byte words that cover WIDTH bytes.
WORDS = -(-WIDTH // 8)

_BYTE = np.array([xxhash.xxh64_intdigest(bytes([b]), 11) for b in range(256)], dtype=np.uint64)
_ODD = [np.uint64(xxhash.xxh64_intdigest(bytes([k]), 13) | 1) for k in range(8)]
NULL_ID = -(1 << 63)
#: Name of the column of stretches, which is read by its place only.
CUT = "_stretches_of_this_document"
#: Name of the column with the key of a row's document, which keeps the order of documents.
KEY = "_key_of_this_document"


# ---- hashes of substrings ------------------------------------------------------------------------------------------


def _fold(x: np.ndarray, k: int) -> np.ndarray:
    """Mixed copy of x for level k; not linear, so differences do not cancel."""
    y = x >> np.uint64(29)
    y ^= x
    y *= _ODD[k]
    return y


def substring_hashes(data: np.ndarray) -> dict[int, np.ndarray]:
    """size -> h with h[i] the hash of data[i:i+size], for sizes 4, 32 and 64, by doubling."""
    h, size, kept = _BYTE[data], 1, {}
    level = 0
    while size < 64:
        if len(h) <= size:
            h = np.zeros(0, dtype=np.uint64)
        else:
            a = _fold(h[:-size], level)
            a += h[size:]
            h = a
        size *= 2
        level += 1
        if size in (4, 32, 64):
            kept[size] = h
    return kept


def string_hashes(h: dict[int, np.ndarray], at: np.ndarray) -> np.ndarray:
    """Hashes of the WIDTH bytes from each position: 64 + 32 + 4."""
    x = _fold(h[64][at], 0) + h[32][at + 64]
    return _fold(_fold(x, 1) + h[4][at + 96], 2)


def _sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    m, size = x, 1
    while 2 * size <= width:
        m = np.minimum(m[:-size], m[size:])
        size *= 2
    return np.minimum(m[: len(m) - (width - size)], m[width - size :]) if width > size else m


def words_at(data: np.ndarray, at: np.ndarray, size: int = 8) -> np.ndarray:
    """The ``size`` bytes from each position as a number in the order of the bytes; at most 8, the rest is zero."""
    out = np.zeros((len(at), 8), dtype=np.uint8)
    for k in range(size):
        out[:, k] = data[at + k]
    return out.view(">u8").ravel().astype(np.uint64)


def find_spans(data: np.ndarray, ends: np.ndarray) -> dict[str, np.ndarray]:
    """Spans of the texts concatenated in data. ends: end of its text for each byte.

    -> start (a position in data), n (number of strings), w and g (leading bytes and hash of the suffix at the anchor),
    s and t (digest of the span).
    """
    kinds = {"start": np.int64, "n": np.int64, "w": np.uint64, "g": np.uint64, "s": np.uint64, "t": np.uint64}
    none = {k: np.zeros(0, dtype=kind) for k, kind in kinds.items()}
    if len(data) < WIDTH:
        return none
    h = substring_hashes(data)
    grams = h[32]
    packed = (grams & ~_POSITION) | np.arange(len(grams), dtype=np.uint64)
    low = _sliding_min(packed, _REACH)
    at = np.flatnonzero(ends[: len(low)] - np.arange(len(low)) >= WIDTH)
    if not len(at):
        return none
    anchor = (low[at] & _POSITION).astype(np.int64)
    new = np.flatnonzero(np.concatenate([[True], anchor[1:] != anchor[:-1]]))
    start, anchor = at[new], anchor[new]
    n = np.diff(np.append(new, len(at)))
    raw, digest = data.tobytes(), xxhash.xxh3_128_digest
    marks = b"".join([digest(raw[a:b]) for a, b in zip(start.tolist(), (start + n - 1 + WIDTH).tolist(), strict=True)])
    halves = np.frombuffer(marks, dtype="<u8").reshape(-1, 2)
    return {"start": start, "n": n, "w": words_at(data, anchor), "g": _fold(grams[anchor], 6), "s": halves[:, 0], "t": halves[:, 1]}


# ---- sorting and dealing ---------------------------------------------------------------------------------------------


def multikey_order(columns: list, small: int = 8192) -> np.ndarray:
    """Order of the rows by their key columns: three-way quicksort that goes one column deeper among equals.

    A column is an array, or a function from row numbers to their keys, which is asked only as deep as ties go.
    """
    n = len(columns[0])
    look = [(lambda rows, c=c: c[rows]) if isinstance(c, np.ndarray) else c for c in columns]
    order = np.arange(n)
    todo = [(0, n, 0)]
    while todo:
        a, b, depth = todo.pop()
        rows = order[a:b]
        if b - a <= small:
            order[a:b] = _small_order(look, rows, depth)
            continue
        key = look[depth](rows)
        pivot = np.sort(key[:: max(1, (b - a) // 255)])[len(key[:: max(1, (b - a) // 255)]) // 2]
        low, high = key < pivot, key > pivot
        equal = ~(low | high)
        x, y = int(low.sum()), int(equal.sum())
        order[a:b] = np.concatenate([rows[low], rows[equal], rows[high]])
        todo += [(a, a + x, depth), (a + x + y, b, depth)]
        if depth + 1 < len(columns) and y > 1:
            todo.append((a + x, a + x + y, depth + 1))
    return order


def _small_order(look: list, rows: np.ndarray, depth: int) -> np.ndarray:
    """Rows by their keys from ``depth`` on: column by column, among those that are still tied."""
    key = look[depth](rows)
    by = np.argsort(key, kind="stable")
    rows, key = rows[by], key[by]
    tie = np.concatenate([[0], np.cumsum(key[1:] != key[:-1])])
    for get in look[depth + 1 :]:
        size = np.bincount(tie)
        open_ = np.flatnonzero(size[tie] > 1)
        if not len(open_):
            break
        key = get(rows[open_])
        by = np.lexsort([key, tie[open_]])
        rows[open_], key = rows[open_][by], key[by]
        # a tie ends where the run ends or the key changes
        step = np.ones(len(rows), dtype=np.int64)
        step[0] = 0
        step[1:] = tie[1:] != tie[:-1]
        step[open_[1:][key[1:] != key[:-1]]] = 1
        tie = np.cumsum(step)
    return rows


class Splitters:
    """Sampled keys (leading bytes, further tokens, document, position) that cut the order of suffixes into buckets."""

    def __init__(self, keys: list[tuple]) -> None:
        self.keys = sorted(keys)
        self.lead = np.array([k[0] for k in self.keys], dtype=np.uint64)

    @classmethod
    def sampled(cls, keys: list[tuple], buckets: int) -> Splitters:
        keys = sorted(set(keys))
        return cls([keys[len(keys) * k // buckets] for k in range(1, buckets)] if keys else [])

    def buckets(self, *columns: np.ndarray) -> np.ndarray:
        """Bucket of each key; only keys whose leading bytes are a splitter's are looked at in full."""
        out = np.searchsorted(self.lead, columns[0], side="left")
        some = np.flatnonzero(out != np.searchsorted(self.lead, columns[0], side="right"))
        for k, key in zip(some.tolist(), zip(*(c[some].tolist() for c in columns), strict=True), strict=False):
            out[k] = bisect_right(self.keys, key)
        return out


def _portions(batches) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """From batches (doc_id, text, ...): (bytes, end of text per byte, document per byte run, start) in portions.

    -> data, ends, document ids and start offsets of the pieces, base position of each piece in its document. A text
    over PORTION bytes is cut into pieces that overlap by WIDTH - 1 bytes, so no string is lost or seen twice.
    """
    held: list[tuple[int, int, bytes]] = []
    size = 0

    def out():
        data = np.frombuffer(b"".join(x[2] for x in held), dtype=np.uint8)
        sizes = np.array([len(x[2]) for x in held], dtype=np.int64)
        stops = np.cumsum(sizes)
        return data, np.repeat(stops, sizes), np.array([x[0] for x in held], dtype=np.int64), stops - sizes, np.array([x[1] for x in held], dtype=np.int64)

    parts = (b.slice(x, y - x) for b in batches for x, y in common.text_runs(b.column(1)))
    for b in parts:
        for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            raw = (text or "").encode()
            doc = NULL_ID if doc is None else doc
            for a in range(0, max(1, len(raw) - WIDTH + 1), PORTION):
                piece = raw[a : a + PORTION + WIDTH - 1]
                if len(piece) < WIDTH:
                    continue
                if size + len(piece) > PORTION and held:
                    yield out()
                    held, size = [], 0
                held.append((doc, a, piece))
                size += len(piece)
    if held:
        yield out()


_SPAN = np.dtype([("w", "<u8"), ("g", "<u8"), ("s", "<u8"), ("t", "<u8"), ("doc", "<i8"), ("at", "<i8"), ("n", "<i2")])


SPAN_KEYS = ("w", "g", "s", "doc", "at")


def spans_of(batches) -> Iterator[np.ndarray]:
    """Spans of whole texts, as records of _SPAN."""
    for data, ends, docs, begins, bases in _portions(batches):
        found = find_spans(data, ends)
        start = found["start"]
        piece = np.searchsorted(begins, start, side="right") - 1
        rows = np.empty(len(start), dtype=_SPAN)
        for c in "wgstn":
            rows[c] = found[c]
        rows["doc"], rows["at"] = docs[piece], start - begins[piece] + bases[piece]
        yield rows


def _packed(rows: np.ndarray) -> bytes:
    """Columns one after the other, compressed: the hashes are all that does not shrink."""
    order = np.lexsort([rows["at"], rows["doc"]])
    rows = rows[order]
    cols = [np.diff(rows[c], prepend=0) if c == "doc" else rows[c] for c in _SPAN.names]
    planes = [np.ascontiguousarray(c).view(np.uint8).reshape(len(rows), -1).T.tobytes() for c in cols]
    return len(rows).to_bytes(4, "little") + zstandard.ZstdCompressor(level=1).compress(b"".join(planes))


def _unpacked(blob: bytes) -> np.ndarray:
    n = int.from_bytes(blob[:4], "little")
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(blob[4:]), dtype=np.uint8)
    out = np.empty(n, dtype=_SPAN)
    a = 0
    for name in _SPAN.names:
        kind = _SPAN[name]
        part = np.ascontiguousarray(raw[a : a + n * kind.itemsize].reshape(kind.itemsize, n).T).view(kind).ravel()
        out[name] = np.cumsum(part) if name == "doc" else part
        a += n * kind.itemsize
    return out


def _dealt(batches, splitters: Splitters) -> Iterator[pa.RecordBatch]:
    """Spans by bucket, packed: one row per bucket and portion of HELD_SPANS spans."""
    held: list[np.ndarray] = []

    def out():
        rows = np.concatenate(held)
        bucket = splitters.buckets(*(rows[c] for c in SPAN_KEYS))
        order = np.argsort(bucket, kind="stable")
        edges = np.flatnonzero(np.diff(bucket[order], prepend=-1, append=len(splitters.keys) + 1))
        blobs = [_packed(rows[order[a:b]]) for a, b in zip(edges, edges[1:], strict=False)]
        made = [pa.array(bucket[order[edges[:-1]]].astype(np.int32)), pa.array(blobs, type=pa.binary())]
        return pa.RecordBatch.from_arrays(made, names=["bucket", "spans"])

    for rows in spans_of(batches):
        held.append(rows)
        if sum(map(len, held)) >= HELD_SPANS:
            yield out()
            held = []
    if held and sum(map(len, held)):
        yield out()


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(np.ascontiguousarray(x).view(np.int64))


def _sorted_spans(batches) -> Iterator[pa.RecordBatch]:
    """Round 1 in a bucket: repeated spans (open = false), and those that need round 2 (open = true)."""
    blobs = [x for b in batches for x in b.column(1).to_pylist()]
    if not blobs:
        return
    rows = np.concatenate([_unpacked(x) for x in blobs])
    del blobs
    order = multikey_order([np.ascontiguousarray(rows[c]) for c in ("w", "g", "s", "t", "doc", "at")])
    rows = rows[order]
    w, g = rows["w"], rows["g"]
    differs = lambda *names: np.concatenate([[True], np.logical_or.reduce([rows[c][1:] != rows[c][:-1] for c in names])])
    new_g = differs("w", "g")
    first = new_g | differs("s", "t")
    run = np.cumsum(new_g) - 1
    kinds = np.bincount(run, weights=first)
    several = kinds > 1
    several[[0, -1]] = True  # what begins before or goes on after this bucket
    open_ = first & several[run]
    keep = np.flatnonzero(open_ | ~first)
    for a in range(0, len(keep), 200_000):
        k = keep[a : a + 200_000]
        made = [pa.array(open_[k]), pa.array(rows["doc"][k]), pa.array(rows["at"][k]), pa.array(rows["n"][k].astype(np.int32)), _signed(w[k]), _signed(g[k])]
        yield pa.RecordBatch.from_arrays(made, names=["open", "doc", "at", "n", "w", "g"])


def _open_strings(batches):
    """From batches (doc, text, ats, ns, ws, gs): per portion the open spans (doc, at, n, w, g) with their bytes."""
    for b in batches:
        for lo, hi in common.text_runs(b.column(1)):
            doc, at, n, w, g, cut = [], [], [], [], [], []
            for d, t, ats, ns, ws, gs in zip(*(c.slice(lo, hi - lo).to_pylist() for c in b.columns), strict=True):
                raw = (t or "").encode()
                doc += [d] * len(ats)
                at += ats
                n += ns
                w += ws
                g += gs
                cut += [raw[a : a + k - 1 + WIDTH] for a, k in zip(ats, ns, strict=True)]
            tokens = (np.array(x, dtype=np.int64).view(np.uint64) for x in (w, g))
            yield np.array(doc), np.array(at), np.array(n), *tokens, cut


@dataclass
class Strings:
    """Every string of some spans: its keys, its place in data, and its span."""

    data: np.ndarray
    span: np.ndarray
    w: np.ndarray
    g: np.ndarray
    h: np.ndarray
    doc: np.ndarray
    at: np.ndarray
    where: np.ndarray

    @property
    def keys(self) -> tuple[np.ndarray, ...]:
        return self.w, self.g, self.h, self.doc, self.at

    def take(self, rows: np.ndarray) -> Strings:
        return Strings(self.data, *(getattr(self, c)[rows] for c in ("span", "w", "g", "h", "doc", "at", "where")))


def expand(doc, at, n, w, g, cut) -> Strings:
    data = np.frombuffer(b"".join(cut), dtype=np.uint8)
    begin = np.cumsum([0, *map(len, cut)])
    span = np.repeat(np.arange(len(n)), n)
    step = np.arange(len(span)) - np.repeat(np.cumsum(n) - n, n)
    where = begin[span] + step
    h = np.empty(len(span), dtype=np.uint64)
    edge = np.cumsum(np.concatenate([[0], n]))
    a = 0
    while a < len(n):  # whole spans in portions, which bounds the arrays of hashes
        b = max(a + 1, int(np.searchsorted(begin, begin[a] + PORTION, side="right")) - 1)
        part = slice(edge[a], edge[b])
        h[part] = string_hashes(substring_hashes(data[begin[a] : begin[b]]), where[part] - begin[a])
        a = b
    return Strings(data, span, w[span], g[span], h, doc[span], at[span] + step, where)


def _round_two(batches, splitters: Splitters) -> Iterator[pa.RecordBatch]:
    """Open spans with their bytes, one row for each bucket that gets strings of the span."""
    for doc, at, n, w, g, cut in _open_strings(batches):
        if not len(n):
            continue
        low = np.searchsorted(splitters.lead, w, side="left")
        split = low != np.searchsorted(splitters.lead, w, side="right")
        span, bucket = np.flatnonzero(~split), low[~split]
        if split.any():
            some = np.flatnonzero(split)
            x = expand(*(c[some] for c in (doc, at, n, w, g)), [cut[k] for k in some])
            pairs = np.unique(np.stack([some[x.span], splitters.buckets(*x.keys)]), axis=1)
            span, bucket = np.concatenate([span, pairs[0]]), np.concatenate([bucket, pairs[1]])
        made = [
            pa.array(bucket.astype(np.int32)),
            pa.array(doc[span]),
            pa.array(at[span]),
            pa.array(n[span].astype(np.int32)),
            _signed(w[span]),
            _signed(g[span]),
            pa.array([cut[k] for k in span], type=pa.binary()),
        ]
        yield pa.RecordBatch.from_arrays(made, names=["bucket", "doc", "at", "n", "w", "g", "bytes"])


def _sorted_strings(batches, splitters: Splitters) -> Iterator[pa.RecordBatch]:
    """Round 2 in a bucket: removed stretches, and the bucket's first and last string for the boundaries."""
    got = [b for b in batches if b.num_rows]
    if not got:
        return
    t = pa.Table.from_batches(got).combine_chunks()
    mine = t.column("bucket")[0].as_py()
    doc, at, n = (t.column(c).to_numpy() for c in ("doc", "at", "n"))
    w, g = (t.column(c).to_numpy().view(np.uint64) for c in "wg")
    x = expand(doc, at, n, w, g, t.column("bytes").to_pylist())
    x = x.take(np.flatnonzero(splitters.buckets(*x.keys) == mine))
    if not len(x.doc):
        return
    edge = [_extreme(x.keys, side) for side in (np.min, np.max)]
    ends = [(x.data[v : v + WIDTH].tobytes(), int(x.doc[k]), int(x.at[k])) for k, v in zip(edge, x.where[edge].tolist(), strict=True)]
    suffix = [lambda rows, k=k: words_at(x.data, x.where[rows] + 8 * k, min(8, WIDTH - 8 * k)) for k in range(WORDS)]
    x = x.take(multikey_order([x.w, x.g, *suffix, x.doc, x.at]))
    same = np.flatnonzero((x.w[1:] == x.w[:-1]) & (x.g[1:] == x.g[:-1]) & (x.h[1:] == x.h[:-1]))  # equal bytes have equal hashes
    repeated = np.zeros(len(x.doc), dtype=bool)
    for a in range(0, len(same), 100_000):
        k = same[a : a + 100_000]
        left, right = (x.data[x.where[y][:, None] + np.arange(WIDTH)] for y in (k, k + 1))
        repeated[k[(left == right).all(axis=1)] + 1] = True
    d2, p2 = x.doc[repeated], x.at[repeated]
    by = np.lexsort([p2, d2])
    d2, p2 = d2[by], p2[by]
    # strings that overlap or touch make one stretch
    new = np.flatnonzero(np.concatenate([[True], (d2[1:] != d2[:-1]) | (p2[1:] > p2[:-1] + WIDTH)])) if len(d2) else np.zeros(0, dtype=np.int64)
    m = len(new)
    last = np.append(new[1:], len(d2))[:m] - 1
    yield pa.RecordBatch.from_arrays(
        [
            pa.array(["run"] * m + ["first", "last"]),
            pa.array([mine] * (m + 2), type=pa.int32()),
            pa.array([*d2[new], *(e[1] for e in ends)], type=pa.int64()),
            pa.array([*p2[new], *(e[2] for e in ends)], type=pa.int64()),
            pa.array([*(p2[last] + WIDTH), *(e[2] + WIDTH for e in ends)], type=pa.int64()),
            pa.array([None] * m + [e[0] for e in ends], type=pa.binary()),
        ],
        names=["kind", "bucket", "doc", "begin", "end", "bytes"],
    )


def _extreme(keys: tuple[np.ndarray, ...], side) -> int:
    """Row of the smallest or largest key."""
    rows = np.arange(len(keys[0]))
    for c in keys:
        rows = rows[c[rows] == side(c[rows])]
    return int(rows[0])


# ---- on Spark ----------------------------------------------------------------------------------------------------------


def _partitions(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def _sample(df: DataFrame, rows: int) -> DataFrame:
    """About ``rows`` rows of df, which is counted from its files' footers; always the same ones."""
    have = max(1, df.count())
    return df.sample(min(1.0, rows / have), seed=17)


def _keys(df: DataFrame, f, names: str, buckets: int) -> list[tuple]:
    """Keys of sampled spans or strings: f gives their columns per portion. At most a bounded number per task reaches the
    driver: SAMPLED_ROWS for each bucket in all, evenly from what the sample holds."""
    columns = names.split()

    def run(batches):
        for made in f(batches):
            pick = np.arange(0, len(made[0]), max(1, len(made[0]) // (SAMPLED_ROWS * 4)))
            yield pa.RecordBatch.from_arrays([_signed(c[pick]) for c in made], names=columns)

    rows = common.map_arrow(df, run, ", ".join(f"{c} long" for c in columns))
    got = rows.orderBy(F.xxhash64(*columns)).limit(SAMPLED_ROWS * buckets).collect()
    wrap = (1 << 64) - 1
    return [tuple(r[c] if c in ("doc", "at") else r[c] & wrap for c in columns) for r in got]


def _numbered(docs: DataFrame) -> tuple[DataFrame, DataFrame, int]:
    """docs (doc_id, text, ...) -> docs with KEY, its texts (doc, text), one row per document, and their bytes.

    Where no two rows share a doc_id, it is the key. Otherwise the distinct (doc_id, text) are numbered in their order.
    """
    spark = docs.sparkSession
    plain = F.coalesce("doc_id", F.lit(NULL_ID))
    per_id = docs.groupBy(plain.alias("doc")).agg(F.count("*").alias("rows"), F.sum(F.octet_length("text")).alias("size"))
    most, size = per_id.agg(F.max("rows"), F.sum("size")).first()
    if (most or 0) <= 1:
        own = docs.withColumn(KEY, plain)
        return own, own.select(F.col(KEY).alias("doc"), "text"), size or 0
    digest = F.sha2(docs["text"], 256)
    some = docs.select("doc_id", digest.alias("digest")).distinct()
    order = (F.col("doc_id").asc_nulls_first(), F.col("digest").asc_nulls_first())
    ranged = some.repartitionByRange(_partitions(docs), *order).sortWithinPartitions(*order)
    # the low 33 bits of the id count the rows of a partition
    place = F.monotonically_increasing_id()
    ranged = common.materialise(ranged.select("doc_id", "digest", F.shiftright(place, 33).alias("part"), place.bitwiseAND(F.lit((1 << 33) - 1)).alias("at")), "documents")
    offsets, total = [], 0
    for r in ranged.groupBy("part").count().orderBy("part").collect():
        offsets.append((r["part"], total))
        total += r["count"]
    first = spark.createDataFrame(offsets, "part long, first long")
    keys = ranged.join(F.broadcast(first), "part").select("doc_id", "digest", (F.col("first") + F.col("at")).alias("doc"))
    met = docs.join(keys, docs["doc_id"].eqNullSafe(keys["doc_id"]) & digest.eqNullSafe(keys["digest"]))
    own = met.select(*[docs[c] for c in docs.columns], keys["doc"].alias(KEY))
    return own, common.materialise(own.select(F.col(KEY).alias("doc"), "text").dropDuplicates(["doc"]), "texts"), size or 0


def repeated_stretches(texts: DataFrame, size: int = 0) -> DataFrame:
    """texts (doc, text), doc distinct and in order -> doc, begin, end: byte stretches to remove; they may overlap.

    size: bytes of all texts, from which the number of buckets follows.
    """
    spark = texts.sparkSession
    buckets = max(_partitions(texts), -(-size // BUCKET_BYTES))

    def span_keys(batches):
        for r in spans_of(batches):
            yield tuple(np.ascontiguousarray(r[c]) for c in SPAN_KEYS)

    found = _keys(_sample(texts, SAMPLED_DOCS * buckets), span_keys, " ".join(SPAN_KEYS), buckets)
    cut = spark.sparkContext.broadcast(Splitters.sampled(found, buckets))
    dealt = common.map_arrow(texts, lambda b: _dealt(b, cut.value), "bucket int, spans binary").repartitionById(buckets, "bucket")
    spans = common.materialise(common.map_arrow(dealt, _sorted_spans, "open boolean, doc long, at long, n int, w long, g long"), "spans")
    whole = spans.filter("not open").select("doc", F.col("at").alias("begin"), (F.col("at") + F.col("n") - 1 + WIDTH).alias("end"))

    open_ = spans.filter("open").groupBy(F.col("doc").alias("key"))
    open_ = open_.agg(*[F.collect_list(c).alias(c) for c in ("at", "n", "w", "g")])
    with_text = texts.join(open_, F.col("doc") == F.col("key")).select("doc", "text", "at", "n", "w", "g")

    def string_keys(batches):
        for portion in _open_strings(batches):
            if len(portion[0]):
                yield expand(*portion).keys

    sampled = _sample(texts, SAMPLED_DOCS * buckets).join(open_, F.col("doc") == F.col("key")).select("doc", "text", "at", "n", "w", "g")
    again = spark.sparkContext.broadcast(Splitters.sampled(_keys(sampled, string_keys, "w g h doc at", buckets), buckets))
    ddl = "bucket int, doc long, at long, n int, w long, g long, bytes binary"
    strings = common.map_arrow(with_text, lambda b: _round_two(b, again.value), ddl).repartitionById(buckets, "bucket")
    ddl = "kind string, bucket int, doc long, begin long, end long, bytes binary"
    runs = common.materialise(common.map_arrow(strings, lambda b: _sorted_strings(b, again.value), ddl), "strings")
    # two rows per bucket: its first string repeats the last one of the bucket before, or not
    edges = runs.filter("kind <> 'run'").select("kind", "bucket", "doc", "begin", "end", "bytes")
    before = Window.orderBy("bucket", F.col("kind") == "last")
    over = edges.withColumn("previous", F.lag("bytes").over(before)).filter("kind = 'first' and bytes = previous")
    return whole.union(runs.filter("kind = 'run'").select("doc", "begin", "end")).union(over.select("doc", "begin", "end"))


def cut_out(raw: bytes, stretches: list[tuple[int, int]]) -> tuple[list[tuple[int, int]], bytes]:
    """Maximal removed runs, and the bytes that stay."""
    runs: list[list[int]] = []
    for a, b in sorted(stretches):
        b = min(b, len(raw))
        if runs and a <= runs[-1][1]:
            runs[-1][1] = max(runs[-1][1], b)
        elif a < b:
            runs.append([a, b])
    kept, at = [], 0
    for a, b in runs:
        kept.append(raw[at:a])
        at = b
    kept.append(raw[at:])
    return [(a, b) for a, b in runs], b"".join(kept)


def _attached(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text, ...) with a last column: all stretches of the document."""
    own, texts, size = _numbered(docs)
    packed = repeated_stretches(texts, size).select("doc", (F.col("begin") * 65536 * 65536 + F.col("end")).alias("x"))
    per_doc = packed.groupBy("doc").agg(F.collect_list("x").alias("x")).select(F.col("doc").alias("key"), "x")
    met = own.join(per_doc, own[KEY] == per_doc["key"], "left")
    return met.select(*[own[c] for c in docs.columns], per_doc["x"].alias(CUT))


def _ranges(cut: list[int] | None) -> list[tuple[int, int]]:
    return [(x >> 32, x & 0xFFFFFFFF) for x in cut or []]


def removal_report(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text) -> doc_id, n_bytes, n_removed, n_spans, kept_sha256; one row per row of docs."""

    def run(batches):
        for b in (b.slice(x, y - x) for b in batches for x, y in common.text_runs(b.column(1))):
            rows = []
            for doc, text, cut in zip(*(c.to_pylist() for c in b.columns), strict=True):
                raw = (text or "").encode()
                runs, kept = cut_out(raw, _ranges(cut))
                rows.append((doc, len(raw), len(raw) - len(kept), len(runs), hashlib.sha256(kept).hexdigest()))
            cols = list(zip(*rows, strict=True)) or [()] * 5
            types = [pa.int64()] * 4 + [pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=t) for c, t in zip(cols, types, strict=True)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    ddl = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
    return common.map_arrow(_attached(docs.select("doc_id", "text")), run, ddl)


def remove_repeats(docs: DataFrame) -> DataFrame:
    """docs, all columns, with repeated passages removed from ``text``.

    A stretch may begin or end inside a character: what is left of a cut character is removed as well. Null texts stay
    null; a text that is removed whole becomes empty. Other columns are not touched.
    """
    found = _attached(docs)
    names, at = docs.columns, docs.columns.index("text")

    def run(batches):
        for b in (b.slice(x, y - x) for b in batches for x, y in common.text_runs(b.column(at))):
            texts = []
            for text, cut in zip(b.column(at).to_pylist(), b.column(len(names)).to_pylist(), strict=True):
                if text is not None and cut:
                    _, kept = cut_out(text.encode(), _ranges(cut))
                    text = kept.decode("utf-8", "ignore")
                texts.append(text)
            cols = [pa.array(texts, type=pa.string()) if k == at else b.column(k) for k in range(len(names))]
            yield pa.RecordBatch.from_arrays(cols, names=names)

    return common.map_arrow(found, run, docs.schema)
