"""Packing of tokenised documents into sequences by length patterns (histogram fit by non-negative least squares).

1. Every whole text becomes token ids plus one closing id. Longer ones are cut into full sequences; the remainder
   comes first, so each document has at most one piece shorter than a sequence.
2. The histogram of piece lengths (at most ``width`` numbers) goes to the driver. Patterns of up to three lengths that
   fill a sequence are enumerated, their repeat counts are fitted to the histogram by non-negative least squares and
   rounded down; what is left is packed best-fit, the largest first, into the gaps of the patterns and new sequences.
3. The plan says, for each length and rank among the pieces of this length, which sequence and place it takes. Ranks
   come from counts per task, so no group of equal lengths ever meets in one task.

Defined results: null texts are empty (one piece, the closing id); repeated rows are packed once each; an empty table
gives an empty result. The plan depends on the histogram alone, its size on the number of lengths and patterns.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common
from .bpe import byte_symbols

WIDTH = 1024
CLOSING_ID = 2
#: Patterns of three lengths may leave at most so many places of a sequence free.
MAX_GAP = 8
FIT_STEPS = 400

_encoders: dict[str, object] = {}


def byte_encoder(path: str):
    """The vocabulary of a byte-level tokenizers file, run by tiktoken: equal ids, several times as fast."""
    if path not in _encoders:
        import json

        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        back = {s: b for b, s in enumerate(byte_symbols())}
        ranks = {bytes(back[c] for c in t): i for t, i in spec["model"]["vocab"].items()}
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        # fixed value: the public word pattern of byte-level vocabularies
        pattern = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
        _encoders[path] = tiktoken.Encoding("byte_level", pat_str=pattern, mergeable_ranks=ranks, special_tokens=special)
    return _encoders[path]


def token_ids(encoder, text: str | None) -> np.ndarray:
    ids = encoder.encode(text, allowed_special="all") if text else []
    return np.array([*ids, CLOSING_ID], dtype="<u4")


def cut_pieces(docs: DataFrame, path: str, width: int = WIDTH, with_ids: bool = False) -> DataFrame:
    """docs (doc_id, text) -> doc_id, piece, start, length, ids_crc32, rank_in_task[, ids]: one row per piece."""

    def kernel():
        encoder = byte_encoder(path)
        seen = np.zeros(width + 1, dtype=np.int64)

        def f(texts: list[str | None]) -> list[pa.Array]:
            out = []
            for t in texts:
                ids = token_ids(encoder, t)
                first = len(ids) % width or width
                edges = [0, *range(first, len(ids) + 1, width)]
                rows = []
                for a, b in zip(edges, edges[1:], strict=False):
                    row = {"start": a, "length": b - a, "ids_crc32": zlib.crc32(ids[a:b].tobytes()), "rank": int(seen[b - a])}
                    rows.append(row | ({"ids": ids[a:b].tolist()} if with_ids else {}))
                    seen[b - a] += 1
                out.append(rows)
            fields = [("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("rank", pa.int64())]
            fields += [("ids", pa.list_(pa.int64()))] if with_ids else []
            return [pa.array(out, type=pa.list_(pa.struct(fields)))]

        return f

    extra = "p array<struct<start:long,length:long,ids_crc32:long,rank:long" + (",ids:array<long>>>" if with_ids else ">>")
    made = common.map_texts(docs.select("doc_id", "text"), "text", extra, kernel).drop("text")
    return made.select(
        "doc_id", F.spark_partition_id().alias("task"), F.posexplode("p").alias("piece", "x")
    ).select("doc_id", "task", "piece", "x.*")


# ---- the plan, on the driver, from the histogram alone -----------------------------------------------------------


@dataclass(frozen=True)
class Plan:
    """For length n, ranks from starts[i] on (keys are n * 2**44 + rank) take sequence base + rank - start."""

    keys: np.ndarray
    base: np.ndarray
    offset: np.ndarray
    sequences: int


def length_patterns(hist: np.ndarray, width: int) -> np.ndarray:
    """Patterns of two and three present lengths that fill a sequence but for MAX_GAP places; zero for no length."""
    present = np.flatnonzero(hist)
    present = present[(present > 0) & (present < width)]
    if not len(present):
        return np.zeros((0, 3), dtype=np.int64)
    floor = np.zeros(width + 1, dtype=np.int64)  # largest present length that is at most the index
    floor[present] = present
    floor = np.maximum.accumulate(floor)
    pairs = np.stack([present, floor[width - present], np.zeros_like(present)], axis=1)
    a, b = (x.ravel() for x in np.meshgrid(present, present, indexing="ij"))
    rest = width - a - b
    ok = (a >= b) & (rest > 0)
    a, b, rest = a[ok], b[ok], rest[ok]
    triples = np.stack([a, b, floor[np.minimum(b, rest)]], axis=1)
    both = np.concatenate([pairs, triples[triples[:, 2] > 0]])
    both = both[(both[:, 1] > 0) & (both.sum(axis=1) >= width - MAX_GAP)]
    return np.unique(-np.sort(-both, axis=1), axis=0)


def fit_counts(patterns: np.ndarray, hist: np.ndarray, steps: int = FIT_STEPS) -> np.ndarray:
    """Repeat counts x >= 0 that bring the patterns' lengths nearest to the histogram, in least squares.

    Accelerated projected gradient; the largest squared singular value comes from power iteration. Column 0 stands for
    "no length" and is left out of the sums.
    """
    m = len(patterns)

    def lengths(x: np.ndarray) -> np.ndarray:
        out = sum(np.bincount(patterns[:, k], weights=x, minlength=len(hist)) for k in range(3))
        out[0] = 0
        return out

    def back(r: np.ndarray) -> np.ndarray:
        r = r.copy()
        r[0] = 0
        return r[patterns].sum(axis=1)

    v = np.full(m, 1 / np.sqrt(max(m, 1)))
    top = 1.0
    for _ in range(20):
        v = back(lengths(v))
        top = float(np.linalg.norm(v)) or 1.0
        v /= top
    target = hist.astype(float)
    target[0] = 0
    x = y = np.zeros(m)
    t = 1.0
    for _ in range(steps):
        new = np.maximum(0.0, y - back(lengths(y) - target) / (1.05 * top))
        t, last = (1 + np.sqrt(1 + 4 * t * t)) / 2, t
        y = new + (last - 1) / t * (new - x)
        x = new
    return x


def best_fit(bins: dict[tuple[int, ...], int], left: np.ndarray, width: int) -> dict[tuple[int, ...], int]:
    """Put the pieces of ``left`` (a histogram) into the bins, each into the tightest gap; bins are counted by content."""
    gaps: dict[int, dict[tuple[int, ...], int]] = {}
    for content, n in bins.items():
        gaps.setdefault(width - sum(content), {})[content] = n
    spaces = sorted(g for g in gaps if g > 0)
    for size in range(width, 0, -1):
        c = int(left[size])
        while c:
            i = bisect_left(spaces, size)
            if i == len(spaces):
                gaps[width] = {(): -(-c // (width // size))}
                spaces.append(width)
            s = spaces[i]
            content, n = next(iter(gaps[s].items()))
            k = min(c, n)
            c -= k
            if n == k:
                del gaps[s][content]
                if not gaps[s]:
                    del gaps[s], spaces[i]
            else:
                gaps[s][content] = n - k
            to = s - size
            if to not in gaps:
                gaps[to] = {}
                if to > 0:
                    spaces.insert(bisect_left(spaces, to), to)
            filled = (*content, size)
            gaps[to][filled] = gaps[to].get(filled, 0) + k
    return {content: n for group in gaps.values() for content, n in group.items() if content}


def make_plan(hist: np.ndarray, width: int = WIDTH) -> Plan:
    """hist[n]: number of pieces of n tokens, n from 0 to width."""
    left = hist.astype(np.int64).copy()
    bins: dict[tuple[int, ...], int] = {}
    if left[width]:
        bins[(width,)] = int(left[width])
        left[width] = 0
    patterns = length_patterns(left, width)
    if len(patterns):
        counts = np.floor(fit_counts(patterns, left) + 1e-6).astype(np.int64)
        for k in np.argsort(-counts, kind="stable"):
            if counts[k] < 1:
                break
            content = tuple(int(n) for n in patterns[k] if n)
            # a rounded fit may ask for a few more pieces than there are
            n = min(int(counts[k]), *(int(left[x]) // content.count(x) for x in content))
            if n > 0:
                bins[content] = bins.get(content, 0) + n
                for x in content:
                    left[x] -= n
    bins = best_fit(bins, left, width)
    taken = np.zeros(width + 1, dtype=np.int64)
    keys, base, offset, total = [], [], [], 0
    for content, n in bins.items():
        at = 0
        for size in content:
            keys.append((size << 44) + int(taken[size]))
            base.append(total)
            offset.append(at)
            taken[size] += n
            at += size
        total += n
    order = np.argsort(np.array(keys, dtype=np.int64), kind="stable")
    return Plan(*(np.array(x, dtype=np.int64)[order] for x in (keys, base, offset)), total)


def place(pieces: DataFrame, plan: Plan) -> DataFrame:
    """Append sequence_id and offset to pieces with columns length and rank."""
    from pyspark.sql import types as T

    held = pieces.sparkSession.sparkContext.broadcast((plan.keys, plan.base, plan.offset))
    more = [T.StructField(n, T.LongType()) for n in ("sequence_id", "offset")]
    schema = T.StructType([*pieces.schema.fields, *more])
    at, by = pieces.columns.index("length"), pieces.columns.index("rank")

    def run(batches):
        keys, base, offset = held.value
        for b in batches:
            rank = b.column(by).to_numpy()
            key = (b.column(at).to_numpy() << 44) + rank
            k = np.searchsorted(keys, key, side="right") - 1
            made = [pa.array(base[k] + key - keys[k]), pa.array(offset[k])]
            yield pa.RecordBatch.from_arrays([*b.columns, *made], names=[f.name for f in schema])

    return common.map_arrow(pieces, run, schema)


def pack_documents(docs: DataFrame, path: str, width: int = WIDTH, with_ids: bool = False) -> DataFrame:
    """docs (doc_id, text) -> one row per piece with its sequence and place; see the module's text."""
    pieces = common.materialise(cut_pieces(docs, path, width, with_ids), "pieces")
    by_task = pieces.groupBy("length", "task").count()
    before = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    offsets = by_task.select("length", "task", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("before"))
    hist = np.zeros(width + 1, dtype=np.int64)
    for r in pieces.groupBy("length").count().collect():  # at most width rows
        hist[r["length"]] = r["count"]
    ranked = pieces.join(offsets, ["length", "task"]).withColumn("rank", F.col("rank") + F.col("before"))
    names = ["doc_id", "piece", "start", "length", "ids_crc32", *(["ids"] if with_ids else [])]
    return place(ranked.select(*names, "rank"), make_plan(hist, width)).drop("rank")
