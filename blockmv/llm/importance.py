"""Quality selection by importance resampling over hashed n-grams.

Words and word pairs are hashed into BUCKETS buckets. Two bag models are counted - one of the target texts, one of all
raw texts - and a document's log weight is the sum, over its n-grams, of the log ratio of the two. Documents are drawn
without replacement in proportion to their weights by the Gumbel top-k rule: log weight plus Gumbel noise, derived from
doc_id, and the k largest stay. The k-th largest key is found by counting keys in ever finer bins, so no sort of the
corpus and no group of rows is needed.

Raw counts cover every document. The target model is fitted on at most MAX_TARGET labelled documents of good quality
(those of the smallest hashes of doc_id); their ids are broadcast. A model is BUCKETS numbers, whatever the input.

Defined results: a null or empty text has no n-grams and the log weight zero; ties of keys are broken by doc_id, then
all equal rows are taken or left together in the order of doc_id; a null doc_id takes part; an empty table gives no
rows; without target texts all weights are zero and the draw is uniform.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

BUCKETS = 10_000
MAX_TARGET = 20_000
SHARE = 0.75
SMOOTHING = 1.0
SEED = 5
BINS = 4096


def ngram_buckets(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all words and word pairs of some texts, and how many each text has. Words are lower-cased."""
    words, sizes = [], []
    for t in texts:
        w = (t or "").lower().encode().split()
        words += w
        sizes.append(len(w))
    n = np.array(sizes, dtype=np.int64)
    h = np.fromiter(map(zlib.crc32, words), dtype=np.uint64, count=len(words))
    pair = (h[:-1] * np.uint64(0x9E3779B1) + h[1:] * np.uint64(0x85EBCA77)) >> np.uint64(7)
    owner = np.repeat(np.arange(len(n)), n)
    inside = owner[:-1] == owner[1:]
    order = np.argsort(np.concatenate([owner, owner[:-1][inside]]), kind="stable")
    both = np.concatenate([h, pair[inside]])[order] % np.uint64(BUCKETS)
    return both.astype(np.int64), n + np.maximum(n - 1, 0)


def count_ngrams(docs: DataFrame, flag: str) -> np.ndarray:
    """docs (flag, text) -> counts per bucket: row 0 of all texts, row 1 of those whose flag is true."""

    def run(batches):
        total = np.zeros((2, BUCKETS), dtype=np.int64)
        for b in batches:
            chosen = np.array(b.column(0).to_pylist(), dtype=bool)
            for lo, hi in common.text_runs(b.column(1)):
                buckets, sizes = ngram_buckets(b.column(1).slice(lo, hi - lo).to_pylist())
                total[0] += np.bincount(buckets, minlength=BUCKETS)
                total[1] += np.bincount(buckets[np.repeat(chosen[lo:hi], sizes)], minlength=BUCKETS)
        at = np.flatnonzero(total[0])
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[0][at]), pa.array(total[1][at])], names=["bucket", "raw", "target"])

    counted = common.map_arrow(docs.select(flag, "text"), run, "bucket long, raw long, target long")
    out = np.zeros((2, BUCKETS), dtype=np.int64)
    for r in counted.groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target")).collect():
        out[:, r["bucket"]] = r["raw"], r["target"]
    return out


def log_ratio(counts: np.ndarray) -> np.ndarray:
    """Per bucket, log of the target model over the raw model, both smoothed."""
    if not counts[1].sum():
        return np.zeros(BUCKETS)
    share = (counts + SMOOTHING) / (counts.sum(axis=1, keepdims=True) + SMOOTHING * BUCKETS)
    return np.log(share[1]) - np.log(share[0])


def threshold(keys: DataFrame, k: int) -> tuple[float, int]:
    """keys (key double) -> (t, m): exactly k rows are those above t and m of those equal to t."""
    low, high = keys.agg(F.min("key"), F.max("key")).first()
    above = 0
    while low < high:
        width = (high - low) / BINS
        if not width or low + width == low:
            break
        at = F.least(F.floor((F.col("key") - low) / width), F.lit(BINS - 1)).cast("int")
        inside = keys.filter(F.col("key").between(low, high)).groupBy(at.alias("bin"))
        rows = sorted(inside.agg(F.count("*").alias("n"), F.min("key").alias("a"), F.max("key").alias("b")).collect(), reverse=True)
        for r in rows:  # at most BINS
            if above + r["n"] >= k:
                if (low, high) == (r["a"], r["b"]):
                    low = high
                low, high = r["a"], r["b"]
                break
            above += r["n"]
    return high, k - above


def resample(docs: DataFrame, labels: DataFrame, share: float = SHARE, seed: int = SEED) -> DataFrame:
    """docs (doc_id, text), labels (doc_id, quality) -> doc_id, n_ngrams, log_weight, gumbel_key, kept."""
    good = labels.filter("quality = 1").select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(MAX_TARGET)
    good = F.broadcast(good.withColumn("target", F.lit(True)))
    flagged = docs.select("doc_id", "text").join(good, "doc_id", "left")
    ratio = log_ratio(count_ngrams(flagged.select(F.coalesce("target", F.lit(False)).alias("target"), "text"), "target"))
    held = docs.sparkSession.sparkContext.broadcast(ratio)

    def f(texts: list) -> list[pa.Array]:
        buckets, sizes = ngram_buckets(texts)
        owner = np.repeat(np.arange(len(sizes)), sizes)
        weight = np.bincount(owner, weights=held.value[buckets], minlength=len(sizes))
        return [pa.array(sizes, type=pa.int64()), pa.array(weight, type=pa.float64())]

    made = common.map_texts(docs.select("doc_id", "text"), "text", "n_ngrams long, log_weight double", lambda: f)
    # a uniform number in (0, 1) from the document's id; the same in every run
    uniform = (F.pmod(F.xxhash64(F.lit(seed), "doc_id"), F.lit(1 << 52)) + 0.5) / float(1 << 52)
    keyed = made.select("doc_id", "n_ngrams", "log_weight", (F.col("log_weight") - F.log(-F.log(uniform))).alias("key"))
    keyed = common.materialise(keyed, "weights")
    k = round(share * keyed.count())
    if not k:
        return keyed.select("doc_id", "n_ngrams", "log_weight", F.col("key").alias("gumbel_key"), F.lit(False).alias("kept"))
    t, m = threshold(keyed.select("key"), k)
    equal = keyed.filter(F.col("key") == t)
    last = None if equal.count() == m else equal.orderBy(F.asc_nulls_last("doc_id")).limit(m).agg(F.max("doc_id")).first()[0]
    tied = F.lit(True) if last is None else F.col("doc_id") <= last
    kept = (F.col("key") > t) | ((F.col("key") == t) & tied)
    return keyed.select("doc_id", "n_ngrams", "log_weight", F.col("key").alias("gumbel_key"), F.coalesce(kept, F.lit(False)).alias("kept"))
