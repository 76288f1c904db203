"""Toxicity by a factorization machine over hashed terms.

A document is a set of hashed terms: its lower-cased words, the first 4 to 7 letters of longer words, and for these
stems a term more if they come twice and three times, since insults are inflected and repeated. The score is the
logistic function of a bias, a weight per term and the products of k-dimensional factors of every two terms, so that a
pair such as an insult next to the mention of a group can count when neither word does alone.

The machine is fitted on the driver, on at most MAX_ROWS labelled documents (those of the smallest hashes of doc_id, so
the choice does not depend on partitions). Its terms are found in two steps:

1. Terms that tell alone: their shares in the two classes are TELLING standard errors apart or more. An additive
   model (no factors) is fitted to them.
2. Terms that tell in pairs: of PAIR_TERMS terms - the most telling ones, and those nearest to half of the documents,
   where a pair can be seen best - all pairs are compared with what the additive model leaves unexplained. Pairs whose
   product goes with that residual beyond what the largest of so many random pairs would join with both their terms,
   whether or not the terms tell alone.

The machine with factors is then fitted to all of them. Without this choice, on all terms that three documents have, a
few hundred labels do not suffice: recall over five folds of sf0.01 falls from 44 to 19 of 51.

The chosen ids are at most MAX_ROWS numbers, so they are broadcast and no text is shuffled. Scoring reads every whole
text once. Learning leaves out the documents with crc32(doc_id as text) mod 5 = 0. Inputs of a score are the words alone.

Defined results: a null or empty text has no terms and gets the score of the bias; without labels, or with labels of
one class only, all scores are that class's share (0 without labels); repeated rows are scored one by one; an empty
table gives no rows; rows without a doc_id are scored and are held out.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

MAX_ROWS = 8_000
STEMS = range(4, 8)
#: Occurrences from which on a stem counts as one term more.
LEVELS = (2, 3)
MAX_TERMS = 4096
#: Standard errors from which on a term tells alone, and terms whose pairs are looked at.
TELLING = 4.0
PAIR_TERMS = 1024
#: Terms whose columns are that close are one, and their product says nothing new.
ALIKE = 0.9
FACTORS = 8
#: Passes over the rows: EPOCHS, and more where that makes fewer than LEAST_STEPS batches.
EPOCHS = 12
LEAST_STEPS = 600
BATCH = 256
RATE = 0.5
LASSO = 1e-5
RIDGE = 1e-4
#: Words kept in a worker's table; it is emptied when full, which costs time only.
WORD_CACHE = 500_000

_WORD = re.compile(r"\w+")


def units(word: str) -> list[int]:
    """Hashed word and stems, 31 bits each; a stem of the whole word is a unit of its own."""
    return [zlib.crc32(word.encode()) >> 1, *(zlib.crc32(f"{word[:k]}-".encode()) >> 1 for k in STEMS if len(word) >= k)]


def repeated(unit: int, level: int) -> int:
    """The term for a stem that occurs ``level`` times or more."""
    return (unit ^ (level * 0x5BD1E995)) & 0x7FFFFFFF


def terms_of(text: str | None) -> np.ndarray:
    """Distinct hashed terms of a text, ascending."""
    seen: dict[int, int] = {}
    out: set[int] = set()
    for w, n in Counter(_WORD.findall((text or "").lower())).items():
        word, *stems = units(w)
        out.add(word)
        for u in stems:
            seen[u] = seen.get(u, 0) + n
    out.update(seen)
    for level in LEVELS:
        out.update(repeated(u, level) for u, n in seen.items() if n >= level)
    return np.array(sorted(out), dtype=np.int32)


@dataclass(frozen=True)
class Machine:
    """terms[i]: the hashed term of row i of the weights and factors."""

    terms: np.ndarray
    bias: float
    weight: np.ndarray
    factor: np.ndarray

    def scores(self, rows: list[list[int]]) -> np.ndarray:
        """rows: per document the positions of its known terms."""
        sizes = np.array([len(r) for r in rows], dtype=np.int64)
        flat = np.array(common.flat(rows), dtype=np.int64)
        owner = np.repeat(np.arange(len(rows)), sizes)
        return _logistic(_raw(self.bias, self.weight, self.factor, flat, owner, len(rows))[0])


def _logistic(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def _raw(bias, weight, factor, flat, owner, n):
    """Sum of weights and of all pairs' factor products, by the square of the sum less the sum of squares."""
    out = bias + np.bincount(owner, weights=weight[flat], minlength=n)
    if not factor.shape[1]:
        return out, None
    sums = np.stack([np.bincount(owner, weights=factor[flat, k], minlength=n) for k in range(factor.shape[1])], axis=1)
    squares = np.bincount(owner, weights=(factor[flat] ** 2).sum(axis=1), minlength=n)
    return out + 0.5 * ((sums**2).sum(axis=1) - squares), sums


def _telling(rows: list[np.ndarray], label: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Terms of three documents or more whose shares in the two classes are TELLING standard errors apart, and the
    candidates for pairs; both ascending."""
    seen, all_ = np.unique(np.concatenate(rows), return_counts=True)
    ones, count = np.unique(np.concatenate([r for r, y in zip(rows, label, strict=True) if y]), return_counts=True)
    one = np.zeros(len(seen))
    one[np.searchsorted(seen, ones)] = count
    n1, n = label.sum(), len(label)
    often = all_ >= 3
    seen, all_, one = seen[often], all_[often], one[often]
    share = all_ / n
    gap = one / n1 - (all_ - one) / (n - n1)
    z = np.abs(gap) / np.sqrt(share * (1 - share) * (1 / n1 + 1 / (n - n1)) + 1e-9)
    order = np.argsort(-z, kind="stable")[:most]
    alone = order[z[order] > TELLING]
    common_ = np.argsort(np.abs(share - 0.5), kind="stable")
    pick = np.concatenate([alone[: PAIR_TERMS // 2], common_[~np.isin(common_, alone)]])[:PAIR_TERMS]
    return np.sort(seen[alone]), np.sort(seen[pick])


def _in_pairs(rows: list[np.ndarray], residual: np.ndarray, terms: np.ndarray) -> np.ndarray:
    """Those of the terms that have a partner whose product with them goes with the residual."""
    m = len(terms)
    if m < 2:
        return terms[:0]
    found = [np.searchsorted(terms, r[np.isin(r, terms)]) for r in rows]
    share = np.bincount(np.concatenate(found), minlength=m).astype(np.float32) / len(rows)
    product, spread, same = (np.zeros((m, m), dtype=np.float32) for _ in range(3))
    for a in range(0, len(rows), 2048):
        x = np.zeros((len(found[a : a + 2048]), m), dtype=np.float32)
        for k, f in enumerate(found[a : a + 2048]):
            x[k, f] = 1
        x -= share
        r = residual[a : a + 2048, None].astype(np.float32)
        product += x.T @ (r * x)
        spread += (x * x).T @ (r * r * x * x)
        same += x.T @ x
    size = np.sqrt(np.diag(same)) + 1e-9
    z = np.abs(product) / np.sqrt(spread + 1e-9)
    z[np.abs(same) > ALIKE * size[:, None] * size[None, :]] = 0
    # 1 more than the largest of so many random pairs
    return terms[(z > np.sqrt(2 * np.log(m * (m - 1) / 2 + 2)) + 1).any(axis=1)]


def _places(rows: list[np.ndarray], terms: np.ndarray) -> list[np.ndarray]:
    return [np.searchsorted(terms, r[np.isin(r, terms)]) for r in rows]


def _descend(rows: list[np.ndarray], label: np.ndarray, m: int, factors: int, seed: int) -> tuple[float, np.ndarray, np.ndarray]:
    """Adaptive stochastic gradient on the logistic loss, with a lasso on the weights and a ridge on the factors."""
    random = np.random.default_rng(seed)
    weight, factor = np.zeros(m), random.normal(0, 0.05, (m, factors))
    gw, gf, gb = np.full(m, 1e-3), np.full((m, factors), 1e-3), 1e-3
    bias = float(np.log(label.mean() / (1 - label.mean())))
    for _ in range(max(EPOCHS, -(-LEAST_STEPS * BATCH // len(rows)))):
        order = random.permutation(len(rows))
        for a in range(0, len(order), BATCH):
            pick = order[a : a + BATCH]
            sizes = np.array([len(rows[k]) for k in pick], dtype=np.int64)
            flat = np.concatenate([rows[k] for k in pick])
            owner = np.repeat(np.arange(len(pick)), sizes)
            raw, sums = _raw(bias, weight, factor, flat, owner, len(pick))
            error = (_logistic(raw) - label[pick]) / len(pick)
            used, back = np.unique(flat, return_inverse=True)
            by_row = error[owner]
            dw = np.bincount(back, weights=by_row, minlength=len(used))
            gw[used] += dw**2
            gb += float(error.sum()) ** 2
            step = RATE / np.sqrt(gw[used])
            moved = weight[used] - step * dw
            if factors:
                df = np.stack(
                    [np.bincount(back, weights=by_row * (sums[owner, k] - factor[flat, k]), minlength=len(used)) for k in range(factors)],
                    axis=1,
                )
                df += RIDGE * factor[used]
                gf[used] += df**2
                factor[used] -= 0.3 * RATE / np.sqrt(gf[used]) * df
            weight[used] = np.sign(moved) * np.maximum(0, np.abs(moved) - step * LASSO)
            bias -= RATE / np.sqrt(gb) * float(error.sum())
    return bias, weight, factor


def fit(rows: list[np.ndarray], label: np.ndarray, seed: int = 7, factors: int = FACTORS) -> Machine:
    """The machine of the labelled rows of terms; without factors, the best additive model.

    Documents with the same terms and label count once, so that many copies of one text do not make its words tell.
    """
    none = np.zeros(0, dtype=np.int64)
    kept = list({(r.tobytes(), int(y)): k for k, (r, y) in enumerate(zip(rows, label, strict=True)) if len(r)}.values())
    rows, label = [rows[k] for k in kept], np.asarray(label, dtype=float)[kept]
    if not len(label) or label.min() == label.max():
        share = float(label.mean()) if len(label) else 0.0
        return Machine(none, 30.0 if share else -30.0, none.astype(float), np.zeros((0, factors)))
    terms, candidates = _telling(rows, label, MAX_TERMS)
    even = float(np.log(label.mean() / (1 - label.mean())))
    if factors:
        at = _places(rows, terms)
        told = Machine(terms, *_descend(at, label, len(terms), 0, seed)) if len(terms) else Machine(terms, even, terms.astype(float), np.zeros((0, 0)))
        pairs = _in_pairs(rows, label - told.scores([r.tolist() for r in at]), candidates)
        terms = np.union1d(terms, pairs)
    if not len(terms):
        return Machine(none, even, none.astype(float), np.zeros((0, factors)))
    bias, weight, factor = _descend(_places(rows, terms), label, len(terms), factors, seed)
    live = np.flatnonzero((weight != 0) | (np.abs(factor).max(axis=1, initial=0.0) > 1e-4))
    return Machine(terms[live], bias, weight[live], factor[live])


def held_out():
    """Whether labels of this document are kept from learning; also true of rows without a doc_id."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(True))


def train(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS) -> Machine:
    chosen = (
        labels.filter(F.col("toxic").isNotNull() & ~held_out())
        .groupBy("doc_id")
        .agg(F.max("toxic").alias("toxic"))
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(max_rows)
    )
    texts = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("text", "toxic")

    def run(batches):
        for b in batches:
            made = pa.array([terms_of(t).tolist() for t in b.column(0).to_pylist()], type=pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([made, b.column(1)], names=["terms", "toxic"])

    got = common.map_arrow(texts, run, "terms array<int>, toxic int").toArrow()
    rows = [x for c in got.column("terms").chunks for x in np.split(c.flatten().to_numpy(), np.cumsum(pc.list_value_length(c))[:-1])] if got.num_rows else []
    machine = fit(rows, np.array(got.column("toxic").to_pylist(), dtype=float))
    del got, rows
    common.give_back()
    return machine


def score(docs: DataFrame, machine: Machine, text: str = "text") -> DataFrame:
    """docs with ``score`` (double, 0 to 1) appended. The model's size is bounded by MAX_TERMS and
    PAIR_TERMS."""
    held = docs.sparkSession.sparkContext.broadcast(machine)

    def kernel():
        model = held.value
        place = {int(t): k for k, t in enumerate(model.terms)}
        known: dict[str, tuple] = {}

        def look(word: str) -> tuple:
            """Place of the word itself, and its stems of which some term is in the model."""
            own, *stems = units(word)
            live = [u for u in stems if u in place or any(repeated(u, v) in place for v in LEVELS)]
            return (place[own], live) if own in place else (-1, live) if live else ()

        def positions(text: str | None) -> list[int]:
            if len(known) > WORD_CACHE:
                known.clear()
            found: set[int] = set()
            seen: dict[int, int] = {}
            for w in _WORD.findall((text or "").lower()):
                got = known.get(w)
                if got is None:
                    got = known[w] = look(w)
                if got:
                    found.add(got[0])
                    for u in got[1]:
                        seen[u] = seen.get(u, 0) + 1
            for u, n in seen.items():
                found.update(place.get(x, -1) for x in (u, *(repeated(u, v) for v in LEVELS if n >= v)))
            found.discard(-1)
            return sorted(found)

        def f(texts: list[str | None]) -> list[pa.Array]:
            return [pa.array(model.scores([positions(t) for t in texts]), type=pa.float64())]

        return f

    return common.map_texts(docs, text, "score double", kernel)


def toxicity_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """docs (doc_id, text) and labels (doc_id, toxic) -> doc_id, held_out, score, predicted; one row per row of docs."""
    own = docs.select("doc_id", "text")
    made = score(own, train(own, labels))
    return made.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame, cutoff: float = 0.5) -> DataFrame:
    """The rows of docs, all columns, that score below the cutoff."""
    machine = train(docs, labels)
    names = docs.columns
    made = score(docs.select(*[F.col(c).alias(f"in_{c}") for c in names]), machine, "in_text")
    return made.filter(F.col("score") < cutoff).select(*[F.col(f"in_{c}").alias(c) for c in names])
