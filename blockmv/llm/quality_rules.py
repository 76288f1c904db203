"""Quality rules whose cutoffs are certified on labelled documents (risk-controlled thresholds).

Each text gets counts (``feature_columns``). A rule rejects a text when a ratio of those counts passes a cutoff; a text
that any rule rejects goes. The labelled documents that pass the base rule are split by a hash of doc_id:

* A third designs, for each stratum, a path of verdicts from lenient to strict: at each step every rule has the cutoff
  that catches most bad documents among those that lose at most the step's share of the good ones, or none.
* The rest is the holdout. Along the path the exact binomial test rejects, step by step, "the verdict loses more than
  ``risk`` of the good documents of this stratum"; the first step that fails ends it. The whole verdict is tested, so
  rules share no budget among them. Of the steps that hold, the verdict is the first one that catches ENOUGH of the bad
  documents of the design third that the last one catches: what catches little more loses no further good documents.

Multiple testing: each stratum starts with ``delta`` over the number of strata (Bonferroni), fixed sequences need no more,
and a stratum whose path is certified to its end leaves its level to the others. Strata whose holdout is so small that
not even a verdict without a loss could be certified are pooled to one, for which the guarantee holds as a whole; the
least size is ``least_good``: 217 good documents for four strata at the risk of 2 %. A pool that small gets no rule: its
documents stay, as do those of strata without labels.

Defined results: a null or empty text has no words and fails the base rule; a null stratum is a stratum of its own;
repeated rows are judged one by one; an empty table gives an empty result; without labels only the base rule acts; a
document that several labels name is good if all of them say so.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\x0b\x0c\r"
WINDOW = 5
MIN_WORDS = 10
MAX_REPEAT_PERCENT = 20
FEATURES = (
    "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_lines long, n_bangs long, n_upper_words long"
)
RISK = 0.02
DELTA = 0.05
#: Steps of a path: shares of the risk that the good documents of the design third may lose to a single rule.
STEPS = (0.0, 0.1, 0.2, 0.3, 0.4, 0.5, 0.75, 1.0)
ENOUGH = 0.98

#: Odd multipliers of the five places of a window.
_PLACES = np.array(
    [0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], dtype=np.uint64
)


def _mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(31))
    x *= np.uint64(0x7FB5D329728EA185)
    return x ^ (x >> np.uint64(29))


def _repeated(hashes: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Per text, the words inside some WINDOW-word window that occurs at least twice in it."""
    n = len(hashes)
    owner = np.repeat(np.arange(len(lengths)), lengths)
    out = np.zeros(len(lengths), dtype=np.int64)
    if n < WINDOW:
        return out
    m = n - WINDOW + 1
    key = np.zeros(m, dtype=np.uint64)
    mixed = _mix(hashes)
    for k in range(WINDOW):
        key += mixed[k : k + m] * _PLACES[k]
    key = _mix(key)
    whole = owner[:m] == owner[WINDOW - 1 :]
    starts = np.flatnonzero(whole)
    # the text's number is mixed in, so equal keys mean equal windows of one text
    key = key[starts] ^ _mix(owner[starts].astype(np.uint64) + np.uint64(1))
    order = np.argsort(key, kind="stable")
    ordered = key[order]
    same = ordered[1:] == ordered[:-1]
    twice = np.zeros(len(key), dtype=bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    edge = np.zeros(n + 1, dtype=np.int64)
    found = starts[twice]
    edge[found] += 1
    edge[found + WINDOW] -= 1  # starts are distinct, so plain fancy indexing counts each once
    covered = np.cumsum(edge[:-1]) > 0
    np.add.at(out, owner[covered], 1) if covered.any() else None
    return out


def count_features(texts: list[str | None]) -> list[pa.Array]:
    words, lengths, rows = [], [], []
    for t in texts:
        t = t or ""
        w = t.encode().split()  # splits at the six ASCII white-space bytes and nothing else
        words += w
        lengths.append(len(w))
        seen: set[str] = set()
        lines = dup = 0
        for line in t.split("\n"):
            if line.strip(SPACES):
                lines += 1
                if line in seen:
                    dup += 1
                else:
                    seen.add(line)
        chars = len(t) - sum(map(t.count, SPACES))
        rows.append((len(w), chars, sum(map(t.count, SYMBOLS)), dup, lines, t.count("!"), sum(map(bytes.isupper, w))))
    hashes = np.fromiter(map(hash, words), dtype=np.int64, count=len(words)).view(np.uint64)
    again = _repeated(hashes, np.array(lengths, dtype=np.int64))
    cols = list(zip(*rows, strict=True)) if rows else [()] * 7
    made = [*cols[:4], again.tolist(), *cols[4:]]
    return [pa.array(c, type=pa.int64()) for c in made]


def feature_columns(df: DataFrame, text: str = "text") -> DataFrame:
    """df with the columns of FEATURES appended; every whole text is read once."""
    return common.map_texts(df, text, FEATURES, lambda: count_features)


def base_failed() -> Column:
    return (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))


@dataclass(frozen=True)
class Rule:
    """Rejects when sign * value > sign * cutoff; cutoffs run from lenient to strict."""

    name: str
    value: str
    cutoffs: tuple[float, ...]
    sign: int = 1


def _steps(a: float, b: float, n: int) -> tuple[float, ...]:
    return tuple(round(a + (b - a) * k / (n - 1), 6) for k in range(n))


RULES = (
    Rule("symbols", "n_symbols / greatest(n_words, 1)", _steps(1.0, 0.02, 50)),
    Rule("dup_lines", "n_dup_lines / greatest(n_lines, 1)", _steps(0.9, 0.02, 45)),
    Rule("repeats", "n_repeat_words / greatest(n_words, 1)", _steps(0.2, 0.02, 19)),
    Rule("long_words", "word_chars / greatest(n_words, 1)", _steps(40.0, 8.0, 65)),
    Rule("short_words", "word_chars / greatest(n_words, 1)", _steps(1.0, 4.0, 31), -1),
    Rule("bangs", "n_bangs / greatest(n_words, 1)", _steps(1.0, 0.02, 50)),
    Rule("upper_words", "n_upper_words / greatest(n_words, 1)", _steps(1.0, 0.1, 46)),
)


def binomial_cdf(k: int, n: int, p: float) -> float:
    """P(X <= k) for X of Binomial(n, p), summed in logarithms."""
    if k >= n:
        return 1.0
    a, b = math.log(p), math.log1p(-p)
    logs = [math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * a + (n - i) * b for i in range(k + 1)]
    top = max(logs)
    return min(1.0, math.exp(top) * sum(math.exp(x - top) for x in logs))


def upper_bound(lost: int, n: int, level: float) -> float:
    """The exact upper confidence bound of the loss rate: the rate at which so few losses have the chance ``level``."""
    low, high = lost / n if n else 0.0, 1.0
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if mid < 1 and binomial_cdf(lost, n, mid) > level else (low, mid)
    return high


def least_good(risk: float, level: float) -> int:
    """Good documents that a holdout needs for any certificate: with no loss at all."""
    return math.ceil(math.log(level) / math.log1p(-risk))


@dataclass(frozen=True)
class Verdict:
    """What is certified for some strata: a cutoff per rule (None: not used), and the holdout's figures."""

    strata: tuple
    cutoffs: tuple[float | None, ...]
    good: int
    lost: int
    bound: float


def _exceeded(rule: Rule, limits: list[float], holds: bool) -> Column:
    """How many of the limits (already times the rule's sign) the value exceeds, or does not. The limits are one literal,
    so the plan stays small."""
    value = F.expr(rule.value) * rule.sign
    return F.size(F.filter(F.array(*[F.lit(float(x)) for x in limits]), lambda x: value > x if holds else value <= x))


def _strictness(rules: tuple[Rule, ...]) -> Column:
    """Per rule, the number of its cutoffs that reject the document."""
    return F.array(*[_exceeded(r, [c * r.sign for c in r.cutoffs], True) for r in rules])


def _first_step(steps: list[tuple[float | None, ...]], rules: tuple[Rule, ...]) -> Column:
    """The first step that rejects the document, or their number. Steps are nested, rule by rule."""
    limits = [[math.inf if x[k] is None else x[k] * r.sign for x in steps] for k, r in enumerate(rules)]
    return F.least(*[_exceeded(r, n, False) for r, n in zip(rules, limits, strict=True)], F.lit(len(steps)))


def design_path(hits: dict[tuple[int, int], tuple[int, int]], rules: tuple[Rule, ...], risk: float) -> list[tuple[float | None, ...]]:
    """hits: (rule, number of its cutoffs that reject) -> good and bad documents. A cutoff per rule for each of STEPS."""
    path = []
    good = sum(g for (k, _), (g, _) in hits.items() if k == 0)
    for share in STEPS:
        step: list[float | None] = []
        for k, r in enumerate(rules):
            best, most = None, 0
            for i, c in enumerate(r.cutoffs):
                # cutoffs are nested: the i-th rejects those that at least len - i cutoffs reject
                g, b = (sum(n[w] for (q, h), n in hits.items() if q == k and h >= len(r.cutoffs) - i) for w in (0, 1))
                if g > share * risk * good:
                    break
                if b > most:
                    best, most = c, b
            step.append(best)
        path.append(tuple(step))
    return path


def certify(paths: dict[tuple, list], losses: dict[tuple, list[int]], caught: dict[tuple, list[int]], risk: float, delta: float) -> list[Verdict]:
    """paths: group of strata -> its steps; losses: group -> good holdout documents by the first step that rejects them,
    the last entry for none; caught: the same of bad design documents. -> the verdict of each group that has one."""
    level = {s: delta / len(paths) for s in paths}
    at, used = dict.fromkeys(paths, 0), dict(level)
    total = {s: sum(losses[s]) for s in paths}
    moved = True
    while moved:
        moved = False
        for s, steps in paths.items():
            while at[s] < len(steps) and total[s] and binomial_cdf(sum(losses[s][: at[s] + 1]), total[s], risk) <= level[s]:
                at[s] += 1
                used[s], moved = level[s], True
        done = [s for s in paths if at[s] == len(paths[s]) and level[s]]
        rest = [s for s in paths if at[s] < len(paths[s])]
        for s in done if rest else []:
            for q in rest:
                level[q] += level[s] / len(rest)
            level[s] = 0.0
    out = []
    for s in paths:
        if at[s] and any(c is not None for c in paths[s][at[s] - 1]):
            k = next(k for k in range(1, at[s] + 1) if sum(caught[s][:k]) >= ENOUGH * sum(caught[s][: at[s]]))
            lost = sum(losses[s][:k])
            out.append(Verdict(s, paths[s][k - 1], total[s], lost, upper_bound(lost, total[s], used[s])))
    return out


def calibrate(
    labelled: DataFrame, stratum: str, rules: tuple[Rule, ...] = RULES, risk: float = RISK, delta: float = DELTA
) -> list[Verdict]:
    """labelled (doc_id, stratum, FEATURES, quality), durable, documents that pass the base rule -> certified verdicts.

    Only histograms reach the driver: strata x rules x cutoffs rows, and strata x steps rows, whatever the number of labels.
    """
    rows = labelled.select(
        F.col(stratum).alias("stratum"), (F.pmod(F.xxhash64("doc_id", F.lit(41)), F.lit(3)) > 0).alias("held"), "quality", _strictness(rules).alias("strict"), "*"
    )
    sizes = {r["stratum"]: r["n"] for r in rows.filter("held and quality = 1").groupBy("stratum").agg(F.count("*").alias("n")).collect()}
    if not sizes:
        return []
    need = least_good(risk, delta / len(sizes))
    small = tuple(sorted((s for s, n in sizes.items() if n < need), key=str))
    groups = [(s,) for s in sorted(sizes, key=str) if s not in small] + ([small] if small else [])
    number = {s: k for k, g in enumerate(groups) for s in g}
    counts = rows.filter("not held").select("stratum", "quality", F.posexplode("strict").alias("rule", "hit")).groupBy("stratum", "quality", "rule", "hit").count()
    hits: list[dict] = [{} for _ in groups]
    for r in counts.collect():
        if r["stratum"] in number:
            h = hits[number[r["stratum"]]]
            g, b = h.get((r["rule"], r["hit"]), (0, 0))
            h[r["rule"], r["hit"]] = (g + r["count"], b) if r["quality"] else (g, b + r["count"])
    paths = {g: design_path(h, rules, risk) for g, h in zip(groups, hits, strict=True)}
    step = F.lit(None).cast("int")
    for g, steps in paths.items():
        step = F.when(_among(g, F.col("stratum")), _first_step(steps, rules)).otherwise(step)
    losses, caught = ({g: [0] * (len(STEPS) + 1) for g in groups} for _ in range(2))
    for r in rows.filter("held = (quality = 1)").groupBy("stratum", "held", step.alias("step")).count().collect():
        if r["stratum"] in number:
            (losses if r["held"] else caught)[groups[number[r["stratum"]]]][r["step"]] += r["count"]
    return certify(paths, losses, caught, risk, delta)


def _among(strata: tuple, column: Column) -> Column:
    out = F.lit(False)
    for s in strata:
        out = out | column.eqNullSafe(F.lit(s))
    return out


def _beyond(cutoffs: tuple[float | None, ...], rules: tuple[Rule, ...]) -> Column:
    out = F.lit(False)
    for r, c in zip(rules, cutoffs, strict=True):
        if c is not None:
            out = out | F.coalesce(F.expr(r.value) * r.sign > c * r.sign, F.lit(False))
    return out


def rejected(chosen: list[Verdict], stratum: str, rules: tuple[Rule, ...] = RULES) -> Column:
    """The method's rejection as one expression over the feature columns."""
    out = F.lit(False)
    for v in chosen:
        out = out | (_among(v.strata, F.col(stratum)) & _beyond(v.cutoffs, rules))
    return out


def certificates(spark: SparkSession, chosen: list[Verdict], rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """stratum, rule, cutoff, good, lost, bound: one row per stratum and rule in use."""
    rows = [(None if s is None else str(s), r.name, c, v.good, v.lost, v.bound) for v in chosen for s in v.strata for r, c in zip(rules, v.cutoffs, strict=True) if c is not None]
    return spark.createDataFrame(rows, "stratum string, rule string, cutoff double, good long, lost long, bound double")


def calibrated_on(features: DataFrame, labels: DataFrame, stratum: str, **how) -> list[Verdict]:
    """Certified verdicts from features (doc_id, stratum, FEATURES) and labels (doc_id, quality)."""
    told = labels.filter("quality is not null").groupBy(F.col("doc_id").alias("_told")).agg((F.min("quality") == 1).cast("int").alias("quality"))
    names = [x.split()[0] for x in FEATURES.split(", ")]
    mine = features.filter(~base_failed()).select("doc_id", F.col(stratum).alias("_stratum"), *names)
    labelled = common.materialise(mine.join(told, mine["doc_id"] == told["_told"]).drop("_told"), "labelled")
    chosen = calibrate(labelled, "_stratum", **how)
    common.discard(labelled)
    return chosen


def quality_verdicts(docs: DataFrame, labels: DataFrame, stratum: str = "lang", **how) -> DataFrame:
    """docs (doc_id, text, stratum) -> doc_id, the counts, base_failed, kept; one row per row of docs."""
    made = feature_columns(docs.select("doc_id", F.col(stratum).alias("_stratum"), "text")).drop("text")
    held = common.materialise(made, "quality-features")
    chosen = calibrated_on(held, labels, "_stratum", **how)
    return held.select(
        "doc_id",
        "n_words",
        "word_chars",
        "n_symbols",
        "n_dup_lines",
        "n_repeat_words",
        base_failed().alias("base_failed"),
        (~base_failed() & ~rejected(chosen, "_stratum")).alias("kept"),
    )


def keep_documents(docs: DataFrame, labels: DataFrame, stratum: str = "lang", **how) -> DataFrame:
    """The rows of docs, all columns, that pass the base rule and the certified cutoffs."""
    names = docs.columns
    with_features = feature_columns(docs.select(*[F.col(c).alias(f"in_{c}") for c in names]), "in_text")
    features = with_features.drop("in_text").withColumnRenamed("in_doc_id", "doc_id")
    chosen = calibrated_on(features, labels, f"in_{stratum}", **how)
    kept = with_features.filter(~base_failed() & ~rejected(chosen, f"in_{stratum}"))
    return kept.select(*[F.col(f"in_{c}").alias(c) for c in names])
