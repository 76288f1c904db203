"""SimHash near-duplicates: exact search within a Hamming radius with pivot distance tables.

A fingerprint has a bit where over half the shingle hashes have it. Documents with equal fingerprints form a class.
Classes are compared as follows, without loss:

* The 64 bits are cut into ``radius + equal`` blocks. Two fingerprints at most ``radius`` apart agree on ``equal``
  blocks at least, so they meet in one of the buckets keyed by a choice of blocks. ``equal`` is a parameter and does not
  depend on the data: a row is written as many times for ten documents as for ten billion. Buckets of random
  fingerprints hold rows / 2**(64 * equal / (radius + equal)) rows; take one block more where that gets large.
* In a bucket, each fingerprint has a row of distances to PIVOTS fixed reference fingerprints (the pivot table). Rows
  are sorted by the first distance and swept: candidates are the pairs whose first distances differ by the radius at
  most, and by the triangle inequality those with a difference over the radius in any other coordinate are discarded.
  Survivors are verified by their Hamming distance.
* Buckets over BLOCK rows are cut into blocks, and each pair of blocks is a group of its own. Large buckets are found by
  counting the buckets of a sample; it decides how the work is dealt, never what is compared.
* Pairs of one component are not looked at again; of each group only a link per row to the smallest node of its
  component leaves the task. Components of the whole come from star contractions.

Defined results: a null or empty text, or one without words, has the fingerprint zero, which links like any other;
fewer words than a shingle make one shingle; repeated rows are members of one class; an empty table gives no rows; a
null doc_id is linked like any other, and never is the smallest of a class unless alone.
"""

from __future__ import annotations

from functools import reduce
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .components import connected_components

SEED = 42
RADIUS = 4
#: Agreeing blocks of a bucket: 35 buckets a fingerprint at the radius of 4, of 27 equal bits each.
EQUAL = 3
#: Removal searches by several fingerprints of a text, with hashes mixed anew, each in 28 buckets of 16 equal bits.
REMOVAL_SEEDS, REMOVAL_RADIUS, REMOVAL_EQUAL = 4, 6, 2
#: Rows of a bucket that are compared in one task; larger buckets are cut into pairs of blocks.
BLOCK = 2048
#: One of so many nodes is counted to find the buckets over BLOCK rows, and most of these that are broadcast.
COUNTED_SHARE, MAX_BROADCAST = 16, 200_000
PIVOTS = 24
#: Reference fingerprints: the first outputs of a 64-bit mixing of 1, 2, 3, ...
_REFERENCES = np.array([xxhash.xxh64_intdigest(str(k), 7) for k in range(1, PIVOTS + 1)], dtype=np.uint64)
#: Bits of the parity sketch of a shingle set, and partners that a document is given in the first verifying round.
SKETCH_BITS = 512
PARTNERS = 8
#: Rows behind it that every row of a bucket is compared with before the largest component is set aside.
NEXT = 64


def shingle_hashes(text: str | None, words: int) -> np.ndarray:
    parts = (text or "").encode().lower().split()
    if not parts:
        return np.zeros(0, dtype=np.uint64)
    line = b" ".join(parts)
    h = xxhash.xxh64_intdigest
    if len(parts) < words:
        return np.array([h(line, SEED)], dtype=np.uint64)
    sizes = np.fromiter(map(len, parts), dtype=np.int64, count=len(parts))
    ends = np.cumsum(sizes + 1) - 1
    begins = (ends - sizes)[: len(parts) - words + 1].tolist()
    return np.array([h(line[a:b], SEED) for a, b in zip(begins, ends[words - 1 :].tolist(), strict=True)], dtype=np.uint64)


def _mixed(hashes: np.ndarray, seed: int) -> np.ndarray:
    """The hashes themselves for seed 0, other hashes of the same shingles for other seeds."""
    if not seed:
        return hashes
    x = hashes ^ np.uint64(xxhash.xxh64_intdigest(str(seed), 9))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(31)
    x *= np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(29))


def fingerprints(texts: list[str | None], words: int, seed: int = 0) -> np.ndarray:
    """Unsigned 64-bit fingerprints, one per text."""
    return _folded([shingle_hashes(t, words) for t in texts], seed)


def _folded(hashes: list[np.ndarray], seed: int) -> np.ndarray:
    counts = np.array([len(h) for h in hashes], dtype=np.int64)
    out = np.zeros(len(hashes), dtype=np.uint64)
    full = np.flatnonzero(counts)
    if len(full):
        flat = _mixed(np.concatenate(hashes), seed)
        bits = np.unpackbits(flat.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        starts = np.concatenate([[0], np.cumsum(counts[full])[:-1]])
        ones = np.add.reduceat(bits, starts, axis=0, dtype=np.int32)
        over = (2 * ones > counts[full][:, None]).astype(np.uint8)
        out[full] = np.packbits(over, axis=1, bitorder="little").view("<u8").ravel()
    return out


def with_fingerprints(docs: DataFrame, words: int = 4, text: str = "text", name: str = "fp") -> DataFrame:
    """docs with a column appended, ``fp`` unless named otherwise: the fingerprint's 64 bits as a (signed) long."""
    return common.map_texts(
        docs, text, f"{name} long", lambda: lambda texts: [pa.array(fingerprints(texts, words).view(np.int64))]
    )


# ---- links between fingerprints ----------------------------------------------------------------------------------


def block_masks(radius: int, equal: int) -> list[int]:
    """One mask per choice of ``equal`` among radius + equal blocks of the 64 bits."""
    n = radius + equal
    edges = [64 * k // n for k in range(n + 1)]
    blocks = [(1 << b) - (1 << a) for a, b in zip(edges, edges[1:], strict=False)]
    return [sum(c) for c in combinations(blocks, equal)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _settle(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> None:
    """Bring the components of i and j together; labels point at the smallest index of their component."""
    while True:
        a, b = label[i], label[j]
        low, high = np.minimum(a, b), np.maximum(a, b)
        open_ = low != high
        if not open_.any():
            return
        i, j, low, high = i[open_], j[open_], low[open_], high[open_]
        np.minimum.at(label, high, low)
        while True:
            up = label[label]
            if (up == label).all():
                break
            label[:] = up


def pivot_table(fp: np.ndarray) -> np.ndarray:
    """Distances of each fingerprint to the reference fingerprints, one row per fingerprint."""
    return np.bitwise_count(fp[:, None] ^ _REFERENCES[None, :]).astype(np.int8)


def undiscarded(table: np.ndarray, i: np.ndarray, j: np.ndarray, radius: int, first: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """The pairs (i, j) whose distances to every reference from ``first`` on differ by the radius at most."""
    for p in range(first, table.shape[1]):
        near = np.abs(table[i, p] - table[j, p]) <= radius
        i, j = i[near], j[near]
    return i, j


def sweep_order(fp: np.ndarray, group: np.ndarray) -> np.ndarray:
    """Order by group, then by the distance to the first reference."""
    return np.lexsort([np.bitwise_count(fp ^ _REFERENCES[0]), group])


def swept(fp: np.ndarray, group: np.ndarray, radius: int, wanted, starts: np.ndarray | None = None, first: int = 1, last: int | None = None, back: bool = False):
    """Pairs (i, j) of one group at most ``radius`` bits apart, i among ``starts``, j ``first`` to ``last`` places behind
    it, or before it with ``back``. Rows are in sweep order.

    A row is compared with the next ones until their first distances differ by more than the radius. ``wanted`` is
    asked with (i, j), or with (i, None) for the rows that are still open, and says which to go on with.
    """
    n, sign = len(fp), -1 if back else 1
    table = pivot_table(fp)
    i, step = np.arange(n) if starts is None else starts, first
    while last is None or step <= last:
        j = i + sign * step
        i = i[(j >= 0) & (j < n)]
        j = i + sign * step
        i = i[(group[i] == group[j]) & (np.abs(table[i, 0] - table[j, 0]) <= radius)]
        if step & (step - 1) == 0 and len(i):
            i = i[wanted(i, None)]
        if not len(i):
            return
        j = i + sign * step
        ask = wanted(i, j)
        x, y = undiscarded(table, i[ask], j[ask], radius, 1)
        near = np.bitwise_count(fp[x] ^ fp[y]) <= radius
        if near.any():
            yield x[near], y[near]
        step += 1


def _numbers(group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where each group begins, and the number of each row's group."""
    begin = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    return begin, np.repeat(np.arange(len(begin)), np.diff(np.append(begin, len(group))))


def outsiders(number: np.ndarray, begin: np.ndarray, label: np.ndarray) -> np.ndarray:
    """Rows that are not of the most frequent label of their group; of two as frequent, the smaller one counts."""
    order = np.lexsort([label, number])
    new = np.concatenate([[True], (number[order][1:] != number[order][:-1]) | (label[order][1:] != label[order][:-1])])
    run = np.cumsum(new) - 1
    size = np.empty(len(label), dtype=np.int64)
    size[order] = np.bincount(run)[run]
    most = np.maximum.reduceat(size, begin)[number]
    chosen = np.minimum.reduceat(np.where(size == most, label, np.iinfo(np.int64).max), begin)
    return np.flatnonzero(label != chosen[number])


def link_labels(fp: np.ndarray, group: np.ndarray, radius: int) -> np.ndarray:
    """Smallest index of each row's component under all links of at most ``radius`` bits inside its group.

    Rows are in sweep order. First each row meets the NEXT ones behind it, which joins most of what belongs together.
    Rows of the largest component of a group need not meet each other any more, so then the others alone meet the rest:
    a group of near copies with a few strangers takes the strangers' pairs, not all.
    """
    n = len(fp)
    label = np.arange(n)
    if not n:
        return label
    begin, number = _numbers(group)

    def wanted(i, j):
        if j is not None:
            return label[i] != label[j]
        open_ = ~np.logical_and.reduceat(label == begin[number], begin)
        return open_[number[i]]

    for i, j in swept(fp, group, radius, wanted, last=NEXT):
        _settle(label, i, j)
    left = outsiders(number, begin, label)
    for back in (False, True):
        for i, j in swept(fp, group, radius, wanted, left, NEXT + 1, back=back):
            _settle(label, i, j)
    return label


def _whole_groups(batches, names: tuple[str, ...]):
    """Batches sorted by their first column -> tables that hold whole runs of it."""
    held = None
    for b in batches:
        now = pa.Table.from_batches([pa.RecordBatch.from_arrays(b.columns, names=names)])
        held = pa.concat_tables([held, now]).combine_chunks() if held is not None and held.num_rows else now
        if not held.num_rows:
            continue
        g = held.column(names[0]).to_numpy()
        cut = int(np.searchsorted(g, g[-1]))  # the last group may go on in the next batch
        if cut:
            yield held.slice(0, cut)
            held = held.slice(cut)
    if held is not None and held.num_rows:
        yield held


def _joined(batches, radius: int):
    """From batches (g, fp, node) sorted by g inside the task: g, fp, node, low of the rows that have a link in their group.

    low is the smallest node that links inside the group reach, the row's own included.
    """
    for t in _whole_groups(batches, ("g", "fp", "node")):
        g, fp, node = (c.to_numpy() for c in t.columns)
        order = sweep_order(fp.view(np.uint64), g)
        g, fp, node = g[order], fp[order], node[order]
        label = link_labels(fp.view(np.uint64), g, radius)
        low = node.copy()
        np.minimum.at(low, label, node)
        k = np.flatnonzero(np.bincount(label, minlength=len(label))[label] > 1)
        yield g[k], fp[k], node[k], low[label[k]]


def _links(batches, radius: int):
    """Of the same batches: forest links (u, v) of every group, v the smallest node that links inside the group reach from u."""
    for _, _, node, low in _joined(batches, radius):
        child = np.flatnonzero(low != node)
        yield pa.RecordBatch.from_arrays([pa.array(node[child]), pa.array(low[child])], names=["u", "v"])


def _grouped(classes: DataFrame, radius: int, equal: int, block: int) -> DataFrame:
    """classes (fps, node, ...) -> g, fp, node, ...: one row per group that a row is compared in, sorted by g.

    fps: an array of fingerprints; the k-th ones of two rows are compared with each other.
    """
    others = [c for c in classes.columns if c not in ("fps", "node")]
    masks = F.array(*[F.lit(_signed(m)).cast("long") for m in block_masks(radius, equal)])
    buckets = F.flatten(
        F.transform(
            "fps",
            lambda fp, k: F.transform(masks, lambda m, at: F.struct(F.xxhash64(k, at, fp.bitwiseAND(m)).alias("bucket"), fp.alias("fp"))),
        )
    )
    spread = classes.select("node", *others, F.explode(buckets).alias("x")).select("x.bucket", "x.fp", "node", *others)
    # buckets that collide in their hash are compared with each other as well, which is harmless
    counted = spread.filter(F.pmod(F.xxhash64("node", F.lit(77)), F.lit(COUNTED_SHARE)) == 0).groupBy("bucket").count()
    blocks = F.ceil(F.col("count") * COUNTED_SHARE / block).cast("int")
    large = common.materialise(counted.select(F.col("bucket").alias("b"), blocks.alias("m")).filter("m > 1"), "large")
    known = F.broadcast(large) if large.count() <= MAX_BROADCAST else large
    met = spread.join(known, spread["bucket"] == known["b"], "left")
    own = F.pmod(F.xxhash64("fp", "node", F.lit(3)), F.col("m")).cast("int")
    # a pair of two blocks holds what each of them holds
    pair = lambda k: F.xxhash64("bucket", F.least("own", k), F.greatest("own", k))
    other = F.filter(F.sequence(F.lit(0), F.col("m") - 1), lambda k: k != F.col("own"))
    groups = F.when(F.col("m").isNull(), F.array("bucket")).otherwise(F.transform(other, pair))
    dealt = met.withColumn("own", own).select(F.explode(groups).alias("g"), "fp", "node", *others)
    return dealt.repartition("g").sortWithinPartitions("g")


def near_links(classes: DataFrame, radius: int = RADIUS, equal: int = EQUAL, block: int = BLOCK) -> DataFrame:
    """classes (fps, node), nodes distinct -> links (u, v) between nodes: their components are those of all pairs of
    k-th fingerprints at most ``radius`` bits apart. v is the smallest node of the component inside a bucket."""
    grouped = _grouped(classes.select("fps", "node"), radius, equal, block)
    return common.map_arrow(grouped, lambda batches: _links(batches, radius), "u long, v long")


def near_members(classes: DataFrame, radius: int, equal: int, block: int = BLOCK) -> DataFrame:
    """classes (fps, node), nodes distinct -> g, fp, node, low: the rows of every bucket that others in it lie within
    ``radius`` bits of, and the smallest node that links inside the bucket reach from them. Two nodes with such a pair of
    fingerprints share a g and a low at least once."""
    grouped = _grouped(classes.select("fps", "node"), radius, equal, block)

    def run(batches):
        for found in _joined(batches, radius):
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in found], names=["g", "fp", "node", "low"])

    return common.map_arrow(grouped, run, "g long, fp long, node long, low long")


def near_duplicates(fingerprinted: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(doc_id, fp), durable -> doc_id, fp, component_id: the smallest doc_id that links of at most ``radius`` bits reach."""
    classes = common.materialise(fingerprinted.groupBy("fp").agg(F.min("doc_id").alias("first")), "classes")
    member = connected_components(near_links(classes.select(F.array("fp").alias("fps"), F.col("fp").alias("node")), radius))
    rooted = classes.join(member, classes["fp"] == member["node"], "left").select(
        "fp", "first", F.coalesce("root", "fp").alias("root")
    )
    lowest = rooted.groupBy("root").agg(F.min("first").alias("component_id"))
    named = rooted.join(lowest, "root").select("fp", "component_id")
    return fingerprinted.join(named, "fp").select("doc_id", "fp", "component_id")


def document_components(docs: DataFrame, words: int = 4, radius: int = RADIUS) -> DataFrame:
    """docs (doc_id, text) -> doc_id, fp, component_id; one row per row of docs."""
    held = common.materialise(with_fingerprints(docs.select("doc_id", "text"), words).drop("text"), "fingerprints")
    return near_duplicates(held, radius)


# ---- removal, with the similarity of word shingles checked -----------------------------------------------------------


def _normal(text: str | None) -> bytes:
    return b" ".join((text or "").encode().lower().split())


def with_contents(docs: DataFrame, words: int, seeds: int) -> DataFrame:
    """docs (doc_id, text) -> doc_id, fps, content: fingerprints, and a hash of the lower-cased words that is equal for
    equal word sequences."""

    def f(texts: list) -> list[pa.Array]:
        content = [xxhash.xxh3_128_digest(_normal(t)) for t in texts]
        hashes = [shingle_hashes(t, words) for t in texts]
        fps = np.stack([_folded(hashes, k).view(np.int64) for k in range(seeds)], axis=1)
        return [pa.array(list(fps), type=pa.list_(pa.int64())), pa.array(content, type=pa.binary())]

    return common.map_texts(docs.select("doc_id", "text"), "text", "fps array<long>, content binary", lambda: f).drop("text")


def similarity(a: str | None, b: str | None, words: int) -> float:
    """Jaccard similarity of the sets of word shingles; 1 for two texts without words."""
    x, y = (set(shingle_hashes(t, words).tolist()) for t in (a, b))
    return len(x & y) / len(x | y) if x or y else 1.0


def similar_links(links: DataFrame, texts: DataFrame, words: int, least: float) -> DataFrame:
    """Links (u, v) whose texts (node, text) have at least the similarity. Only texts that some link names are moved."""
    u, v = (texts.select(F.col("node").alias(c), F.col("text").alias(f"{c}_text")) for c in "uv")
    met = links.join(u, "u").join(v, "v").select("u", "v", "u_text", "v_text")

    def run(batches):
        for b in (b.slice(x, y - x) for b in batches for x, y in common.text_runs(b.column(2))):
            near = [similarity(x, y, words) >= least for x, y in zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True)]
            k = pa.array(np.flatnonzero(np.array(near, dtype=bool)))
            yield pa.RecordBatch.from_arrays([b.column(0).take(k), b.column(1).take(k)], names=["u", "v"])

    return common.map_arrow(met, run, "u long, v long")


def with_sketches(texts: DataFrame, words: int) -> DataFrame:
    """texts (node, text) with ``size``, the number of distinct shingles, and ``sketch``: the parity of their count in
    each of SKETCH_BITS cells. A shingle that two sets do not share flips one bit at most, so sketches never differ in
    more bits than the sets differ in shingles."""

    def f(batch: list) -> list[pa.Array]:
        sizes, sketches = [], []
        for t in batch:
            own = np.unique(shingle_hashes(t, words))
            cells = np.bincount((own % np.uint64(SKETCH_BITS)).astype(np.int64), minlength=SKETCH_BITS)
            sizes.append(len(own))
            sketches.append(np.packbits((cells & 1).astype(np.uint8)).tobytes())
        return [pa.array(sizes, type=pa.int32()), pa.array(sketches, type=pa.binary())]

    return common.map_texts(texts, "text", "size int, sketch binary", lambda: f)


def not_ruled_out(size, sketch, i, j, least: float) -> np.ndarray:
    """Whether the sketches of the pairs leave room for the similarity."""
    room = (size[i] + size[j]) * (1 - least) + 1e-6
    return np.bitwise_count(sketch[i] ^ sketch[j]).sum(axis=1, dtype=np.int64) * (1 + least) <= room


def open_pairs(fp, group, root, size, sketch, radius: int, least: float, most: int):
    """Pairs (i, j) of one group that may be similar and have different roots: at most ``most`` for each i.

    Rows are in sweep order. -> i, j, and the rows i that have further pairs. Fingerprints are at most ``radius`` bits
    apart, and neither sizes nor sketches rule a similarity of ``least`` out. Of two rows with different roots one is not of the
    most frequent root of its group, so only those rows, i, meet the others.
    """
    seen = np.zeros(len(fp), dtype=np.int64)
    none = np.zeros(0, dtype=np.int64)
    if not len(fp):
        return none, none, none
    begin, number = _numbers(group)
    left = outsiders(number, begin, root)
    is_left = np.zeros(len(fp), dtype=bool)
    is_left[left] = True
    found = [(none, none)]
    for back in (False, True):

        def wanted(i, j, back=back):
            if j is None:
                return np.ones(len(i), dtype=bool)
            # sets with a similarity of ``least`` differ in so many shingles at most
            room = (size[i] + size[j]) * (1 - least) + 1e-6
            fits = (root[i] != root[j]) & (np.abs(size[i] - size[j]) * (1 + least) <= room)
            return fits & ~is_left[j] if back else fits  # two such rows have met on the way forward

        for i, j in swept(fp, group, radius, wanted, left, back=back):
            near = not_ruled_out(size, sketch, i, j, least)
            i, j = i[near], j[near]
            seen[i] += 1
            within = seen[i] <= most
            found.append((i[within], j[within]))
    i, j = (np.concatenate(x) for x in zip(*found, strict=True))
    return i, j, np.flatnonzero(seen > most)


def unsettled_pairs(members: DataFrame, settled: DataFrame, radius: int, least: float, most: int) -> DataFrame:
    """members of ``near_members``, settled (node, root, size, sketch) -> pairs (u, v), u > v, still to be verified, at most
    ``most`` for each node in a group; a row with u = v says that u has more.

    Rows meet where links joined them, and only where these rows have several roots.
    """

    def run(batches):
        for t in _whole_groups(batches, ("g", "fp", "node", "root", "size", "sketch")):
            g, fp, node, root, size = (c.to_numpy() for c in t.columns[:-1])
            sketch = np.frombuffer(b"".join(t.column("sketch").to_pylist()), dtype=np.uint64).reshape(len(g), -1)
            order = sweep_order(fp.view(np.uint64), g)
            g, fp, node, root, size, sketch = (x[order] for x in (g, fp, node, root, size, sketch))
            i, j, more = open_pairs(fp.view(np.uint64), g, root, size, sketch, radius, least, most)
            u = np.concatenate([np.maximum(node[i], node[j]), node[more]])
            v = np.concatenate([np.minimum(node[i], node[j]), node[more]])
            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], names=["u", "v"])

    own = members.select(F.xxhash64("g", "low").alias("g"), "fp", "node")
    roots = own.join(settled.select("node", "root"), "node").groupBy("g").agg(F.min("root").alias("a"), F.max("root").alias("b"))
    open_ = own.join(roots.filter("a < b").select("g"), "g", "left_semi").join(settled, "node")
    # a fixed number: few bytes may be much work here, so that their partitions must not be put together
    parts = int(members.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    grouped = open_.select("g", "fp", "node", "root", "size", "sketch").repartition(parts, "g").sortWithinPartitions("g")
    return common.map_arrow(grouped, run, "u long, v long")


def _may_be_similar(pairs: DataFrame, texts: DataFrame, least: float) -> DataFrame:
    """The pairs whose sketches do not rule the similarity out."""
    u, v = (texts.select(F.col("node").alias(c), F.col("size").alias(f"{c}_size"), F.col("sketch").alias(f"{c}_sketch")) for c in "uv")
    met = pairs.join(u, "u").join(v, "v").select("u", "v", "u_size", "v_size", "u_sketch", "v_sketch")

    def run(batches):
        for b in batches:
            n = b.num_rows
            size = np.concatenate([b.column(2).to_numpy(), b.column(3).to_numpy()])
            sketch = np.frombuffer(b"".join([*b.column(4).to_pylist(), *b.column(5).to_pylist()]), dtype=np.uint64).reshape(2 * n, -1)
            k = pa.array(np.flatnonzero(not_ruled_out(size, sketch, np.arange(n), np.arange(n, 2 * n), least)))
            yield pa.RecordBatch.from_arrays([b.column(0).take(k), b.column(1).take(k)], names=["u", "v"])

    return common.map_arrow(met, run, "u long, v long")


def similar_components(nodes: DataFrame, own: DataFrame, words: int, least: float, radius: int, equal: int) -> DataFrame:
    """nodes (node, fps), own (doc_id, text) -> node, root: components of all pairs of nodes with a fingerprint within
    ``radius`` bits whose texts have the similarity. Nodes without such a pair do not appear.

    Links to the smallest node of a bucket's component are verified first, which settles most groups. Then, in each
    round, every pair that may be similar and is not in one component of verified links yet is verified, up to a number
    of partners for each node that grows eightfold, until no node has more: groups of true copies take one round, and the
    number of rounds is bounded by the size of a group, since a round without limit leaves no pair out. Buckets are dealt
    once; the rounds go over the rows that have a link in them. Texts are moved where sketches leave a pair open.
    """
    members = common.materialise(near_members(nodes, radius, equal), "members")
    linked = members.select("node").distinct()
    # a node without a link has no other within the radius
    texts = own.select(F.col("doc_id").alias("node"), "text").join(linked, "node", "left_semi").dropDuplicates(["node"])
    texts = common.materialise(with_sketches(texts, words), "linked")
    links = members.filter("node <> low").select(F.col("node").alias("u"), F.col("low").alias("v")).distinct()
    links = common.materialise(_may_be_similar(links, texts, least), "links")
    # one link each first; only those that it does not settle look at the rest of their links
    lowest = links.groupBy("u").agg(F.min("v").alias("v"))
    first = common.materialise(similar_links(lowest, texts, words, least), "similar")
    rest = links.join(first.select("u"), "u", "left_anti").join(lowest, ["u", "v"], "left_anti")
    found = [first, common.materialise(similar_links(rest, texts, words, least), "similar")]
    common.discard(links)
    roots, most = connected_components(reduce(DataFrame.union, found)), PARTNERS
    for made in found:
        common.discard(made)
    while True:
        settled = texts.join(roots, "node", "left").select("node", F.coalesce("root", "node").alias("root"), "size", "sketch")
        settled = common.materialise(settled, "settled")
        pairs = common.materialise(unsettled_pairs(members, settled, radius, least, most).distinct(), "pairs")
        common.discard(settled)
        open_ = pairs.agg(F.count_if(F.expr("u <> v")), F.count_if(F.expr("u = v"))).first()
        if open_[0]:
            more = common.materialise(similar_links(pairs.filter("u <> v"), texts, words, least), "similar")
            # what is joined already is a star for each component
            roots = connected_components(roots.select(F.col("node").alias("u"), F.col("root").alias("v")).union(more))
            common.discard(more)
        common.discard(pairs)
        if not open_[1]:
            common.discard(members)
            common.discard(texts)
            return roots
        most *= 8


def keep_firsts(
    docs: DataFrame,
    shingle: int = 5,
    least: float = 0.8,
    words: int = 2,
    radius: int = REMOVAL_RADIUS,
    equal: int = REMOVAL_EQUAL,
    seeds: int = REMOVAL_SEEDS,
    text: str = "text",
) -> DataFrame:
    """The rows of docs, all columns, without near copies: of each group of documents that near copies join, the one
    with the smallest doc_id stays.

    Near copies are documents whose sets of ``shingle``-word shingles have a Jaccard similarity of ``least`` or more.
    They are searched by SimHash: small edits flip few bits of a fingerprint over ``words``-word shingles, so of the
    ``seeds`` fingerprints of texts that similar one at least lies within ``radius`` bits as a rule (README has the
    measured share). All pairs within the radius count, and groups are components of those whose similarity is verified.
    Texts that differ in case and white space only are copies. Rows without a doc_id stay; rows of one doc_id are one
    document and stay or go together.
    """
    own = docs.select("doc_id", F.col(text).alias("text")).filter("doc_id is not null")
    held = common.materialise(with_contents(own, words, seeds), "contents")
    nodes = held.groupBy("content").agg(F.min("doc_id").alias("node"), F.first("fps").alias("fps"))
    nodes = common.materialise(nodes.groupBy("node").agg(F.min("fps").alias("fps")), "nodes")
    near = similar_components(nodes, own, shingle, least, radius, equal).filter("node <> root").select(F.col("node").alias("u"))
    later = held.join(nodes.select("node"), held["doc_id"] == F.col("node"), "left_anti").select("doc_id")
    # written, so that its size is known before the texts would be moved for the join
    gone = common.materialise(later.union(near).distinct().select(F.col("doc_id").alias("_gone")), "gone")
    return docs.join(gone, docs["doc_id"] == gone["_gone"], "left_anti")
