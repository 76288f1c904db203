"""Operators on single texts: exact round trips and brute force. Without Spark."""

import base64
import hashlib
import random
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
import xxhash
import zstandard
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from blockmv.llm import bpe, fingerprints, importance, packing, quality_rules, simhash, suffix_dedup, toxicity, warc

TEXTS = ["", "a", "Hello, World's 12 ÀÉ ΑΣ", "x" * 300, "<|endoftext|> a<|startoftext|>", "😀 한국 　 İ", "tab\tand\nline\r\n"]


@pytest.fixture(scope="module")
def words():
    path = public_tokenizers.path("word_bpe_49k.json")
    return bpe.WordBpe(path), Tokenizer.from_file(path)


def test_encoding_equals_the_library(words):
    own, library = words
    random.seed(5)
    pool = [chr(c) for c in (*range(9, 0x17F), 0x3A3, 0x130, 0x301, 0x2019, 0x4E2D, 0x10400, 0x1F600)] + ["'s", "the ", "<|endoftext|>"]
    texts = TEXTS + ["".join(random.choices(pool, k=random.randint(1, 80))) for _ in range(400)]
    for t, e in zip(texts, library.encode_batch(texts, add_special_tokens=False), strict=True):
        assert own.encode(t) == e.ids, t
        assert own.decode(e.ids) == library.decode(e.ids, skip_special_tokens=False)
    assert own.encode(None) == []


def test_fragments_join_to_the_word_and_are_safe(words):
    own, _ = words
    for w in ("internationalisation", "qzxjkvqq", "ßüöqqzx"):
        symbols = "".join(own.symbol[b] for b in w.encode())
        parts = own.fragments(symbols)
        assert "".join(parts) == symbols
        for a, b in zip(parts, parts[1:], strict=False):
            assert not any(a[-1] + b[0] in t.removesuffix("</w>") for t in own.ids)


def test_byte_encoder_equals_the_library():
    path = public_tokenizers.path("byte_bpe_50k.json")
    library, own = Tokenizer.from_file(path), packing.byte_encoder(path)
    for t in TEXTS:
        assert packing.token_ids(own, t).tolist() == [*library.encode(t, add_special_tokens=False).ids, 2]


@given(st.lists(st.integers(1, 64), max_size=200))
@settings(max_examples=80, deadline=None)
def test_plans_place_each_piece_once(lengths):
    hist = np.bincount(lengths, minlength=65)[:65] if lengths else np.zeros(65, dtype=np.int64)
    plan = packing.make_plan(hist, 64)
    seen, used = set(), Counter()
    for n, c in enumerate(hist):
        for rank in range(int(c)):
            key = (n << 44) + rank
            k = int(np.searchsorted(plan.keys, key, side="right")) - 1
            sequence, at = int(plan.base[k] + key - plan.keys[k]), int(plan.offset[k])
            assert (sequence, at) not in seen
            seen.add((sequence, at))
            used[sequence] += n
    assert all(v <= 64 for v in used.values())
    assert len(used) == plan.sequences
    starts = {}
    for s, at in seen:
        starts.setdefault(s, []).append(at)
    assert all(min(v) == 0 for v in starts.values())


def test_packing_is_near_the_bound():
    random.seed(2)
    hist = np.bincount([random.randint(1, 1024) for _ in range(20_000)], minlength=1025)
    bound = -(-int((hist * np.arange(1025)).sum()) // 1024)
    assert packing.make_plan(hist).sequences <= 1.01 * bound


def naive_features(t):
    w = [x for x in __import__("re").findall(r"[^\x20\x09-\x0D]+", t or "")]
    grams = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    inside = {j for i in range(len(w) - 4) if grams[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
    lines = [x for x in (t or "").split("\n") if x.strip(" \t\n\x0b\x0c\r")]
    return [len(w), sum(map(len, w)), sum((t or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(inside), len(lines), (t or "").count("!"), sum(bytes(b for b in x.encode() if b < 128).isupper() for x in w)]


def test_quality_counts():
    random.seed(1)
    texts = [None, *TEXTS, "a b c d e a b c d e", "same\nsame\n \nsame", "é x y"]
    texts += [" ".join(random.choices("abc", k=random.randint(0, 60))) for _ in range(200)]
    got = zip(*(c.to_pylist() for c in quality_rules.count_features(texts)), strict=True)
    assert [list(r) for r in got] == [naive_features(t) for t in texts]


def test_certified_losses_are_rare():
    """With true losses above the limit at every step of three strata, any certificate is wrong: they must be rare."""
    rng = np.random.default_rng(3)
    steps = [(0.5,), (0.4,), (0.3,)]
    paths = {(s,): steps for s in "abc"}
    wrong = 0
    for _ in range(2000):
        losses = {s: [int(k), 2, 1, 500 - int(k) - 3] for s, k in zip(paths, rng.binomial(500, 0.0501, 3), strict=True)}
        wrong += bool(quality_rules.certify(paths, losses, losses, 0.05, 0.05))
    assert wrong <= 2000 * 0.05 + 3 * (2000 * 0.05) ** 0.5
    assert quality_rules.binomial_cdf(2, 10, 0.5) == pytest.approx(56 / 1024)
    assert quality_rules.least_good(0.02, 0.05 / 4) == 217
    assert quality_rules.upper_bound(0, 217, 0.05 / 4) <= 0.02 < quality_rules.upper_bound(0, 216, 0.05 / 4)


def test_levels_go_on_to_other_strata():
    """b alone fails at delta / 2; once a is certified to its end, b is tested at the whole of delta."""
    paths = {("a",): [(0.5,), (0.4,)], ("b",): [(0.5,)]}
    fit = {("a",): [0, 0, 400], ("b",): [0, 170]}  # 0.98**170 lies between 0.025 and 0.05
    seen = {("a",): [50, 50, 0], ("b",): [1, 0]}
    assert [(v.strata, v.cutoffs) for v in quality_rules.certify(paths, fit, seen, 0.02, 0.05)] == [(("a",), (0.4,)), (("b",), (0.5,))]
    bad = {("a",): [0, 40, 360], ("b",): [0, 170]}
    got = quality_rules.certify(paths, bad, seen, 0.02, 0.05)
    assert [(v.strata, v.cutoffs, v.good, v.lost) for v in got] == [(("a",), (0.5,), 400, 0)]
    little = {("a",): [99, 1, 0], ("b",): [1, 0]}
    assert [v.cutoffs for v in quality_rules.certify(paths, fit, little, 0.02, 0.05)] == [(0.5,), (0.5,)]


def test_fingerprint_string_round_trip_and_containment():
    a = fingerprints.fingerprint("some text of a length that is cut. " * 20 + "end")
    assert fingerprints.from_string(fingerprints.to_string(a)) == a
    assert fingerprints.containment(a, a) == 1
    assert fingerprints.containment({}, {}) == 1
    assert fingerprints.containment({}, a) == 0 == fingerprints.containment(a, {})


def test_chunks_resist_a_shift():
    random.seed(4)
    text = "".join(random.choices("abcdefgh ", k=4000))
    moved = text[:2000] + "inserted" + text[2000:]
    assert fingerprints.containment(fingerprints.fingerprint(text), fingerprints.fingerprint(moved)) > 0.95


@given(st.binary(max_size=600))
@settings(max_examples=60, deadline=None)
def test_chunks_cover_the_text(data):
    edges = fingerprints.chunk_edges(data)
    assert edges[0] == 0
    assert edges[-1] == len(data)
    assert all(0 < b - a <= fingerprints.MOST for a, b in zip(edges, edges[1:], strict=False))


@pytest.mark.parametrize("rows", [[], [(1, "u", b"x", None)], [(k, None, b"page %d" % (k % 3), k % 3 if k > 2 else None) for k in range(40)]])
def test_archives_round_trip(rows):
    data = warc.archive_bytes([warc.page_record(*r) for r in rows])
    info, *got = warc.read_records(data)
    assert info["record_type"] == "warcinfo"
    assert [(r["page_id"], r["record_type"], r["refers_to"]) for r in got] == [(r[0], "response" if r[3] is None else "revisit", r[3]) for r in rows]
    assert all(r["payload_bytes"] == len(x[2]) and r["payload_digest"] == warc.payload_digest(x[2]) for r, x in zip(got, rows, strict=True))


def test_damaged_archives_are_reported():
    rows = [warc.page_record(k, "http://a/\n%", b"payload %d" % k * 50, None) for k in range(20)]
    data = warc.archive_bytes(rows)
    assert all("error" not in r for r in warc.read_records(data))
    assert list(warc.read_records(data[:-9]))[-1]["error"]
    assert list(warc.read_records(data[:20]))[0]["error"]
    broken = bytearray(data)
    broken[len(data) // 2] ^= 255
    assert any("error" in r for r in warc.read_records(bytes(broken)))
    for bad in (b"x", rows[0].replace(b"WARC/1.1", b"WARC/9"), rows[0].replace(b"sha1:", b"sha1:A"), rows[0] + b"!", rows[0].replace(b"WARC-Date: ", b"WARC-Day: ")):
        with pytest.raises(ValueError, match=r"."):
            warc.parse_record(bad)


def _foreign(kind: str, block: bytes, *more: tuple[str, str], ident: str = "<urn:uuid:6b5b1d8e-0000-4000-8000-000000000001>") -> bytes:
    lines = ["WARC/1.0", f"WARC-Type: {kind}", f"WARC-Record-ID: {ident}", "WARC-Date: 2020-02-03T04:05:06Z", f"Content-Length: {len(block)}"]
    return "\r\n".join([*lines, *(f"{k}: {v}" for k, v in more)]).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def _streamed(raw: bytes, **how) -> bytes:
    """A frame without content size, as streaming writers make it."""
    packer = zstandard.ZstdCompressor(**how).compressobj()
    return packer.compress(raw) + packer.flush()


HTTP = ("Content-Type", "application/http; msgtype=response")


@pytest.mark.parametrize("dictionary", [None, "plain", "packed"])
def test_archives_of_other_writers(dictionary):
    body = b"<p>hi</p>" * 9
    sha = base64.b32encode(hashlib.sha1(body).digest()).decode()
    records = [
        _foreign("warcinfo", b"software: other\r\n", ("Content-Type", "application/warc-fields")),
        _foreign("request", b"GET / HTTP/1.1\r\nHost: h\r\n\r\n", ("Content-Type", "application/http;msgtype=request")),
        _foreign("response", b"HTTP/1.1 200 OK\r\nServer: s\r\n\r\n" + body, HTTP, ("WARC-Payload-Digest", f"sha1:{sha}"), ("WARC-Target-URI", "<http://h/>")),
        _foreign("response", b"HTTP/1.1 200 OK\r\nTransfer-Encoding: chunked\r\nContent-Length: 7\r\n\r\n" + body, HTTP, ("WARC-Payload-Digest", f"sha256:{hashlib.sha256(body).hexdigest()}")),
        _foreign("metadata", b"outlink: http://h/2\r\n", ("X-Long", "one\r\n  two")),
        _foreign("resource", b"\x00\x01png", ("Content-Type", "image/png"), ("WARC-Block-Digest", "blake3:ab")),
        _foreign("revisit", b"HTTP/1.1 304 Not Modified\r\n\r\n", HTTP, ("WARC-Refers-To", "<urn:uuid:x>"), ("WARC-Payload-Digest", f"sha1:{sha}")),
        _foreign("revisit", b"", ("WARC-Refers-To-Target-URI", "http://h/")),
        _foreign("conversion", b"hi", ("Content-Type", "text/plain")),
    ]
    raw = b"WARC/1.0\r\nWARC-Type: response\r\n" * 9
    stored = zstandard.ZstdCompressor().compress(raw) if dictionary == "packed" else raw
    how = {"dict_data": zstandard.ZstdCompressionDict(raw)} if dictionary else {}
    data = (warc.DICTIONARY_FRAME.to_bytes(4, "little") + len(stored).to_bytes(4, "little") + stored) if dictionary else b""
    data += b"".join(_streamed(r, **how) for r in records) + b"\x50\x2a\x4d\x18\x02\x00\x00\x00ab"
    got = list(warc.read_records(data))
    assert [r.get("error") for r in got] == [None] * len(records)
    assert [r["record_type"] for r in got] == ["warcinfo", "request", "response", "response", "metadata", "resource", "revisit", "revisit", "conversion"]
    assert {r["record_id"] for r in got} == {"<urn:uuid:6b5b1d8e-0000-4000-8000-000000000001>"}
    assert {r["page_id"] for r in got} == {None}
    assert [r.get("payload") for r in got] == [b"software: other\r\n", b"", body, body, b"outlink: http://h/2\r\n", b"\x00\x01png", None, None, b"hi"]
    assert (got[2]["url"], got[2]["payload_digest"], got[2]["payload_bytes"]) == ("http://h/", sha, len(body))
    assert (got[6]["refers_to_id"], got[6]["refers_to"], got[6]["payload_digest"]) == ("<urn:uuid:x>", None, sha)


def test_wrong_records_of_other_writers_are_reported():
    ok = b"HTTP/1.1 200 OK\r\nContent-Length: 2\r\n\r\nhi"
    bad = [
        _foreign("response", ok + b"!", HTTP),
        _foreign("response", ok, HTTP, ("WARC-Payload-Digest", "sha1:AAAA")),
        _foreign("resource", b"x", ("WARC-Block-Digest", "md5:00")),
        _foreign("response", b"no head", HTTP),
        _foreign("revisit", b"", ("X", "y")),
        _foreign("resource", b"x" * 600),
    ]
    frames = [_streamed(r) for r in [*bad, _foreign("response", ok, HTTP)]]
    got = list(warc.read_records(b"".join(frames), most=500))
    assert [bool(r.get("error")) for r in got] == [True] * len(bad) + [False]
    assert got[-1]["payload"] == b"hi"


def test_shingles_and_fingerprints():
    assert simhash.fingerprints([None, "", " \n"], 4).tolist() == [0, 0, 0]
    one = simhash.shingle_hashes("A b", 4)
    assert one.tolist() == simhash.shingle_hashes("a\tB ", 4).tolist()
    assert len(simhash.shingle_hashes("a a a a a a", 4)) == 3


@pytest.mark.parametrize("next_", [1, 5, 64])
def test_link_labels_equal_brute_force(monkeypatch, next_):
    monkeypatch.setattr(simhash, "NEXT", next_)
    rng = np.random.default_rng(1)
    base = rng.integers(0, 2**63, 30, dtype=np.uint64)
    fp = np.unique(np.concatenate([base, *[base ^ np.uint64(1 << int(rng.integers(63))) ^ np.uint64(1 << int(rng.integers(63))) for _ in range(6)]]))
    rng.shuffle(fp)
    for group in (np.zeros(len(fp), dtype=int), np.sort(rng.integers(0, 5, len(fp)))):
        fp = fp[simhash.sweep_order(fp, group)]
        near = (np.bitwise_count(fp[:, None] ^ fp[None, :]) <= 4) & (group[:, None] == group[None, :])
        want = np.arange(len(fp))
        for _ in range(20):
            want = np.array([want[near[i]].min() for i in range(len(fp))])
        assert simhash.link_labels(fp, group, 4).tolist() == want.tolist()
    assert simhash.link_labels(fp[:0], group[:0], 4).tolist() == []


def test_pivots_discard_pairs_but_none_within_the_radius():
    rng = np.random.default_rng(2)
    fp = rng.integers(0, 2**63, 2000, dtype=np.uint64)
    table = simhash.pivot_table(fp)
    i, j = np.triu_indices(2000, 1)
    left, _ = simhash.undiscarded(table, i, j, 4)
    assert len(left) < 1e-4 * len(i)  # the table alone, before any distance is looked at
    flips = rng.integers(0, 63, (2000, 4), dtype=np.uint64)
    near = fp.copy()
    for k in range(4):
        near ^= np.uint64(1) << flips[:, k]
    both = simhash.pivot_table(np.concatenate([fp, near]))
    assert len(simhash.undiscarded(both, np.arange(2000), np.arange(2000, 4000), 4)[0]) == 2000


def test_outsiders():
    group = np.array([0, 0, 0, 0, 3, 3, 9, 9, 9])
    label = np.array([5, 4, 5, 1, 2, 1, 7, 7, 7])
    begin, number = simhash._numbers(group)
    assert simhash.outsiders(number, begin, label).tolist() == [1, 3, 4]


@pytest.mark.parametrize("most", [1, 10**6])
def test_open_pairs_equal_brute_force(most):
    rng = np.random.default_rng(7)
    fp = rng.integers(0, 2**9, 300, dtype=np.uint64)
    group, root, size = np.sort(rng.integers(0, 6, 300)), rng.choice([5, 5, 5, 6, 7, 8], 300), rng.integers(80, 130, 300)
    fp = fp[simhash.sweep_order(fp, group)]
    i, j, more = simhash.open_pairs(fp, group, root, size, np.zeros((300, 8), dtype=np.uint64), 2, 0.8, most)
    near = (np.bitwise_count(fp[:, None] ^ fp[None, :]) <= 2) & (group[:, None] == group[None, :]) & (root[:, None] != root[None, :])
    near &= np.abs(size[:, None] - size[None, :]) * 1.8 <= (size[:, None] + size[None, :]) * 0.2 + 1e-6
    want = {(a, b) for a, b in zip(*map(np.ndarray.tolist, np.nonzero(near)), strict=True) if a < b}
    got = [(min(p), max(p)) for p in zip(i.tolist(), j.tolist(), strict=True)]
    assert len(got) == len(set(got))
    assert set(got) <= want
    assert (set(got) == want) == (not len(more))
    assert len(more) > 0 or most > 1
    # a row that gives no more pairs has given all of its own
    assert all((a, b) in set(got) for a, b in want if a not in more and b not in more)


def test_sweep_yields_exactly_the_pairs_within_the_radius():
    rng = np.random.default_rng(3)
    fp = rng.integers(0, 2**9, 400, dtype=np.uint64)
    group = np.sort(rng.integers(0, 7, 400))
    fp = fp[simhash.sweep_order(fp, group)]
    everything = lambda i, j: np.ones(len(i), dtype=bool)
    got = {p for i, j in simhash.swept(fp, group, 2, everything) for p in zip(i.tolist(), j.tolist(), strict=True)}
    near = (np.bitwise_count(fp[:, None] ^ fp[None, :]) <= 2) & (group[:, None] == group[None, :])
    assert got == {(i, j) for i, j in zip(*map(np.ndarray.tolist, np.nonzero(near)), strict=True) if i < j}


@pytest.mark.parametrize(("radius", "equal"), [(4, 1), (4, 2), (4, 3), (6, 2), (8, 3)])
def test_masks_lose_no_pair(radius, equal):
    masks = np.array(simhash.block_masks(radius, equal), dtype=np.uint64)
    rng = np.random.default_rng(2)
    for _ in range(300):
        flips = np.uint64(sum(1 << int(b) for b in rng.choice(64, radius, replace=False)))
        assert ((masks & flips) == 0).any()


def test_similarity():
    assert simhash.similarity(None, "", 5) == 1
    assert simhash.similarity("a b c d e f", "a b c d e g", 5) == pytest.approx(1 / 3)


def naive_edges(data: bytes) -> list[int]:
    """Chunk ends by looking at one byte after the other, the hash of the last 16 bytes summed anew each time."""
    gear = [xxhash.xxh32_intdigest(bytes([b]), 1) >> 16 for b in range(256)]
    edges, begin = [0], 0
    if len(data) <= 8:
        return [0, len(data)] if data else [0]
    for i in range(len(data)):
        h = sum(gear[data[i - age]] << age for age in range(min(16, i + 1))) & 0xFFFF
        size = i + 1 - begin
        zeros = 16 - h.bit_length()
        if (size >= 32 and zeros >= 4) or (8 <= size < 32 and zeros >= 6) or size == 128:
            begin = i + 1
            edges.append(begin)
    return edges if edges[-1] == len(data) else [*edges, len(data)]


def test_chunks_equal_those_found_byte_by_byte():
    rng = random.Random(6)
    texts = [bytes(rng.choices(range(256), k=rng.randrange(900))) for _ in range(40)] + [b"a" * 400, b"ab" * 300, b"", b"12345678", b"123456789"]
    texts += [" ".join(rng.choices(["some", "words", "of", "a", "text"], k=200)).encode() for _ in range(20)]
    for t in texts:
        assert fingerprints.chunk_edges(t) == naive_edges(t)
    for a, b in zip(texts, texts[1:], strict=False):
        pieces = [[t[i:j] for i, j in zip(e, e[1:], strict=False)] for t in (a, b) for e in [naive_edges(t)]]
        common_ = sum(min(pieces[0].count(c), pieces[1].count(c)) * len(c) for c in set(pieces[0]))
        got = fingerprints.containment(*(fingerprints.fingerprint(t.decode("latin-1")) for t in (a, b))) if max(a + b"\0" + b) < 128 else None
        assert got is None or got == pytest.approx(common_ / len(a) if a else float(not b))


@pytest.mark.parametrize("small", [4, 64, 10_000])
def test_multikey_order(small):
    rng = np.random.default_rng(1)
    cols = [rng.integers(0, 3, 5000, dtype=np.uint64), rng.integers(0, 50, 5000, dtype=np.uint64), rng.integers(0, 2, 5000), rng.integers(0, 9**9, 5000)]
    got = suffix_dedup.multikey_order([cols[0], lambda rows: cols[1][rows], *cols[2:]], small=small)
    assert sorted(got.tolist()) == list(range(5000))
    assert [tuple(c[k] for c in cols) for k in got] == sorted(zip(*cols, strict=True))


def test_suffixes_are_sorted_by_their_bytes():
    rng = np.random.default_rng(2)
    data = rng.integers(97, 99, 3000, dtype=np.uint8)
    at = np.arange(2900)
    words = [lambda rows, k=k: suffix_dedup.words_at(data, at[rows] + 8 * k, min(8, 100 - 8 * k)) for k in range(suffix_dedup.WORDS)]
    order = suffix_dedup.multikey_order([np.zeros(2900, dtype=np.uint64), *words, at], small=32)
    raw = data.tobytes()
    assert order.tolist() == sorted(range(2900), key=lambda k: raw[k : k + 100])


def test_equal_spans_have_equal_keys_and_others_do_not():
    rng = random.Random(5)
    base = "".join(rng.choices("ab cd", k=400)).encode()
    keys: dict[tuple, bytes] = {}
    for _ in range(300):
        cut = bytearray(base)
        cut[rng.randrange(400)] = 120
        data = np.frombuffer(bytes(cut), dtype=np.uint8)
        f = suffix_dedup.find_spans(data, np.full(400, 400))
        assert f["n"].sum() == 301
        for k, a in enumerate(f["start"].tolist()):
            text = bytes(cut[a : a + int(f["n"][k]) + 99])
            assert keys.setdefault(tuple(int(f[c][k]) for c in "wgst"), text) == text


def test_cut_out():
    assert suffix_dedup.cut_out(b"abcdef", [(1, 3), (2, 4), (5, 9)]) == ([(1, 4), (5, 6)], b"ae")
    assert suffix_dedup.cut_out(b"", []) == ([], b"")


def test_splitters_split_inside_a_run():
    keys = [(7, 7, 7, d, 0) for d in range(100)]
    s = suffix_dedup.Splitters.sampled(keys, 4)
    got = s.buckets(*(np.array(c) for c in zip(*keys, strict=True)))
    assert Counter(got.tolist()) == {0: 25, 1: 25, 2: 25, 3: 25}


def _machine_accuracy(agree: bool, factors: int) -> float:
    """Two words among others: the label says whether they come together (agree) or one alone; both are neutral alone."""
    rng = random.Random(3 + agree)

    def made(n):
        out = []
        for _ in range(n):
            a, b = rng.random() < 0.5, rng.random() < 0.5
            words = [f"w{int(rng.paretovariate(0.7)) % 800}" for _ in range(20)] + ["insult"] * a + ["group"] * b
            out.append((toxicity.terms_of(" ".join(words)), float((a == b) == agree)))
        return out

    learn, ask = made(3000), made(600)
    m = toxicity.fit([r for r, _ in learn], np.array([y for _, y in learn]), factors=factors)
    place = {int(t): k for k, t in enumerate(m.terms)}
    scores = m.scores([[place[x] for x in r.tolist() if x in place] for r, _ in ask])
    return float(((scores >= 0.5) == np.array([y for _, y in ask], dtype=bool)).mean())


@pytest.mark.parametrize("agree", [True, False])
def test_machine_learns_what_no_additive_model_can(agree):
    assert _machine_accuracy(agree, 0) < 0.6
    assert _machine_accuracy(agree, toxicity.FACTORS) > 0.95


def test_random_pairs_are_not_taken():
    rng = np.random.default_rng(4)
    rows = [np.unique(rng.integers(0, 300, 60)).astype(np.int32) for _ in range(1500)]
    found = toxicity._in_pairs(rows, rng.choice([-0.5, 0.5], 1500), np.arange(300, dtype=np.int32))
    assert len(found) <= 2


def test_machine_without_two_classes():
    rows = [toxicity.terms_of("a b"), toxicity.terms_of("c")]
    assert toxicity.fit([], np.zeros(0)).scores([[]])[0] < 1e-6
    assert toxicity.fit(rows, np.zeros(2)).scores([[]])[0] < 1e-6
    assert toxicity.fit(rows, np.ones(2)).scores([[]])[0] > 1 - 1e-6


def test_ngram_buckets():
    buckets, sizes = importance.ngram_buckets(["a b c", None, "", "a"])
    assert sizes.tolist() == [5, 0, 0, 1]
    assert len(buckets) == 6
    assert buckets[-1] == zlib.crc32(b"a") % importance.BUCKETS
    assert importance.ngram_buckets([])[1].tolist() == []
