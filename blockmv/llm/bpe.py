"""Byte-pair encoding and decoding with forced boundaries.

Two neighbouring bytes that stand next to each other inside no vocabulary token can never be merged across, so a cut
between them is certain. Each word is split at all such cuts, the fragments are merged independently and the results
are concatenated: the ids equal those of merging the whole word, and no merge ever handles more than a fragment.

The vocabulary file is read with the ``tokenizers`` JSON layout; normaliser and word pattern are those of the
word-end vocabulary (compose, collapse white space, lower-case each character, words / digits / other runs). Texts
holding characters whose class differs between Unicode tables are split by the library itself (``_ODD``), and merged
here. Special tokens standing in a text are recognised, as the library does by default.

Defined results: a null or empty text has no tokens and decodes to the empty text; repeated rows are encoded one by
one; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import unicodedata
from array import array
from collections.abc import Callable
from itertools import chain

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from . import common

#: Words kept in a worker's table; it is emptied when full, which costs time only.
WORD_CACHE = 400_000

#: Everything beyond the blocks for which the library's tables and Python's were compared in full.
_ODD = regex.compile(r"[^\x00-ԯḀ-῿‐-‧‰-⁞₠-₿ぁ-ゖ一-龥가-힣]")


def byte_symbols() -> list[str]:
    """The printable character that byte-level vocabularies use for each byte value."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class WordBpe:
    """Encoder and decoder of one vocabulary file; one per worker process."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.path = path
        self.end = model.get("end_of_word_suffix") or ""
        self.ids: dict[str, int] = model["vocab"]
        self.special: dict[str, int] = {t["content"]: t["id"] for t in spec["added_tokens"]}
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        self.rank = {pair: k for k, pair in enumerate(merges)}
        names = {i: t for t, i in self.ids.items()} | {i: t for t, i in self.special.items()}
        self.tokens = [names.get(i, "") for i in range(max(names) + 1)]
        self.symbol = byte_symbols()
        self.joins = self._inner_pairs()
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.words = regex.compile(split["pattern"]["Regex"])
        self.specials = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self.known: dict[str, tuple[int, ...]] = {}
        self._library = None

    def _inner_pairs(self) -> set[str]:
        """All pairs of symbols that are neighbours inside some token."""
        out: set[str] = set()
        for t in self.ids:
            body = t[: -len(self.end)] if self.end and t.endswith(self.end) else t
            out.update(a + b for a, b in zip(body, body[1:], strict=False))
        return out

    def fragments(self, symbols: str) -> list[str]:
        """A word in byte symbols, cut at every certain boundary."""
        cuts = [k for k in range(1, len(symbols)) if symbols[k - 1 : k + 1] not in self.joins]
        return [symbols[a:b] for a, b in zip([0, *cuts], [*cuts, len(symbols)], strict=True)]

    def merge(self, fragment: str, last: bool) -> list[int]:
        """Merge one fragment by rank, leftmost first among equals: a heap over a linked list of parts."""
        part = list(fragment)
        if last:
            part[-1] += self.end
        n = len(part)
        left, right = list(range(-1, n - 1)), list(range(1, n + 1))
        heap = [(r, k, part[k], part[k + 1]) for k in range(n - 1) if (r := self.rank.get((part[k], part[k + 1]))) is not None]
        heapq.heapify(heap)
        while heap:
            _, k, a, b = heapq.heappop(heap)
            j = right[k]
            if part[k] != a or j >= n or part[j] != b:
                continue  # one of the two has been merged since
            part[k], part[j] = a + b, ""
            right[k] = right[j]
            if right[j] < n:
                left[right[j]] = k
            for x, y in ((left[k], k), (k, right[k])):
                if x >= 0 and y < n and (r := self.rank.get((part[x], part[y]))) is not None:
                    heapq.heappush(heap, (r, x, part[x], part[y]))
        return [self.ids[p] for p in part if p]

    def word(self, word: str) -> tuple[int, ...]:
        symbols = "".join([self.symbol[b] for b in word.encode()])
        parts = self.fragments(symbols)
        return tuple(chain.from_iterable(self.merge(p, k == len(parts) - 1) for k, p in enumerate(parts)))

    def _normal(self, text: str) -> str:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text)
            # one character at a time: without the final form of sigma
            text = text.replace("Σ", "σ")
        return text.lower()

    def _split(self, text: str) -> list[str]:
        if not text.isascii() and _ODD.search(text):
            if self._library is None:
                from tokenizers import Tokenizer

                self._library = Tokenizer.from_file(self.path)
            pieces = self._library.pre_tokenizer.pre_tokenize_str(self._library.normalizer.normalize_str(text))
            back = {s: b for b, s in enumerate(self.symbol)}
            return [bytes(back[c] for c in w).decode("utf-8", "replace") for w, _ in pieces]
        return self.words.findall(self._normal(text))

    def _plain(self, text: str) -> list[int]:
        words, known = self._split(text), self.known
        try:
            return list(chain.from_iterable([known[w] for w in words]))
        except KeyError:
            if len(known) > WORD_CACHE:
                known.clear()
            found = [known.get(w) or known.setdefault(w, self.word(w)) for w in words]
            return list(chain.from_iterable(found))

    def encode(self, text: str | None) -> list[int]:
        if not text:
            return []
        if self.specials is None or "<|" not in text:
            return self._plain(text)
        out: list[int] = []
        for k, piece in enumerate(self.specials.split(text)):
            out += [self.special[piece]] if k % 2 else self._plain(piece)
        return out

    def decode(self, ids: list[int]) -> str:
        """Tokens of the ids with a space between: what a vocabulary without a decoder defines."""
        tokens = self.tokens
        return " ".join([tokens[i] for i in ids])


_loaded: dict[str, WordBpe] = {}


def load(path: str) -> WordBpe:
    """The encoder of a vocabulary file, read once in each worker process."""
    if path not in _loaded:
        _loaded[path] = WordBpe(path)
    return _loaded[path]


def _per_text(path: str, of: Callable[[WordBpe, list[int]], tuple], types: list[pa.DataType]) -> Callable:
    def kernel():
        bpe = load(path)

        def f(texts: list[str | None]) -> list[pa.Array]:
            rows = [of(bpe, bpe.encode(t)) for t in texts]
            cols = list(zip(*rows, strict=True)) if rows else [()] * len(types)
            return [pa.array(c, type=t) for c, t in zip(cols, types, strict=True)]

        return f

    return kernel


def encode_texts(docs: DataFrame, path: str, text: str = "text") -> DataFrame:
    """docs with ``ids`` (array of int) and ``decoded`` appended."""
    types = [pa.list_(pa.int32()), pa.string()]
    return common.map_texts(
        docs, text, "ids array<int>, decoded string", _per_text(path, lambda b, i: (i, b.decode(i)), types)
    )


def _digest(bpe: WordBpe, ids: list[int]) -> tuple[int, str, str]:
    # "I" is four bytes, little-endian, on every platform that Spark's workers run on
    return (
        len(ids),
        hashlib.sha256(array("I", ids).tobytes()).hexdigest(),
        hashlib.sha256(bpe.decode(ids).encode()).hexdigest(),
    )


def encode_digests(docs: DataFrame, path: str, text: str = "text") -> DataFrame:
    """docs with n_tokens and the digests of the ids and of the decoded text: nothing of the size of the ids moves."""
    types = [pa.int64(), pa.string(), pa.string()]
    extra = "n_tokens long, ids_sha256 string, decoded_sha256 string"
    return common.map_texts(docs, text, extra, _per_text(path, _digest, types))
