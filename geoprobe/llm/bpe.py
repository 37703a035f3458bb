"""Byte-pair encoding and decoding with a given vocabulary, merged through a segment tree.

The pairs of a word's adjacent symbols are the leaves of a segment tree over their ranks. The root holds the
leftmost lowest rank; a merge changes two leaves and switches one off, each a logarithmic update, and the word is done
when the root is infinite. The new words of a batch are merged side by side: words whose trees have one size are the columns of
an array whose rows are the tree's nodes (`forest`); a size with a few words only is merged word by word (`merge`). Text outside special
tokens is composed (NFC), lower-cased character by character and cut
into contractions, letter runs, single digits and other runs; white space is dropped.

Null text is the empty text: no ids, empty decoded text. Very long words stay logarithmic per merge; repeated rows stay;
other columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import re
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_text

VOCABULARY = "word_bpe_49k.json"
NEVER = 1 << 62
#: Distinct runs between white space that each of two generations remembers.
REMEMBERED = 250_000
#: Trees of one size are merged side by side if there are so many; an array of them holds about so many leaves.
SIDE_BY_SIDE, LEAVES = 16, 1 << 19


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(VOCABULARY)


#: Unicode white space (a fixed value); str.split() would also cut at the separators U+001C to U+001F.
_SPACE = re.compile("[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]+")
_ODD = re.compile("[\x1c-\x1f]")


def runs(text: str) -> list[str]:
    """Runs of a text between white space."""
    return [x for x in _SPACE.split(text) if x] if _ODD.search(text) else text.split()


def byte_letters() -> list[str]:
    """A printable character for every byte: printable Latin-1 bytes stand for themselves, the others follow from 256."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


def put(low: list[int], at: int, value: int) -> None:
    """Set a leaf of a minimum tree kept as a heap and renew the nodes above it as far as they change."""
    low[at] = value
    at >>= 1
    while at:
        a, b = low[2 * at], low[2 * at + 1]
        if b < a:
            a = b
        if low[at] == a:
            return
        low[at] = a
        at >>= 1


class Encoder:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.ids: dict[str, int] = model["vocab"]
        self.names = {v: k for k, v in self.ids.items()}
        self.end = model["end_of_word_suffix"] or ""
        self.ranks: dict[int, int] = {}
        self.products: list[int] = []
        for a, b in model["merges"]:
            self.ranks.setdefault(self.ids[a] << 20 | self.ids[b], len(self.products))
            self.products.append(self.ids[a + b])
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.names |= {v: k for k, v in self.special.items()}
        letters = byte_letters()
        self.inner, self.last = [self.ids[x] for x in letters], [self.ids[x + self.end] for x in letters]
        self.pairs = np.array(sorted(self.ranks), np.int64)
        self.pair_ranks = np.array([self.ranks[x] for x in self.pairs.tolist()], np.int64)
        self.made = np.array(self.products, np.int64)
        self.inner_ids, self.last_ids = np.array(self.inner, np.int64), np.array(self.last, np.int64)
        #: Runs come without white space, which Python's own class would extend by four control characters.
        self.pieces = regex.compile(spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"].replace(r"[^\s", "[^"))
        self.cut = regex.compile("(" + "|".join(regex.escape(t) for t in sorted(self.special, key=len, reverse=True)) + ")")
        self.by_number = {str(i).encode(): name for i, name in self.names.items()}
        self.known: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}

    def merge(self, live: list[int]) -> list[int]:
        """Merge the symbols of one word (the list is used up). A leaf holds its pair's rank above its position, so the
        root of the tree is the leftmost pair of the lowest rank."""
        n = len(live)
        if n < 2:
            return live
        ranks, products = self.ranks, self.products
        size = 1 << (n - 2).bit_length()
        low = [NEVER] * (2 * size)
        for i in range(n - 1):
            if (rank := ranks.get(live[i] << 20 | live[i + 1])) is not None:
                low[size + i] = rank << 32 | i
        for i in range(size - 1, 0, -1):
            a, b = low[2 * i], low[2 * i + 1]
            low[i] = b if b < a else a
        if low[1] == NEVER:
            return live
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        while (top := low[1]) != NEVER:
            i = top & 0xFFFFFFFF
            j = after[i]
            k = after[i] = after[j]
            live[i], live[j] = products[top >> 32], -1
            if j < n - 1:
                put(low, size + j, NEVER)
            rank = None
            if k < n:
                before[k] = i
                rank = ranks.get(live[i] << 20 | live[k])
            put(low, size + i, NEVER if rank is None else rank << 32 | i)
            if (h := before[i]) >= 0:
                rank = ranks.get(live[h] << 20 | live[i])
                put(low, size + h, NEVER if rank is None else rank << 32 | h)
        return [s for s in live if s >= 0]

    def ranked(self, left: np.ndarray, right: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Leaves: the rank of each pair above its position, or NEVER."""
        wanted = left << 20 | right
        place = np.minimum(np.searchsorted(self.pairs, wanted), len(self.pairs) - 1)
        return np.where(self.pairs[place] == wanted, self.pair_ranks[place] << 32 | at, NEVER)

    def forest(self, words: list[bytes], size: int) -> list[list[int]]:
        """Merge many words of at most size + 1 bytes, a segment tree of `size` leaves for each: row k of `low` holds node k
        of all trees. Every turn makes one merge in each word that isn't done."""
        count, lengths = len(words), np.array([len(w) for w in words])
        flat = np.frombuffer(b"".join(words), np.uint8)
        ends = np.cumsum(lengths)
        word, at = np.repeat(np.arange(count), lengths), np.arange(len(flat)) - np.repeat(ends - lengths, lengths)
        live = np.full((size + 2, count), -1, np.int64)
        live[at, word] = self.inner_ids[flat]
        live[lengths - 1, np.arange(count)] = self.last_ids[flat[ends - 1]]
        low = np.full((2 * size, count), NEVER, np.int64)
        low[size:] = np.where(live[1 : size + 1] >= 0, self.ranked(live[:size], live[1 : size + 1], np.arange(size)[:, None]), NEVER)
        for i in range(size - 1, 0, -1):
            np.minimum(low[2 * i], low[2 * i + 1], out=low[i])
        after, before = (np.repeat(np.arange(size + 2)[:, None] + d, count, axis=1) for d in (1, -1))
        w = np.flatnonzero(low[1] != NEVER)
        while len(w):
            top = low[1, w]
            i = top & 0xFFFFFFFF
            j = after[i, w]
            k = after[j, w]
            live[i, w], live[j, w], after[i, w] = self.made[top >> 32], -1, k
            more = k < lengths[w]
            before[k[more], w[more]] = i[more]
            own, right = live[i, w], live[np.minimum(k, size + 1), w]
            h = before[i, w]
            low[size + np.minimum(j, size - 1), w] = NEVER
            low[size + i, w] = np.where(more, self.ranked(own, right, i), NEVER)
            first = h >= 0
            low[size + h[first], w[first]] = self.ranked(live[h[first], w[first]], own[first], h[first])
            nodes = [(size + i, w), (size + np.minimum(j, size - 1), w), (size + h[first], w[first])]
            for _ in range(size.bit_length() - 1):
                nodes = [(n >> 1, c) for n, c in nodes]
                for n, c in nodes:
                    low[n, c] = np.minimum(low[2 * n, c], low[2 * n + 1, c])
            w = w[low[1, w] != NEVER]
        done = live.T
        kept = done >= 0
        ids, cuts = done[kept].tolist(), np.cumsum(kept.sum(axis=1)).tolist()
        return [ids[a:b] for a, b in zip([0, *cuts], cuts, strict=False)]

    def merged_words(self, words: list[bytes]) -> list[list[int]]:
        """The ids of each word."""
        out: list[list[int]] = [[]] * len(words)
        sizes: dict[int, list[int]] = {}
        for n, word in enumerate(words):
            sizes.setdefault(1 << max(0, len(word) - 2).bit_length(), []).append(n)
        for size, places in sizes.items():
            if len(places) < SIDE_BY_SIDE or size >= LEAVES:
                for n in places:
                    data = words[n]
                    out[n] = self.merge([*map(self.inner.__getitem__, data[:-1]), self.last[data[-1]]])
                continue
            step = max(SIDE_BY_SIDE, LEAVES // size)
            for a in range(0, len(places), step):
                for n, ids in zip(places[a : a + step], self.forest([words[n] for n in places[a : a + step]], size), strict=True):
                    out[n] = ids
        return out

    def pieces_of(self, chunk: str) -> list[str]:
        """Pieces of a run without white space; composing and lower-casing can be done run by run."""
        if chunk.isascii():
            text = chunk.lower()
        else:
            text = unicodedata.normalize("NFC", chunk)
            text = "".join(map(str.lower, text)) if "Σ" in text else text.lower()
        return [text] if text.isalpha() else self.pieces.findall(text)

    def encode(self, text: str) -> list[int]:
        return self.encoded([text])[0]

    def decode(self, ids: list[int]) -> str:
        """Token strings joined by spaces: the vocabulary file names no decoder, special tokens are kept."""
        return " ".join(self.names[i] for i in ids)

    def remember(self, fresh: dict[str, bytes]) -> None:
        """Keep ids in two generations: when the younger is full it becomes the older, from which what comes again is taken
        over, so frequent runs stay."""
        if len(self.known) >= REMEMBERED:
            self.older, self.known = self.known, {}
        self.known.update({k: v for k, v in fresh.items() if len(k) <= 64})

    def rendered(self, chunks: list[str]) -> dict[str, bytes]:
        """The decimal ids of runs that the younger generation doesn't know; pieces are runs themselves."""
        known, older = self.known, self.older
        fresh = {x: got for x in chunks if (got := older.get(x)) is not None}
        cut = {x: self.pieces_of(x) for x in chunks if x not in fresh}
        pieces = [p for p in {p: None for own in cut.values() for p in own} if p not in known and p not in older and p not in fresh]
        fresh.update(zip(pieces, (" ".join(map(str, ids)).encode() for ids in self.merged_words([p.encode() for p in pieces])), strict=True))
        for x, own in cut.items():
            if x not in fresh:
                fresh[x] = b" ".join([fresh[p] if p in fresh else known[p] if p in known else older[p] for p in own])
        self.remember(fresh)
        return fresh

    def decimals(self, texts: list[str]) -> Iterator[bytes]:
        """The decimal ids of each text, joined by spaces; what the texts of a batch bring that is new is merged together."""
        cut, found, new = [], [], {}
        find = self.known.get
        for text in texts:
            if "<|" in text:
                parts = [x for part in self.cut.split(text) for x in ([part] if part in self.special else runs(part))]
            else:
                parts = runs(text)
            ids = list(map(find, parts))
            if None in ids:
                new.update((x, None) for x, got in zip(parts, ids, strict=True) if got is None)
            cut.append(parts)
            found.append(ids)
        fresh = {x: str(i).encode() for x, i in self.special.items() if x in new}
        fresh |= self.rendered([x for x in new if x not in fresh])
        for parts, ids in zip(cut, found, strict=True):
            yield b" ".join([x for x in (fresh[p] if got is None else got for p, got in zip(parts, ids, strict=True)) if x])

    def encoded(self, texts: list[str]) -> list[list[int]]:
        return [list(map(int, x.split())) for x in self.decimals(texts)]

    def summaries(self, texts: list[str]) -> list[tuple[int, str, str]]:
        """Token count, digest of the decimal ids and digest of the decoded text of each text."""
        out = []
        for joined in self.decimals(texts):
            tokens = joined.split()
            decoded = " ".join(map(self.by_number.__getitem__, tokens))
            out.append((len(tokens), hashlib.sha256(joined).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest()))
        return out

    def summary(self, text: str) -> tuple[int, str, str]:
        return self.summaries([text])[0]


_LOADED: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _LOADED:
        _LOADED[path] = Encoder(path)
    return _LOADED[path]


def tokenised(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, ids (array of token ids), decoded (text of those ids)."""
    place = path or default_path()

    def run(batch: pa.RecordBatch) -> dict:
        made = encoder(place).encoded([t or "" for t in batch.column("text").to_pylist()])
        return {"doc_id": batch.column("doc_id"), "ids": made, "decoded": [encoder(place).decode(x) for x in made]}

    return map_text(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, "doc_id long, ids array<int>, decoded string")


def token_digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 without shipping the ids themselves."""
    place = path or default_path()

    def run(batch: pa.RecordBatch) -> dict:
        made = encoder(place).summaries([t or "" for t in batch.column("text").to_pylist()])
        return {"doc_id": batch.column("doc_id"), "n_tokens": [m[0] for m in made], "ids_sha256": [m[1] for m in made], "decoded_sha256": [m[2] for m in made]}

    return map_text(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
