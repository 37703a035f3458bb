"""Removal of repeated word windows, by super-k-mer partitioning.

Every window of 50 consecutive words has a minimiser, the smallest hash among its 8-word runs. Consecutive windows with
one minimiser form a super-k-mer. Equal windows have equal minimisers, so a super-k-mer whose minimiser occurs in one
document only is done. The others are settled in two steps:

1. equal super-k-mers (same minimiser, same word sequence) are reduced to their smallest document by a combining
   aggregation; all windows of later occurrences are repeats;
2. where one minimiser has several different super-k-mers, those of the smallest documents travel as one packed
   string each to the minimiser's bucket, where its windows are sorted word for word (ranks of single words, then of runs of
   2, 4, ... words from pairs of ranks), which brings equal ones together and counts them. Super-k-mers of a minimiser with more than `HOT` occurrences (a very common line) are not gathered in one
   bucket: they are cut again by a minimiser of another order, up to `ORDERS` times; of what is common even then, single
   windows are dealt out under a 128-bit hash and reduced by aggregation.

A word is removed if a window that covers it also starts in a document with a smaller doc_id.

Null or short texts have no window and keep all words; a document never removes its own repeats; rows with a null
doc_id take no part and keep their words; rows that share a doc_id don't affect each other and are judged each on its own text (a row is known by
doc_id and a 64-bit hash of its text); other columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_binary, checkpointed, map_text
from .words import Powers, hashed, mix, odd_constants, runs_of, sliding_minimum, split_words

WINDOW, SEED_WORDS, HOT, ORDERS = 50, 8, 512, 4
#: Text bytes that are packed at a time (super-k-mers overlap, so what is packed is several times that), and words of buckets that are sorted together.
PACKED_BYTES, SORTED_WORDS = 1 << 18, 1 << 16
_SEEDS = odd_constants(SEED_WORDS, 3)
_SEQUENCE, _OTHER = Powers(0x5851F42D4C957F2D), Powers(0x2545F4914F6CDD1D)


def super_kmers(flat: np.ndarray, ends: np.ndarray, window: int = WINDOW, order: int = 0):
    """(document number, first word within it, windows, minimiser, sequence hash) of every super-k-mer. `order` says by
    which of several hash orders runs are compared."""
    none = np.zeros(0, np.int64)
    if len(flat) < window:
        return none, none, none, none.astype(np.uint64), none.astype(np.uint64)
    seeds = runs_of(flat, SEED_WORDS, _SEEDS)
    lows = sliding_minimum(mix(seeds + np.uint64(order)) if order else seeds, window - SEED_WORDS + 1)
    owner = np.repeat(np.arange(len(ends) - 1), np.diff(ends))
    at = np.flatnonzero(owner[: len(lows)] == owner[window - 1 :])
    if not len(at):
        return none, none, none, none.astype(np.uint64), none.astype(np.uint64)
    fresh = np.ones(len(at), bool)
    fresh[1:] = (at[1:] != at[:-1] + 1) | (lows[at[1:]] != lows[at[:-1]]) | (owner[at[1:]] != owner[at[:-1]])
    begin = np.flatnonzero(fresh)
    count = np.diff(np.append(begin, len(at)))
    first = at[begin]
    doc = owner[first]
    return doc, first - ends[doc], count, lows[first], _SEQUENCE.stretches(flat, first, first + count + window - 1)


def _occurrences(docs: DataFrame, window: int) -> DataFrame:
    def run(batch: pa.RecordBatch) -> dict:
        ids, rows = _numbers(batch, "doc_id", "row")
        doc, start, count, low, sequence = super_kmers(*hashed(split_words(as_binary(batch.column("text")))), window)
        return {"key": low.view(np.int64), "sequence": sequence.view(np.int64), "doc_id": ids[doc], "row": rows[doc], "place": (start << 32) | count}

    return map_text(docs, run, "key long, sequence long, doc_id long, row long, place long")


def _numbers(batch: pa.RecordBatch, *columns: str) -> list[np.ndarray]:
    return [np.array(batch.column(c).to_pylist(), np.int64) for c in columns]


def _with_places(docs: DataFrame, wanted: DataFrame, fn, schema: str) -> DataFrame:
    """fn(batch of doc_id, row, text, places) for documents that have wanted super-k-mers (a left join, so that the same
    exchange of the documents serves every use)."""
    places = wanted.groupBy(F.col("doc_id").alias("wanted_id"), F.col("row").alias("wanted_row")).agg(F.collect_list(F.struct("key", "place")).alias("places"))
    return map_text(docs.join(places, (F.col("doc_id") == F.col("wanted_id")) & (F.col("row") == F.col("wanted_row")), "left").select("doc_id", "row", "text", "places"), fn, schema, limit=PACKED_BYTES)


def _packed(batch: pa.RecordBatch, window: int) -> dict:
    out: dict[str, list] = {"key": [], "doc_id": [], "row": [], "start": [], "packed": []}
    for doc, row, text, places in zip(batch.column("doc_id").to_pylist(), batch.column("row").to_pylist(), as_binary(batch.column("text")), batch.column("places").to_pylist(), strict=True):
        words = text.split() if places else []
        for p in places or ():
            start, count = p["place"] >> 32, p["place"] & 0xFFFFFFFF
            out["key"].append(p["key"])
            out["doc_id"].append(doc)
            out["row"].append(row)
            out["start"].append(start)
            out["packed"].append(b" ".join(words[start : start + count + window - 1]))
    return out


def _cut_again(batch: pa.RecordBatch, window: int, order: int) -> dict:
    """Packed super-k-mers cut at changes of another order's minimiser; the key tells both minimisers."""
    texts = as_binary(batch.column("packed"))
    words = split_words(texts)
    own, start, count, low, sequence = super_kmers(*hashed(words), window, order)
    keys, ids, rows, firsts = _numbers(batch, "key", "doc_id", "row", "start")
    return {
        "key": mix(low ^ mix(keys.view(np.uint64)[own] + np.uint64(order))).view(np.int64), "sequence": sequence.view(np.int64), "doc_id": ids[own], "row": rows[own], "start": firsts[own] + start, "windows": count,
        "packed": [b" ".join(words[r][s : s + n + window - 1]) for r, s, n in zip(own.tolist(), start.tolist(), count.tolist(), strict=True)],
    }


def _single(batch: pa.RecordBatch, window: int) -> dict:
    """Every window of packed super-k-mers under two 64-bit hashes."""
    flat, ends = hashed(split_words(as_binary(batch.column("packed"))))
    ids, rows, firsts = _numbers(batch, "doc_id", "row", "start")
    sizes = np.maximum(0, np.diff(ends) - window + 1)
    own = np.repeat(np.arange(len(sizes)), sizes)
    at = np.arange(len(own)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    first = ends[own] + at
    return {"a": _SEQUENCE.stretches(flat, first, first + window).view(np.int64), "b": _OTHER.stretches(mix(flat), first, first + window).view(np.int64), "doc_id": ids[own], "row": rows[own], "start": firsts[own] + at}


class _Numbers(dict):
    def __missing__(self, word: bytes) -> int:
        self[word] = value = len(self)
        return value


def window_ranks(words: np.ndarray, window: int) -> np.ndarray:
    """A number for the run of `window` words at each position, equal for equal runs: ranks of runs of 1, 2, 4, ... words, each
    sorted from the pairs of ranks of its halves (overlapping ones in the end)."""
    ranks, size = words.astype(np.int64), 1
    while size < window:
        step = min(size, window - size)
        pairs = ranks[: len(ranks) - step] * (len(words) + 1) + ranks[step:]
        ranks = np.unique(pairs, return_inverse=True)[1]
        size += step
    return ranks


def repeats_in_buckets(rows: list[tuple[int, int, int, np.ndarray]], window: int) -> np.ndarray:
    """(document, row, first word, windows) of the windows that also start in a smaller document, for rows (document, row,
    first word, word numbers) of whole buckets; equal windows share a bucket."""
    sizes = np.array([len(r[3]) for r in rows])
    own = np.repeat(np.arange(len(rows)), sizes)
    at = np.arange(len(own)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    first = np.flatnonzero(at <= sizes[own] - window)
    if not len(first):
        return np.zeros((0, 4), np.int64)
    run = window_ranks(np.concatenate([r[3] for r in rows]), window)[first]
    docs, keys, starts = (np.array([r[i] for r in rows], np.int64) for i in (0, 1, 2))
    row = own[first]
    order = np.argsort(run, kind="stable")
    begins = np.flatnonzero(np.diff(run[order], prepend=-1))
    least = np.empty(int(run.max()) + 1, np.int64)
    least[run[order][begins]] = np.minimum.reduceat(docs[row][order], begins)
    gone = np.flatnonzero(docs[row] > least[run])
    if not len(gone):
        return np.zeros((0, 4), np.int64)
    fresh = np.flatnonzero(np.diff(first[gone], prepend=-2) + np.diff(row[gone], prepend=-2) * len(own) != 1)
    r, count = row[gone][fresh], np.diff(np.append(fresh, len(gone)))
    return np.stack([docs[r], keys[r], starts[r] + at[first[gone][fresh]], count], axis=1)


_REPEATS = "doc_id long, row long, start long, windows long"


def _bucket_repeats(packed: DataFrame, window: int) -> DataFrame:
    names = [c.split()[0] for c in _REPEATS.split(", ")]

    def run(batches):
        # Whole buckets are gathered until they hold enough words; only numbers of words are kept.
        key, rows, numbers, size = None, [], _Numbers(), 0

        def settled():
            found = repeats_in_buckets(rows, window) if rows else np.zeros((0, 4), np.int64)
            return [pa.RecordBatch.from_arrays([pa.array(c) for c in found.T], names=names)] if len(found) else []

        for batch in batches:
            for k, doc, row, start, text in zip(*(batch.column(c).to_pylist() for c in ("key", "doc_id", "row", "start", "packed")), strict=True):
                if k != key and size >= SORTED_WORDS:
                    yield from settled()
                    rows, numbers, size = [], _Numbers(), 0
                key = k
                words = text.split(b" ")
                rows.append((doc, row, start, np.fromiter(map(numbers.__getitem__, words), np.int32, len(words))))
                size += len(words)
        yield from settled()

    dealt = packed.repartition("key").sortWithinPartitions("key")
    return dealt.mapInArrow(run, _REPEATS)


def _told(found: DataFrame, hot: int) -> DataFrame:
    """Super-k-mers whose minimiser occurs in several documents: `least` is the smallest document with the same words,
    `mixed` says whether the minimiser has other words too, `hot` whether it is very common."""
    rest = [c for c in found.columns if c not in ("key", "sequence")]
    keys = found.groupBy("key").agg(F.count("*").alias("n"), F.min("doc_id").alias("a"), F.max("doc_id").alias("z"), (F.min("sequence") != F.max("sequence")).alias("mixed"))
    shared = checkpointed(keys.where("a < z").select(F.col("key").alias("shared_key"), "mixed", (F.col("n") > hot).alias("hot")))
    some = checkpointed(found.join(shared, F.col("key") == F.col("shared_key")).select("key", "sequence", *rest, "mixed", "hot"))
    least = checkpointed(some.groupBy("key", "sequence").agg(F.min("doc_id").alias("least")).select(F.col("key").alias("k"), F.col("sequence").alias("s"), "least"))
    return checkpointed(some.join(least, (F.col("key") == F.col("k")) & (F.col("sequence") == F.col("s"))).select("key", *rest, "mixed", "hot", "least"))


def _known(docs: DataFrame) -> DataFrame:
    text = F.col("text").cast("string")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("row"), text.alias("text"))


def repeated_windows(docs: DataFrame, window: int = WINDOW, hot: int = HOT, orders: int = ORDERS) -> DataFrame:
    """doc_id, row (hash of the text), start, windows: runs of windows that also start in a document with a smaller doc_id (they may overlap)."""
    docs = _known(docs)
    told = _told(_occurrences(docs.where("doc_id is not null"), window), hot)
    out = told.where("least < doc_id").select("doc_id", "row", F.shiftright("place", 32).alias("start"), F.col("place").bitwiseAND(0xFFFFFFFF).alias("windows"))
    strings = "key long, doc_id long, row long, start long, packed binary"
    pack = lambda b: _packed(b, window)
    out = out.unionByName(_bucket_repeats(_with_places(docs, told.where("least = doc_id and mixed and not hot").select("key", "doc_id", "row", "place"), pack, strings), window))
    common = told.where("least = doc_id and mixed and hot").select("key", "doc_id", "row", "place")
    if common.isEmpty():
        return out
    left = checkpointed(_with_places(docs, common, pack, strings))
    for order in range(1, orders + 1):
        cut = checkpointed(map_text(left, lambda b, order=order: _cut_again(b, window, order), "key long, sequence long, doc_id long, row long, start long, windows long, packed binary", column="packed"))
        told = _told(cut, hot)
        out = out.unionByName(told.where("least < doc_id").select("doc_id", "row", "start", "windows"))
        out = out.unionByName(_bucket_repeats(told.where("least = doc_id and mixed and not hot").select("key", "doc_id", "row", "start", "packed"), window))
        left = told.where("least = doc_id and mixed and hot").select("key", "doc_id", "row", "start", "packed")
        if left.isEmpty():
            return out
    single = checkpointed(map_text(left, lambda b: _single(b, window), "a long, b long, doc_id long, row long, start long", column="packed"))
    first = checkpointed(single.groupBy("a", "b").agg(F.min("doc_id").alias("least"), F.max("doc_id").alias("z")).where("least < z").select(F.col("a").alias("c"), F.col("b").alias("d"), "least"))
    return out.unionByName(single.join(first, (F.col("a") == F.col("c")) & (F.col("b") == F.col("d"))).where("doc_id > least").select("doc_id", "row", "start", F.lit(1).cast("long").alias("windows")))


def _kept(words: list[bytes], spans, window: int) -> list[bytes]:
    mark = np.zeros(len(words) + 1, np.int64)
    for start, windows in spans:
        mark[start] += 1
        mark[start + windows + window - 1] -= 1
    keep = np.cumsum(mark[:-1]) == 0
    return [w for w, k in zip(words, keep.tolist(), strict=True) if k]


def without_repeats(docs: DataFrame, window: int = WINDOW, hot: int = HOT, texts: bool = True) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 and, if wanted, the kept words joined by one space."""
    spans = repeated_windows(docs, window, hot).groupBy(F.col("doc_id").alias("span_id"), F.col("row").alias("span_row")).agg(F.collect_list(F.struct("start", "windows")).alias("spans"))
    docs = _known(docs)

    def run(batch: pa.RecordBatch) -> dict:
        out: dict[str, list] = {"n_words": [], "n_removed": [], "kept_sha256": [], "kept": []}
        for text, own in zip(as_binary(batch.column("text")), batch.column("spans").to_pylist(), strict=True):
            words = text.split()
            kept = _kept(words, [(s["start"], s["windows"]) for s in own], window) if own else words
            joined = b" ".join(kept)
            out["n_words"].append(len(words))
            out["n_removed"].append(len(words) - len(kept))
            out["kept_sha256"].append(hashlib.sha256(joined).hexdigest())
            out["kept"].append(joined.decode() if texts else None)
        return {"doc_id": batch.column("doc_id")} | out

    made = map_text(docs.join(spans, (F.col("doc_id") == F.col("span_id")) & (F.col("row") == F.col("span_row")), "left").select("doc_id", "text", "spans"), run, "doc_id long, n_words long, n_removed long, kept_sha256 string, kept string")
    return made if texts else made.drop("kept")
