"""Benchmark decontamination with one Aho-Corasick automaton over normalised test items.

Texts are lower-cased (A-Z) and cut into words of digits, letters and non-ASCII characters; a test item gives every
run of `window` consecutive words (an item of fewer words is one run). The automaton reads each normalised text once;
matches are mapped back to word numbers and to code-point offsets of the original text.

Null or word-less texts have no words and no hits; items that are null or word-less match nothing; repeated
rows are reported row by row; an empty benchmark leaves every document clean; other columns are ignored.
"""

from __future__ import annotations

import re
from bisect import bisect_left

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_binary, checkpointed, map_text, workers_can_import

WINDOW = 10
#: Items are dealt into blocks of about this many bytes, one automaton and one scan a block, so that what is
#: broadcast stays bounded however large the benchmark grows.
BLOCK_BYTES = 8 << 20

_KEPT = set(b"0123456789abcdefghijklmnopqrstuvwxyz") | set(range(128, 256))
_FOLD = bytes(c if (c := b + 32 if 65 <= b <= 90 else b) in _KEPT else 32 for b in range(256))
_WORD = re.compile(rb"[0-9A-Za-z\x80-\xff]+")

HITS = "array<struct<first:int,last:int,start:int,end:int>>"
SCHEMA = f"doc_id long, n_words long, hits {HITS}, items array<string>"


def words_of(text: bytes) -> list[bytes]:
    return text.translate(_FOLD).split()


def patterns_of(rows, window: int = WINDOW) -> list[tuple[str, int, list[str]]]:
    """(normalised run, its word count, ids of the items that hold it); rows are (item id, text)."""
    found: dict[bytes, tuple[int, set[str]]] = {}
    for item, text in rows:
        words = words_of((text or "").encode())
        size = min(window, len(words))
        for i in range(len(words) - size + 1 if size and item is not None else 0):
            found.setdefault(b" ".join(words[i : i + size]), (size, set()))[1].add(str(item))
    return [(f" {key.decode('latin-1')} ", size, sorted(ids)) for key, (size, ids) in sorted(found.items())]


def automaton_of(patterns):
    import ahocorasick

    made = ahocorasick.Automaton()
    for i, (key, size, _) in enumerate(patterns):
        made.add_word(key, (i, size))
    if patterns:
        made.make_automaton()
    return made


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Union of closed integer intervals, joined where they overlap or touch."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1] + 1:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def scan(text: bytes, automaton, patterns) -> tuple[int, list[dict], list[str]]:
    """Word count, hit spans in words (first, last) and in code points (start, end), and ids of the items found."""
    words = words_of(text)
    flat = f" {b' '.join(words).decode('latin-1')} "
    found = list(automaton.iter(flat)) if patterns and words else []
    if not found:
        return len(words), [], []
    ends, at = [], 0
    for word in words:
        at += len(word) + 1
        ends.append(at)
    spans, items = [], set()
    for end, (i, size) in found:
        last = bisect_left(ends, end)
        spans.append((last - size + 1, last))
        items.update(patterns[i][2])
    places = [m.span() for m in _WORD.finditer(text)]
    hits = []
    for first, last in merged(spans):
        start = len(text[: places[first][0]].decode(errors="replace"))
        end = start + len(text[places[first][0] : places[last][1]].decode(errors="replace"))
        hits.append({"first": first, "last": last, "start": start, "end": end})
    return len(words), hits, sorted(items)


#: Automata that a worker keeps, by the identity of their broadcast patterns.
_BUILT: dict[int, tuple] = {}


def _built(patterns) -> tuple:
    key = id(patterns)
    if key not in _BUILT:
        if len(_BUILT) >= 4:
            _BUILT.clear()
        _BUILT[key] = (patterns, automaton_of(patterns))
    return _BUILT[key]


def _blocks(benchmark: DataFrame, block_bytes: int):
    """The items in blocks of about `block_bytes`, each small enough for the driver and a broadcast."""
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), F.col("text").cast("string").alias("text"))
    total = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    count = max(1, -(-total // block_bytes))
    dealt = items if count == 1 else checkpointed(items.withColumn("block", F.pmod(F.xxhash64("item_id", "text"), F.lit(count))))
    for block in range(count):
        here = dealt if count == 1 else dealt.where(F.col("block") == block)
        yield [tuple(r) for r in here.select("item_id", "text").collect()]


def _scan_block(docs: DataFrame, rows, window: int) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(patterns_of(rows, window))

    def run(batch: pa.RecordBatch) -> dict:
        patterns, automaton = _built(shared.value)
        made = [scan(t, automaton, patterns) for t in as_binary(batch.column("text"))]
        return {"doc_id": batch.column("doc_id"), "n_words": [m[0] for m in made], "hits": [m[1] for m in made], "items": [m[2] for m in made]}

    return map_text(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, SCHEMA)


def find_contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, n_words, hits (disjoint spans in words and code points), items (ids of the test items found).

    A benchmark of several blocks is worked through block by block: one is on the driver at a time, its scan is written before the
    next begins, and of all but the first only the documents with hits are written."""
    blocks = _blocks(benchmark, block_bytes)
    block, more = next(blocks), next(blocks, None)
    if more is None:
        return _scan_block(docs, block, window)
    keyed = checkpointed(docs.select("doc_id", "text", F.monotonically_increasing_id().alias("row")))
    numbered = keyed.select(F.col("row").alias("doc_id"), "text")
    made = checkpointed(_scan_block(numbered, block, window))
    while more is not None:
        made = made.unionByName(checkpointed(_scan_block(numbered, more, window).where("size(hits) > 0")))
        more = next(blocks, None)
    joined = made.groupBy("doc_id").agg(F.max("n_words").alias("n_words"), F.flatten(F.collect_list("hits")).alias("hits"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))

    def union(batch: pa.RecordBatch) -> dict:
        out = []
        for hits in batch.column("hits").to_pylist():
            text = {(h["first"], "a"): h["start"] for h in hits} | {(h["last"], "b"): h["end"] for h in hits}
            out.append([{"first": a, "last": b, "start": text[a, "a"], "end": text[b, "b"]} for a, b in merged([(h["first"], h["last"]) for h in hits])])
        return {k: batch.column(k) for k in ("doc_id", "n_words", "items")} | {"hits": out}

    whole = map_text(joined.withColumn("text", F.lit("")), union, SCHEMA)
    return keyed.select("row", F.col("doc_id").cast("long").alias("own_id")).join(whole.withColumnRenamed("doc_id", "row"), "row").select(F.col("own_id").alias("doc_id"), "n_words", "hits", "items")


def _free_of(shared):
    """Whether a text holds no pattern; the scan ends at the first one."""

    @F.pandas_udf("boolean")
    def free(texts: pd.Series) -> pd.Series:
        patterns, automaton = _built(shared.value)
        return texts.map(lambda t: not patterns or next(automaton.iter(f" {b' '.join(words_of((t or '').encode())).decode('latin-1')} "), None) is None).astype(bool)

    return free


def decontaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The documents, with all their columns, in which no test item window occurs: a filter on each row's own text."""
    workers_can_import(docs.sparkSession)
    for rows in _blocks(benchmark, block_bytes):
        shared = docs.sparkSession.sparkContext.broadcast(patterns_of(rows, window))
        docs = docs.where(_free_of(shared)(F.col("text").cast("string")))
    return docs
