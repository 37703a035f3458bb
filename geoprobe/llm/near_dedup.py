"""Near-duplicate groups from SetSketch registers, banded, estimated by likelihood and verified on whole shingle sets.

A document's set holds its distinct 5-word shingles (A-Z lower-cased; fewer than five words: the sequence as one). Each
of 128 registers keeps the truncated, exponentially spaced minimum of the set's hashed values; registers merge by
maximum and agree with a probability close to the similarity. Four registers make one of 32 band values; a pair at the threshold
misses all bands with a probability of about 5e-6.

Documents with equal sets are one class, found by aggregation. Between classes, candidates share a band value. They are
not paired all with all: in each of a few rounds every document of a bucket is compared with one pivot of its bucket,
verified links are merged into components, and only buckets that still span several components go on. What is left
(near copies of one text that are mostly just under the threshold) is compared block by block: documents that hang
together through such buckets are dealt into blocks of bounded bytes, a task gets two blocks with their whole sets and compares, in memory,
the documents of different components that share a band value; a link found there joins its components for the rest of the task. A set is copied once for each block of its
group: BLOCKS times, or once for every BLOCK_BYTES of the group if that is more. Pairs are never rows, and no link is lost.
A comparison first estimates the similarity from both sketches by maximum likelihood and skips pairs more than
`SLACK` under the threshold (five standard errors); the rest is decided on the whole sets.

Null, empty or word-less texts have an empty set and are linked with nothing; rows with a null doc_id are linked with
nothing and kept; repeated rows (same doc_id) share their result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.graphs import connected
from .common import as_binary, checkpointed, map_text, swept, tables_written, unused
from .words import Powers, hashed, mix, odd_constants, runs_of, split_words

SHINGLE, THRESHOLD = 5, 75
BANDS, ROWS = 32, 4
REGISTERS = BANDS * ROWS
#: SetSketch parameters: base, rate, largest register value.
BASE, RATE, TOP = 1.001, 20.0, (1 << 16) - 2
SLACK = 0.2
#: Partners that are compared with one copy of a pivot's set; rounds of pivots before the comparison in blocks.
BATCH, PIVOT_ROUNDS = 64, 2
#: A group is dealt into BLOCKS blocks, of at least and at most so many bytes of sets.
BLOCKS, BLOCK_LEAST, BLOCK_BYTES = 20, 128 << 10, 16 << 20

_SHINGLE = odd_constants(SHINGLE, 5)
_TIMES, _PLUS = odd_constants(REGISTERS, 7), odd_constants(REGISTERS, 11)
_BAND = mix(odd_constants(BANDS, 13))
_SHORT = Powers(0x9FB21C651E98DF25)


def shingle_sets(texts: list[bytes]) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    flat, ends = hashed(split_words([t.lower() for t in texts]))
    runs = runs_of(flat, SHINGLE, _SHINGLE)
    out = []
    for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
        if b - a >= SHINGLE:
            out.append(np.unique(runs[a : b - SHINGLE + 1]))
        else:
            out.append(_SHORT.stretches(flat[a:b], np.array([0]), np.array([b - a])) if b > a else np.zeros(0, np.uint64))
    return out


def sketches(sets: list[np.ndarray]) -> np.ndarray:
    """Registers (one row a set) of non-empty sets."""
    out = np.empty((len(sets), REGISTERS), np.uint16)
    if not sets:
        return out
    flat = np.concatenate(sets)
    starts = np.cumsum([0, *(len(s) for s in sets[:-1])])
    lows, room = np.empty((REGISTERS, len(sets)), np.uint64), np.empty_like(flat)
    for i in range(REGISTERS):
        np.multiply(flat, _TIMES[i], out=room)
        np.add(room, _PLUS[i], out=room)
        lows[i] = np.minimum.reduceat(room, starts)
    spaced = -np.log1p(-np.minimum(lows / 2.0**64, 1 - 2.0**-53)) / RATE
    level = np.floor(1 - np.log(np.maximum(spaced, 1e-300)) / np.log(BASE))
    return np.clip(level, 0, TOP + 1).astype(np.uint16).T


def merged_sketch(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The sketch of the union of two sets."""
    return np.maximum(a, b)


def band_values(registers: np.ndarray) -> np.ndarray:
    packed = np.zeros((len(registers), BANDS), np.uint64)
    parts = registers.reshape(-1, BANDS, ROWS).astype(np.uint64)
    for j in range(ROWS):
        packed |= parts[:, :, j] << np.uint64(16 * j)
    return mix(packed ^ _BAND).view(np.int64)


_GRID = np.linspace(0, 1, 201)


def likely_similarity(a: np.ndarray, b: np.ndarray, n_a: int, n_b: int) -> float:
    """The similarity that makes the observed register order (greater, smaller, equal) likeliest, sizes given."""
    u, v = n_a / (n_a + n_b), n_b / (n_a + n_b)
    more, less = int((a > b).sum()), int((a < b).sum())
    grid = _GRID * min(u / v, v / u)
    chance = lambda x: -np.log1p(-x * (BASE - 1) / BASE) / np.log(BASE)
    up, down = chance(u - v * grid), chance(v - u * grid)
    tiny = 1e-12
    value = more * np.log(up + tiny) + less * np.log(down + tiny) + (len(a) - more - less) * np.log(np.maximum(1 - up - down, tiny))
    return float(grid[int(np.argmax(value))])


def _signatures(docs: DataFrame) -> DataFrame:
    def run(batch: pa.RecordBatch) -> dict:
        sets = shingle_sets(as_binary(batch.column("text")))
        full = [i for i, s in enumerate(sets) if len(s)]
        bands = [None] * len(sets)
        a, b = np.zeros(len(sets), np.uint64), np.zeros(len(sets), np.uint64)
        for i, row in zip(full, band_values(sketches([sets[i] for i in full])), strict=True):
            bands[i] = row
            a[i], b[i] = mix(sets[i]).sum(dtype=np.uint64), mix(sets[i] ^ _BAND[0]).sum(dtype=np.uint64)
        return {"doc_id": batch.column("doc_id"), "n_shingles": [len(s) for s in sets], "set_a": a.view(np.int64), "set_b": b.view(np.int64), "bands": bands}

    return map_text(docs, run, "doc_id long, n_shingles long, set_a long, set_b long, bands array<long>")


def _whole_sets(docs: DataFrame) -> DataFrame:
    def run(batch: pa.RecordBatch) -> dict:
        sets = shingle_sets(as_binary(batch.column("text")))
        return {"doc_id": batch.column("doc_id"), "registers": [r.tobytes() for r in sketches(sets)], "shingles": [s.tobytes() for s in sets]}

    return map_text(docs, run, "doc_id long, registers binary, shingles binary")


def linked(a: np.ndarray, b: np.ndarray, threshold: int) -> bool:
    common = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * common >= threshold * (len(a) + len(b) - common)


def likely(a: tuple, b: tuple, threshold: int) -> bool:
    """Whether the sketches of two (registers, set) leave a link possible."""
    return likely_similarity(a[0], b[0], len(a[1]), len(b[1])) >= threshold / 100 - SLACK


def verified(pairs: DataFrame, sets: DataFrame, threshold: int) -> DataFrame:
    """The pairs (doc_id, pivot) that are similar enough, as links (a, b). A pivot's set is sent once for each BATCH of
    partners, so neither a popular pivot nor its partners meet in one task."""
    parts = checkpointed(pairs.groupBy("pivot").agg(F.ceil(F.count("*") / BATCH).cast("int").alias("parts")).withColumnRenamed("pivot", "p"))
    partners = pairs.join(parts, F.col("pivot") == F.col("p")).select(F.col("p").alias("pivot"), F.pmod(F.xxhash64("doc_id"), F.col("parts")).cast("int").alias("part"), F.lit(1).alias("kind"), F.col("doc_id").alias("needed"))
    pivots = parts.select(F.col("p").alias("pivot"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(0).alias("kind"), F.col("p").alias("needed"))
    filled = partners.unionByName(pivots).join(sets, F.col("needed") == F.col("doc_id")).select("pivot", "part", "kind", "needed", "registers", "shingles")
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(batches):
        own = None
        for batch in batches:
            found = []
            for pivot, kind, doc, registers, shingles in zip(*(batch.column(c).to_pylist() for c in ("pivot", "kind", "needed", "registers", "shingles")), strict=True):
                here = np.frombuffer(registers, np.uint16), np.frombuffer(shingles, np.uint64)
                if kind == 0:
                    own = here
                elif likely(own, here, threshold) and linked(own[1], here[1], threshold):
                    found.append((pivot, doc))
            yield pa.RecordBatch.from_arrays([pa.array([f[i] for f in found], pa.int64()) for i in (0, 1)], schema=schema)

    return filled.repartition("pivot", "part").sortWithinPartitions("pivot", "part", "kind").mapInArrow(run, "a long, b long")


def links_in_blocks(left: list[tuple], right: list[tuple], threshold: int) -> list[tuple[int, int]]:
    """Links between two blocks of (doc_id, label, registers, set) that join all labels which links between documents sharing
    a band value join. One document is compared with the documents of other labels at a time: first with the likeliest of each
    label, then with the rest of the labels that are still apart."""
    if not left or not right:
        return []
    names = {label: i for i, label in enumerate(dict.fromkeys(r[1] for r in left + right))}
    here, labels, ids = np.array([names[r[1]] for r in left]), np.array([names[r[1]] for r in right]), np.array([r[0] for r in right])
    bands, own = band_values(np.stack([r[2] for r in right])), band_values(np.stack([r[2] for r in left]))
    registers, sizes = np.stack([r[2] for r in right]), np.array([len(r[3]) for r in right])
    out = []

    def verified_ones(one: tuple, some: np.ndarray) -> np.ndarray:
        flat = np.concatenate([right[j][3] for j in some])
        at = np.minimum(np.searchsorted(one[3], flat), len(one[3]) - 1)
        common = np.add.reduceat((one[3][at] == flat).astype(np.int64), np.cumsum([0, *sizes[some[:-1]]]))
        return some[100 * common >= threshold * (len(one[3]) + sizes[some] - common)]

    for i, (one, values) in enumerate(zip(left, own, strict=True)):
        size = len(one[3])
        possible = np.flatnonzero((labels != here[i]) & (100 * np.minimum(sizes, size) >= threshold * np.maximum(sizes, size)))
        possible = possible[(bands[possible] == values).any(axis=1)]
        if left is right:
            possible = possible[ids[possible] > one[0]]
        same = (registers[possible] == one[2]).sum(axis=1)
        # The exact likelihood is only worked out where the plain share of equal registers is low.
        fit = np.array([n >= 0.7 * REGISTERS or likely(one[2:], right[j][2:], threshold) for j, n in zip(possible.tolist(), same.tolist(), strict=True)], bool)
        possible, same = possible[fit], same[fit]
        order = np.argsort(-same, kind="stable")
        possible = possible[order]
        best = np.unique(labels[possible], return_index=True)[1]
        for some in (possible[np.sort(best)], np.delete(possible, best)):
            some = some[labels[some] != here[i]]
            for j in verified_ones(one, some).tolist() if len(some) else ():
                if (old := labels[j]) != here[i]:
                    out.append((one[0], right[j][0]))
                    labels[labels == old] = here[i]
                    here[here == old] = here[i]
    return out


def _block_links(here: DataFrame, sets: DataFrame, threshold: int) -> DataFrame:
    """Verified links between documents of different labels that share a bucket of `here` (bucket, doc_id, label)."""
    first = checkpointed(here.groupBy(F.col("bucket").alias("bk")).agg(F.min("doc_id").alias("a")))
    groups = connected(here.join(first, F.col("bucket") == F.col("bk")).where("a < doc_id").select("a", F.col("doc_id").alias("b")).distinct())
    weights = sets.select(F.col("doc_id").alias("weighed"), (F.octet_length("shingles") + 2 * REGISTERS).alias("bytes"))
    sizes = groups.join(weights, F.col("node") == F.col("weighed")).groupBy(F.col("label").alias("of")).agg(F.sum("bytes").alias("n"))
    width = F.least(F.greatest(F.col("n") / BLOCKS, F.lit(BLOCK_LEAST)), F.lit(BLOCK_BYTES))
    sizes = checkpointed(sizes.select("of", F.greatest(F.lit(1), F.ceil(F.col("n") / width)).cast("int").alias("blocks")))
    labels = here.select(F.col("doc_id").alias("owner"), F.col("label").alias("own_label")).distinct()
    dealt = checkpointed(groups.join(sizes, F.col("label") == F.col("of")).select(F.col("label").alias("group"), "blocks", F.col("node").alias("member"), F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int").alias("block")))
    full = dealt.join(labels, F.col("member") == F.col("owner")).join(sets, F.col("member") == F.col("doc_id"))
    placed = full.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("group", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "member", "own_label", "registers", "shingles")
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(batches):
        key, left, right = None, [], []

        def settled():
            found = links_in_blocks(left, left if key[1] == key[2] else right, threshold) if key else []
            return [pa.RecordBatch.from_arrays([pa.array([f[i] for f in found], pa.int64()) for i in (0, 1)], schema=schema)] if found else []

        for batch in batches:
            for group, i, j, block, doc, label, registers, shingles in zip(*(batch.column(c).to_pylist() for c in batch.schema.names), strict=True):
                if (group, i, j) != key:
                    yield from settled()
                    key, left, right = (group, i, j), [], []
                (left if block == i else right).append((doc, label, np.frombuffer(registers, np.uint16), np.frombuffer(shingles, np.uint64)))
        yield from settled()

    return placed.repartition("group", "i", "j").sortWithinPartitions("group", "i", "j").mapInArrow(run, "a long, b long")


def _class_links(buckets: DataFrame, sets: DataFrame, threshold: int) -> DataFrame | None:
    """Verified links between the documents of each bucket (bucket, doc_id), complete up to components."""
    links, live = None, buckets.withColumn("label", F.col("doc_id"))
    for step in range(PIVOT_ROUNDS + 1):
        order = F.xxhash64("doc_id", F.lit(step)) if step else F.col("doc_id")
        spans = live.groupBy(F.col("bucket").alias("of")).agg(F.min("label").alias("low"), F.max("label").alias("high"), F.min(F.struct(order.alias("o"), "doc_id", "label")).alias("pick")).where("low < high")
        spans = checkpointed(spans.select("of", F.col("pick.doc_id").alias("pivot"), F.col("pick.label").alias("pivot_label")))
        if spans.isEmpty():
            break
        here = checkpointed(live.join(spans, F.col("bucket") == F.col("of")).select("bucket", "doc_id", "label", "pivot", "pivot_label"))
        if step == PIVOT_ROUNDS:
            found = _block_links(here.select("bucket", "doc_id", "label"), sets, threshold)
        else:
            pairs = here.where("label != pivot_label").groupBy("doc_id").agg(F.min("pivot").alias("pivot"))
            found = verified(checkpointed(pairs), sets, threshold)
        found = checkpointed(found)
        links = found if links is None else links.unionByName(found)
        if step < PIVOT_ROUNDS:
            labels = connected(links)
            live = here.select("bucket", "doc_id").join(labels, F.col("doc_id") == F.col("node"), "left").select("bucket", "doc_id", F.coalesce("label", "doc_id").alias("label"))
            live = checkpointed(live)
    return links


def near_duplicates(docs: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable over links), kept (it is the smallest itself)."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    mark = tables_written()
    signed = checkpointed(_signatures(docs))
    full = signed.where("doc_id is not null and n_shingles > 0")
    classes = checkpointed(full.groupBy("set_a", "set_b").agg(F.min("doc_id").alias("least"), F.count("*").alias("n")).where("n > 1").select(F.col("set_a").alias("a"), F.col("set_b").alias("b"), "least"))
    member = full.join(classes, (F.col("set_a") == F.col("a")) & (F.col("set_b") == F.col("b")), "left").select("doc_id", F.coalesce("least", "doc_id").alias("rep"), "bands")
    member = checkpointed(member)
    banded = member.where("doc_id = rep").select("doc_id", F.explode("bands").alias("bucket"))
    several = checkpointed(banded.groupBy(F.col("bucket").alias("bk")).agg(F.count("*").alias("n")).where("n > 1").select("bk"))
    buckets = checkpointed(banded.join(several, F.col("bucket") == F.col("bk")).select("bucket", "doc_id").distinct())
    wanted = checkpointed(buckets.select(F.col("doc_id").alias("w")).distinct())
    sets = checkpointed(_whole_sets(docs.join(wanted, F.col("doc_id") == F.col("w")).select("doc_id", "text")).dropDuplicates(["doc_id"]))
    links = _class_links(buckets, sets, threshold)
    reach = member.select("doc_id", "rep")
    if links is not None:
        labels = connected(links)
        reach = reach.join(labels, F.col("rep") == F.col("node"), "left").select("doc_id", F.coalesce("label", "rep").alias("rep"))
    reach = reach.select(F.col("doc_id").alias("d"), F.col("rep").alias("component")).distinct()
    out = signed.join(reach, F.col("doc_id") == F.col("d"), "left")
    component = F.coalesce("component", "doc_id")
    return swept(out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept")), mark)


def deduplicated(docs: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """The documents, with all their columns, that represent their group (rows without an id stay)."""
    (name,) = unused(docs, "gone")
    gone = near_duplicates(docs, threshold).where("not kept").select(F.col("doc_id").alias(name)).distinct()
    return docs.join(gone, F.col("doc_id").cast("long") == F.col(name), "left_anti")
