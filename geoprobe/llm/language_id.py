"""Language identification with a blended n-gram presence kernel, Nystroem landmarks and ridge regression.

Texts are lower-cased, everything that isn't a letter counts as one boundary sign. The kernel of two texts sums, over
n = 1, 2, 3, the number of distinct n-grams that they have in common, divided by the root of both set sizes. N-grams are exact (code
points packed into one number), not hashed. Landmarks span the feature space: the kernel of a text with all of them is one product of its
presence row over the landmarks' n-grams with their matrix. One ridge regression per language is solved from sums over a bounded
labelled sample, which executors add up; the driver gets the landmarks' n-grams and the sums, never texts. Scoring is two batched matrix products.

Null texts and texts without a letter are `und` with score 0; labels that are null are never learned; ties go to the
alphabetically first language; with no labelled row everything is `und`; repeated rows are treated alike; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import held_out, map_text, workers_can_import

#: At most about so many labelled rows of each language are learned from, chosen by a hash of their id.
SAMPLE_PER_LANGUAGE = 500
#: Landmarks in all, and of each language at least.
LANDMARKS, LEAST_LANDMARKS = 128, 8
RIDGE, SHARPNESS, GRAMS = 1e-3, 6.0, 3
#: Texts in one matrix product; sample rows that one task adds up.
BATCH, ROWS_PER_TASK = 64, 1000
_LETTERS: list[np.ndarray] = []


def _letters() -> np.ndarray:
    if not _LETTERS:
        _LETTERS.append(np.array([chr(c).isalpha() for c in range(0x110000)]))
    return _LETTERS[0]


def gram_sets(text: str) -> list[np.ndarray]:
    """The sorted distinct n-grams of a text for each n, 21 bits a sign; empty if it has no letter."""
    codes = np.frombuffer(text.lower().encode("utf-32-le", "replace"), np.uint32)
    kept = _letters()[codes]
    if not kept.any():
        return []
    signs = np.zeros(len(codes) + 2, np.int64)
    signs[1:-1] = codes * kept
    out, packed = [], signs
    for n in range(GRAMS):
        packed = packed[:-1] << 21 | signs[n:] if n else packed
        out.append(np.unique(packed))
    return out


class Landmarks:
    """The n-grams of the landmark texts: one sorted vocabulary for each n, and a matrix of scaled presence."""

    def __init__(self, sets: list[list[np.ndarray]]):
        self.grams = [np.unique(np.concatenate([s[n] for s in sets])) if sets else np.zeros(0, np.int64) for n in range(GRAMS)]
        self.starts = np.cumsum([0, *map(len, self.grams)])
        self.matrix = self.presence(sets)

    def presence(self, sets: list[list[np.ndarray]]) -> np.ndarray:
        """A row for each text: which of the landmarks' n-grams it has, each n scaled by the root of its own set size."""
        rows = np.zeros((len(sets), int(self.starts[-1])), np.float32)
        for row, own in zip(rows, sets, strict=True):
            for grams, start, vocabulary in zip(own, self.starts, self.grams, strict=False):
                if not len(vocabulary):
                    continue
                at = np.minimum(np.searchsorted(vocabulary, grams), len(vocabulary) - 1)
                row[start + at[vocabulary[at] == grams]] = len(grams) ** -0.5
        return rows

    def kernel(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Kernel values of every text with every landmark, and whether the text has a letter."""
        sets = [gram_sets(t) for t in texts]
        return (self.presence(sets) @ self.matrix.T).astype(np.float64), np.array([bool(s) for s in sets], bool)


class Classifier:
    """Landmarks and one weight column per language."""

    def __init__(self, languages: list[str], landmarks: Landmarks, weights: np.ndarray):
        self.languages, self.landmarks, self.weights = languages, landmarks, weights

    @classmethod
    def solved(cls, languages: list[str], landmarks: Landmarks, square: np.ndarray, target: np.ndarray) -> Classifier:
        among = (landmarks.matrix @ landmarks.matrix.T).astype(np.float64)
        return cls(languages, landmarks, np.linalg.lstsq(square + RIDGE * among + 1e-8 * np.eye(len(among)), target, rcond=None)[0])

    def predict(self, texts: list[str]) -> tuple[list[str], list[float]]:
        names, scores = [], []
        for i in range(0, len(texts), BATCH):
            rows, known = self.landmarks.kernel(texts[i : i + BATCH])
            if not self.languages:
                known[:] = False
            else:
                value = rows @ self.weights
                share = np.exp(SHARPNESS / 2 * (value - value.max(axis=1, keepdims=True)))
                share /= share.sum(axis=1, keepdims=True)
            for j, k in enumerate(known):
                best = int(np.argmax(value[j])) if k else -1
                names.append(self.languages[best] if k else "und")
                scores.append(float(share[j, best]) if k else 0.0)
        return names, scores


def labelled_sample(docs: DataFrame, per_language: int) -> tuple[DataFrame, dict[str, int]]:
    """doc_id, text, label, u of about `per_language` rows of every label outside the test fold, the same rows at any
    partitioning, and the rows that each label has."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("label"))
    rows = rows.where(F.col("label").isNotNull() & F.col("text").rlike(r"\p{L}") & ~held_out(F.col("doc_id")))
    counts = rows.groupBy("label").agg(F.count("*").alias("n"))
    sizes = {r["label"]: r["n"] for r in counts.collect()}  # a row per language
    chance = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / float(1 << 30)
    shares = F.create_map(*(F.lit(x) for label, n in sizes.items() for x in (label, per_language / n))) if sizes else None
    picked = rows.withColumn("u", chance)
    return (picked.where(F.col("u") < F.element_at(shares, F.col("label"))) if sizes else picked.where(F.lit(False))), sizes


def fit(docs: DataFrame, per_language: int = SAMPLE_PER_LANGUAGE) -> Classifier:
    """Learn from the labelled rows outside the test fold."""
    spark = docs.sparkSession
    workers_can_import(spark)
    sample, sizes = labelled_sample(docs, per_language)
    languages = sorted(sizes)
    if not languages:
        return Classifier([], Landmarks([]), np.zeros((0, 0)))
    # The sample is dealt by id, so that sums are made in the same order at any partitioning of the input.
    tasks = max(1, len(languages) * per_language // ROWS_PER_TASK)
    sample = sample.repartition(tasks, "doc_id").sortWithinPartitions("doc_id", "text", "label").persist()
    try:
        each = max(LEAST_LANDMARKS, LANDMARKS // len(languages))
        first = sample.withColumn("place", F.row_number().over(Window.partitionBy("label").orderBy("u", "doc_id", "text"))).where(F.col("place") <= each)

        def sets(batch: pa.RecordBatch) -> dict:
            made = [gram_sets(t) for t in batch.column("text").to_pylist()]
            return {"label": batch.column("label"), "place": batch.column("place"), "grams": [[g.tolist() for g in s] for s in made]}

        marks = sorted(map_text(first.select("label", "place", "text"), sets, "label string, place int, grams array<array<long>>").collect())
        landmarks = Landmarks([[np.array(g, np.int64) for g in r["grams"]] for r in marks if r["grams"]])
        seen = dict(sample.groupBy("label").agg(F.count("*").alias("n")).collect())
        shared = spark.sparkContext.broadcast(landmarks)
        size, kinds = len(landmarks.matrix), len(languages)

        def run(batches):
            # Every language weighs as much as any other.
            square, target, number, first_id = np.zeros((size, size)), np.zeros((size, kinds)), 0, None
            for batch in batches:
                texts, labels = batch.column("text").to_pylist(), batch.column("label").to_pylist()
                first_id = batch.column("doc_id")[0].as_py() if number == 0 else first_id
                for i in range(0, len(texts), BATCH):
                    rows, known = shared.value.kernel(texts[i : i + BATCH])
                    own = [label for label, k in zip(labels[i : i + BATCH], known, strict=True) if k]
                    rows, weight = rows[known], np.array([1 / seen[x] for x in own])[:, None]
                    goal = np.array([[1.0 if x == y else -1.0 for y in languages] for x in own]).reshape(-1, kinds)
                    square += rows.T @ (rows * weight)
                    target += rows.T @ (goal * weight)
                    number += len(own)
            if number:
                yield pa.RecordBatch.from_arrays([pa.array([first_id], pa.int64()), pa.array([square.tobytes() + target.tobytes()])], names=["first", "sums"])

        sums = sorted((r["first"] is not None, r["first"] or 0, bytes(r["sums"])) for r in sample.select("doc_id", "text", "label").mapInArrow(run, "first long, sums binary").collect())
    finally:
        sample.unpersist()
    total = sum((np.frombuffer(s, np.float64) for _, _, s in sums), np.zeros(size * (size + kinds)))
    return Classifier.solved(languages, landmarks, total[: size * size].reshape(size, size), total[size * size :].reshape(size, kinds))


def identified(docs: DataFrame, model: Classifier) -> DataFrame:
    """doc_id, lang_pred, score of every whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batch: pa.RecordBatch) -> dict:
        names, scores = shared.value.predict([t or "" for t in batch.column("text").to_pylist()])
        return {"doc_id": batch.column("doc_id"), "lang_pred": names, "score": scores}

    return map_text(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), run, "doc_id long, lang_pred string, score double")
