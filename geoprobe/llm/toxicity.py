"""Toxicity after noisy-channel deobfuscation.

A character trigram model is counted over all documents. A token that looks disguised (letters mixed with digits or
signs, letters repeated three times or more) becomes a lattice of readings, and Viterbi decoding under the model picks
the likeliest restored word. Three or more single characters in a row, spaced out, are one lattice in which every gap is
nothing or a word break. The restored text is scored by logistic regression on the presence of words and word
beginnings, fitted on a bounded sample of labelled rows.

Null and empty texts score the intercept (the share of toxic labels); without labelled rows, or with one class only,
the score is that share; null labels are never learned; repeated rows are treated alike; other columns are ignored.
"""

from __future__ import annotations

import math
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SLICE_BYTES, checkpointed, held_out, map_text, slices, swept, tables_written, workers_can_import

#: At most about so many labelled rows of each class are learned from, chosen by a hash of their id.
SAMPLE_PER_CLASS = 2000
#: Sample documents that must hold a feature, and the log-likelihood gain that it must bring.
LEAST_SUPPORT, LEAST_GAIN = 3, 6.0
BEGINNINGS = (3, 4, 5, 6, 7)
CUTOFF, PENALTY, STEPS = 0.3, 1e-4, 600
#: Distinct tokens whose restored form and features a worker remembers.
REMEMBERED = 100_000

#: The model's letters, and which letters a sign can stand for.
LETTERS = "abcdefghijklmnopqrstuvwxyzäöüßáéíóúñàâèêëîïôùûçœæ"
LEET = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "*": "aeiou", "€": "e", "£": "l"}
JOINTS = set(".-_~'*")

_CODE = {c: i + 1 for i, c in enumerate(LETTERS)}
SIGNS = len(LETTERS) + 2
_OTHER = SIGNS - 1
#: Three or more single characters (letters, digits or signs that stand for letters) with gaps between them, and one gap.
_SINGLE, _GAP = r"[^\W_@$!|+€£]|[@$!|+€£]", r"[\s.\-_*]{1,3}"
_SPACED = re.compile(rf"(?<![\w'’@$!|+€£])(?:(?:{_SINGLE}){_GAP}){{2,}}(?:{_SINGLE})(?![\w'’@$|+€£])")
_SPLIT = re.compile(rf"({_GAP})")
#: What a word break costs in a gap, and what no break costs in a gap wider than the narrowest of its run.
BREAK, WIDE = 2.0, 4.0
#: Readings of a run that are scored at most, and how much less likely than the best (in log) they may be: letters alone
#: don't always tell where a word ends. The one word, and it after a one-letter word, are scored as well.
READINGS, CLOSE = 16, 10.0
_PLAIN = re.compile(r"[^\W\d_]+")
_TRIPLE = re.compile(r"(.)\1\1")
_EDGE = re.compile(r"^[^\w@$!|+*€£]+|[^\w@$!|+*€£]+$")
#: Where letters alone don't tell: signs at an edge that are hardly punctuation, doubled digits and signs.
_OPEN = re.compile(r"^[@$!|€£]|[@$|€£]$|([013457-9@$!|€£])\1")
_SIGNS_AT_EDGE = re.compile(r"^[@$!|+*€£]+|[@$!|+*€£]+$")
#: What a token is cut at: signs and digits that stand for no letter.
_CUT = re.compile(r"[^\w@$!|+*€£.\-~']+|[^\D0134-57-9]+")
#: What signs cost as nothing at the start and at the end of a token (others ONLY), and what they cost more as letters at
#: its end.
START, END, ONLY, MORE = {"*": 0.0, "+": 1.0, "|": 1.0}, {"!": 0.0, "*": 0.0, "+": 1.0, "|": 1.0}, 6.0, {"!": 3.0, "*": 3.0}


def _table() -> np.ndarray:
    out = np.zeros(0x110000, np.uint8)
    for c, i in _CODE.items():
        out[ord(c)] = i
    out[[i for i in range(0x370, 0x3000) if chr(i).isalpha()]] = _OTHER
    return out


def trigram_counts(docs: DataFrame) -> DataFrame:
    """gram (three sign numbers in base SIGNS), n: over all texts. A task sums its own batches and emits each gram once."""
    workers_can_import(docs.sparkSession)

    def run(batches):
        table, total = _table(), np.zeros(SIGNS**3, np.int64)
        for batch in batches:
            for part in slices(batch, "text", SLICE_BYTES):
                text = "\n".join(x for x in part.column("text").to_pylist() if x).lower()
                signs = table[np.frombuffer(f"\n{text}\n".encode("utf-32-le", "replace"), np.uint32)].astype(np.int64)
                if len(signs) > 2:
                    grams = (signs[:-2] * SIGNS + signs[1:-1]) * SIGNS + signs[2:]
                    total += np.bincount(grams, minlength=SIGNS**3)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["gram", "n"])

    counted = docs.select(F.col("text").cast("string").alias("text")).mapInArrow(run, "gram long, n long")
    return counted.groupBy("gram").agg(F.sum("n").alias("n"))


class LetterModel:
    """Interpolated log probabilities of the next sign after two."""

    def __init__(self, grams: list[tuple[int, int]]):
        three = np.zeros(SIGNS**3)
        for gram, n in grams:
            three[gram] = n
        three = three.reshape(SIGNS, SIGNS, SIGNS)
        two, one = three.sum(axis=0), three.sum(axis=(0, 1))
        flat = (one + 1) / (one.sum() + SIGNS)
        mid = (two + 20 * flat) / (two.sum(axis=1, keepdims=True) + 20)
        self.log = np.log((three + 20 * mid[None]) / (three.sum(axis=2, keepdims=True) + 20)).tolist()


def readings(token: str) -> list[list[tuple[str, float]]]:
    """The lattice: for each run of equal characters, what it may stand for and at what cost."""
    out, i = [], 0
    while i < len(token):
        j = i
        while j < len(token) and token[j] == token[i]:
            j += 1
        c, run = token[i], j - i
        options: list[tuple[str, float]] = []
        for x in [c] if c in _CODE else LEET.get(c, ""):
            cost = 0.0 if c in _CODE else 1.0
            options.append((x, cost if run == 1 else cost + 1.0 if run > 2 else cost + 2.0))
            if run > 1:
                options.append((x + x, cost if run == 2 else cost + 1.5))
        if c in JOINTS or c in LEET and not c.isdigit():
            options.append(("", 2.0 if c in JOINTS else 6.0))
        if not options:
            options = [(c, 0.0)]
        out.append(options)
        i = j
    return out


def likeliest(lattice: list[list[tuple[str, float]]], model: LetterModel, most: int = 1) -> list[str]:
    """The likeliest texts through a lattice, at most so many, the best first; constant work for each position."""
    log = model.log
    best: dict[tuple[int, int], list[tuple[float, tuple]]] = {(0, 0): [(0.0, ())]}
    for options in lattice:
        after: dict[tuple[int, int], list[tuple[float, tuple]]] = {}
        for (a, b), paths in best.items():
            for text, cost in options:
                x, y, value = a, b, -cost
                for c in text:
                    k = 0 if c == " " else _CODE.get(c, _OTHER)
                    value += log[x][y][k]
                    x, y = y, k
                made = [(score + value, (path, text) if text else path) for score, path in paths]
                if (had := after.get((x, y))) is None:
                    after[x, y] = made
                elif most == 1:
                    if made[0][0] > had[0][0]:
                        after[x, y] = made
                else:
                    after[x, y] = sorted(had + made, key=lambda r: -r[0])[:most]
        best = after
    ends = sorted(((s + log[a][b][0], p) for (a, b), paths in best.items() for s, p in paths), key=lambda r: -r[0])[:most]
    out = []
    for score, path in ends:
        parts: list[str] = []
        if score >= ends[0][0] - CLOSE:
            while path:
                path, text = path
                parts.append(text)
            out.append("".join(reversed(parts)))
    return out


def decode(token: str, model: LetterModel) -> str:
    """The likeliest word through the lattice of a token."""
    return likeliest(readings(token), model)[0]


def respaced(run: str, model: LetterModel, most: int = 1) -> str:
    """The likeliest words of a run of spaced-out characters; for more than one reading, the different words of all."""
    parts = _SPLIT.split(run)
    narrow = min(map(len, parts[1::2]))

    def lattice(first: list[str], later: list[str]) -> list[list[tuple[str, float]]]:
        out = readings(parts[0])
        for i in range(1, len(parts), 2):
            open_ = first if i == 1 else later
            out += [[(x, BREAK if x else 0.0) for x in open_] if len(parts[i]) == narrow else [("", WIDE), (" ", 0.0)], *readings(parts[i + 1])]
        return out

    texts = likeliest(lattice(["", " "], ["", " "]), model, most)
    if most == 1:
        return " ".join(texts[0].split())
    texts += likeliest(lattice([""], [""]), model) + likeliest(lattice([" "], [""]), model)
    return " ".join(dict.fromkeys(w for x in texts for w in x.split()))


def decoded(part: str, model: LetterModel, most: int = 1) -> list[str]:
    """Readings of a part of a token, decoded if it looks disguised; signs at its edges are letters or nothing. Only where
    letters alone don't tell, there are more than one."""
    part = part.strip(".-_~'")
    if _PLAIN.fullmatch(part) and not _TRIPLE.search(part):
        return [part]
    if not any(c.isalpha() for c in part):
        # Without a letter: a number, punctuation, or signs of several kinds that may spell a word.
        if any(c.isalnum() for c in part) or len(set(part) & set("@$€£")) < 2:
            return []
    lattice, at = readings(part), 0
    for i, options in enumerate(lattice):
        c = part[at]
        while at < len(part) and part[at] == c:
            at += 1
        if i in (0, len(lattice) - 1) and c in LEET and not c.isdigit():
            more, none = (MORE.get(c, 0.0), END.get(c, ONLY)) if i else (0.0, START.get(c, ONLY))
            lattice[i] = [(x, cost + more) for x, cost in options if x] + [("", none)]
    return likeliest(lattice, model, most if _OPEN.search(part) else 1)


def restored(token: str, model: LetterModel, most: int = 1) -> str:
    """A lower-case token as plain letters: as it is, stripped of signs at its edges, or decoded if it looks disguised. Other
    characters cut it into words, each decoded on its own; for more than one reading, the words of all."""
    core = _EDGE.sub("", token)
    if not core or (_PLAIN.fullmatch(core) and not _TRIPLE.search(core)):
        return core
    words = [w for x in _CUT.split(core) if x for w in decoded(x, model, most) if w]
    if words or not any(c.isalnum() for c in core):
        return " ".join(words)
    return _SIGNS_AT_EDGE.sub("", core)


def joined(text: str, model: LetterModel | None = None, most: int = 1) -> str:
    """Lower-case text with spaced-out words (`a b c d`) put together; the model chooses where words end."""
    return _SPACED.sub(lambda m: respaced(m[0], model, most) if model else _SPLIT.sub("", m[0]), text.lower())


def features_of(word: str) -> list[int]:
    """Numbers (checksums) of the word and its beginnings."""
    return [zlib.crc32(word.encode()), *(zlib.crc32(f"^{word[:n]}".encode()) for n in BEGINNINGS if len(word) > n)]


class Scorer:
    """Letter model, feature weights and intercept; remembers what each token adds."""

    def __init__(self, letters: LetterModel, weights: dict[int, float], intercept: float):
        self.letters, self.weights, self.intercept = letters, weights, intercept
        self.names = sorted(weights)
        self.number = {x: i for i, x in enumerate(self.names)}
        self.values = [weights[x] for x in self.names]
        self.known: dict[str, tuple[int, ...]] = {}

    def __getstate__(self):
        return self.__dict__ | {"known": {}}

    def hits(self, token: str) -> tuple[int, ...]:
        if (got := self.known.get(token)) is None:
            word = restored(token, self.letters, READINGS)
            got = tuple(i for w in word.split() for x in features_of(w) if (i := self.number.get(x)) is not None)
            if len(self.known) >= REMEMBERED:
                self.known.clear()
            self.known[token] = got
        return got

    def score(self, text: str) -> float:
        present: set[int] = set()
        known, full = self.known, self.hits
        for token in set(joined(text, self.letters, READINGS).split()):
            if (got := known.get(token)) is None:
                got = full(token)
            if got:
                present.update(got)
        value = self.intercept + sum(self.values[i] for i in sorted(present))
        return 1 / (1 + math.exp(-max(-500.0, min(500.0, value))))


def _largest(x: np.ndarray) -> float:
    """Largest eigenvalue of x'x, by power iteration."""
    v = np.ones(x.shape[1], np.float32)
    for _ in range(20):
        v = x.T @ (x @ v)
        size = float(np.linalg.norm(v))
        v /= size or 1
    return size * 1.05


def _solved(x: np.ndarray, labels: np.ndarray, share: float) -> tuple[np.ndarray, float]:
    """Weights and intercept of a logistic regression; the intercept is moved from the sample's share of toxic rows to the
    labels' own."""
    base = math.log((share + 1e-6) / (1 - share + 1e-6))
    if not len(labels) or labels.min() == labels.max():
        return np.zeros(x.shape[1]), base
    w = np.zeros(x.shape[1] + 1)
    x = np.hstack([x, np.ones((len(x), 1), np.float32)])
    step = 1 / (0.25 * _largest(x) / len(x) + PENALTY)
    ahead, was = w.copy(), w
    for turn in range(STEPS):
        p = 1 / (1 + np.exp(-np.clip(x @ ahead.astype(np.float32), -30, 30)))
        slope = x.T @ ((p - labels) / len(x)).astype(np.float32) + PENALTY * np.append(ahead[:-1], 0)
        was, w = w, ahead - step * slope
        ahead = w + turn / (turn + 3) * (w - was)
    return w[:-1], float(w[-1]) + base - math.log(labels.sum() / (len(labels) - labels.sum()))


def _gain(with_one, with_zero, ones: int, zeros: int):
    """Log-likelihood that knowing a feature brings, from the toxic and the other sample rows that hold it."""
    p, q, r = (with_one + 0.5) / (ones + 1), (with_zero + 0.5) / (zeros + 1), (with_one + with_zero + 0.5) / (ones + zeros + 1)
    return with_one * F.log(p / r) + with_zero * F.log(q / r) + (ones - with_one) * F.log((1 - p) / (1 - r)) + (zeros - with_zero) * F.log((1 - q) / (1 - r))


def fit(docs: DataFrame, labels: DataFrame, per_class: int = SAMPLE_PER_CLASS) -> Scorer:
    """Learn from labelled rows outside the test fold; the letter model counts every document. The sample's texts become
    numbers of features where they are; the driver gets the features that tell the classes apart and which rows hold them."""
    spark = docs.sparkSession
    letters = LetterModel([tuple(r) for r in trigram_counts(docs).collect()])
    told = labels.where("toxic is not null").select(F.col("doc_id").alias("label_id"), F.col("toxic").cast("int").alias("toxic")).where(~held_out(F.col("label_id")))
    sizes = {r["toxic"]: r["n"] for r in told.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    share = sizes.get(1, 0) / max(1, sum(sizes.values()))
    chance = F.pmod(F.xxhash64("label_id"), F.lit(1 << 30)) / float(1 << 30)
    some = told.where(chance < F.when(F.col("toxic") == 1, per_class / max(1, sizes.get(1, 0))).otherwise(per_class / max(1, sizes.get(0, 0))))
    # The sample has about 2 x per_class rows whatever the input, so it is broadcast and the documents stay where they are.
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    rows = texts.join(F.broadcast(some), F.col("label_id") == F.col("doc_id")).select("doc_id", "text", "toxic")
    shared = spark.sparkContext.broadcast(letters)

    def bags(batch: pa.RecordBatch) -> dict:
        out = []
        for text in batch.column("text").to_pylist():
            words = {w for t in set(joined(text or "", shared.value, READINGS).split()) for w in restored(t, shared.value, READINGS).split()}
            out.append(sorted({f for w in words for f in features_of(w)}))
        return {"doc_id": batch.column("doc_id"), "toxic": batch.column("toxic"), "held": out}

    mark = tables_written()
    held = checkpointed(map_text(rows.repartition(spark.sparkContext.defaultParallelism), bags, "doc_id long, toxic int, held array<long>"))
    ones, zeros = held.agg(F.count_if(F.col("toxic") == 1), F.count_if(F.col("toxic") != 1)).first()
    scorer = Scorer(letters, {}, _solved(np.zeros((0, 0), np.float32), np.zeros(0), share)[1])
    if ones and zeros:
        each = held.select(F.explode("held").alias("feature"), (F.col("toxic") == 1).alias("one")).groupBy("feature").agg(F.count_if("one").alias("with_one"), F.count_if(~F.col("one")).alias("with_zero"))
        telling = each.where((F.col("with_one") + F.col("with_zero") >= LEAST_SUPPORT) & (_gain(F.col("with_one"), F.col("with_zero"), ones, zeros) >= LEAST_GAIN))
        chosen = np.array(sorted(r["feature"] for r in telling.select("feature").collect()), np.int64)
        kept = F.array_intersect("held", F.lit(chosen.tolist()) if len(chosen) else F.array().cast("array<long>"))
        found = sorted((r["doc_id"], r["toxic"], tuple(sorted(r["held"]))) for r in held.select("doc_id", "toxic", kept.alias("held")).collect())
        x = np.zeros((len(found), len(chosen)), np.float32)
        for row, (_, _, own) in zip(x, found, strict=True):
            row[np.searchsorted(chosen, np.array(own, np.int64))] = 1
        weights, intercept = _solved(x, np.array([float(y == 1) for _, y, _ in found]), share)
        scorer = Scorer(letters, dict(zip(chosen.tolist(), weights.tolist(), strict=True)), intercept)
    swept(None, mark)
    return scorer


def scored(docs: DataFrame, model: Scorer) -> DataFrame:
    """doc_id, score of every whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batch: pa.RecordBatch) -> dict:
        return {"doc_id": batch.column("doc_id"), "score": [shared.value.score(t or "") for t in batch.column("text").to_pylist()]}

    return map_text(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), run, "doc_id long, score double")


def restored_texts(docs: DataFrame, model: Scorer) -> DataFrame:
    """doc_id, text with disguised words restored."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batch: pa.RecordBatch) -> dict:
        letters = shared.value.letters
        return {"doc_id": batch.column("doc_id"), "text": [" ".join(restored(t, letters) for t in joined(x or "", letters).split()) for x in batch.column("text").to_pylist()]}

    return map_text(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), run, "doc_id long, text string")


def without_toxic(docs: DataFrame, labels: DataFrame, cutoff: float = CUTOFF) -> DataFrame:
    """The documents, with all their columns, that score under the cutoff."""
    model = fit(docs, labels)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    from pyspark.sql.functions import pandas_udf

    workers_can_import(docs.sparkSession)

    @pandas_udf("double")
    def score(texts):
        return texts.map(lambda t: shared.value.score(t or ""))

    return docs.where(score(F.col("text").cast("string")) < cutoff)
