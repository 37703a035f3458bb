"""Alignment of the surrogate encoder, the adaptation strategies over Spark, and fused intervention probing.

Rasters are written once (`rasterised`). Training has three modes:

- `exact`: steps over global batches in a seeded order of the whole epoch, as with one accelerator. All strategies are fitted by one
  job, a task each, on features or images that the task holds in memory, so it is for a bounded training sample (the study draws
  one); the result doesn't depend on partitions. What no step changes (features of frozen encoders, what the last block or the adapters' first block reads) is worked out once.
- `local`: for data of any size. An epoch is one job; each partition takes seeded local steps from the shared weights in the order of its rows' hashes and hands
  back its trainable tensors, which are averaged.
- `sync`: an epoch is one job and one step of the driver on the gradient of all rows (a full-batch step, not one per batch).

In the last two only trainable tensors travel, summed in groups of tasks before they reach the driver."""

from __future__ import annotations

import math
import pickle
import time
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import checkpointed, workers_can_import
from . import encoder as enc
from . import rasters

#: Published rates, and a preset that moves the small surrogate encoder in ten epochs.
PUBLISHED_RATES = {"zero_shot": 0.0, "text_score": 1e-4, "linear": 1e-4, "last_block": 1e-5, "low_rank": 1e-4, "full": 1e-5}
SURROGATE_RATES = {"zero_shot": 0.0, "text_score": 3e-2, "linear": 3e-2, "last_block": 3e-3, "low_rank": 3e-3, "full": 3e-3}


@dataclass
class Config:
    epochs: int = 10
    batch: int = 8
    decay: float = 0.01
    seed: int = 42
    dropout: float = 0.1
    mode: str = "exact"
    precision: str = "full"
    rates: dict | None = None

    def rate(self, strategy: str) -> float:
        return (self.rates or SURROGATE_RATES)[strategy]


def cosine_rate(start: float, epoch: int, t_max: int = 10) -> float:
    """The rate of an epoch on the cosine schedule (0 is the first)."""
    return start * (1 + math.cos(math.pi * epoch / t_max)) / 2


class AdamW:
    """Decoupled weight decay; the tensors are stepped as one flat vector."""

    def __init__(self, decay: float = 0.01, beta1: float = 0.9, beta2: float = 0.999, eps: float = 1e-8):
        self.decay, self.b1, self.b2, self.eps, self.t = decay, beta1, beta2, eps, 0
        self.m = self.v = 0.0

    def step(self, tensors: dict, grads: dict, rate: float) -> dict:
        """The stepped tensors of those that have a gradient, always the same ones."""
        self.t += 1
        g = np.concatenate([np.ravel(x) for x in grads.values()])
        self.m = self.b1 * self.m + (1 - self.b1) * g
        self.v = self.b2 * self.v + (1 - self.b2) * g * g
        move = rate * (self.m / (1 - self.b1**self.t)) / (np.sqrt(self.v / (1 - self.b2**self.t)) + self.eps)
        flat = (np.concatenate([np.ravel(tensors[k]) for k in grads]) * (1 - rate * self.decay) - move).astype(np.float32)
        out, at = {}, 0
        for k, x in grads.items():
            out[k] = flat[at : at + x.size].reshape(x.shape)
            at += x.size
        return out


class LossScale:
    """Dynamic scaling for half-precision gradients: halved on overflow, doubled after a run of clean steps."""

    def __init__(self, scale: float = 65536.0, patience: int = 2000):
        self.scale, self.patience, self.clean = scale, patience, 0

    def update(self, finite: bool) -> bool:
        if not finite:
            self.scale, self.clean = max(1.0, self.scale / 2), 0
            return False
        self.clean += 1
        if self.clean >= self.patience:
            self.scale, self.clean = self.scale * 2, 0
        return True


def halved(model: enc.Model) -> enc.Model:
    """The model with every tensor rounded to half precision, as a mixed-precision forward pass sees it."""
    half = lambda d: {k: v.astype(np.float16).astype(np.float32) for k, v in d.items()}
    return replace(model, encoder=half(model.encoder), extra=half(model.extra))


def mixed_gradients(model: enc.Model, inputs, y, scale: LossScale, dropout: float = 0.0, rng=None):
    """Loss and gradients through half precision: gradients are scaled before they are rounded and unscaled after; None
    if they overflow, which also lowers the scale."""
    loss, grads = halved(model).gradients_prepared(inputs, y, dropout, rng)
    with np.errstate(over="ignore"):
        small = {k: (g * scale.scale).astype(np.float16) for k, g in grads.items()}
    if not scale.update(all(np.isfinite(g).all() for g in small.values())):
        return loss, None
    return loss, {k: g.astype(np.float32) / scale.scale for k, g in small.items()}


def aligned(spark, corpus: DataFrame, ridge: float = 10.0, seed: int = 42) -> dict[str, np.ndarray]:
    """Encoder weights whose projection maps pooled image features of unlabelled texts onto their text features, by ridge
    regression. Partitions add up their moment matrices and emit them once; the sums are aggregated by position, in whole
    2^-24ths, so that their order doesn't matter."""
    workers_can_import(spark)
    weights = enc.initial(seed)
    shared = spark.sparkContext.broadcast(weights)
    d, e = enc.WIDTH, enc.OUT

    def run(batches):
        total = np.zeros((d + 1) * d + d * e + e + 1)
        for batch in batches:
            texts = [t or "" for t in batch.column("text").to_pylist()]
            for i in range(0, len(texts), 64):
                part = texts[i : i + 64]
                pool = enc.forward(shared.value, enc.patches(np.stack([rasters.of_text(t) for t in part])))[1]["pool"].astype(np.float64)
                goal = enc.text_features(part, seed).astype(np.float64)
                total += np.concatenate([(pool.T @ pool).ravel(), pool.sum(axis=0), (pool.T @ goal).ravel(), goal.sum(axis=0), [len(part)]])
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], names=["at", "value"])

    sums = corpus.select("text").mapInArrow(run, "at long, value double").groupBy("at").agg(F.sum(F.floor(F.col("value") * 2**24 + 0.5).cast("decimal(38,0)")).alias("value")).collect()
    flat = np.zeros((d + 1) * d + d * e + e + 1)
    for at, value in sums:
        flat[at] = float(value) / 2**24
    n = max(1.0, flat[-1])
    xx, x, xy, y = flat[: d * d].reshape(d, d), flat[d * d : d * d + d], flat[d * d + d : d * d + d + d * e].reshape(d, e), flat[d * d + d + d * e : -1]
    centred = xx - np.outer(x, x) / n
    weights["proj"] = np.linalg.solve(centred + ridge * np.trace(centred) / d / 1000 * np.eye(d) + 1e-6 * np.eye(d), xy - np.outer(x, y) / n).astype(np.float32)
    # The final normalisation's offset takes the mean out of what is projected.
    weights["bf"] = (weights["bf"] - x / n).astype(np.float32)
    return weights


def _pack(tensors: dict) -> bytes:
    return pickle.dumps({k: v.astype(np.float32) for k, v in tensors.items()})


def rasterised(rows: DataFrame) -> DataFrame:
    """The rows (doc_id, text, y, split) with their 8-bit rasters (column pixels), written once."""
    workers_can_import(rows.sparkSession)

    def run(batches):
        for batch in batches:
            made = [rasters.to_bytes(rasters.of_text(t or "")) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(made, pa.binary())], names=[*batch.schema.names, "pixels"])

    plain = rows.select("doc_id", "text", "y", "split")
    return checkpointed(plain.mapInArrow(run, "doc_id long, text string, y int, split string, pixels binary"))


def _with_pixels(rows: DataFrame) -> DataFrame:
    return rows if "pixels" in rows.columns else rasterised(rows)


def _images(batch: pa.RecordBatch) -> np.ndarray:
    return np.stack([rasters.from_bytes(b) for b in batch.column("pixels").to_pylist()])


def epoch_order(ids: np.ndarray, seed: int, epoch: int) -> np.ndarray:
    """Positions of the ids in the seeded order of an epoch (equal ids by position)."""
    score = np.array([xxhash.xxh3_64_intdigest(f"{seed}|epoch:{epoch}|{i}") for i in ids.tolist()], np.uint64)
    return np.argsort(score, kind="stable")


class Steps:
    """An optimiser with what a step of either precision needs."""

    def __init__(self, config: Config):
        self.config, self.adam, self.scale = config, AdamW(config.decay), LossScale(1024.0)

    def take(self, model: enc.Model, inputs, y, rate: float, rng) -> tuple[enc.Model, float]:
        if self.config.precision == "mixed":
            loss, grads = mixed_gradients(model, inputs, y, self.scale, self.config.dropout, rng)
        else:
            loss, grads = model.gradients_prepared(inputs, y, self.config.dropout, rng)
        return (model if grads is None else model.replaced(self.adam.step({k: model.tensor(k) for k in grads}, grads, rate))), loss


def fit_exact(model: enc.Model, ids: np.ndarray, y: np.ndarray, train: np.ndarray, inputs: np.ndarray, config: Config) -> tuple[enc.Model, list[dict]]:
    """Adapt a model to prepared inputs held in memory: global batches in the seeded order of each epoch; the epoch with the best
    accuracy on the rows that aren't trained on is kept (the earliest of equals)."""
    steps, history, best = Steps(config), [], None
    own, rest = np.flatnonzero(train), np.flatnonzero(~train)
    for epoch in range(config.epochs if len(own) else 0):
        rate, loss, rng = cosine_rate(config.rate(model.strategy), epoch, config.epochs), 0.0, np.random.default_rng([config.seed, epoch])
        order = own[epoch_order(ids[own], config.seed, epoch)]
        for i in range(0, len(order), config.batch):
            some = order[i : i + config.batch]
            model, one = steps.take(model, inputs[some], y[some], rate, rng)
            loss += one * len(some)
        hits = sum(int((model.predict_prepared(inputs[rest[i : i + 256]]) == y[rest[i : i + 256]]).sum()) for i in range(0, len(rest), 256))
        history.append({"strategy": model.strategy, "epoch": epoch, "rate": rate, "train_loss": loss / len(own), "val_acc": hits / len(rest) if len(rest) else 0.0})
        if best is None or history[-1]["val_acc"] > best[0]:
            best = history[-1]["val_acc"], model
    return (best[1] if best else model), history


def trained_together(rows: DataFrame, models: dict[str, enc.Model], config: Config | None = None) -> dict[str, tuple[enc.Model, list[dict], float]]:
    """Every model adapted to the training rows in exact mode: (model, history, seconds) by name. One job deals the rows to a task
    for each model that trains; rows of a frozen encoder travel as features."""
    config, spark = config or Config(), rows.sparkSession
    workers_can_import(spark)
    live = [name for name, m in models.items() if m.trainable()]
    out: dict = {name: (m, [], 0.0) for name, m in models.items() if name not in live}
    if not live:
        return out
    shared = spark.sparkContext.broadcast([models[name] for name in live])
    probe = next((m for m in models.values() if m.strategy in enc.FROZEN), None)
    frozen = [i for i, name in enumerate(live) if models[name].strategy in enc.FROZEN]

    def dealt(batches):
        for batch in batches:
            images = _images(batch)
            for start in range(0, len(images), 64):
                part, cut = images[start : start + 64], batch.slice(start, 64)
                ids, y, train = (cut.column(c).to_pylist() for c in ("doc_id", "y", "split"))
                small = [f.tobytes() for f in probe.prepared(part).astype(np.float32)] if frozen else None
                whole = cut.column("pixels").to_pylist()
                for i in range(len(shared.value)):
                    made = pa.array(small if i in frozen else whole, pa.binary())
                    yield pa.RecordBatch.from_arrays([pa.array([i] * len(ids), pa.int32()), pa.array(ids, pa.int64()), pa.array(y, pa.int32()), pa.array([t == "train" for t in train]), made], names=["number", "doc_id", "y", "train", "input"])

    def run(batches):
        held: dict[int, list] = {}
        for batch in batches:
            for number, *row in zip(*(batch.column(c).to_pylist() for c in ("number", "doc_id", "y", "train", "input")), strict=True):
                held.setdefault(number, []).append(tuple(row))
        for number, own in held.items():
            began, model = time.time(), shared.value[number]
            own.sort(key=lambda r: (r[0], r[3]))
            ids, y, train = np.array([r[0] for r in own], np.int64), np.array([r[1] for r in own]), np.array([r[2] for r in own])
            if number in frozen:
                inputs = np.stack([np.frombuffer(r[3], np.float32) for r in own])
            else:
                pixels = np.stack([np.frombuffer(r[3], np.uint8).reshape(rasters.SIDE, rasters.SIDE, -1) for r in own])
                inputs = pixels if model.strategy == "full" else np.concatenate([model.prepared(pixels[i : i + 64]) for i in range(0, len(pixels), 64)])
            made, history = fit_exact(model, ids, y, train, inputs, config)
            packed = pickle.dumps(({k: made.tensor(k) for k in made.trainable()}, history, time.time() - began))
            yield pa.RecordBatch.from_arrays([pa.array([number], pa.int32()), pa.array([packed], pa.binary())], names=["number", "packed"])

    given = _with_pixels(rows).where("split in ('train', 'val')").select("doc_id", "y", "split", "pixels")
    each = given.mapInArrow(dealt, "number int, doc_id long, y int, train boolean, input binary").repartitionById(len(live), F.col("number"))
    for r in each.mapInArrow(run, "number int, packed binary").collect():
        tensors, history, seconds = pickle.loads(r["packed"])
        out[live[r["number"]]] = models[live[r["number"]]].replaced(tensors), history, seconds
    return {name: out.get(name, (m, [], 0.0)) for name, m in models.items()}


def _epoch(rows: DataFrame, model: enc.Model, config: Config, epoch: int) -> list:
    """One job over training and validation rows: (steps, loss, gradients or tensors, validation hits), summed over groups of
    about the root of the number of tasks."""
    spark = rows.sparkSession
    workers_can_import(spark)
    shared = spark.sparkContext.broadcast(model)
    rate = cosine_rate(config.rate(model.strategy), epoch, config.epochs)
    schema = "part int, count long, loss double, tensors binary, seen long, hits long"

    def run(batches):
        start = shared.value
        here, steps = start, Steps(config)
        count, loss, sums, seen, hits, first = 0, 0.0, {}, 0, 0, None
        rng = np.random.default_rng([config.seed, epoch])
        for batch in batches:
            ids, y, split = (np.array(batch.column(c).to_pylist()) for c in ("doc_id", "y", "split"))
            first = int(ids[0]) if first is None and len(ids) else first
            inputs = start.prepared(_images(batch)) if len(ids) else None
            val, own = np.flatnonzero(split == "val"), np.flatnonzero(split == "train")
            if len(val):
                hits, seen = hits + int((start.predict_prepared(inputs[val]) == y[val]).sum()), seen + len(val)
            if epoch >= config.epochs or not len(own):
                continue
            order = own[epoch_order(ids[own], config.seed, epoch)]
            for i in range(0, len(order), config.batch):
                some = order[i : i + config.batch]
                if config.mode == "local":
                    here, one = steps.take(here, inputs[some], y[some], rate, rng)
                else:
                    one, grads = here.gradients_prepared(inputs[some], y[some], config.dropout, rng)
                    sums = {k: sums.get(k, 0) + g * len(some) for k, g in grads.items()}
                loss, count = loss + one * len(some), count + len(some)
        out = {k: here.tensor(k) * count for k in start.trainable()} if config.mode == "local" else sums
        yield pa.RecordBatch.from_arrays([pa.array([(first or 0) & 0x7FFFFFFF], pa.int32()), pa.array([count]), pa.array([loss]), pa.array([_pack(out) if count else None], pa.binary()), pa.array([seen]), pa.array([hits])], names=["part", "count", "loss", "tensors", "seen", "hits"])

    def added(batches):
        numbers, total = [0, 0.0, 0, 0], {}
        for batch in batches:
            for r in batch.to_pylist():
                numbers = [a + b for a, b in zip(numbers, (r["count"], r["loss"], r["seen"], r["hits"]), strict=True)]
                for k, v in pickle.loads(r["tensors"]).items() if r["tensors"] else ():
                    total[k] = total.get(k, 0) + v
        count, loss, seen, hits = numbers
        yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([count]), pa.array([float(loss)]), pa.array([_pack(total) if total else None], pa.binary()), pa.array([seen]), pa.array([hits])], names=["part", "count", "loss", "tensors", "seen", "hits"])

    parts = rows.select("doc_id", "y", "split", "pixels").mapInArrow(run, schema)
    tasks = rows.rdd.getNumPartitions()
    if tasks > 16:
        parts = parts.repartition(math.isqrt(tasks), "part").mapInArrow(added, schema)
    return parts.collect()


def trained(rows: DataFrame, model: enc.Model, config: Config | None = None) -> tuple[enc.Model, list[dict]]:
    """Adapt a model to rows (doc_id, text, y, split): the epoch with the best validation accuracy (the earliest of equals)
    is kept, with the history of (epoch, rate, training loss, validation accuracy after it)."""
    config = config or Config()
    if not model.trainable():
        return model, []
    rows = _with_pixels(rows)
    if config.mode == "exact":
        return trained_together(rows, {"one": model}, config)["one"][:2]
    rows = rows.where("split in ('train', 'val')")
    adam, history, best, waiting = AdamW(config.decay), [], None, None
    for epoch in range(config.epochs + 1):
        parts = _epoch(rows, model, config, epoch)
        seen, hits = sum(p["seen"] for p in parts), sum(p["hits"] for p in parts)
        if waiting:
            waiting["val_acc"] = hits / seen if seen else 0.0
            history.append(waiting)
            if best is None or waiting["val_acc"] > best[0]:
                best = (waiting["val_acc"], model)
        count = sum(p["count"] for p in parts)
        if epoch == config.epochs or not count:
            break
        total: dict = {}
        for p in parts:
            if p["tensors"]:
                for k, v in pickle.loads(p["tensors"]).items():
                    total[k] = total.get(k, 0) + v
        mean = {k: (v / count).astype(np.float32) for k, v in total.items()}
        rate = cosine_rate(config.rate(model.strategy), epoch, config.epochs)
        model = model.replaced(mean if config.mode == "local" else adam.step({k: model.tensor(k) for k in mean}, mean, rate))
        waiting = {"strategy": model.strategy, "epoch": epoch, "rate": rate, "train_loss": sum(p["loss"] for p in parts) / count}
    return (best[1] if best else model), history


WEIGHTS = "model string, strategy string, shape string, rank int, alpha double, part string, tensor string, dims array<int>, data binary"


def weights_table(spark, models: dict[str, enc.Model]) -> DataFrame:
    """Models as rows, one for each tensor (its part: encoder, extra or texts), to be kept as Parquet."""
    rows = []
    for name, m in models.items():
        for part, tensors in (("encoder", m.encoder), ("extra", m.extra), ("texts", {"texts": m.texts})):
            rows += [(name, m.strategy, m.shape, m.rank, m.alpha, part, k, list(v.shape), np.ascontiguousarray(v, np.float32).tobytes()) for k, v in tensors.items()]
    return spark.createDataFrame(rows, WEIGHTS)


def models_of(table: DataFrame) -> dict[str, enc.Model]:
    """The models of a weights table (as many as were kept; a model's size doesn't depend on data). Those of frozen strategies share one encoder."""
    found: dict[str, dict] = {}
    for r in table.collect():
        one = found.setdefault(r["model"], {"head": r, "encoder": {}, "extra": {}, "texts": {}})
        one[r["part"]][r["tensor"]] = np.frombuffer(r["data"], np.float32).reshape(r["dims"])
    base, out = None, {}
    for name, one in sorted(found.items()):
        h, encoder = one["head"], one["encoder"]
        if h["strategy"] in enc.FROZEN:
            encoder = base = base or encoder
        start = enc.Model.start(h["strategy"], encoder, one["texts"]["texts"], rank=h["rank"], alpha=h["alpha"], shape=h["shape"])
        order = [k for k in start.extra if k in one["extra"]] + sorted(k for k in one["extra"] if k not in start.extra)
        out[name] = replace(start, extra={k: one["extra"][k] for k in order})
    return out


def predicted(models: dict[str, enc.Model], images: np.ndarray) -> dict[str, np.ndarray]:
    """Predictions of every model. Models with the frozen encoder share its features, and a model whose last block alone was
    changed reads what the frozen one's last block reads."""
    tokens, base, out = enc.patches(images), next((m.encoder for m in models.values() if m.strategy in enc.FROZEN), None), {}
    start, hidden, feature = None, None, None
    for name, m in models.items():
        shared = base is not None and (m.strategy in enc.FROZEN or m.strategy == "last_block")
        if shared and hidden is None:
            start = enc.embedded(base, tokens)
            hidden, _ = enc.through(base, start, 0, enc.depth(base) - 1)
        if m.strategy in enc.FROZEN:
            feature = enc.forward(base, None, hidden, enc.depth(base) - 1)[0] if feature is None else feature
            out[name] = m.scores(feature).argmax(axis=1)
        elif shared:
            out[name] = m.predict_prepared(hidden)
        else:
            out[name] = m.scores(enc.forward(m.merged(), tokens)[0]).argmax(axis=1)
    return out


def probed(rows: DataFrame, models: dict[str, enc.Model], transforms: tuple[str, ...] = rasters.TRANSFORMS, seed: int = 42, fill: str = "mean") -> DataFrame:
    """The prediction log: every model on every transform of every image, in one narrow pass that makes each raster and
    each transform once. Each row has pred0, the model's prediction on the untouched image, so measures of change need no join.
    All frozen models of one call share one encoder."""
    spark = rows.sparkSession
    workers_can_import(spark)
    shared = spark.sparkContext.broadcast(models)
    with_pixels = "pixels" in rows.columns

    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 64):
                batch = whole.slice(at, 64)
                ids, texts, y = (batch.column(c).to_pylist() for c in ("doc_id", "text", "y"))
                base = _images(batch) if with_pixels else np.stack([rasters.from_bytes(rasters.to_bytes(rasters.of_text(t or ""))) for t in texts])
                before = predicted(shared.value, base)
                for spec in transforms:
                    after = before if spec == "identity" else predicted(shared.value, np.stack([rasters.apply(spec, t or "", b, seed, i, fill) for i, t, b in zip(ids, texts, base, strict=True)]))
                    for name in shared.value:
                        yield pa.RecordBatch.from_arrays(
                            [pa.array([name] * len(ids)), pa.array([spec] * len(ids)), pa.array(ids, pa.int64()), pa.array(y, pa.int32()), pa.array(after[name].tolist(), pa.int32()), pa.array(before[name].tolist(), pa.int32())],
                            names=["model", "transform", "image_id", "y", "pred", "pred0"],
                        )

    columns = ["doc_id", "text", "y", *(["pixels"] if with_pixels else [])]
    return rows.select(*columns).mapInArrow(run, "model string, transform string, image_id long, y int, pred int, pred0 int")
