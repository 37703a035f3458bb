"""Queries that adapt the surrogate encoder on `documents` and probe it: strategies, interventions, prompts, control.

One study is fitted per session and input folder and kept: alignment, rasters (written once), six strategies, the prediction log (written once)
and the class texts. The class is `lang`, which the alignment corpus knows only for pages. Strategies are fitted on a bounded sample (SAMPLE documents of the training and
validation splits, by a hash of the id, as the source samples its images); probing covers every test document."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scalars import hash01, hash01_sql, haversine_km, seeded
from ..operators import encoder as enc
from ..operators import ladder, measures, prompts, rasters, spatial
from ..session import checkpointed, spread, workers_can_import
from ..sources.tables import load, region_dim

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
FROZEN = list(enc.FROZEN)
SCRAMBLES = tuple(t for t in rasters.TRANSFORMS if t.startswith("scramble"))
#: Strategies that are compared between splits.
STRATA_MODELS = ("zero_shot", "linear", "last_block")
CUE_TRANSFORMS = tuple(t for t in rasters.TRANSFORMS if ":" in t and not t.startswith("scramble"))


def register(sql: str | None = None):
    def keep(fn):
        QUERIES[fn.__name__] = fn
        if sql:
            ORACLE_SQL[fn.__name__] = sql
        return fn

    return keep


def scenes(spark: SparkSession, sf_dir: str, label: str = "lang") -> DataFrame:
    """doc_id, text, y, split: y numbers the label's values alphabetically; split by a hash of the text, so that copies
    stay on one side."""
    docs = load(spark, sf_dir, "documents").select("doc_id", "text", F.col(label).alias("label")).where("label is not null")
    names = F.broadcast(docs.select("label").distinct().agg(F.array_sort(F.collect_set("label")).alias("names")))
    u = seeded(42, "d", F.md5(F.coalesce("text", F.lit(""))))
    return docs.crossJoin(names).select("doc_id", "text", (F.array_position("names", F.col("label")) - 1).cast("int").alias("y"), F.when(u < 0.7, "train").when(u < 0.85, "val").otherwise("test").alias("split"))


#: Training and validation documents that strategies are fitted on, about (as many as the source has); a smaller input is used whole.
SAMPLE = 6_359 + 1_363


def sampled(rows: DataFrame, size: int = SAMPLE) -> DataFrame:
    """The test rows and a hash sample of about `size` of the others."""
    fit = rows.where("split <> 'test'").count()
    return rows.where((F.col("split") == "test") | (seeded(42, "fit", F.col("doc_id")) < size / max(1, fit)))


def class_texts(described: DataFrame, condition: str) -> np.ndarray:
    rows = prompts.prompts(condition, described).orderBy("region").collect()  # a row per class
    return enc.text_features([r["text"] for r in rows])


class Study:
    """Everything that is fitted for one input folder."""

    def __init__(self, spark: SparkSession, sf_dir: str, label: str = "lang", strategies: tuple[str, ...] = enc.STRATEGIES):
        began = time.time()
        corpus = prompts.alignment_corpus(spread(load(spark, sf_dir, "pages")), load(spark, sf_dir, "conversations"))
        self.weights = ladder.aligned(spark, corpus)
        self.described = checkpointed(prompts.descriptors(corpus))
        self.texts = class_texts(self.described, "baseline")
        self.rows = ladder.rasterised(spread(sampled(scenes(spark, sf_dir, label))))
        self.align_seconds = time.time() - began
        began = time.time()
        fitted = ladder.trained_together(self.rows, {name: enc.Model.start(name, self.weights, self.texts) for name in strategies})
        self.models = {name: f[0] for name, f in fitted.items()}
        self.history = [h for f in fitted.values() for h in f[1]]
        self.seconds = {name: f[2] for name, f in fitted.items()}
        self.fit_seconds = time.time() - began
        self.spark, self._log, self.probe_seconds = spark, None, 0.0

    def log(self) -> DataFrame:
        if self._log is None:
            began = time.time()
            self._log = checkpointed(ladder.probed(spread(self.rows.where("split = 'test'")), self.models))
            self.probe_seconds = time.time() - began
        return self._log


_STUDIES: dict[tuple[str, str], Study] = {}


def study(spark: SparkSession, sf_dir: str) -> Study:
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _STUDIES:
        _STUDIES[key] = Study(spark, sf_dir)
    return _STUDIES[key]


def _adapt(name: str):
    @register()
    def run(spark, sf_dir):
        log = study(spark, sf_dir).log().where((F.col("model") == name) & (F.col("transform") == "identity"))
        return measures.accuracy(log)

    QUERIES[f"adapt_{name}"] = QUERIES.pop("run")
    return run


for _name in enc.STRATEGIES:
    _adapt(_name)


@register()
def w4_ladder(spark, sf_dir):
    """Accuracy of each strategy beside the majority share and chance."""
    log = study(spark, sf_dir).log().where("transform = 'identity'")
    per = measures.accuracy(log, ["model"])
    base = log.where("model = 'zero_shot'").groupBy("y").agg(F.count("*").alias("n")).agg((F.max("n") / F.sum("n")).alias("majority"), (1 / F.count("*")).alias("chance"))
    return per.crossJoin(base)


@register()
def w5_per_class_gain(spark, sf_dir):
    return measures.gain(study(spark, sf_dir).log(), "zero_shot", ["y"])


@register()
def w6_cue_removal(spark, sf_dir):
    return measures.switches(study(spark, sf_dir).log().where(F.col("transform").isin("identity", *CUE_TRANSFORMS)))


@register()
def w6_net_effect(spark, sf_dir):
    return measures.net_effect(study(spark, sf_dir).log())


@register()
def w8_edges_and_blur(spark, sf_dir):
    return measures.retention(study(spark, sf_dir).log().where("transform in ('identity', 'edges', 'blur')"))


@register()
def w9_scrambling(spark, sf_dir):
    return measures.switch_rate(study(spark, sf_dir).log().where("transform = 'identity' or transform like 'scramble:%'"))


@register()
def w9_scramble_trend(spark, sf_dir):
    return measures.trend(study(spark, sf_dir).log(), "scramble")


@register()
def w9_regimes(spark, sf_dir):
    return measures.regimes(study(spark, sf_dir).log().where("transform = 'identity' or transform like 'scramble:%'"), FROZEN)


_DRAWN = hash01_sql("'42|n|' || page_id")


@register()
def w10_control(spark, sf_dir):
    """Zero-shot on pages that no step has seen, untouched and scrambled."""
    fitted = study(spark, sf_dir)
    pages = prompts.control_set(load(spark, sf_dir, "pages"))
    names = fitted.described.select(F.col("name"), F.col("region").alias("y"))
    rows = pages.join(F.broadcast(names), F.col("lang") == F.col("name")).select("doc_id", "text", "y", F.lit("test").alias("split"))
    # One label more than there are classes: a background text that no page belongs to.
    background = enc.text_features([prompts.BACKGROUND])
    model = enc.Model.start("zero_shot", fitted.weights, np.vstack([fitted.texts, background]))
    log = checkpointed(ladder.probed(rows, {"zero_shot": model}, ("identity", *SCRAMBLES)))
    return measures.joint_table(log)


@register(f"SELECT row_number() OVER (ORDER BY {_DRAWN}, page_id)::INT AS place, page_id FROM pages WHERE {hash01_sql(chr(39) + '42|a|' + chr(39) + ' || page_id')} >= 0.5 ORDER BY {_DRAWN}, page_id LIMIT {prompts.CONTROL_SIZE}")
def w10_control_ids(spark, sf_dir):
    """The recorded sample of the control set: page numbers in the order in which they were drawn."""
    return prompts.control_ids(load(spark, sf_dir, "pages"))


@register()
def w10_second_control(spark, sf_dir):
    """A second control set without geography: the role of a conversation turn, read out of frozen features and scrambled."""
    fitted = study(spark, sf_dir)
    turns = load(spark, sf_dir, "conversations").where("role is not null and text is not null")
    names = F.broadcast(turns.select("role").distinct().agg(F.array_sort(F.collect_set("role")).alias("names")))
    # A conversation's turns stay on one side, and copies of a text do.
    u = seeded(42, "c", F.md5("text"))
    rows = turns.crossJoin(names).select((F.col("conv_id") * 4096 + F.col("turn")).alias("doc_id"), "text", (F.array_position("names", F.col("role")) - 1).cast("int").alias("y"), F.when(u < 0.7, "train").when(u < 0.85, "val").otherwise("test").alias("split"))
    rows = ladder.rasterised(sampled(rows))
    classes = rows.agg(F.max("y")).first()[0] + 1
    model, _ = ladder.trained(rows, enc.Model.start("linear", fitted.weights, np.zeros((classes, enc.OUT), np.float32)), ladder.Config(epochs=5))
    log = checkpointed(ladder.probed(rows.where("split = 'test'"), {"linear": model}, ("identity", *SCRAMBLES)))
    majority = rows.where("split = 'test'").groupBy("y").agg(F.count("*").alias("m")).agg(F.max("m").alias("majority"))
    return measures.joint_table(log).crossJoin(majority)


def _prompt_query(condition: str):
    return lambda spark, sf_dir: prompts.prompts(condition, prompts.descriptors(prompts.alignment_corpus(load(spark, sf_dir, "pages"), load(spark, sf_dir, "conversations"))))


for _condition in prompts.CONDITIONS:
    QUERIES[f"prompt_{_condition}"] = _prompt_query(_condition)


@register()
def w11_prompts(spark, sf_dir):
    """Zero-shot under the four prompt conditions."""
    fitted = study(spark, sf_dir)
    models = {c: enc.Model.start("zero_shot", fitted.weights, class_texts(fitted.described, c)) for c in prompts.CONDITIONS}
    return measures.accuracy(ladder.probed(fitted.rows.where("split = 'test'"), models, ("identity",)))


@register()
def w12_joint(spark, sf_dir):
    return measures.joint_table(study(spark, sf_dir).log())


@register()
def w13_cases(spark, sf_dir):
    """Qualitative cases: for each class the first five test images that middle-size scrambling switches under some model, each
    with a training partner of its class, the pixels of its four cue masks, whether it has edges, and the predictions of three models. Documents
    stand where `positions` puts them; the distance is to the partner."""
    from pyspark.sql import Window

    fitted = study(spark, sf_dir)
    names = ("zero_shot", "low_rank", "full")
    rows = fitted.log().where(F.col("model").isin(*names) & (F.col("transform") == "scramble:8"))
    pick = lambda m, c: F.max(F.when(F.col("model") == m, F.col(c)))
    wide = rows.groupBy("image_id", "y").agg(*(pick(m, c).alias(f"{m}_{n}") for m in names for c, n in (("pred0", "before"), ("pred", "after"))), F.max((~F.col("pred").eqNullSafe(F.col("pred0"))).cast("int")).alias("switched"))
    cases = wide.where("switched = 1").withColumn("place", F.row_number().over(Window.partitionBy("y").orderBy("image_id"))).where("place <= 5")
    cases = checkpointed(cases)  # five rows a class
    test = fitted.rows.where("split = 'test'").select(F.col("doc_id").alias("image_id"), "text", "pixels").join(F.broadcast(cases), "image_id")
    placed = positions(fitted.rows.where("split = 'train'").select(F.col("doc_id").alias("partner"), F.col("y").alias("of")), "partner", "of").withColumnsRenamed({"lat": "lat2", "lon": "lon2"})
    first = placed.groupBy("of").agg(F.min(F.struct("partner", "lat2", "lon2")).alias("t")).select("of", "t.*")
    cued = positions(cue_pixels(test), "image_id", "y").join(F.broadcast(first), F.col("y") == F.col("of"))
    return cued.withColumn("partner_km", haversine_km(F.col("lat"), F.col("lon"), F.col("lat2"), F.col("lon2"))).drop("of", "lat", "lon", "lat2", "lon2", "switched")


def cue_pixels(rows: DataFrame) -> DataFrame:
    """Rows (text, pixels and more) with the pixels under each cue's mask and whether the image has edges, instead of text and pixels."""
    workers_can_import(rows.sparkSession)
    rest = [f for f in rows.schema.fields if f.name not in ("text", "pixels")]

    def run(batches):
        for batch in batches:
            texts = [t or "" for t in batch.column("text").to_pylist()]
            masks = [pa.array([int(rasters.cue_mask(t, c).sum()) for t in texts], pa.int64()) for c in rasters.CUES]
            edges = pa.array([bool(rasters.edges(rasters.from_bytes(b)).any()) for b in batch.column("pixels").to_pylist()], pa.bool_())
            yield pa.RecordBatch.from_arrays([*(batch.column(f.name) for f in rest), *masks, edges], names=[*(f.name for f in rest), *(f"mask_{c}" for c in rasters.CUES), "has_edges"])

    schema = ", ".join([*(f"{f.name} {f.dataType.simpleString()}" for f in rest), *(f"mask_{c} long" for c in rasters.CUES), "has_edges boolean"])
    return rows.select("text", "pixels", *(f.name for f in rest)).mapInArrow(run, schema)


def positions(rows: DataFrame, key: str, region: str) -> DataFrame:
    """Adds lat and lon: documents stand in the square of the region with their class's number, at a place by a hash of their id.
    Place within a region and content are independent; the region is the class."""
    boxes = spatial.with_boxes(region_dim(rows.sparkSession)).select(F.col("region").alias("box"), "south", "west", "north", "east")
    u, v = (hash01(F.concat(F.lit(f"{name}|"), F.col(key).cast("string"))) for name in ("lat", "lon"))
    placed = rows.join(F.broadcast(boxes), F.pmod(F.col(region), F.lit(8)) == F.col("box"))
    return placed.withColumns({"lat": F.col("south") + u * (F.col("north") - F.col("south")), "lon": F.col("west") + v * (F.col("east") - F.col("west"))}).drop("box", "south", "west", "north", "east")


@register()
def w4_centroid_error(spark, sf_dir):
    """Centroid error of each strategy on the test documents where `positions` puts them, with centres from the training
    documents; `floor_km` is the error of right answers."""
    fitted = study(spark, sf_dir)
    placed = positions(fitted.rows.select(F.col("doc_id").alias("image_id"), F.col("y").alias("region"), "split"), "image_id", "region")
    centres = spatial.centroids(placed)
    log = fitted.log().where("transform = 'identity'").join(placed.where("split = 'test'").select("image_id", "lat", "lon"), "image_id")
    right = spatial.centroid_error(log.withColumn("pred", F.col("y")), centres, ["model"]).select("model", F.col("km").alias("floor_km"))
    return spatial.centroid_error(log, centres, ["model"]).join(right, "model")


def _control_labels(label: str):
    """The linear readout on labels without known signal, beside the majority share."""

    def run(spark, sf_dir):
        fitted = study(spark, sf_dir)
        rows = ladder.rasterised(sampled(scenes(spark, sf_dir, label)))
        classes = rows.agg(F.max("y")).first()[0] + 1
        texts = np.zeros((classes, enc.OUT), np.float32)
        model, _ = ladder.trained(rows, enc.Model.start("linear", fitted.weights, texts), ladder.Config(epochs=3))
        log = ladder.probed(rows.where("split = 'test'"), {"linear": model}, ("identity",))
        per = log.groupBy("y").agg(F.count("*").alias("n"), F.count_if(F.col("pred") == F.col("y")).alias("correct"))
        return per.agg(F.sum("n").alias("n"), F.sum("correct").alias("correct"), F.max("n").alias("majority"))

    return run


QUERIES["w4n_source_control"] = _control_labels("source")


@register()
def w4q_quality(spark, sf_dir):
    """A second label: the linear readout of document quality on the labelled documents."""
    fitted = study(spark, sf_dir)
    told = load(spark, sf_dir, "labels").select(F.col("doc_id").alias("told_id"), F.col("quality").cast("int").alias("quality")).where("quality is not null")
    rows = ladder.rasterised(sampled(scenes(spark, sf_dir).drop("y").join(told, F.col("doc_id") == F.col("told_id")).select("doc_id", "text", F.col("quality").alias("y"), "split")))
    model, _ = ladder.trained(rows, enc.Model.start("linear", fitted.weights, np.zeros((2, enc.OUT), np.float32)))
    return measures.accuracy(ladder.probed(rows.where("split = 'test'"), {"linear": model}, ("identity",)), ["y"])


@register()
def w17_content_strata(spark, sf_dir):
    """Accuracy by whether a test document's text occurs in training, for models fitted on the loose id-wise split (copies on both
    sides) and on the strict one by text (none in training)."""
    fitted = study(spark, sf_dir)
    u = seeded(42, "d", F.col("doc_id"))
    splits = {"strict": fitted.rows, "loose": checkpointed(fitted.rows.withColumn("split", F.when(u < 0.7, "train").when(u < 0.85, "val").otherwise("test")))}
    out = None
    for name, rows in splits.items():
        models = {m: fitted.models[m] for m in STRATA_MODELS}
        if name == "loose":
            models = {m: f[0] for m, f in ladder.trained_together(rows, {m: enc.Model.start(m, fitted.weights, fitted.texts) for m in STRATA_MODELS}).items()}
        test = rows.where("split = 'test'")
        seen = rows.where("split = 'train'").select(F.md5("text").alias("h"), F.lit(True).alias("seen")).distinct()
        strata = test.withColumn("h", F.md5("text")).join(seen, "h", "left").select(F.col("doc_id").alias("image_id"), F.when(F.col("seen"), "copy in training").otherwise("new").alias("stratum"))
        log = checkpointed(ladder.probed(test, models, ("identity",)))
        part = measures.by_stratum(log, strata).withColumn("split", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


@register()
def ladder_variants(spark, sf_dir):
    """Variants of what the source leaves open, each beside its default: shapes of the text-score probe, adapter targets and a
    trained head of the low-rank strategy, starts of the linear head."""
    fitted = study(spark, sf_dir)
    start = lambda s, **kw: enc.Model.start(s, fitted.weights, fitted.texts, **kw)
    models = {f"text_score_{x}": start("text_score", shape=x) for x in enc.SHAPES} | {f"linear_{x}": start("linear", head_start=x) for x in ("texts", "zero", "normal")}
    models |= {f"low_rank_{t}": start("low_rank", targets=(t,)) for t in enc.ADAPTED} | {"low_rank_both": start("low_rank"), "low_rank_head": start("low_rank", head="linear")}
    made = ladder.trained_together(fitted.rows, models)
    sizes = spark.createDataFrame([(n, m.trainable_parameters()) for n, m in models.items()], "model string, parameters long")
    log = checkpointed(ladder.probed(fitted.rows.where("split = 'test'"), {n: f[0] for n, f in made.items()}, ("identity",)))
    return measures.accuracy(log, ["model"]).join(sizes, "model")


@register()
def trainable_parameters(spark, sf_dir):
    """Trainable parameters of each strategy, and of the low-rank one by target, on the class texts that `pages` give: heads grow with the classes."""
    texts = class_texts(prompts.descriptors(prompts.alignment_corpus(load(spark, sf_dir, "pages"), load(spark, sf_dir, "conversations"))), "baseline")
    weights = enc.initial()
    counts = [(s, enc.Model.start(s, weights, texts).trainable_parameters()) for s in enc.STRATEGIES]
    counts += [(f"low_rank_{t}", enc.Model.start("low_rank", weights, texts, targets=(t,)).trainable_parameters()) for t in enc.ADAPTED]
    return spark.createDataFrame([(s, len(texts), n) for s, n in counts], "strategy string, classes long, parameters long")


_TEXT_U, _FIT_U = hash01_sql("'42|d|' || md5(coalesce(text, ''))"), hash01_sql("'42|fit|' || doc_id")


@register(
    f"""WITH d AS (SELECT doc_id, {_TEXT_U} AS u FROM documents WHERE lang IS NOT NULL), f AS (SELECT greatest(1, count(*)) AS fit FROM d WHERE u < 0.85),
t AS (SELECT count(*)::BIGINT AS images FROM d, f WHERE u < 0.7 AND {_FIT_U} < {SAMPLE} / fit::DOUBLE)
SELECT e::BIGINT AS epoch, images, e::BIGINT * ((images + 7) // 8) AS first_step, (images + 7) // 8 AS steps, floor(0.0001::DOUBLE * (1 + cos(pi() * e / 10)) / 2 * 1e12 + 0.5)::BIGINT AS rate_1e12 FROM range(10) r(e), t"""
)
def lr_schedule(spark, sf_dir):
    """The rate of each epoch, with the steps that take it on the training documents of the study."""
    config = ladder.Config()
    rates = spark.createDataFrame([(e, ladder.cosine_rate(1e-4, e)) for e in range(config.epochs)], "epoch long, rate double")
    images = sampled(scenes(spark, sf_dir)).where("split = 'train'").agg(F.count("*").alias("images"))
    steps = F.ceil(F.col("images") / config.batch)
    return rates.crossJoin(images).select("epoch", "images", (F.col("epoch") * steps).alias("first_step"), steps.alias("steps"), F.floor(F.col("rate") * 1e12 + 0.5).cast("long").alias("rate_1e12"))


@register()
def training_history(spark, sf_dir):
    return spark.createDataFrame([(h["strategy"], h["epoch"], float(h["rate"]), float(h["train_loss"]), float(h["val_acc"])) for h in study(spark, sf_dir).history], "strategy string, epoch int, rate double, train_loss double, val_acc double")


#: Epochs of the rules below, the price by which a rule moves in an epoch, the first year.
EPOCHS, PRICE_STEP, FIRST_YEAR = 10, 50_000, 1992
_U = hash01_sql("'42|v|' || o_orderkey")


@register(
    f"""WITH o AS (SELECT substr(o_orderpriority, 1, 1) AS y, o_totalprice, year(o_orderdate) AS t FROM orders WHERE {_U} >= 0.7 AND {_U} < 0.85),
r AS (SELECT method, e::INT AS epoch, count(*)::BIGINT AS n, count(*) FILTER (WHERE y = CASE WHEN CASE method WHEN 'by_price' THEN o_totalprice < {PRICE_STEP} * (e + 1) ELSE t < {FIRST_YEAR} + e END THEN '1' ELSE '5' END)::BIGINT AS correct
FROM o, range({EPOCHS}) r(e), (VALUES ('by_price'), ('by_date')) m(method) GROUP BY ALL)
SELECT method, max(n) AS n, arg_max(epoch, (correct, -epoch))::INT AS epoch, max(correct) AS correct FROM r GROUP BY method"""
)
def checkpoint_choice(spark, sf_dir):
    """The epoch with the best validation accuracy, the earliest of equals: two rules that tell urgent orders from others move their limit each
    epoch, and are judged on the orders of the validation split."""
    u = seeded(42, "v", F.col("o_orderkey"))
    orders = load(spark, sf_dir, "orders").where((u >= 0.7) & (u < 0.85))
    urgent = {"by_price": lambda e: F.col("o_totalprice") < PRICE_STEP * (e + 1), "by_date": lambda e: F.year("o_orderdate") < FIRST_YEAR + e}
    right = lambda m, e: F.substring("o_orderpriority", 1, 1) == F.when(urgent[m](e), "1").otherwise("5")
    # One pass: a count for each rule and epoch.
    counts = orders.agg(F.count("*").alias("n"), *(F.count_if(right(m, e)).alias(f"{m}_{e}") for m in urgent for e in range(EPOCHS)))
    runs = counts.where("n > 0").select("n", F.explode(F.array(*(F.struct(F.lit(m).alias("method"), F.lit(e).alias("epoch"), F.col(f"{m}_{e}").alias("correct")) for m in urgent for e in range(EPOCHS)))).alias("r"))
    return measures.best_epoch(runs.select("r.method", "r.epoch", "n", "r.correct"))


@register()
def cost_report(spark, sf_dir):
    """What each strategy costs on this input: trainable parameters, seconds of fitting, training images a second, bytes of a
    broadcast of the model and of the rows sent to its task; and the probe's images a second (a transform of an image under a model)."""
    fitted = study(spark, sf_dir)
    probes = fitted.log().count()
    sizes = {r["split"]: r["n"] for r in fitted.rows.groupBy("split").agg(F.count("*").alias("n")).collect()}
    rows, seen = sizes.get("train", 0) + sizes.get("val", 0), sizes.get("train", 0) * ladder.Config().epochs
    table = []
    for name, m in fitted.models.items():
        sent = 0 if not m.trainable() else rows * (4 * enc.OUT if name in FROZEN else rasters.SIDE**2 * rasters.CHANNELS)
        size = sum(t.nbytes for t in (*m.encoder.values(), *m.extra.values()))
        table.append((name, m.trainable_parameters(), fitted.seconds[name], seen / fitted.seconds[name] if fitted.seconds[name] else None, size, sent, probes / fitted.probe_seconds))
    return spark.createDataFrame(table, "strategy string, parameters long, seconds double, images_per_second double, broadcast_bytes long, shuffled_bytes long, probes_per_second double")
