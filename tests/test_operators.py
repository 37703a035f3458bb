"""Worked examples, published numbers, invariants and independent twins of the operators."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from geoprobe.operators import duplicates
from geoprobe.operators import encoder as enc
from geoprobe.operators import ladder, measures, rasters, sampling, spatial, statistics, vectors
from geoprobe.plans import geography, rule_logs
from geoprobe.sources.tables import region_dim


def test_rank_is_exact_at_any_partitioning(spark):
    df = spark.range(5000).withColumn("g", F.col("id") % 3).withColumn("u", F.pmod(F.xxhash64("id"), F.lit(997)) / 997.0)
    made = [sorted(map(tuple, sampling.bucketed_rank(df.repartition(n), "g", F.col("u"), "id", buckets=16).select("id", "rank").collect())) for n in (1, 7)]
    rows = df.collect()
    wanted = {}
    for g in range(3):
        for i, r in enumerate(sorted((r["u"], r["id"]) for r in rows if r["g"] == g)):
            wanted[r[1]] = i + 1
    assert made[0] == made[1] == sorted(wanted.items())


def test_splits_are_disjoint_and_complete(spark, sf_dir):
    rows = geography.split_rows(spark, sf_dir)
    sizes = {r["split"]: r["n"] for r in rows.groupBy("split").agg(F.count("*").alias("n")).collect()}
    assert (sizes["train"], sizes["val"], sizes["test"]) == (498, 108, 112)
    audit = spatial.overlap_audit(rows).first()
    assert (audit["n_test"], audit["same_site"], audit["within"]) == (112, 78, 79)


def test_radius_join_equals_nested_loop(spark):
    step = 1 / 111195.08
    points = [(0, "test", "a", 34.0, -118.0), (1, "train", "b", 34.0 + 49 * step, -118.0), (2, "test", "c", 34.01, -118.0), (3, "train", "d", 34.01 + 51 * step, -118.0), (4, "test", "e", 34.02, -118.0), (5, "train", "f", 34.02, -118.0 + 49 * step / math.cos(math.radians(34.02)))]
    rows = spark.createDataFrame(points, "image_id int, split string, site string, lat double, lon double")
    assert sorted(r["image_id"] for r in spatial.near_training(rows).collect()) == [0, 4]


def test_ray_casting(spark):
    ring = "array(named_struct('lon', 0D, 'lat', 0D), named_struct('lon', 4D, 'lat', 0D), named_struct('lon', 2D, 'lat', 3D))"
    rows = spark.createDataFrame([(2.0, 1.0), (0.1, 2.0), (3.9, 0.05), (2.0, -1.0)], "x double, y double")
    got = [r[0] for r in rows.select(spatial.inside_ring(F.col("x"), F.col("y"), F.expr(ring))).collect()]
    assert got == [True, False, True, False]


LOG = [
    *(("m", "identity", i, y, p) for i, (y, p) in enumerate([(0, 0), (0, 1), (1, 0), (1, 2), (2, 2), (2, None)])),
    *(("m", "t", i, y, p) for i, (y, p) in enumerate([(0, 1), (0, 0), (1, 0), (1, 0), (2, 2), (2, 2)])),
    ("z", "identity", 0, 0, 1), ("z", "t", 0, 0, 0),
]


def test_switch_kinds_and_identities(spark):
    log = spark.createDataFrame(LOG, "model string, transform string, image_id int, y int, pred int")
    got = {r["model"]: r.asDict() for r in measures.switches(log).collect()}
    assert {k: got["m"][k] for k in ("n", "switched", "lost", "gained", "moved", "correct0", "correct1")} == {"n": 6, "switched": 4, "lost": 1, "gained": 2, "moved": 1, "correct0": 2, "correct1": 3}
    kept = {r["model"]: r for r in measures.retention(log).collect()}
    assert kept["z"]["retention"] is None and kept["m"]["relative_drop"] == pytest.approx(100 * (1 - kept["m"]["retention"]))
    assert all(abs(r["correct0"] - r["correct1"]) <= r["switched"] for r in got.values())


def test_published_tables(spark):
    accuracy = {r["model"]: round(100 * r["accuracy"], 2) for r in measures.accuracy(rule_logs.published_log(spark)).collect()}
    assert accuracy == {"zero_shot": 39.03, "text_score": 41.45, "linear": 38.52, "last_block": 75.94, "low_rank": 78.36, "full": 82.10}
    rates = {(r["model"], r["transform"]): round(100 * r["switch_rate"], 2) for r in measures.switch_rate(rule_logs.published_switches(spark)).collect()}
    assert [rates[m, "scramble:16"] for m in rule_logs.CORRECT] == [12.40, 14.60, 10.79, 45.56, 43.21, 42.92]
    assert [rates[m, "remove:sky"] for m in ("zero_shot", "low_rank", "full")] == [4.40, 5.65, 4.70]
    assert all(r["falls"] is not False for r in measures.trend(rule_logs.published_switches(spark), "scramble").collect())


def test_two_group_f_is_t_squared(spark):
    a, b = [1.0, 2.0, 4.0, 4.5], [2.0, 5.0, 6.0]
    rows = spark.createDataFrame([(x, 0) for x in a] + [(x, 1) for x in b] + [(None, 1)], "v double, g int")
    pooled = ((len(a) - 1) * np.var(a, ddof=1) + (len(b) - 1) * np.var(b, ddof=1)) / (len(a) + len(b) - 2)
    t2 = (np.mean(a) - np.mean(b)) ** 2 / (pooled * (1 / len(a) + 1 / len(b)))
    got = statistics.with_p(statistics.anova_oneway(rows, "v", "g")).first()
    assert got["f"] == pytest.approx(t2) and 0 < got["p"] < 1
    assert statistics.f_tail(4.964603, 1, 10) == pytest.approx(0.05, abs=1e-6)
    assert statistics.f_tail(3.0, 2, 27) == pytest.approx(0.0666, abs=1e-3)


@pytest.mark.parametrize("n", [4, 8, 16, 56])
def test_scramble_keeps_blocks(n):
    x = np.arange(56 * 56 * 3, dtype=np.float32).reshape(56, 56, 3)
    y = rasters.scrambled(x, n, 42, 7)
    assert sorted(x.ravel()) == sorted(y.ravel())
    assert np.array_equal(rasters.scrambled(x, 56, 42, 7), x)
    side = 56 // n * n
    blocks = lambda r: {r[i : i + n, j : j + n].tobytes() for i in range(0, side, n) for j in range(0, side, n)}
    assert blocks(x) == blocks(y) and np.array_equal(x[side:], y[side:])


@pytest.mark.parametrize("fill", ["zero", "mean", "fast_marching"])
def test_masks_and_inpainting(fill):
    rng = np.random.default_rng(0)
    x, mask = np.full((56, 56, 3), 7.0, np.float32), rng.random((56, 56)) < 0.1
    other = rasters.random_mask(mask, 42, 3, "short_word")
    assert other.sum() == mask.sum() and rasters.random_mask(mask, 42, 3, "short_word", "shift").sum() == mask.sum()
    out = rasters.inpainted(x, mask, fill)
    assert np.array_equal(out[~mask], x[~mask])
    if fill != "zero":
        assert np.allclose(out, 7.0, atol=1e-4)
    assert np.array_equal(rasters.inpainted(x, np.zeros((56, 56), bool), fill), x)


def test_blur_and_edges():
    x = np.zeros((56, 56, 3), np.float32)
    x[:, 28:] = 255
    e = rasters.edges(x)
    assert set(np.unique(e)) == {0.0, 255.0} and 0 < (e[:, :, 0] > 0).sum() <= 2 * 56 and not e[:, :20].any()
    assert rasters.blurred(x).mean() == pytest.approx(x.mean(), rel=0.01)
    assert not rasters.edges(np.full((56, 56, 3), 9.0, np.float32)).any()


def test_text_raster_covers_whole_text():
    long = "ab " * 20000
    a, b = rasters.of_text(long), rasters.of_text(long[:-3000] + "X" * 3000)
    assert a.shape == (56, 56, 3) and not np.array_equal(a, b) and not rasters.of_text("").any()


@pytest.mark.parametrize("strategy", enc.STRATEGIES[1:])
def test_gradients(strategy, monkeypatch):
    monkeypatch.setattr(enc, "HEAT", 5.0)
    rng = np.random.default_rng(0)
    images, y = rng.random((3, 56, 56, 3)) * 255, np.array([0, 1, 2])
    texts = rng.standard_normal((3, enc.OUT))
    texts /= np.linalg.norm(texts, axis=1, keepdims=True)
    model = enc.Model.start(strategy, {k: v.astype(np.float64) for k, v in enc.initial().items()}, texts)
    model.extra = {k: v.astype(np.float64) + 0.01 * rng.standard_normal(v.shape) for k, v in model.extra.items()}
    _, grads = model.gradients(images, y)
    assert list(grads) == model.trainable()
    for name, g in grads.items():
        at = tuple(rng.integers(0, n) for n in g.shape)
        moved = []
        for e in (1e-5, -1e-5):
            t = model.tensor(name).copy()
            t[at] += e
            moved.append(model.replaced({name: t}).gradients(images, y)[0])
        assert (moved[0] - moved[1]) / 2e-5 == pytest.approx(g[at], rel=2e-3, abs=1e-6)


def test_low_rank_starts_as_base_and_merges():
    rng = np.random.default_rng(1)
    images = rng.random((2, 56, 56, 3)) * 255
    texts = enc.text_features(["a b", "c d"])
    base, low = (enc.Model.start(s, enc.initial(), texts) for s in ("zero_shot", "low_rank"))
    assert np.array_equal(base.predict(images), low.predict(images))
    low.extra = {k: v + 0.1 for k, v in low.extra.items()}
    folded = enc.Model("zero_shot", low.merged(), texts)
    assert np.allclose(low.scores(enc.forward(low.merged(), enc.patches(images))[0]), folded.scores(enc.forward(folded.encoder, enc.patches(images))[0]))
    counts = [enc.Model.start(s, enc.initial(), texts).trainable_parameters() for s in enc.STRATEGIES]
    assert counts[0] == 0 < counts[1] < counts[2] < counts[3] and counts[4] < counts[5] == max(counts)


def test_probe_leaves_encoder_alone(spark):
    rows = spark.createDataFrame([(i, ("the cat sat " if i % 2 else "der hund lief ") * 40, i % 2, "val" if i % 5 == 0 else "train") for i in range(60)], "doc_id long, text string, y int, split string")
    start = enc.Model.start("linear", enc.initial(), enc.text_features(["x", "y"]))
    for mode, precision in (("local", "full"), ("sync", "full"), ("local", "mixed")):
        model, history = ladder.trained(rows, start, ladder.Config(epochs=3, mode=mode, precision=precision))
        assert all(np.array_equal(model.encoder[k], start.encoder[k]) for k in start.encoder)
        assert history[-1]["train_loss"] < history[0]["train_loss"] and len(history) == 3
    block, _ = ladder.trained(rows, enc.Model.start("last_block", enc.initial(), start.texts), ladder.Config(epochs=1))
    assert all(np.array_equal(block.encoder[k], start.encoder[k]) for k in (*enc.EMBED, *enc.block_names(0), "proj"))
    assert not np.array_equal(block.encoder["1.wq"], start.encoder["1.wq"])


def test_optimiser_parts():
    assert ladder.cosine_rate(1.0, 0) == 1.0 and ladder.cosine_rate(1.0, 10) == pytest.approx(0)
    x = {"w": np.ones(2, np.float32)}
    adam = ladder.AdamW(decay=0.0)
    for _ in range(300):
        x = adam.step(x, {"w": 2 * (x["w"] - 3)}, 0.1)
    assert np.allclose(x["w"], 3, atol=0.1)
    scale = ladder.LossScale(8.0, patience=2)
    assert not scale.update(False) and scale.scale == 4 and scale.update(True) and scale.update(True) and scale.scale == 8


def test_native_scramble_matches_numpy(spark, sf_dir):
    df = spark.read.parquet(f"{sf_dir}/embeddings.parquet").limit(20)
    for r0, r1 in zip(df.orderBy("vec_id").collect(), vectors.scrambled(df, 4).orderBy("vec_id").collect(), strict=True):
        a, b = np.array(r0["embedding"]).reshape(8, 8), np.array(r1["embedding"]).reshape(8, 8)
        cut = lambda x: sorted(x[i : i + 4, j : j + 4].tobytes() for i in (0, 4) for j in (0, 4))
        assert cut(a) == cut(b)


def test_plans_hold_no_product_and_push_columns(spark, sf_dir, capsys):
    geography.QUERIES["radius_overlap"](spark, sf_dir).explain()
    text = capsys.readouterr().out
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text
    geography.QUERIES["pool_counts"](spark, sf_dir).explain("formatted")
    assert "props" not in capsys.readouterr().out


def test_image_folder_and_report(spark, tmp_path):
    from geoprobe.sources import images

    wide = np.arange(6 * 10 * 3, dtype=np.uint8).reshape(6, 10, 3)
    (tmp_path / "a.ppm").write_bytes(b"P6\n# made here\n10 6\n255\n" + wide.tobytes())
    row = images.image_folder(spark, str(tmp_path), side=6).first()
    assert np.array_equal(np.frombuffer(bytes(row["pixels"]), np.uint8).reshape(6, 6, 3), wide[:, 2:8])
    with pytest.raises(ValueError, match="PGM"):
        images.decode_pnm(b"\x89PNG")
    images.write_report(spark.createDataFrame([("baseline", 0, "x")], "condition string, region int, text string"), str(tmp_path / "r"))
    assert images.prompt_file(spark, str(tmp_path / "r")).first()["text"] == "x"


def test_table_functions(spark):
    from geoprobe.functions import tables
    from geoprobe.session import workers_can_import

    workers_can_import(spark)
    tables.register(spark)
    assert spark.sql("SELECT * FROM explode_blocks(56, 16)").count() == 9
    assert spark.sql("SELECT * FROM polygon_cells(0.0D, 0.0D, 0.25D, 0.15D, 0.1D)").count() == 6


def test_schema_check(spark, sf_dir):
    from geoprobe.sources.tables import assert_schema, load

    assert assert_schema(load(spark, sf_dir, "events"), "events") is not None
    with pytest.raises(TypeError, match="user_id"):
        assert_schema(load(spark, sf_dir, "events").drop("user_id"), "events")


def test_prediction_log_is_replaced_by_partition(spark, tmp_path):
    log = spark.createDataFrame(LOG, "model string, transform string, image_id int, y int, pred int")
    for _ in range(2):
        measures.append_log(log, str(tmp_path / "log"))
        measures.append_log(log.where("model = 'z'"), str(tmp_path / "log"))
    assert spark.read.parquet(str(tmp_path / "log")).count() == len(LOG)


def test_capture_source(spark):
    from geoprobe.session import workers_can_import
    from geoprobe.sources.fixture import Captures

    workers_can_import(spark)
    spark.dataSource.register(Captures)
    rows = spark.read.format("captures").option("rows", 500).option("partitions", 3).load()
    table = {r["region"]: r for r in sampling.sampling_table(rows).collect()}
    assert table[-1]["available"] == 500 and all(r["sampled"] <= r["available"] for r in table.values())
    boxes = spatial.with_boxes(region_dim(spark))
    assert spatial.assign_region(rows, boxes).where("found <> region").isEmpty()


def test_near_texts_keep_every_word(spark):
    """More distinct words than any vocabulary of 2^18 holds: rare words still tell texts apart, texts of rare words only stay."""
    many = " ".join(f"w{i}" for i in range(270_000))
    near = [f"n{i}" for i in range(40)]
    rows = [(1, many), (2, many + " more"), (3, "w1 w2 w3 ra rb rc"), (4, "w1 w2 w3 rd re rf"), (5, "rg rh"), (6, None), (7, " \t"), (8, " ".join(near)), (9, " ".join(near[:36]).upper()), (10, " ".join(near[:31]))]
    got = duplicates.near_duplicates(spark.createDataFrame(rows, "id long, text string"), "text", "id", 0.2).collect()
    assert {(r["a"], r["b"]): round(r["distance"], 6) for r in got} == {(1, 2): round(1 - 270_000 / 270_001, 6), (8, 9): 0.1, (9, 10): round(1 - 31 / 36, 6)}


def test_banding_finds_the_threshold():
    for similarity in (0.05, 0.3, 0.5, 0.8, 0.95):
        bands, rows = duplicates.banding(similarity)
        assert (1 - similarity**rows) ** bands <= duplicates.MISSED * 1.001
