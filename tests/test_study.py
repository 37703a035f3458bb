"""The trained study against plain Python: its log, every measure over it, the 56 x 56 transforms, and how it is fitted."""

import collections
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from geoprobe import catalogue
from geoprobe.operators import duplicates, ladder, measures, rasters, spatial
from geoprobe.operators import encoder as enc
from geoprobe.plans import probing, rule_logs


@pytest.fixture(scope="module")
def fitted(spark, sf_dir):
    return probing.study(spark, sf_dir)


@pytest.fixture(scope="module")
def log(fitted):
    return fitted.log().toPandas()


def query(spark, sf_dir, name):
    return [r.asDict() for r in catalogue.QUERIES[name](spark, sf_dir).collect()]


def one_image(w, image):
    """Features of one image, token by token, without batches or shared parts."""
    per = 56 // enc.PATCH
    x = [(image[r * 7 : r * 7 + 7, c * 7 : c * 7 + 7].astype(np.float64).reshape(-1) - 96) / 96 for r in range(per) for c in range(per)]
    x = [np.maximum(t @ w["we"] + w["be"], 0) + w["pos"][i] for i, t in enumerate(x)]
    norm = lambda t, g, b: (t - t.mean()) / np.sqrt(t.var() + 1e-5) * g + b
    for i in range(enc.BLOCKS):
        p = {n: w[f"{i}.{n}"] for n in enc.BLOCK}
        a = [norm(t, p["g1"], p["b1"]) for t in x]
        keys, values = [t @ p["wk"] for t in a], [t @ p["wv"] for t in a]
        for j, t in enumerate(a):
            q = t @ p["wq"]
            e = np.exp([q @ k / math.sqrt(enc.WIDTH) for k in keys])
            x[j] = x[j] + sum(s * v for s, v in zip(e / e.sum(), values, strict=True)) @ p["wo"]
        x = [t + np.maximum(norm(t, p["g2"], p["b2"]) @ p["w1"] + p["c1"], 0) @ p["w2"] + p["c2"] for t in x]
    z = np.mean([norm(t, w["gf"], w["bf"]) for t in x], axis=0) @ w["proj"]
    return z / np.linalg.norm(z)


def test_log_against_single_images(fitted, log):
    """Predictions of all models and transforms for a few images, from a forward pass written once more."""
    rows = {r["doc_id"]: r for r in fitted.rows.where("split = 'test'").orderBy("doc_id").limit(3).collect()}
    specs = ("identity", "blur", "scramble:8", "remove:short_word", "edges")
    told = {(r.model, r.transform, r.image_id): (r.pred, r.pred0, r.y) for r in log.itertuples()}
    assert len(told) == len(log) == len(fitted.models) * len(rasters.TRANSFORMS) * fitted.rows.where("split = 'test'").count()
    for i, r in rows.items():
        base = np.frombuffer(r["pixels"], np.uint8).reshape(56, 56, 3).astype(np.float32)
        assert np.array_equal(base, np.clip(np.round(rasters.of_text(r["text"] or "")), 0, 255))
        for spec in specs:
            image = rasters.apply(spec, r["text"] or "", base, 42, i)
            for name, m in fitted.models.items():
                f = one_image(m.merged(), image)
                if "head" in m.extra:
                    score = f @ m.extra["head"] + m.extra["bias"]
                else:
                    score = enc.HEAT * m.texts @ f * (m.extra["scale"] if m.extra and "scale" in m.extra else 1) + (m.extra["shift"] if "shift" in m.extra else 0)
                top = np.sort(score)[-2:]
                pred, pred0, y = told[name, spec, i]
                assert y == r["y"] and pred0 == told[name, "identity", i][0]
                assert pred == score.argmax() or top[1] - top[0] < 1e-3


def counts(log):
    """What each (model, transform) counts, row by row."""
    out = collections.defaultdict(collections.Counter)
    first = {(r.model, r.image_id): r.pred for r in log.itertuples() if r.transform == "identity"}
    for r in log.itertuples():
        c, before = out[r.model, r.transform], first[r.model, r.image_id]
        c["n"] += 1
        c["correct0"] += before == r.y
        c["correct1"] += r.pred == r.y
        c["switched"] += r.pred != before
        c["lost"] += before == r.y != r.pred
        c["gained"] += before != r.y == r.pred
        c["moved"] += r.pred != before and r.y not in (r.pred, before)
    return out


def test_measures_of_the_study(spark, sf_dir, log):
    told = counts(log)
    plain = log[log["transform"] == "identity"]
    ladder_rows = {r["model"]: r for r in query(spark, sf_dir, "w4_ladder")}
    sizes = collections.Counter(plain[plain["model"] == "full"]["y"])
    for name, r in ladder_rows.items():
        c = told[name, "identity"]
        assert (r["n"], r["correct"]) == (c["n"], c["correct0"]) and r["accuracy"] == pytest.approx(c["correct0"] / c["n"])
        assert r["majority"] == pytest.approx(max(sizes.values()) / sum(sizes.values())) and r["chance"] == pytest.approx(1 / len(sizes))
        assert query(spark, sf_dir, f"adapt_{name}")[0]["correct"] == c["correct0"]
    for r in query(spark, sf_dir, "w5_per_class_gain"):
        own = [x for x in plain.itertuples() if x.y == r["y"]]
        right = lambda m: sum(x.pred == x.y for x in own if x.model == m)
        assert (r["correct"], r["base_correct"]) == (right(r["model"]), right("zero_shot")) and r["gain_points"] == pytest.approx(100 * (right(r["model"]) - right("zero_shot")) / sizes[r["y"]])
    for name, wanted in (("w6_cue_removal", probing.CUE_TRANSFORMS), ("w8_edges_and_blur", ("edges", "blur")), ("w9_scrambling", probing.SCRAMBLES), ("w12_joint", rasters.TRANSFORMS[1:])):
        rows = query(spark, sf_dir, name)
        assert {(r["model"], r["transform"]) for r in rows} == {(m, t) for m in enc.STRATEGIES for t in wanted}
        for r in rows:
            c = told[r["model"], r["transform"]]
            assert all(r[k] == c[k] for k in c if k in r)
            if "switch_rate" in r:
                assert r["switch_rate"] == pytest.approx(c["switched"] / c["n"])
            if "retention" in r:
                assert r["retention"] == (pytest.approx(c["correct1"] / c["correct0"]) if c["correct0"] else None)
            if "relative_drop" in r and c["correct0"]:
                assert r["relative_drop"] == pytest.approx(100 * (c["correct0"] - c["correct1"]) / c["correct0"])
            assert abs(c["correct0"] - c["correct1"]) <= c["switched"] == c["lost"] + c["gained"] + c["moved"]
    for r in query(spark, sf_dir, "w6_net_effect"):
        a, b = told[r["model"], f"remove:{r['cue']}"], told[r["model"], f"random:{r['cue']}"]
        assert r["net_switched"] == a["switched"] - b["switched"] and (r["removed_correct"], r["random_correct"]) == (a["correct1"], b["correct1"])
    for r in query(spark, sf_dir, "w9_regimes"):
        group = [told[m, r["transform"]]["switched"] for m in enc.STRATEGIES if (m in enc.FROZEN) == (r["regime"] == "frozen")]
        assert (r["least"], r["most"]) == (min(group), max(group))
    for r in query(spark, sf_dir, "w9_scramble_trend"):
        assert r["switched"] == told[r["model"], f"scramble:{r['size']}"]["switched"]


def test_centroid_error_of_the_study(spark, sf_dir, fitted, log):
    placed = {r["id"]: r for r in probing.positions(fitted.rows.select(F.col("doc_id").alias("id"), "y", "split"), "id", "y").collect()}
    assert len(placed) == fitted.rows.count()
    centres = {y: np.mean([(r["lat"], r["lon"]) for r in placed.values() if r["split"] == "train" and r["y"] == y], axis=0) for y in {r["y"] for r in placed.values()}}

    def km(a, b):
        (p, s), (q, t) = np.radians(a), np.radians(b)
        return 6371.0 * 2 * math.asin(math.sqrt(math.sin((q - p) / 2) ** 2 + math.cos(p) * math.cos(q) * math.sin((t - s) / 2) ** 2))

    for r in query(spark, sf_dir, "w4_centroid_error"):
        own = [x for x in log.itertuples() if x.model == r["model"] and x.transform == "identity"]
        at = lambda x: (placed[x.image_id]["lat"], placed[x.image_id]["lon"])
        assert r["n"] == len(own) and r["unplaced"] == 0
        assert r["km"] == pytest.approx(np.mean([km(at(x), centres[x.pred]) for x in own]), rel=2e-3)
        assert r["floor_km"] == pytest.approx(np.mean([km(at(x), centres[x.y]) for x in own]), rel=2e-3)


def test_prompts_and_controls(spark, sf_dir, fitted):
    test = fitted.rows.where("split = 'test'").orderBy("doc_id").collect()
    feature = fitted.models["zero_shot"].prepared(np.stack([np.frombuffer(r["pixels"], np.uint8).reshape(56, 56, 3) for r in test]))
    for r in query(spark, sf_dir, "w11_prompts"):
        texts = probing.class_texts(fitted.described, r["model"])
        assert r["n"] == len(test) and abs(r["correct"] - sum(int((texts @ f).argmax()) == x["y"] for f, x in zip(feature, test, strict=True))) <= 1
    control = query(spark, sf_dir, "w10_control")
    drawn = query(spark, sf_dir, "w10_control_ids")
    assert {r["transform"] for r in control} == set(probing.SCRAMBLES) and all(r["n"] <= len(drawn) for r in control)
    second = query(spark, sf_dir, "w10_second_control")
    assert all(0 <= r["correct1"] <= r["n"] and r["majority"] <= r["n"] for r in second) and len({r["n"] for r in second}) == 1


def test_prompt_texts(spark, sf_dir):
    """Descriptors by tf-idf between classes, worked out once more; the four conditions from them."""
    import re

    from geoprobe.operators import prompts

    corpus = prompts.alignment_corpus(spark.read.parquet(f"{sf_dir}/pages.parquet"), spark.read.parquet(f"{sf_dir}/conversations.parquet")).collect()
    counts = collections.defaultdict(collections.Counter)
    for r in corpus:
        if r["lang"]:
            counts[r["lang"]].update(w for w in re.split(r"[\W\d_]+", r["text"].lower()) if len(w) > 1)
    names = sorted(counts)
    holders = collections.Counter(w for own in counts.values() for w in own)
    top = {n: [w for w, _ in sorted(((w, c * math.log((len(names) + 1) / holders[w])) for w, c in own.items()), key=lambda x: (-x[1], x[0]))[: prompts.WORDS]] for n, own in counts.items()}
    told = {c: {r["region"]: r["text"] for r in query(spark, sf_dir, f"prompt_{c}")} for c in prompts.CONDITIONS}
    for i, n in enumerate(names):
        words = " ".join(top[n])
        assert told["visual_only"][i] == words == told["swapped"][(i + 1) % len(names)] and told["baseline"][i].endswith(words) and n in told["baseline"][i]
        assert told["baseline"][i] in told["padded"][i] and len(told["padded"][i].split()) > len(told["baseline"][i].split())
    assert all(set(t) == set(range(len(names))) for t in told.values())


def test_fast_marching_follows_its_surroundings():
    """On a ramp the fill lies between what surrounds it, follows the ramp, and doesn't depend on what was under the mask."""
    x = np.repeat(np.arange(56, dtype=np.float32)[None, :, None] * 4, 56, axis=0).repeat(3, axis=2)
    mask = np.zeros((56, 56), bool)
    mask[20:30, 20:28] = True
    out = rasters.inpainted(x, mask, "fast_marching")
    junk = x.copy()
    junk[mask] = 255
    assert np.array_equal(out, rasters.inpainted(junk, mask, "fast_marching"))
    assert out[mask].min() >= 4 * 17 - 1e-3 and out[mask].max() <= 4 * 30 + 1e-3
    assert out[24, 20, 0] < out[24, 27, 0] and abs(out[mask] - x[mask]).mean() < abs(rasters.inpainted(x, mask, "mean")[mask] - x[mask]).mean()


def test_strata(spark, sf_dir):
    rows = query(spark, sf_dir, "w17_content_strata")
    total = collections.Counter()
    for r in rows:
        total[r["split"], r["model"]] += r["n"]
        assert r["correct"] <= r["n"] and (r["split"], r["stratum"]) != ("strict", "copy in training")
    assert len({n for (split, _), n in total.items() if split == "strict"}) == 1 and len(total) == 2 * len(probing.STRATA_MODELS)


def test_variants(spark, sf_dir):
    rows = {r["model"]: r for r in query(spark, sf_dir, "ladder_variants")}
    assert {n for n in rows if n.startswith("text_score")} == {f"text_score_{s}" for s in enc.SHAPES}
    size = {n: r["parameters"] for n, r in rows.items()}
    assert size["text_score_scalar"] == 2 and size["text_score_per_dim"] == 2 * enc.OUT and size["low_rank_both"] == size["low_rank_attention"] + size["low_rank_perceptron"] < size["low_rank_head"]
    assert size["linear_texts"] == size["linear_zero"] == size["linear_normal"]


ROWS = [(i, ("the cat sat on " if i % 2 else "der hund lief im ") * (10 + i % 7) + f"number{i % 11}", i % 2, "val" if i % 5 == 0 else "train") for i in range(90)]


def test_exact_fits_do_not_depend_on_partitions(spark):
    texts = enc.text_features(["the cat", "der hund"])
    models = {s: enc.Model.start(s, enc.initial(), texts) for s in enc.STRATEGIES}
    made = []
    for parts in (1, 8):
        rows = spark.createDataFrame(ROWS, "doc_id long, text string, y int, split string").repartition(parts)
        made.append(ladder.trained_together(rows, models, ladder.Config(epochs=2)))
    for name in models:
        a, b = (m[name][0] for m in made)
        # Features are made in batches of the input, whose sizes change the last digits of a product.
        same = (lambda x, y: np.allclose(x, y, atol=1e-4)) if name in enc.FROZEN else np.array_equal
        assert all(same(a.tensor(k), b.tensor(k)) for k in a.trainable()) and same([h["train_loss"] for h in made[0][name][1]], [h["train_loss"] for h in made[1][name][1]])
        assert all(np.array_equal(a.encoder[k], models[name].encoder[k]) for k in a.encoder if k not in a.trainable())


def test_fit_is_sequential_descent(spark):
    """Exact mode takes the steps that a loop over seeded global batches of eight takes."""
    texts = enc.text_features(["the cat", "der hund"])
    start, config = enc.Model.start("linear", enc.initial(), texts, head_start="zero"), ladder.Config(epochs=3)
    got, history = ladder.trained(spark.createDataFrame(ROWS, "doc_id long, text string, y int, split string"), start, config)
    images = np.stack([rasters.from_bytes(rasters.to_bytes(rasters.of_text(r[1]))) for r in ROWS])
    x, y, train = start.prepared(images), np.array([r[2] for r in ROWS]), np.array([r[3] == "train" for r in ROWS])
    w, b, m, v, t, best = start.extra["head"].astype(float), start.extra["bias"].astype(float), 0, 0, 0, (-1, None)
    for epoch in range(3):
        rate = 3e-2 * (1 + math.cos(math.pi * epoch / 3)) / 2
        ids = np.flatnonzero(train)
        order = ids[ladder.epoch_order(ids, 42, epoch)]
        assert sorted(order) == ids.tolist()
        for i in range(0, len(order), 8):
            s = order[i : i + 8]
            p = np.exp(x[s] @ w + b)
            d = (p / p.sum(axis=1, keepdims=True) - np.eye(2)[y[s]]) / len(s)
            g = np.concatenate([(x[s].T @ d).ravel(), d.sum(axis=0)])
            t, m, v = t + 1, 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
            flat = np.concatenate([w.ravel(), b]) * (1 - rate * 0.01) - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
            w, b = flat[:-2].reshape(w.shape), flat[-2:]
        accuracy = float(((x[~train] @ w + b).argmax(axis=1) == y[~train]).mean())
        assert history[epoch]["val_acc"] == pytest.approx(accuracy)
        best = max(best, (accuracy, epoch), key=lambda r: r[0])
        if best[1] == epoch:
            kept = w.copy()
    assert np.allclose(got.extra["head"], kept, atol=1e-3)


@pytest.mark.parametrize("mode", ["local", "sync"])
def test_averaged_modes_over_many_tasks(spark, mode):
    """More tasks than a driver should hear from: their tensors are summed in groups first."""
    texts = enc.text_features(["the cat", "der hund"])
    rows = ladder.rasterised(spark.createDataFrame(ROWS, "doc_id long, text string, y int, split string"))
    start = enc.Model.start("linear", enc.initial(), texts, head_start="zero")
    made = [ladder.trained(rows.repartition(n, "doc_id"), start, ladder.Config(epochs=2, mode=mode))[1] for n in (1, 20)]
    assert all(h[-1]["train_loss"] < h[0]["train_loss"] for h in made)
    if mode == "sync":
        assert made[0][-1]["train_loss"] == pytest.approx(made[1][-1]["train_loss"], rel=1e-3)


def test_study_of_an_image_folder(spark, tmp_path):
    """Real image files, resized and cropped to the encoder's size, go through adaptation and probing as documents do."""
    from geoprobe.sources import images as files

    rng = np.random.default_rng(5)
    for i in range(60):
        light = 60 if i % 2 else 190
        made = np.clip(light + rng.integers(-40, 40, (64, 90, 3)), 0, 255).astype(np.uint8)
        (tmp_path / f"{i:03d}.ppm").write_bytes(b"P6 90 64 255\n" + made.tobytes())
    found = files.image_folder(spark, str(tmp_path), side=rasters.SIDE)
    number = F.regexp_extract("path", r"(\d+)\.ppm$", 1).cast("long")
    rows = found.select(number.alias("doc_id"), F.lit(None).cast("string").alias("text"), (number % 2).cast("int").alias("y"), F.when(number < 40, "train").when(number < 50, "val").otherwise("test").alias("split"), "pixels")
    texts = enc.text_features(["dark", "light"])
    models = {s: enc.Model.start(s, enc.initial(), texts) for s in ("zero_shot", "linear", "last_block")}
    made = {n: f[0] for n, f in ladder.trained_together(rows, models, ladder.Config(epochs=12, rates={"linear": 0.1, "last_block": 0.01})).items()}
    got = ladder.probed(rows.where("split = 'test'"), made, ("identity", "blur", "scramble:8", "remove:short_word")).toPandas()
    assert len(got) == 10 * 3 * 4
    plain = got[got["transform"] == "identity"]
    assert (plain[plain["model"] == "last_block"]["pred"] == plain[plain["model"] == "last_block"]["y"]).mean() >= 0.9
    bare = got[got["transform"] == "remove:short_word"]
    assert (bare["pred"] == bare["pred0"]).all()


def test_dropout_gradients():
    """Masks differ between examples, and gradients through them are right."""
    rng = np.random.default_rng(0)
    images, y = rng.random((3, 56, 56, 3)) * 255, np.array([0, 1, 2])
    texts = rng.standard_normal((3, enc.OUT)) / 8
    model = enc.Model.start("low_rank", {k: v.astype(np.float64) for k, v in enc.initial().items()}, texts, head="linear")
    model.extra = {k: v.astype(np.float64) + 0.02 * rng.standard_normal(v.shape) for k, v in model.extra.items()}
    at = lambda m: m.gradients(images, y, 0.3, np.random.default_rng(7))
    _, grads = at(model)
    for name in ("0.wq.a", "1.w2.b", "1.wo.a", "head"):
        place = tuple(rng.integers(0, n) for n in grads[name].shape)
        moved = []
        for e in (1e-5, -1e-5):
            t = model.tensor(name).copy()
            t[place] += e
            moved.append(at(model.replaced({name: t}))[0])
        assert (moved[0] - moved[1]) / 2e-5 == pytest.approx(grads[name][place], rel=5e-3, abs=1e-6)
    twins = np.stack([images[0]] * 2)
    drawn = np.random.default_rng(3)
    masks = {n: (drawn.random((2, len(model.encoder[n]))) >= 0.5) / 0.5 for n in model.adapters()}
    a, b = model.features(model.prepared(twins), masks)[0]
    assert not np.allclose(a, b)


def test_linear_probe_reaches_the_convex_optimum(spark):
    """Run to convergence, the probe's loss is that of an independent solver on the same features."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.linalg import Vectors

    rng = np.random.default_rng(1)
    x, y = rng.standard_normal((900, enc.OUT)).astype(np.float32), rng.integers(0, 3, 900)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    model = enc.Model.start("linear", enc.initial(), np.zeros((3, enc.OUT), np.float32))
    config = ladder.Config(epochs=400, batch=900, decay=0.0, rates={"linear": 0.1})
    _, history = ladder.fit_exact(model, np.arange(900), y, np.ones(900, bool), x, config)
    given = spark.createDataFrame([(Vectors.dense(a.tolist()), float(b)) for a, b in zip(x, y, strict=True)], ["features", "label"])
    ml = LogisticRegression(maxIter=200, tol=1e-9, family="multinomial", standardization=False).fit(given)
    assert history[-1]["train_loss"] == pytest.approx(ml.summary.objectiveHistory[-1], abs=1e-3)


def changed(spark, sf_dir, name):
    return {r["doc_id"]: r for r in catalogue.QUERIES[name](spark, sf_dir).collect()}


def digest(image):
    import hashlib

    return hashlib.md5(np.round(image).astype(np.int16).tobytes()).hexdigest()


@pytest.fixture(scope="module")
def images(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/documents.parquet").orderBy("doc_id").limit(25).collect()
    return {r["doc_id"]: (r["text"] or "", rasters.of_text(r["text"] or "")) for r in rows}


@pytest.mark.parametrize("n", [4, 8, 16])
def test_scramble_queries(spark, sf_dir, images, n):
    got = changed(spark, sf_dir, f"scramble_56_n{n}")
    for i, (_, x) in images.items():
        per = 56 // n
        order = rasters.generator(42, i, f"scramble:{n}").permutation(per * per)
        y = x.copy()
        for to, source in enumerate(order):
            for r in range(n):
                for c in range(n):
                    y[to // per * n + r, to % per * n + c] = x[source // per * n + r, source % per * n + c]
        assert got[i]["digest"] == digest(y) and got[i]["changed"] == int((abs(y - x).max(axis=2) > 1e-6).sum())


def test_blur_query(spark, sf_dir, images):
    got = changed(spark, sf_dir, "macro_blur_56")
    reach, sigma = 6, 2.0
    weights = np.exp(-0.5 * (np.arange(-reach, reach + 1) / sigma) ** 2)
    for i, (_, x) in list(images.items())[:6]:
        y = np.zeros(x.shape)
        for r in range(56):
            for c in range(56):
                rows, columns = np.clip(np.arange(r - reach, r + reach + 1), 0, 55), np.clip(np.arange(c - reach, c + reach + 1), 0, 55)
                y[r, c] = np.tensordot(np.outer(weights, weights) / weights.sum() ** 2, x[np.ix_(rows, columns)], 2)
        mine = rasters.blurred(x)
        assert np.allclose(mine, y, atol=1e-2) and got[i]["digest"] == digest(mine) and got[i]["changed"] > 0 or not x.any()


def test_edge_query(spark, sf_dir, images):
    """Smoothing, gradients, thinning and hysteresis, pixel by pixel."""
    got = changed(spark, sf_dir, "edges_56")
    for i, (_, x) in list(images.items())[:6]:
        grey = rasters.blurred(x.mean(axis=2, keepdims=True), 1.4)[:, :, 0].astype(float)
        p = np.pad(grey, 1, mode="edge")
        size, side = np.zeros((58, 58)), {}
        for r in range(56):
            for c in range(56):
                a = p[r : r + 3, c : c + 3]
                gx = (a[0, 2] + 2 * a[1, 2] + a[2, 2]) - (a[0, 0] + 2 * a[1, 0] + a[2, 0])
                gy = (a[2, 0] + 2 * a[2, 1] + a[2, 2]) - (a[0, 0] + 2 * a[0, 1] + a[0, 2])
                size[r + 1, c + 1] = math.hypot(gx, gy)
                side[r, c] = [(0, 1), (1, 1), (1, 0), (1, -1)][round(math.atan2(gy, gx) / (math.pi / 4)) % 4]
        top = {(r, c) for (r, c), (u, v) in side.items() if size[r + 1, c + 1] >= size[r + 1 + u, c + 1 + v] and size[r + 1, c + 1] >= size[r + 1 - u, c + 1 - v]}
        strong = [q for q in top if size[q[0] + 1, q[1] + 1] >= 200]
        seen = set(strong)
        while strong:
            r, c = strong.pop()
            for q in ((r + u, c + v) for u in (-1, 0, 1) for v in (-1, 0, 1)):
                if q in top and q not in seen and size[q[0] + 1, q[1] + 1] >= 100:
                    seen.add(q)
                    strong.append(q)
        mine = rasters.edges(x)[:, :, 0] > 0
        assert got[i]["digest"] == digest(rasters.edges(x))
        # Ties at thresholds and directions may fall otherwise in single precision.
        assert len(seen ^ set(zip(*map(lambda v: v.tolist(), np.nonzero(mine)), strict=True))) <= 0.02 * max(50, len(seen))


@pytest.mark.parametrize("cue", rasters.CUES)
def test_removal_and_random_mask_queries(spark, sf_dir, images, cue):
    removed, random_ = changed(spark, sf_dir, f"remove_cue_{cue}"), changed(spark, sf_dir, f"random_mask_{cue}")
    for i, (text, x) in images.items():
        mask = rasters.cue_mask(text, cue)
        other = rasters.random_mask(mask, 42, i, cue)
        assert removed[i]["masked"] == random_[i]["masked"] == mask.sum() == other.sum()
        for got, m in ((removed[i], mask), (random_[i], other)):
            y = x.copy()
            if m.all():
                y[m] = 0
            elif m.any():
                y[m] = [np.mean(x[~m][:, c]) for c in range(3)]
            assert got["changed"] <= m.sum() and (got["digest"] == digest(y) or np.allclose(rasters.inpainted(x, m), y, atol=0.01))


def test_weights_table(spark, fitted, tmp_path):
    ladder.weights_table(spark, fitted.models).write.parquet(str(tmp_path / "weights"))
    again = ladder.models_of(spark.read.parquet(str(tmp_path / "weights")))
    rng = np.random.default_rng(2)
    some = rng.integers(0, 256, (5, 56, 56, 3), np.uint8)
    a, b = ladder.predicted(fitted.models, some), ladder.predicted(again, some)
    assert again.keys() == fitted.models.keys() and all(np.array_equal(a[n], b[n]) for n in a)
    assert all(set(again[n].trainable()) == set(m.trainable()) for n, m in fitted.models.items())


def test_mask_table(spark, sf_dir, tmp_path, images):
    from geoprobe.operators import masks

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    table = masks.detected(docs)
    for _ in range(2):
        masks.write_masks(table, str(tmp_path / "masks"))
    got = {(r["doc_id"], r["cue"]): r for r in spark.read.parquet(str(tmp_path / "masks")).collect()}
    assert len(got) == 4 * docs.count()
    for i, (text, _) in images.items():
        for cue in rasters.CUES:
            mask, r = rasters.cue_mask(text, cue), got[i, cue]
            assert np.array_equal(masks.unpacked(r["mask"]), mask) and r["pixels"] == mask.sum() and r["coverage"] == pytest.approx(mask.mean())
    sizes = {r["cue"]: r for r in catalogue.QUERIES["cue_masks"](spark, sf_dir).collect()}
    assert all(sizes[c]["pixels"] == sum(r["pixels"] for (_, x), r in got.items() if x == c) for c in rasters.CUES)
    own = masks.detected(docs.limit(3), {"dark": lambda text: rasters.of_text(text).max(axis=2) == 0}).collect()
    assert {r["cue"] for r in own} == {"dark"}


def test_measures_over_the_log_need_no_exchange_of_it(spark, sf_dir):
    log = rule_logs.lineitem_log(spark, sf_dir)
    assert "pred0" in log.columns and measures.paired(log) is log
    bare = log.drop("pred0")
    assert sorted(map(tuple, measures.switches(bare).collect())) == sorted(map(tuple, measures.switches(log).collect()))


def test_passages_by_words(spark, sf_dir, monkeypatch):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(F.col("doc_id").alias("doc"), "text")
    rows = [r["text"] for r in docs.collect() if r["text"]]
    cut = [t[a:b] for t, a, b in ((rows[3], 5, 90), (rows[5], 0, 7), (rows[7], 3, 4), (rows[9], 2, 40), (rows[2], 10, 18)) if t[a:b]] + ["no such passage in any text here at all", "", "a", "two words"]
    passages = spark.createDataFrame(list(enumerate(cut)), "item long, passage string")
    want = {(r["doc"], i) for r in docs.collect() for i, p in enumerate(cut) if p and r["text"] is not None and p in r["text"]}
    for bound in (duplicates.BROADCAST_ANCHORS, 2):
        monkeypatch.setattr(duplicates, "BROADCAST_ANCHORS", bound)
        assert {tuple(r) for r in duplicates.containing(docs, passages).select("doc", "item").collect()} == want


def test_vector_pairs_against_all(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    x = np.stack([r["embedding"] for r in rows.orderBy("vec_id").collect()])
    ids = [r["vec_id"] for r in rows.orderBy("vec_id").collect()]
    far = np.sqrt(np.maximum(0, ((x[:, None] - x[None]) ** 2).sum(axis=2)))
    want = {(ids[a], ids[b]) for a, b in zip(*np.nonzero(np.triu(far < 1.1, 1)), strict=True)}
    got = {(r["a"], r["b"]): r["distance"] for r in duplicates.near_duplicates(rows, "embedding", "vec_id", 1.1).collect()}
    assert set(got) <= want and len(got) >= 0.9 * len(want) > 0


def test_linked_vectors_against_all(spark, sf_dir, monkeypatch):
    data = [(r["vec_id"], r["embedding"]) for r in spark.read.parquet(f"{sf_dir}/embeddings.parquet").orderBy("vec_id").limit(300).collect()]
    data += [(1000 + i, data[7][1]) for i in range(40)] + [(2000, None), (2001, []), (2002, [float("nan")] * 64), (2003, [1.0]), (2004, [2.0]), (2005, [1.0, None]), (None, data[9][1])]
    rows = spark.createDataFrame(data, "vec_id long, embedding array<float>").repartition(3)
    fit = lambda v: bool(v) and None not in v and np.isfinite(v).all()
    near = lambda v, w: fit(v) and fit(w) and len(v) == len(w) and math.dist(v, w) < 1.1
    want = {}
    links = [[j for j, (_, w) in enumerate(data) if j != i and near(v, w)] for i, (_, v) in enumerate(data)]
    for i in range(len(data)):
        seen, todo = {i}, [i]
        while todo:
            fresh = set(links[todo.pop()]) - seen
            seen |= fresh
            todo += fresh
        want[data[i][0]] = (min((data[j][0] for j in seen if data[j][0] is not None), default=None), len(links[i]))
    assert max(n for _, n in want.values()) >= 40 and len({c for c, _ in want.values()}) > 5
    for block, slab in ((4096, 32 << 20), (64, 100 * 256)):
        monkeypatch.setattr(duplicates, "BLOCK", block)
        monkeypatch.setattr(duplicates, "SLAB_BYTES", slab)
        got = duplicates.linked_vectors(rows, "vec_id", 1.1).collect()
        assert {r["vec_id"]: (r["class_id"], r["n_links"]) for r in got} == want and len(got) == len(data)
    pairs = {(r["a"], r["b"]): r["distance"] for r in duplicates.near_duplicates(rows, "embedding", "vec_id", 1.1).collect()}
    assert pairs == {(a, b): pytest.approx(math.dist(data[i][1], data[j][1])) for i, (a, _) in enumerate(data) for j in links[i] if (b := data[j][0]) is not None and a is not None and a < b}
    assert duplicates.linked_vectors(rows.limit(0), "vec_id", 1.1).count() == 0


def test_polygon_centre_and_null_predictions(spark):
    ring = "array(named_struct('lon', 1D, 'lat', 1D), named_struct('lon', 4D, 'lat', 1D), named_struct('lon', 1D, 'lat', 4D))"
    got = spatial.polygon_centroids(spark.sql(f"SELECT 7 AS region, {ring} AS ring")).first()
    assert (got["c_lat"], got["c_lon"]) == pytest.approx((2, 2))
    views = spark.createDataFrame([(34.0, -118.0, 0), (34.0, -118.0, 9), (34.0, -118.0, None)], "lat double, lon double, pred int")
    centres = spark.createDataFrame([(0, 34.0, -118.0)], "region int, c_lat double, c_lon double")
    r = spatial.centroid_error(views.withColumn("g", F.lit(1)), centres, ["g"]).first()
    assert (r["n"], r["unplaced"], r["km"]) == (3, 2, 0.0)


def test_split_is_written_and_read(spark, sf_dir, tmp_path):
    from geoprobe.operators import sampling
    from geoprobe.plans import geography

    rows = geography.split_rows(spark, sf_dir).select("image_id", "region", "split")
    sampling.write_split(rows, str(tmp_path / "split"))
    again = spark.read.parquet(str(tmp_path / "split"))
    assert sorted(map(tuple, again.select("image_id", "region", "split").collect())) == sorted(map(tuple, rows.collect()))


def test_swept_tables(spark):
    import os

    from geoprobe import session

    mark = session.tables_written()
    first, second = (session.checkpointed(spark.range(n)) for n in (3, 5))
    paths = [p for _, p in session._WRITTEN[mark:]]
    result = session.swept(second.withColumn("x", F.lit(1)), mark)
    local = [p.replace("file:", "") for p in paths]
    assert [os.path.exists(p) for p in local] == [False, True] and result.count() == 5 and session.tables_written() == mark + 1
    session.swept(None, mark)
    assert not os.path.exists(local[1]) and first is not None
