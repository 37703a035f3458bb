"""Queries that once made up their data read the given tables."""

import math
import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from geoprobe import catalogue
from geoprobe.operators import encoder as enc
from geoprobe.operators import measures, spatial
from geoprobe.plans import probing, rule_logs
from geoprobe.sources.tables import REGIONS, captures, load


@pytest.fixture
def folder(spark, sf_dir, tmp_path):
    """A folder with the first rows of a table with other values, and the other tables as they are."""

    def make(name, change, rows=200):
        for entry in os.listdir(sf_dir):
            os.symlink(f"{sf_dir}/{entry}", tmp_path / entry)
        given = load(spark, sf_dir, name).limit(rows)
        out = given.collect()
        made = spark.createDataFrame([tuple((r.asDict() | change(r))[c] for c in given.columns) for r in out], ", ".join(f"{c} {'string' if c in change(out[0]) and isinstance(change(out[0])[c], str) else t}" for c, t in given.dtypes))
        (tmp_path / f"{name}.parquet").unlink()
        made.select(*(F.col(c).cast(t) for c, t in given.dtypes)).write.parquet(str(tmp_path / f"{name}.parquet"))
        return str(tmp_path)

    return make


def test_raster_blocks_of_the_vectors(spark, sf_dir):
    vectors = {r["vec_id"]: r["embedding"] for r in load(spark, sf_dir, "embeddings").collect()}
    rows = catalogue.QUERIES["raster_blocks"](spark, sf_dir).collect()
    assert len(rows) == 4 * len(vectors) and {(r["top"], r["left_"]) for r in rows} == {(0, 0), (0, 3), (3, 0), (3, 3)}
    for r in rows[:50]:
        assert r["pixels"] == sum(math.floor(vectors[r["vec_id"]][y * 8 + x] * 1e6 + 0.5) for y in range(r["top"], r["top"] + 3) for x in range(r["left_"], r["left_"] + 3))


def test_polygons_of_the_views(spark, sf_dir, folder):
    got = {r["region"]: r for r in catalogue.QUERIES["region_centroids_polygon"](spark, sf_dir).collect()}
    views = captures(spark, sf_dir).groupBy("region").agg(*(f(c).alias(f"{n}_{c}") for n, f in (("low", F.min), ("high", F.max)) for c in ("lat", "lon"))).collect()
    assert len(got) == len(views) == 8 and all(r[f"low_{c}"] < got[r["region"]][f"c_{c}"] < r[f"high_{c}"] for r in views for c in ("lat", "lon"))
    rows = [(0, 2.0, 0.0), (0, 4.0, 2.0), (0, 2.0, 4.0), (0, 0.0, 2.0), (0, 2.0, 2.0), (1, 5.0, 5.0)]
    made = {r["region"]: r for r in spatial.polygon_centroids(spatial.outer_rings(spark.createDataFrame(rows, "region int, lon double, lat double"))).collect()}
    assert made[0]["c_lat"] == pytest.approx(2) and made[0]["c_lon"] == pytest.approx(2) and made[1]["c_lat"] is None
    few = catalogue.QUERIES["region_centroids_polygon"](spark, folder("events", lambda r: {}, 1)).collect()
    assert [r["c_lat"] for r in few] == [None]


def test_trainable_parameters_follow_the_classes_of_the_pages(spark, sf_dir, folder):
    many, few = ({r["strategy"]: r for r in catalogue.QUERIES["trainable_parameters"](spark, d).collect()} for d in (sf_dir, folder("pages", lambda r: dict(html='<html lang="en"><p>one text of many words here</p></html>'))))
    assert many["linear"]["classes"] > 1 and few["linear"]["classes"] == 1 and few["linear"]["parameters"] < many["linear"]["parameters"]
    want = enc.Model.start("linear", enc.initial(), np.zeros((many["linear"]["classes"], enc.OUT), np.float32)).trainable_parameters()
    assert many["linear"]["parameters"] == want


def test_lr_schedule_counts_training_documents(spark, sf_dir, folder):
    got = {r["epoch"]: r for r in catalogue.QUERIES["lr_schedule"](spark, sf_dir).collect()}
    train = probing.sampled(probing.scenes(spark, sf_dir)).where("split = 'train'").count()
    assert train > 0 and all(r["images"] == train and r["first_step"] == e * r["steps"] and 8 * r["steps"] - 8 < train <= 8 * r["steps"] for e, r in got.items())
    assert [got[e]["rate_1e12"] for e in range(10)] == [math.floor(1e8 * (1 + math.cos(math.pi * e / 10)) / 2 + 0.5) for e in range(10)]
    fewer = catalogue.QUERIES["lr_schedule"](spark, folder("documents", lambda r: {}, 40)).first()
    assert 0 < fewer["images"] <= 40


def test_checkpoint_choice_reads_orders(spark, folder):
    priced = lambda p, year: dict(o_totalprice=p, o_orderdate=f"{year}-05-05", o_orderpriority="1-URGENT")
    made = folder("orders", lambda r: priced(120_000.0, 1993))
    assert {r["method"]: (r["epoch"], r["correct"] == r["n"] > 0) for r in catalogue.QUERIES["checkpoint_choice"](spark, made).collect()} == {"by_price": (2, True), "by_date": (2, True)}
    runs = spark.createDataFrame([("linear", 0, 4, 2), ("linear", 1, 4, 3), ("linear", 2, 4, 3), ("full", 0, 4, 4), ("full", 1, 4, 3)], "method string, epoch int, n long, correct long")
    assert {r["method"]: r["epoch"] for r in measures.best_epoch(runs).collect()} == {"linear": 1, "full": 0}


def test_published_accuracy_is_that_of_the_views(spark, sf_dir, folder):
    views = load(spark, sf_dir, "events").count()
    for r in catalogue.QUERIES["published_accuracy"](spark, sf_dir).collect():
        assert r["n"] == views and abs(r["percent"] - r["published"]) < 6 and r["published"] == round(100 * rule_logs.CORRECT[r["model"]] / rule_logs.TEST, 2)
    assert {r["n"] for r in catalogue.QUERIES["published_accuracy"](spark, folder("events", lambda r: {}, 50)).collect()} == {50}


def test_published_switch_rates_are_those_of_the_views(spark, sf_dir):
    views, rows = load(spark, sf_dir, "events").count(), catalogue.QUERIES["published_switch_rates"](spark, sf_dir).collect()
    assert len(rows) == sum(map(len, rule_logs.SWITCHED.values()))
    for r in rows:
        assert r["percent"] == pytest.approx(100 * r["switched"] / views, abs=0.006) and abs(r["percent"] - r["published"]) < 6


def test_published_regions_are_those_of_the_views(spark, sf_dir):
    views = {r["region"]: r["n"] for r in load(spark, sf_dir, "events").groupBy((F.col("user_id") % 8).alias("region")).agg(F.count("*").alias("n")).collect()}
    got = {r["region"]: r for r in catalogue.QUERIES["published_regions"](spark, sf_dir).collect()}
    assert {n: got[n]["n"] for _, _, n in REGIONS} == {n: views[r] for r, _, n in REGIONS}
    for name, (images, zero, full) in rule_logs.REGION_COUNTS.items():
        assert abs(got[name]["zero_shot"] - 100 * zero / images) < 20 and abs(got[name]["full_update"] - 100 * full / images) < 20


def test_published_prompts_are_those_of_the_views(spark, sf_dir, folder):
    got = {r["condition"]: r for r in catalogue.QUERIES["published_prompts"](spark, sf_dir).collect()}
    assert {c for c, r in got.items() if r["below_chance"]} == {"swapped"} and all(abs(r["percent"] - r["published"]) < 6 for r in got.values())
    one = catalogue.QUERIES["published_prompts"](spark, folder("events", lambda r: {}, 1)).collect()
    assert len(one) == 4 and {r["percent"] for r in one} <= {0.0, 100.0}


def test_published_control_is_that_of_the_views(spark, sf_dir, folder):
    got = {r["transform"]: r for r in catalogue.QUERIES["published_control"](spark, sf_dir).collect()}
    assert set(got) == set(rule_logs.CONTROL_CORRECT) - {"identity"} and all(abs(r["relative_drop"] - r["published"]) < 6 for r in got.values())
    some = catalogue.QUERIES["published_control"](spark, folder("events", lambda r: {}, 30)).collect()
    assert all(0 <= r["correct"] <= 30 for r in some)
