"""Accuracy, switching, retention and interval measures over one prediction log.

The log has a row per (model, transform, image_id): y the true class, pred the predicted one. A null prediction counts as
wrong, and as a switch if the other prediction isn't null. `identity` is the untouched input. Ratios come with their integer parts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

def _right(pred: str = "pred") -> Column:
    return F.coalesce(F.col(pred) == F.col("y"), F.lit(False))


def accuracy(log: DataFrame, by: list[str] | None = None) -> DataFrame:
    """n, correct, accuracy per group (model and transform by default)."""
    made = log.groupBy(*(by or ["model", "transform"])).agg(F.count("*").alias("n"), F.count_if(_right()).alias("correct"))
    return made.withColumn("accuracy", F.col("correct") / F.col("n"))


def accuracy_with_total(log: DataFrame, by: str) -> DataFrame:
    """Accuracy per model and `by`, with the model's total where `by` is null."""
    made = log.rollup("model", by).agg(F.count("*").alias("n"), F.count_if(_right()).alias("correct"))
    return made.where("model is not null").withColumn("accuracy", F.col("correct") / F.col("n"))


def paired(log: DataFrame) -> DataFrame:
    """Adds pred0, the same model's prediction on the untouched input. A log that was written with pred0 stays as it is, without any exchange;
    otherwise one exchange on (model, image), no self-join per transform."""
    if "pred0" in log.columns:
        return log
    image = Window.partitionBy("model", "image_id")
    first = F.max(F.when(F.col("transform") == "identity", F.struct(F.col("pred").alias("p")))).over(image)
    return log.withColumn("pred0", first["p"])


def switches(log: DataFrame, by: list[str] | None = None) -> DataFrame:
    """n, switched and its parts (lost: right to wrong, gained: wrong to right, moved: wrong to another wrong), n0 and n1
    correct before and after, for every transform but the identity."""
    rows = paired(log).where("transform <> 'identity'")
    changed = ~F.col("pred").eqNullSafe(F.col("pred0"))
    was, now = _right("pred0"), _right()
    return rows.groupBy(*(by or ["model", "transform"])).agg(
        F.count("*").alias("n"), F.count_if(changed).alias("switched"), F.count_if(was & ~now).alias("lost"), F.count_if(~was & now).alias("gained"), F.count_if(changed & ~was & ~now).alias("moved"), F.count_if(was).alias("correct0"), F.count_if(now).alias("correct1")
    )


def switch_rate(log: DataFrame) -> DataFrame:
    return switches(log).select("model", "transform", "n", "switched", (F.col("switched") / F.col("n")).alias("switch_rate"))


def accuracy_drop(log: DataFrame) -> DataFrame:
    """Points lost, may be negative."""
    return switches(log).select("model", "transform", "n", "correct0", "correct1", (100.0 * (F.col("correct0") - F.col("correct1")) / F.col("n")).alias("drop_points"))


def retention(log: DataFrame) -> DataFrame:
    """Share of the own original accuracy that is kept (null if that is 0), and the relative drop in percent."""
    kept = F.expr("try_divide(correct1, correct0)")
    return switches(log).select("model", "transform", "correct0", "correct1", kept.alias("retention"), (100.0 * (1 - kept)).alias("relative_drop"))


def net_effect(log: DataFrame) -> DataFrame:
    """Switches under `remove:<cue>` less those under `random:<cue>`, per model and cue."""
    parts = switches(log).withColumn("family", F.split_part("transform", F.lit(":"), F.lit(1))).withColumn("cue", F.split_part("transform", F.lit(":"), F.lit(2)))
    picked = parts.where("family in ('remove', 'random')").groupBy("model", "cue").pivot("family", ["remove", "random"]).agg(F.sum("switched"), F.sum("correct1"))
    columns = [c for c in picked.columns if c not in ("model", "cue")]
    return picked.select("model", "cue", *(F.col(f"`{c}`").alias(n) for c, n in zip(columns, ("removed_switched", "removed_correct", "random_switched", "random_correct"), strict=True))).withColumn("net_switched", F.col("removed_switched") - F.col("random_switched"))


def gain(log: DataFrame, base: str, by: list[str]) -> DataFrame:
    """Correct answers of each model on the untouched input beyond those of the base model, per group."""
    per = log.where("transform = 'identity'").groupBy(*by, "model").agg(F.count("*").alias("n"), F.count_if(_right()).alias("correct"))
    first = F.max(F.when(F.col("model") == base, F.col("correct"))).over(Window.partitionBy(*by))
    return per.withColumn("base_correct", first).withColumn("gain_points", 100.0 * (F.col("correct") - F.col("base_correct")) / F.col("n"))


def confusion(log: DataFrame) -> DataFrame:
    """n per (model, y, pred) on the untouched input, with the size of the true class."""
    per = log.where("transform = 'identity'").groupBy("model", "y", "pred").agg(F.count("*").alias("n"))
    return per.withColumn("of_class", F.sum("n").over(Window.partitionBy("model", "y")))


def ordered(log: DataFrame) -> DataFrame:
    """Rank of the transforms by switches within each model, most first, ties by name."""
    return switches(log).select("model", "transform", "switched", F.row_number().over(Window.partitionBy("model").orderBy(F.desc("switched"), "transform")).cast("long").alias("place"))


def order_agreement(log: DataFrame) -> DataFrame:
    """Spearman correlation of the transforms' places between every two models, over the K transforms that they share."""
    a, b = ordered(log), ordered(log).select(F.col("model").alias("other"), "transform", F.col("place").alias("place2"))
    both = a.join(b, "transform").where("model < other")
    made = both.groupBy("model", "other").agg(F.count("*").alias("k"), F.sum(F.pow(F.col("place") - F.col("place2"), F.lit(2))).cast("long").alias("squares"))
    return made.withColumn("spearman", F.expr("1 - try_divide(6.0D * squares, k * (k * k - 1))"))


def trend(log: DataFrame, family: str) -> DataFrame:
    """Switches of `<family>:<n>` by n, and whether they fall from one n to the next."""
    sized = switches(log).where(F.col("transform").startswith(f"{family}:")).withColumn("size", F.split_part("transform", F.lit(":"), F.lit(2)).cast("int"))
    before = F.lag("switched").over(Window.partitionBy("model").orderBy("size"))
    return sized.select("model", "size", "switched", (F.col("switched") <= before).alias("falls"))


def regimes(log: DataFrame, frozen: list[str]) -> DataFrame:
    """Least and most switches of the frozen and of the adapted models, per transform."""
    kind = F.when(F.col("model").isin(frozen), "frozen").otherwise("adapted")
    return switches(log).groupBy(kind.alias("regime"), "transform").agg(F.min("switched").alias("least"), F.max("switched").alias("most"))


def wilson(log: DataFrame, z: float = 1.959963984540054) -> DataFrame:
    """Accuracy with its Wilson score interval."""
    made = accuracy(log)
    p, n = F.col("accuracy"), F.col("n")
    middle, half = p + z * z / (2 * n), z * F.sqrt(p * (1 - p) / n + z * z / (4 * n * n))
    return made.select("model", "transform", "n", "correct", ((middle - half) / (1 + z * z / n)).alias("low"), ((middle + half) / (1 + z * z / n)).alias("high"))


def mcnemar(log: DataFrame) -> DataFrame:
    """Paired test statistic of lost against gained answers (null if there are none)."""
    return switches(log).select("model", "transform", "lost", "gained", F.expr("try_divide(CAST((lost - gained) * (lost - gained) AS DOUBLE), lost + gained)").alias("chi_square"))


def bootstrap(log: DataFrame, rounds: int = 50, seed: int = 42) -> DataFrame:
    """Seeded Poisson bootstrap of accuracy: hash weights, so the same resamples at any partitioning. Each row adds its
    weighted counts to all rounds at once in an array that is summed."""
    from ..functions.scalars import hash01

    weights = []
    for i in range(rounds):
        u = hash01(F.concat(F.lit(f"{seed}|b{i}|"), F.col("image_id").cast("string")))
        weights.append(sum(((u >= c).cast("int") for c in (0.36787944, 0.73575888, 0.91969860, 0.98101184, 0.99634015)), F.lit(0)))
    sums = [F.sum(w).alias(f"n{i}") for i, w in enumerate(weights)] + [F.sum(F.when(_right(), w).otherwise(0)).alias(f"c{i}") for i, w in enumerate(weights)]
    made = log.groupBy("model", "transform").agg(*sums)
    shares = F.array_sort(F.array(*(F.col(f"c{i}") / F.col(f"n{i}") for i in range(rounds))))
    return made.select("model", "transform", F.element_at(shares, max(1, round(rounds * 0.025))).alias("low"), F.element_at(shares, round(rounds * 0.975)).alias("high"))


def joint_table(log: DataFrame) -> DataFrame:
    """Accuracy on the untouched input beside switches and kept accuracy of every transform."""
    return switches(log).select("model", "transform", "n", "correct0", "switched", "correct1", (F.col("correct0") / F.col("n")).alias("accuracy"), (F.col("switched") / F.col("n")).alias("switch_rate"), F.expr("try_divide(correct1, correct0)").alias("retention"))


def by_stratum(log: DataFrame, strata: DataFrame) -> DataFrame:
    """Accuracy within each stratum (image_id, stratum) of an audit."""
    return accuracy(log.join(strata, "image_id"), ["model", "transform", "stratum"])


def best_epoch(runs: DataFrame) -> DataFrame:
    """The epoch of each method with the most right answers on its n validation rows, the earliest of equals."""
    return runs.groupBy("method").agg(F.max("n").alias("n"), F.max_by("epoch", F.struct("correct", -F.col("epoch"))).alias("epoch"), F.max("correct").alias("correct"))


def append_log(log: DataFrame, path: str) -> None:
    """Write predictions so that a rerun replaces exactly the models and transforms that it holds."""
    log.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("model", "transform").parquet(path)
