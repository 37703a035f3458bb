"""Prediction logs with exact answers: threshold rules over `lineitem`, and logs that reproduce published counts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.scalars import seeded
from ..session import spread
from ..sources.tables import load

#: Counts that the published percentages of 1,363 (control: 2,000) test images stand for.
TEST, CONTROL = 1363, 2000
CORRECT = {"zero_shot": 532, "text_score": 565, "linear": 525, "last_block": 1035, "low_rank": 1068, "full": 1119}
SWITCHED = {
    "scramble:16": {"zero_shot": 169, "text_score": 199, "linear": 147, "last_block": 621, "low_rank": 589, "full": 585},
    "scramble:32": {"zero_shot": 119, "text_score": 126, "linear": 108, "last_block": 563, "low_rank": 415, "full": 391},
    "scramble:64": {"zero_shot": 72, "text_score": 88, "linear": 67, "last_block": 492, "low_rank": 310, "full": 235},
    "remove:vegetation": {"zero_shot": 97, "low_rank": 108, "full": 104},
    "remove:sky": {"zero_shot": 60, "low_rank": 77, "full": 64},
    "remove:text": {"zero_shot": 12, "low_rank": 25, "full": 2},
    "remove:vehicles": {"zero_shot": 9, "low_rank": 26, "full": 15},
}
REGION_COUNTS = {"downtown": (149, 53, 135), "pasadena": (225, 80, 203), "beverly hills": (262, 159, 221), "santa monica": (187, 68, 154), "hollywood": (180, 29, 138), "long beach": (180, 66, 136), "venice beach": (90, 62, 68), "koreatown": (90, 15, 64)}
PROMPTS = {"padded": 522, "baseline": 532, "visual_only": 494, "swapped": 152}
CONTROL_CORRECT = {"identity": 1793, "scramble:16": 678, "scramble:32": 1228, "scramble:64": 1572}

RULES, BLOCK_SIZES = ("by_quantity", "by_discount", "by_date"), (4, 16)


def image_id():
    """Order and line do not identify a row of the given table; with the part and the price in cents they do."""
    return F.concat_ws("|", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.floor(F.col("l_extendedprice") * 100 + 0.5).cast("long").cast("string"))


IMAGE_SQL = "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, floor(l_extendedprice * 100 + 0.5)::BIGINT)"


def _rule(name: str, q, d, t):
    if name == "by_quantity":
        return F.when(q < 17, 0).when(q < 34, 1).otherwise(2)
    if name == "by_discount":
        return F.floor(d * 100 + 0.5).cast("int") % 3
    return F.when(t < "1995-06-17", F.when(F.floor(q) % 2 == 0, 0).otherwise(2)).otherwise(1)


def lineitem_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three rules on the untouched columns, on coarsened ones, with a column replaced by a constant (and, as its control,
    by another row's value), and with columns permuted inside blocks of orders; one pass, no join."""
    rows = load(spark, sf_dir, "lineitem").select(
        image_id().alias("image_id"), F.col("l_orderkey").alias("o"), F.col("l_quantity").alias("q"), F.col("l_discount").alias("d"), F.date_format("l_shipdate", "yyyy-MM-dd").alias("t"),
        F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2).alias("y"),
    )
    for n in BLOCK_SIZES:
        block = Window.partitionBy(F.floor(F.col("o") / n)).orderBy(F.md5(F.concat(F.lit("42|b|"), "image_id")))
        whole = block.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
        rows = rows.withColumns({f"{c}{n}": F.coalesce(F.lead(c).over(block), F.first(c).over(whole)) for c in "qdt"})
    q, d, t = F.col("q"), F.col("d"), F.col("t")
    inputs = {
        "identity": (q, d, t), "coarse": (F.floor(q / 10) * 10, F.floor(d * 20) / 20, F.concat(F.substring(t, 1, 4), F.lit("-01-01"))),
        "remove:quantity": (F.lit(25.0), d, t), "random:quantity": (F.col("q4"), d, t), "remove:discount": (q, F.lit(0.05), t), "random:discount": (q, F.col("d4"), t),
        **{f"scramble:{n}": (F.col(f"q{n}"), F.col(f"d{n}"), F.col(f"t{n}")) for n in BLOCK_SIZES},
    }
    rows = rows.withColumns({f"pred0_{m}": _rule(m, q, d, t).cast("int") for m in RULES})
    cells = F.array(*(F.struct(F.lit(m).alias("model"), F.lit(x).alias("transform"), _rule(m, *v).cast("int").alias("pred"), F.col(f"pred0_{m}").alias("pred0")) for m in RULES for x, v in inputs.items()))
    return rows.select("image_id", "y", F.explode(cells).alias("c")).select("c.model", "c.transform", "image_id", "y", "c.pred", "c.pred0")


def _rule_sql(name: str, q: str, d: str, t: str) -> str:
    return {
        "by_quantity": f"CASE WHEN {q} < 17 THEN 0 WHEN {q} < 34 THEN 1 ELSE 2 END", "by_discount": f"floor({d} * 100 + 0.5)::INT % 3",
        "by_date": f"CASE WHEN {t} < '1995-06-17' THEN CASE WHEN floor({q})::INT % 2 = 0 THEN 0 ELSE 2 END ELSE 1 END",
    }[name]


def lineitem_log_sql() -> str:
    """The same log as common table expressions ending in `log`."""
    shifted = ", ".join(f"coalesce(lead({c}) OVER w{n}, first({c}) OVER w{n}) AS {c}{n}" for n in BLOCK_SIZES for c in "qdt")
    windows = ", ".join(f"w{n} AS (PARTITION BY o // {n} ORDER BY md5('42|b|' || image_id))" for n in BLOCK_SIZES)
    inputs = {
        "identity": ("q", "d", "t"), "coarse": ("(floor(q / 10) * 10)", "(floor(d * 20) / 20)", "(substr(t, 1, 4) || '-01-01')"), "remove:quantity": ("25.0", "d", "t"), "random:quantity": ("q4", "d", "t"), "remove:discount": ("q", "0.05", "t"),
        "random:discount": ("q", "d4", "t"), **{f"scramble:{n}": (f"q{n}", f"d{n}", f"t{n}") for n in BLOCK_SIZES},
    }
    parts = " UNION ALL ".join(f"SELECT '{m}' AS model, '{x}' AS transform, image_id, y, {_rule_sql(m, *v)} AS pred FROM moved" for m in RULES for x, v in inputs.items())
    return f"""WITH base AS (SELECT {IMAGE_SQL} AS image_id, l_orderkey AS o, l_quantity AS q, l_discount AS d, strftime(l_shipdate, '%Y-%m-%d') AS t,
CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END AS y FROM lineitem),
moved AS (SELECT *, {shifted} FROM base WINDOW {windows}),
log AS ({parts}),
pairs AS (SELECT l.*, i.pred AS pred0 FROM log l JOIN log i ON i.model = l.model AND i.image_id = l.image_id AND i.transform = 'identity' WHERE l.transform <> 'identity'),
sw AS (SELECT model, transform, count(*)::BIGINT AS n, count(*) FILTER (WHERE pred <> pred0)::BIGINT AS switched, count(*) FILTER (WHERE pred0 = y AND pred <> y)::BIGINT AS lost, count(*) FILTER (WHERE pred0 <> y AND pred = y)::BIGINT AS gained,
count(*) FILTER (WHERE pred <> pred0 AND pred0 <> y AND pred <> y)::BIGINT AS moved, count(*) FILTER (WHERE pred0 = y)::BIGINT AS correct0, count(*) FILTER (WHERE pred = y)::BIGINT AS correct1 FROM pairs GROUP BY model, transform)
"""


def counted(spark: SparkSession, cells: list[tuple[str, str, int, int]]) -> DataFrame:
    """A log from (model, transform, images, agreeing): the first `agreeing` images are predicted as class 0, their true class, the rest as 1."""
    cell = spark.createDataFrame(cells, "model string, transform string, images int, agreeing int")
    rows = cell.select("model", "transform", "agreeing", F.explode(F.sequence(F.lit(1), F.col("images"))).alias("image_id"))
    return rows.select("model", "transform", "image_id", F.lit(0).alias("y"), F.when(F.col("image_id") <= F.col("agreeing"), 0).otherwise(1).alias("pred"))


def published_log(spark: SparkSession) -> DataFrame:
    """Accuracy of the six strategies on the untouched input."""
    return counted(spark, [(m, "identity", TEST, n) for m, n in CORRECT.items()])


def published_switches(spark: SparkSession) -> DataFrame:
    """Predictions that change for the published numbers of images; the untouched input is always class 0."""
    cells = [(m, "identity", TEST, TEST) for m in CORRECT]
    return counted(spark, cells + [(m, x, TEST, TEST - n) for x, per in SWITCHED.items() for m, n in per.items()])


def replayed(spark: SparkSession, sf_dir: str, cells: list[tuple]) -> DataFrame:
    """A log over the views of `events` at published rates, from cells (model, transform, images, agreeing) or (..., region) for one region only: a view stands by
    its hash at one of so many places, and is predicted as its region at the first `agreeing` of them, as the next region at the others. One pass, beside the broadcast cells."""
    views = spread(load(spark, sf_dir, "events").select("event_id", "user_id")).where("user_id is not null").select(F.col("event_id").alias("image_id"), F.pmod("user_id", F.lit(8)).cast("int").alias("y"), seeded(42, "p", F.col("event_id")).alias("u"))
    before = {m: (n, k) for m, x, n, k, *_ in cells if x == "identity"}
    told = [(m, x, n, k, *before.get(m, (None, None)), *(of or [None])) for m, x, n, k, *of in cells]
    cell = F.broadcast(spark.createDataFrame(told, "model string, transform string, images int, agreeing int, images0 int, agreeing0 int, of int"))
    pred = lambda images, agreeing: F.when(F.floor(F.col("u") * F.col(images)) < F.col(agreeing), F.col("y")).otherwise(F.pmod(F.col("y") + 1, F.lit(8)))
    # Every view has a place below 1; said in the condition, its hash is worked out once, not again for each cell.
    log = views.join(cell, (F.coalesce("u", F.lit(0.0)) < F.col("images")) & (F.col("of").isNull() | (F.col("of") == F.col("y"))))
    return log.select("model", "transform", "image_id", "y", pred("images", "agreeing").alias("pred"), F.when(F.col("images0").isNotNull(), pred("images0", "agreeing0")).alias("pred0"))
