"""Queries on vectors and 8 x 8 rasters of `embeddings`, with their SQL twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.scalars import hash01_sql
from ..operators import vectors
from ..sources.tables import load

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def register(sql: str | None = None):
    def keep(fn):
        QUERIES[fn.__name__] = fn
        if sql:
            ORACLE_SQL[fn.__name__] = sql
        return fn

    return keep


def _printed(column: str = "embedding"):
    """Pixels as whole millionths in one string, which both engines print alike."""
    return F.array_join(F.transform(column, lambda x: F.floor(x.cast("double") * 1e6 + 0.5).cast("long").cast("string")), ",")


_PRINT = "array_to_string(list_transform({}, lambda x: floor(x::DOUBLE * 1000000 + 0.5)::BIGINT), ',')"


def _zero_shot_sql(label: str = "label", source: str = "embeddings", shift: int = 0) -> str:
    u = hash01_sql("'42|e|' || vec_id")
    wanted = f"((of + {shift}) % 10)" if shift else "of"
    return f"""WITH v AS (SELECT vec_id, embedding, {label} AS label, CASE WHEN {u} < 0.7 THEN 'train' WHEN {u} < 0.85 THEN 'val' ELSE 'test' END AS split FROM {source}),
m AS (SELECT label AS of, i, avg(embedding[i]::DOUBLE) AS x FROM v, range(1, 65) r(i) WHERE split = 'train' GROUP BY label, i), c AS (SELECT {wanted} AS of, list(x ORDER BY i) AS centre FROM m GROUP BY of),
s AS (SELECT vec_id, label, of, floor(list_cosine_similarity(embedding::DOUBLE[], centre) * 1000000000 + 0.5) AS score FROM v, c WHERE split = 'test')
SELECT vec_id, label, arg_min(of, (-score, of))::INT AS pred FROM s GROUP BY vec_id, label"""


def _zero_shot(rows, shift: int = 0):
    rows = rows.withColumn("split", vectors.split_of(F.col("vec_id")))
    matrix = vectors.class_matrix(rows.where("split = 'train'"), "label", 64)
    if shift:
        matrix = matrix.withColumn("of", ((F.col("of") + shift) % 10).cast("int"))
    return vectors.zero_shot(rows.where("split = 'test'"), matrix).select("vec_id", "label", F.col("pred").cast("int").alias("pred"))


@register(_zero_shot_sql())
def zero_shot_vectors(spark, sf_dir):
    return _zero_shot(load(spark, sf_dir, "embeddings"))


@register(_zero_shot_sql(shift=1))
def zero_shot_vectors_swapped(spark, sf_dir):
    """Class vectors handed to the next class: a falsification of label use."""
    return _zero_shot(load(spark, sf_dir, "embeddings"), shift=1)


_PERMUTED = "(SELECT vec_id, embedding, coalesce(lead(label) OVER w, first(label) OVER (PARTITION BY vec_id // 64 ORDER BY md5('42|l|' || vec_id) ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)) AS label FROM embeddings WINDOW w AS (PARTITION BY vec_id // 64 ORDER BY md5('42|l|' || vec_id)))"


@register(_zero_shot_sql(source=_PERMUTED))
def zero_shot_permuted_labels(spark, sf_dir):
    return _zero_shot(vectors.permuted_labels(load(spark, sf_dir, "embeddings")))


@register("SELECT count(*)::BIGINT AS n, count(DISTINCT lang)::BIGINT AS classes, max(n_lang)::BIGINT AS majority FROM (SELECT lang, count(*) OVER (PARTITION BY lang) AS n_lang FROM documents)")
def chance_and_majority(spark, sf_dir):
    per = load(spark, sf_dir, "documents").groupBy("lang").agg(F.count("*").alias("n"))
    return per.agg(F.sum("n").alias("n"), F.count("*").alias("classes"), F.max("n").alias("majority"))


def _scramble_sql(n: int, scope: str = "vec_id") -> str:
    per = 8 // n
    return f"""WITH o AS (SELECT vec_id, embedding, list_transform(list_sort(list_transform(range(0, {per * per}), lambda i: {{'h': md5('42|x{n}|' || {scope} || '|' || i), 'i': i}})), lambda r: r.i) AS ord FROM embeddings)
SELECT vec_id, {_PRINT.format(f"list_transform(range(0, 64), lambda p: embedding[(ord[(p // 8 // {n}) * {per} + (p % 8) // {n} + 1] // {per} * {n} + (p // 8) % {n}) * 8 + (ord[(p // 8 // {n}) * {per} + (p % 8) // {n} + 1] % {per}) * {n} + (p % 8) % {n} + 1])")} AS pixels FROM o"""


def _scramble(n: int, scope: str = "image"):
    def run(spark, sf_dir):
        return vectors.scrambled(load(spark, sf_dir, "embeddings"), n, scope=scope).select("vec_id", _printed().alias("pixels"))

    run.__name__ = f"scramble_8x8_n{n}" + ("_shared" if scope != "image" else "")
    return run


for _n in (1, 2, 4):
    register(_scramble_sql(_n))(_scramble(_n))
register(_scramble_sql(2, "'all'"))(_scramble(2, "all"))

_MASK = "list_filter(range(0, 32), lambda p: embedding[p + 1] > 0.1)"
_RANDOM = f"list_sort(list_transform(list_sort(list_transform(range(0, 64), lambda p: {{'h': md5('42|m|' || vec_id || '|' || p), 'p': p}}))[1:len({_MASK})], lambda r: r.p))"


@register(f"SELECT vec_id, len({_MASK})::INT AS n_cue, array_to_string({_MASK}, ',') AS cue, array_to_string({_RANDOM}, ',') AS random FROM embeddings")
def random_mask_counts(spark, sf_dir):
    rows = vectors.random_mask(vectors.bright_mask(load(spark, sf_dir, "embeddings")))
    text = lambda c: F.array_join(F.transform(c, lambda x: x.cast("string")), ",")
    return rows.select("vec_id", F.size("cue_mask").alias("n_cue"), text("cue_mask").alias("cue"), text("random_mask").alias("random"))


@register(f"WITH m AS (SELECT *, {_MASK} AS cue FROM embeddings) SELECT vec_id, {_PRINT.format('list_transform(embedding, lambda x, i: CASE WHEN list_contains(cue, i - 1) THEN 0 ELSE x::DOUBLE END)')} AS pixels FROM m")
def remove_cue_8x8(spark, sf_dir):
    rows = vectors.bright_mask(load(spark, sf_dir, "embeddings"))
    return vectors.filled(rows, "cue_mask").select("vec_id", _printed().alias("pixels"))


_BANDS = "list_transform(range(0, 4), lambda b: {'less': -floor((list_sum(list_transform(embedding[b * 16 + 1:b * 16 + 16], lambda x: x::DOUBLE * x::DOUBLE)) - pow(list_sum(list_transform(embedding[b * 16 + 1:b * 16 + 16], lambda x: x::DOUBLE)), 2) / 16) * 1000000 + 0.5)::BIGINT, 'b': b})"


@register(f"SELECT vec_id, list_min({_BANDS}).b::INT AS band FROM embeddings")
def varied_band(spark, sf_dir):
    """Which band of two rows varies most: a second raster cue beside the bright one."""
    rows = vectors.varied_mask(load(spark, sf_dir, "embeddings"))
    return rows.select("vec_id", F.floor(F.element_at("cue_mask", 1) / 16).cast("int").alias("band"))


_CLAMP = "least(greatest({}, 0), 7)"
_BLUR = " + ".join(f"embedding[{_CLAMP.format(f'p // 8 + {i}')} * 8 + {_CLAMP.format(f'p % 8 + {j}')} + 1]::DOUBLE * {(2 - abs(i)) * (2 - abs(j))}" for i in (-1, 0, 1) for j in (-1, 0, 1))


@register(f"SELECT vec_id, {_PRINT.format(f'list_transform(range(0, 64), lambda p: ({_BLUR}) / 16)')} AS pixels FROM embeddings")
def blur_8x8(spark, sf_dir):
    return vectors.blurred(load(spark, sf_dir, "embeddings")).select("vec_id", _printed().alias("pixels"))
