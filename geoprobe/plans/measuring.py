"""Queries on the measures, over the rule logs and the logs of published counts, with their SQL twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.scalars import hash01_sql, rounded, rounded_sql
from ..operators import cues, duplicates, measures, statistics
from ..session import spread
from ..sources.tables import REGIONS, load
from . import rule_logs

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
LOG = rule_logs.lineitem_log_sql()


def register(sql: str | None = None):
    def keep(fn):
        QUERIES[fn.__name__] = fn
        if sql:
            ORACLE_SQL[fn.__name__] = sql
        return fn

    return keep


def _round(df, *columns):
    return df.withColumns({c: rounded(F.col(c)) for c in columns})


@register(LOG + f"SELECT model, transform, count(*)::BIGINT AS n, count(*) FILTER (WHERE pred = y)::BIGINT AS correct, {rounded_sql('count(*) FILTER (WHERE pred = y) / count(*)::DOUBLE')} AS accuracy FROM log GROUP BY model, transform")
def accuracy(spark, sf_dir):
    return _round(measures.accuracy(rule_logs.lineitem_log(spark, sf_dir)), "accuracy")


@register(LOG + "SELECT model, coalesce(y, -1) AS y, count(*)::BIGINT AS n, count(*) FILTER (WHERE pred = y)::BIGINT AS correct FROM log WHERE transform = 'identity' GROUP BY GROUPING SETS ((model, y), (model))")
def per_region_accuracy(spark, sf_dir):
    log = rule_logs.lineitem_log(spark, sf_dir).where("transform = 'identity'")
    return measures.accuracy_with_total(log, "y").select("model", F.coalesce("y", F.lit(-1)).alias("y"), "n", "correct")


@register(
    LOG
    + f""", c AS (SELECT y, model, count(*)::BIGINT AS n, count(*) FILTER (WHERE pred = y)::BIGINT AS correct FROM log WHERE transform = 'identity' GROUP BY y, model),
b AS (SELECT *, max(correct) FILTER (WHERE model = 'by_quantity') OVER (PARTITION BY y) AS base_correct FROM c)
SELECT *, {rounded_sql("100.0::DOUBLE * (correct - base_correct) / n")} AS gain_points FROM b"""
)
def gain(spark, sf_dir):
    return _round(measures.gain(rule_logs.lineitem_log(spark, sf_dir), "by_quantity", ["y"]), "gain_points")


@register(LOG + f"SELECT model, transform, n, correct0, correct1, {rounded_sql('100.0::DOUBLE * (correct0 - correct1) / n')} AS drop_points FROM sw")
def accuracy_drop(spark, sf_dir):
    return _round(measures.accuracy_drop(rule_logs.lineitem_log(spark, sf_dir)), "drop_points")


@register(LOG + f"SELECT model, transform, n, switched, {rounded_sql('switched / n::DOUBLE')} AS switch_rate FROM sw")
def switch_rate(spark, sf_dir):
    return _round(measures.switch_rate(rule_logs.lineitem_log(spark, sf_dir)), "switch_rate")


@register(LOG + "SELECT * FROM sw")
def switch_breakdown(spark, sf_dir):
    return measures.switches(rule_logs.lineitem_log(spark, sf_dir))


@register(
    LOG
    + """SELECT a.model, split_part(a.transform, ':', 2) AS cue, a.switched AS removed_switched, a.correct1 AS removed_correct, b.switched AS random_switched, b.correct1 AS random_correct, a.switched - b.switched AS net_switched
FROM sw a JOIN sw b ON a.model = b.model AND a.transform LIKE 'remove:%' AND b.transform = 'random:' || split_part(a.transform, ':', 2)"""
)
def net_effect(spark, sf_dir):
    return measures.net_effect(rule_logs.lineitem_log(spark, sf_dir))


@register(LOG + f"SELECT model, transform, correct0, correct1, {rounded_sql('correct1 / nullif(correct0, 0)::DOUBLE')} AS retention FROM sw")
def retention(spark, sf_dir):
    return _round(measures.retention(rule_logs.lineitem_log(spark, sf_dir)).drop("relative_drop"), "retention")


@register(LOG + f"SELECT model, transform, {rounded_sql('100.0::DOUBLE * (1 - correct1 / nullif(correct0, 0)::DOUBLE)', 4)} AS relative_drop FROM sw")
def relative_drop(spark, sf_dir):
    made = measures.retention(rule_logs.lineitem_log(spark, sf_dir))
    return made.select("model", "transform", rounded(F.col("relative_drop"), 4).alias("relative_drop"))


@register(LOG + "SELECT model, y, pred, count(*)::BIGINT AS n, (sum(count(*)) OVER (PARTITION BY model, y))::BIGINT AS of_class FROM log WHERE transform = 'identity' GROUP BY model, y, pred")
def confusion(spark, sf_dir):
    return measures.confusion(rule_logs.lineitem_log(spark, sf_dir))


@register(LOG + "SELECT model, transform, switched, row_number() OVER (PARTITION BY model ORDER BY switched DESC, transform) AS place FROM sw")
def cue_order(spark, sf_dir):
    return measures.ordered(rule_logs.lineitem_log(spark, sf_dir))


@register(
    LOG
    + f""", o AS (SELECT model, transform, row_number() OVER (PARTITION BY model ORDER BY switched DESC, transform) AS place FROM sw),
p AS (SELECT a.model, b.model AS other, count(*)::BIGINT AS k, sum((a.place - b.place) * (a.place - b.place))::BIGINT AS squares FROM o a JOIN o b USING (transform) WHERE a.model < b.model GROUP BY a.model, b.model)
SELECT *, {rounded_sql("1 - 6.0::DOUBLE * squares / (k * (k * k - 1))")} AS spearman FROM p"""
)
def cue_order_agreement(spark, sf_dir):
    return _round(measures.order_agreement(rule_logs.lineitem_log(spark, sf_dir)), "spearman")


@register(LOG + ", s AS (SELECT model, split_part(transform, ':', 2)::INT AS size, switched FROM sw WHERE transform LIKE 'scramble:%') SELECT model, size, switched, switched <= lag(switched) OVER (PARTITION BY model ORDER BY size) AS falls FROM s")
def scramble_trend(spark, sf_dir):
    return measures.trend(rule_logs.lineitem_log(spark, sf_dir), "scramble")


@register(LOG + "SELECT CASE WHEN model = 'by_discount' THEN 'frozen' ELSE 'adapted' END AS regime, transform, min(switched) AS least, max(switched) AS most FROM sw GROUP BY ALL")
def regime_range(spark, sf_dir):
    return measures.regimes(rule_logs.lineitem_log(spark, sf_dir), ["by_discount"])


_Z = "1.959963984540054::DOUBLE"


@register(
    LOG
    + f""", a AS (SELECT model, transform, count(*)::BIGINT AS n, count(*) FILTER (WHERE pred = y)::BIGINT AS correct FROM log GROUP BY model, transform), p AS (SELECT *, correct / n::DOUBLE AS p FROM a)
SELECT model, transform, n, correct, {rounded_sql(f"(p + {_Z} * {_Z} / (2 * n) - {_Z} * sqrt(p * (1 - p) / n + {_Z} * {_Z} / (4 * n * n::DOUBLE))) / (1 + {_Z} * {_Z} / n)")} AS low,
{rounded_sql(f"(p + {_Z} * {_Z} / (2 * n) + {_Z} * sqrt(p * (1 - p) / n + {_Z} * {_Z} / (4 * n * n::DOUBLE))) / (1 + {_Z} * {_Z} / n)")} AS high FROM p"""
)
def wilson_interval(spark, sf_dir):
    return _round(measures.wilson(rule_logs.lineitem_log(spark, sf_dir)), "low", "high")


@register(LOG + f"SELECT model, transform, lost, gained, {rounded_sql('(lost - gained) * (lost - gained) / nullif(lost + gained, 0)::DOUBLE', 4)} AS chi_square FROM sw")
def mcnemar_test(spark, sf_dir):
    made = measures.mcnemar(rule_logs.lineitem_log(spark, sf_dir))
    return made.withColumn("chi_square", rounded(F.col("chi_square"), 4))


@register(LOG + f"SELECT model, transform, n, correct0, switched, correct1, {rounded_sql('correct0 / n::DOUBLE')} AS accuracy, {rounded_sql('switched / n::DOUBLE')} AS switch_rate, {rounded_sql('correct1 / nullif(correct0, 0)::DOUBLE')} AS retention FROM sw")
def joint_table(spark, sf_dir):
    return _round(measures.joint_table(rule_logs.lineitem_log(spark, sf_dir)), "accuracy", "switch_rate", "retention")


@register(LOG + "SELECT model, transform, (length(image_id) % 5)::INT AS stratum, count(*)::BIGINT AS n, count(*) FILTER (WHERE pred = y)::BIGINT AS correct FROM log GROUP BY ALL")
def accuracy_by_overlap(spark, sf_dir):
    log = rule_logs.lineitem_log(spark, sf_dir)
    strata = load(spark, sf_dir, "lineitem").select(rule_logs.image_id().alias("image_id")).withColumn("stratum", F.length("image_id") % 5)
    return measures.by_stratum(log, strata).select("model", "transform", "stratum", "n", "correct")


@register(LOG + "SELECT y AS class, model, image_id, pred, pred0, row_number() OVER (PARTITION BY y ORDER BY image_id) AS place FROM pairs WHERE model = 'by_quantity' AND transform = 'coarse' AND pred <> pred0 QUALIFY place <= 3")
def topk_switched(spark, sf_dir):
    """Qualitative cases: the first three switched images of each class."""
    from pyspark.sql import Window

    log = rule_logs.lineitem_log(spark, sf_dir).where("model = 'by_quantity' and transform in ('identity', 'coarse')")
    rows = measures.paired(log).where("transform = 'coarse' and pred <> pred0").withColumn("place", F.row_number().over(Window.partitionBy("y").orderBy("image_id")))
    return rows.where("place <= 3").select(F.col("y").alias("class"), "model", "image_id", "pred", "pred0", F.col("place").cast("long").alias("place"))


@register(LOG + "SELECT transform, count(*) FILTER (WHERE model = 'by_quantity' AND pred = y)::BIGINT AS by_quantity, count(*) FILTER (WHERE model = 'by_discount' AND pred = y)::BIGINT AS by_discount, count(*) FILTER (WHERE model = 'by_date' AND pred = y)::BIGINT AS by_date FROM log GROUP BY transform")
def pivot_models(spark, sf_dir):
    made = measures.accuracy(rule_logs.lineitem_log(spark, sf_dir))
    return made.groupBy("transform").pivot("model", list(rule_logs.RULES)).agg(F.sum("correct"))


@register()
def accuracy_bootstrap(spark, sf_dir):
    return measures.bootstrap(rule_logs.lineitem_log(spark, sf_dir).where("transform = 'identity'"))


def _values(rows) -> str:
    return ", ".join("(" + ", ".join(f"'{x}'" if isinstance(x, str) else str(x) for x in r) + ")" for r in rows)

def _beside(made, by: list[str], published: dict[tuple, float]):
    """Adds `published`, the percentage by the fixed counts; a few rows."""
    fixed = F.coalesce(*(F.when(F.concat_ws("|", *by) == "|".join(k), F.lit(p)) for k, p in published.items()))
    return made.withColumn("published", rounded(fixed, 2))


def _with_place(images: int) -> str:
    return f"floor({hash01_sql(chr(39) + '42|p|' + chr(39) + ' || event_id')} * {images})"


#: The views of `events` with their published place among so many images.
_TEST_VIEWS, _CONTROL_VIEWS = (f"WITH v AS (SELECT {_with_place(n)} AS place FROM events WHERE user_id IS NOT NULL)" for n in (rule_logs.TEST, rule_logs.CONTROL))


@register(
    _TEST_VIEWS
    + f"""SELECT model, 'identity' AS transform, count(*)::BIGINT AS n, count(*) FILTER (WHERE place < k)::BIGINT AS correct, {rounded_sql('100 * (count(*) FILTER (WHERE place < k) / count(*)::DOUBLE)', 2)} AS percent, {rounded_sql(f'100.0::DOUBLE * k / {rule_logs.TEST}', 2)} AS published
FROM v, (VALUES {_values(rule_logs.CORRECT.items())}) c(model, k) GROUP BY model, k"""
)
def published_accuracy(spark, sf_dir):
    """Accuracy of the six strategies on the views of `events` at the published rates, beside the published percentages."""
    made = measures.accuracy(rule_logs.replayed(spark, sf_dir, [(m, "identity", rule_logs.TEST, k) for m, k in rule_logs.CORRECT.items()]))
    return _beside(made.select("model", "transform", "n", "correct", rounded(100 * F.col("accuracy"), 2).alias("percent")), ["model"], {(m,): 100.0 * k / rule_logs.TEST for m, k in rule_logs.CORRECT.items()})


@register(
    _TEST_VIEWS
    + f"""SELECT model, transform, count(*) FILTER (WHERE place >= {rule_logs.TEST} - k)::BIGINT AS switched, {rounded_sql(f'100 * (count(*) FILTER (WHERE place >= {rule_logs.TEST} - k) / count(*)::DOUBLE)', 2)} AS percent, {rounded_sql(f'100.0::DOUBLE * k / {rule_logs.TEST}', 2)} AS published
FROM v, (VALUES {_values((m, x, n) for x, per in rule_logs.SWITCHED.items() for m, n in per.items())}) c(model, transform, k) GROUP BY model, transform, k"""
)
def published_switch_rates(spark, sf_dir):
    """Switches of the views of `events` at the published rates, beside the published percentages."""
    cells = [(m, x, k) for x, per in rule_logs.SWITCHED.items() for m, k in per.items()]
    log = rule_logs.replayed(spark, sf_dir, [(m, "identity", rule_logs.TEST, rule_logs.TEST) for m in rule_logs.CORRECT] + [(m, x, rule_logs.TEST, rule_logs.TEST - k) for m, x, k in cells])
    made = measures.switch_rate(log).select("model", "transform", "switched", rounded(100 * F.col("switch_rate"), 2).alias("percent"))
    return _beside(made, ["model", "transform"], {(m, x): 100.0 * k / rule_logs.TEST for m, x, k in cells})


@register(
    f"""WITH c(region, of, images, zero, full_) AS (SELECT * FROM (VALUES {_values((name, r, *rule_logs.REGION_COUNTS[name]) for r, _, name in REGIONS)})),
v AS (SELECT c.*, {hash01_sql("'42|p|' || event_id")} AS u FROM events JOIN c ON of = user_id % 8)
SELECT region, count(*)::BIGINT AS n, {rounded_sql('100 * (count(*) FILTER (WHERE floor(u * images) < zero) / count(*)::DOUBLE)', 2)} AS zero_shot, {rounded_sql('100 * (count(*) FILTER (WHERE floor(u * images) < full_) / count(*)::DOUBLE)', 2)} AS full_update FROM v GROUP BY region"""
)
def published_regions(spark, sf_dir):
    """Accuracy of two strategies in each region on the views of `events`, at the region's published rates."""
    log = rule_logs.replayed(spark, sf_dir, [(m, name, rule_logs.REGION_COUNTS[name][0], rule_logs.REGION_COUNTS[name][i], r) for r, _, name in REGIONS for i, m in ((1, "zero_shot"), (2, "full"))])
    made = measures.accuracy(log).groupBy("transform").pivot("model", ["zero_shot", "full"]).agg(F.max("n"), F.max("accuracy"))
    names = [c for c in made.columns if c != "transform"]
    return made.select(F.col("transform").alias("region"), F.col(f"`{names[0]}`").alias("n"), rounded(100 * F.col(f"`{names[1]}`"), 2).alias("zero_shot"), rounded(100 * F.col(f"`{names[3]}`"), 2).alias("full_update"))


@register(
    _TEST_VIEWS
    + f"""SELECT condition, {rounded_sql('100 * (count(*) FILTER (WHERE place < k) / count(*)::DOUBLE)', 2)} AS percent, count(*) FILTER (WHERE place < k) < count(*) / 8.0::DOUBLE AS below_chance, {rounded_sql(f'100.0::DOUBLE * k / {rule_logs.TEST}', 2)} AS published
FROM v, (VALUES {_values(rule_logs.PROMPTS.items())}) c(condition, k) GROUP BY condition, k"""
)
def published_prompts(spark, sf_dir):
    """Accuracy under the four prompt conditions on the views of `events` at the published rates."""
    made = measures.accuracy(rule_logs.replayed(spark, sf_dir, [("zero_shot", p, rule_logs.TEST, k) for p, k in rule_logs.PROMPTS.items()]))
    shown = made.select(F.col("transform").alias("condition"), rounded(100 * F.col("accuracy"), 2).alias("percent"), (F.col("accuracy") < 1 / 8).alias("below_chance"))
    return _beside(shown, ["condition"], {(p,): 100.0 * k / rule_logs.TEST for p, k in rule_logs.PROMPTS.items()})


_CLEAN = rule_logs.CONTROL_CORRECT["identity"]


@register(
    _CONTROL_VIEWS
    + f"""SELECT transform, count(*) FILTER (WHERE place < k)::BIGINT AS correct, {rounded_sql(f'100.0::DOUBLE * (1 - count(*) FILTER (WHERE place < k) / nullif(count(*) FILTER (WHERE place < {_CLEAN}), 0)::DOUBLE)', 2)} AS relative_drop, {rounded_sql(f'100.0::DOUBLE * (1 - k / {_CLEAN}.0::DOUBLE)', 2)} AS published
FROM v, (VALUES {_values(rule_logs.CONTROL_CORRECT.items())}) c(transform, k) WHERE transform <> 'identity' GROUP BY transform, k"""
)
def published_control(spark, sf_dir):
    """Drop of the control under scrambling on the views of `events` at the published rates."""
    log = rule_logs.replayed(spark, sf_dir, [("zero_shot", x, rule_logs.CONTROL, k) for x, k in rule_logs.CONTROL_CORRECT.items()])
    made = measures.retention(log).select("transform", F.col("correct1").alias("correct"), rounded(F.col("relative_drop"), 2).alias("relative_drop"))
    return _beside(made, ["transform"], {(x,): 100.0 * (1 - k / _CLEAN) for x, k in rule_logs.CONTROL_CORRECT.items() if x != "identity"})


def _anova_sql(value: str, group: str, source: str) -> str:
    return f"""WITH r AS (SELECT {value} AS v, {group} AS g FROM {source}), p AS (SELECT g, count(*) AS n, avg(v) AS mean, coalesce(var_samp(v), 0) AS var FROM r WHERE v IS NOT NULL AND g IS NOT NULL GROUP BY g),
t AS (SELECT count(*) AS k, sum(n) AS total, sum(n * mean) / sum(n) AS grand FROM p)
SELECT max(k)::BIGINT AS groups, max(total)::BIGINT AS n, {rounded_sql("sum(n * pow(mean - grand, 2)) / (max(k) - 1) / (sum((n - 1) * var) / (max(total) - max(k)))")} AS f FROM p, t"""


def _anova(rows, value, group):
    return _round(statistics.anova_oneway(rows, value, group), "f")


@register(_anova_sql("l_discount", "l_returnflag || l_linestatus", "lineitem"))
def anova_lineitem(spark, sf_dir):
    return _anova(load(spark, sf_dir, "lineitem").withColumn("g", F.concat("l_returnflag", "l_linestatus")), "l_discount", "g")


@register(_anova_sql("value", "event_type", "events"))
def anova_events(spark, sf_dir):
    return _anova(load(spark, sf_dir, "events"), "value", "event_type")


@register(_anova_sql("value", "user_id % 8", "events"))
def anova_region(spark, sf_dir):
    return _anova(load(spark, sf_dir, "events").withColumn("g", F.col("user_id") % 8), "value", "g")


@register(_anova_sql("p_retailprice", "p_type", "part"))
def anova_part(spark, sf_dir):
    return _anova(load(spark, sf_dir, "part"), "p_retailprice", "p_type")


@register(_anova_sql("c_acctbal", "c_mktsegment", "customer"))
def anova_customer(spark, sf_dir):
    return _anova(load(spark, sf_dir, "customer"), "c_acctbal", "c_mktsegment")


def _covered(spark, sf_dir):
    return cues.coverage(spread(load(spark, sf_dir, "documents").select("doc_id", "lang", "source", "text")))


_WORDS = r"string_split_regex(coalesce(text, ''), '[^\p{L}]+')"
_COVER = f"""(SELECT doc_id, lang, source, length(coalesce(text, '')) AS length, unnest([
{{'cue': 'short_word', 'masked': coalesce(list_sum(list_transform(list_filter({_WORDS}, lambda w: length(w) BETWEEN 1 AND 3), lambda w: length(w))), 0)::BIGINT}},
{{'cue': 'sentence_head', 'masked': coalesce(list_sum(list_transform(list_filter({_WORDS}, lambda w: regexp_matches(w, '^\\p{{Lu}}')), lambda w: length(w))), 0)::BIGINT}},
{{'cue': 'license_line', 'masked': coalesce(list_sum(list_transform(regexp_extract_all(coalesce(text, ''), '(?im)^[^\\n]*(?:license|licence|copyright|spdx)[^\\n]*$'), lambda w: length(w))), 0)::BIGINT}},
{{'cue': 'contact_secret', 'masked': coalesce(list_sum(list_transform(regexp_extract_all(coalesce(text, ''), '[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+|\\d[\\d.\\-]{{7,}}\\d'), lambda w: length(w))), 0)::BIGINT}}]) AS c FROM documents)"""
_COVERED = f"(SELECT doc_id, lang, source, c.cue AS cue, c.masked AS masked, coalesce(c.masked / nullif(length, 0)::DOUBLE, 0) AS coverage FROM {_COVER})"


@register(f"SELECT doc_id, cue, masked FROM {_COVERED}")
def cue_coverage(spark, sf_dir):
    return _covered(spark, sf_dir).select("doc_id", "cue", "masked")


@register(f"SELECT coalesce(cue, 'all') AS cue, coalesce(lang, 'all') AS lang, count(*)::BIGINT AS n, count(*) FILTER (WHERE masked > 0)::BIGINT AS with_mask, sum(masked)::BIGINT AS masked FROM {_COVERED} GROUP BY CUBE (cue, lang)")
def coverage_cube(spark, sf_dir):
    made = cues.summary(_covered(spark, sf_dir), "lang")
    return made.select(F.coalesce("cue", F.lit("all")).alias("cue"), F.coalesce("lang", F.lit("all")).alias("lang"), "n", "with_mask", "masked")


@register(
    r"""WITH l AS (SELECT doc_id, trim(line) AS line, count(*) AS n FROM (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line FROM documents) WHERE trim(line) <> '' GROUP BY ALL HAVING count(*) >= 3),
r AS (SELECT doc_id, sum(n * length(line)) AS masked FROM l GROUP BY doc_id)
SELECT doc_id, coalesce(list_sum(list_transform(regexp_extract_all(coalesce(text, ''), '[^\p{L}\s]{8,}'), lambda w: length(w))), 0)::BIGINT AS junk_run, coalesce(masked, 0)::BIGINT AS repeated_line FROM documents LEFT JOIN r USING (doc_id)"""
)
def extra_cues(spark, sf_dir):
    """Characters under the two cues that no model is probed with."""
    text = F.coalesce("text", F.lit(""))
    return spread(load(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", *(cues.covered(text, c).cast("long").alias(c) for c in cues.EXTRA_CUES))


@register("SELECT d.doc_id, sum(length(b.text))::BIGINT AS masked FROM documents d JOIN benchmark b ON b.text <> '' AND contains(d.text, b.text) GROUP BY d.doc_id")
def benchmark_cue(spark, sf_dir):
    """Characters of literal benchmark passages in each document that has some."""
    passages = load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("item"), F.col("text").alias("passage"))
    found = duplicates.containing(load(spark, sf_dir, "documents").select(F.col("doc_id").alias("doc"), "text"), passages)
    return cues.benchmark_coverage(found, passages).withColumnRenamed("doc", "doc_id")


def _cue_anova(group_sql: str, group):
    sql = " UNION ALL ".join("SELECT '" + c + "' AS cue, * FROM (" + _anova_sql("coverage", group_sql, f"(SELECT * FROM {_COVERED} WHERE cue = '{c}')") + ")" for c in cues.CUES)

    def run(spark, sf_dir):
        return _round(statistics.anova_by(_covered(spark, sf_dir).withColumn("g", group), "coverage", "g", "cue"), "f")

    return sql, run


ORACLE_SQL["anova_lang"] = _cue_anova("lang", None)[0]
ORACLE_SQL["anova_source"] = _cue_anova("substr(source, 4)::INT % 8", None)[0]


@register()
def anova_lang(spark, sf_dir):
    return _cue_anova("lang", F.col("lang"))[1](spark, sf_dir)


@register()
def anova_source(spark, sf_dir):
    return _cue_anova("", F.substring("source", 4, 9).cast("int") % 8)[1](spark, sf_dir)


@register()
def anova_pvalue(spark, sf_dir):
    rows = load(spark, sf_dir, "lineitem").withColumn("g", F.concat("l_returnflag", "l_linestatus"))
    return statistics.with_p(statistics.anova_oneway(rows, "l_discount", "g"))
