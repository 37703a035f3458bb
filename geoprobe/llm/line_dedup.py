"""Cross-site boilerplate lines: how many distinct sites carry a line, from HyperLogLog sketches.

Lines (between line feeds, trimmed of spaces) are aggregated by hash: one HyperLogLog sketch of their sites, their count and their first document.
Sketches merge under partial aggregation, so a line that every page carries costs no more than a rare one. Lines whose
estimate is clearly above or below the threshold are decided by it; those near it get an exact distinct count. Lines are
looked up in a join by hash in which no line, however common, is one task's: the (at most PARTS) lines that make up a PARTS-th of all
occurrences or more are broadcast, the others shuffled. A
boilerplate line stays in its first document (smallest doc_id), so no content vanishes, and goes everywhere else.

Null text has no lines; blank lines are never boilerplate; a null site counts as one site; rows with a null doc_id count
for the spread and keep their lines; repeated rows are treated alike; an emptied document stays as an empty text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed, unused

MIN_SITES = 10
#: Estimates within this factor of the threshold are counted exactly (a sketch of 2^12 registers errs by under 3 %).
NEAR, LOG_REGISTERS = 0.3, 12
#: A line with one of so many parts of the occurrences of all lines looked up is broadcast; fewer lines than that are broadcast as they are.
PARTS = 10_000


def _lines(docs: DataFrame, site: str) -> DataFrame:
    cut = docs.select("doc_id", F.coalesce(F.col(site).cast("string"), F.lit("")).alias("site"), F.posexplode(F.split("text", "\n", -1)).alias("at", "line"))
    return cut.where(F.trim("line") != "").select("doc_id", "site", "at", F.unhex(F.md5(F.trim("line"))).alias("key"))


def _found(lines: DataFrame, wanted: DataFrame) -> DataFrame:
    """lines joined with the wanted ones (wanted_key, n: occurrences, and more), a written table."""
    size = wanted.agg(F.count("*").alias("lines"), F.coalesce(F.sum("n"), F.lit(0)).alias("n")).first()
    join = lambda rows, some: rows.join(some.drop("n"), F.col("key") == F.col("wanted_key"))
    if size["lines"] <= PARTS:
        return join(lines, F.broadcast(wanted))
    common = F.col("n") >= size["n"] / PARTS
    often = wanted.where(common)
    rare = lines.join(F.broadcast(often.select(F.col("wanted_key").alias("often"))), F.col("key") == F.col("often"), "left_anti")
    return join(lines, F.broadcast(often)).unionByName(join(rare, wanted.where(~common)))


def boilerplate_lines(docs: DataFrame, site: str = "source", min_sites: int = MIN_SITES) -> DataFrame:
    """wanted_key (hash of a line), first_doc, n (occurrences): lines carried by at least `min_sites` distinct sites."""
    lines = _lines(docs, site)
    spread = lines.groupBy(F.col("key").alias("wanted_key")).agg(F.hll_sketch_agg("site", LOG_REGISTERS).alias("sketch"), F.min("doc_id").alias("first_doc"), F.count("*").alias("n"))
    told = spread.where(F.col("n") >= min_sites).select("wanted_key", "first_doc", "n", F.hll_sketch_estimate("sketch").alias("sites")).where(F.col("sites") >= min_sites * (1 - NEAR))
    told = checkpointed(told)
    sure = told.where(F.col("sites") > min_sites * (1 + NEAR)).drop("sites")
    near = told.where(F.col("sites") <= min_sites * (1 + NEAR)).drop("sites")
    if near.isEmpty():
        return sure
    exact = _found(lines.select("key", "site"), near).select("wanted_key", "site").distinct().groupBy(F.col("wanted_key").alias("counted")).agg(F.count("*").alias("sites")).where(F.col("sites") >= min_sites)
    return checkpointed(sure.unionByName(near.join(exact, F.col("wanted_key") == F.col("counted")).drop("counted", "sites")))


def without_boilerplate(docs: DataFrame, site: str = "source", min_sites: int = MIN_SITES) -> DataFrame:
    """The documents with all their columns, text without boilerplate lines, plus n_lines and n_removed (columns that have
    these names go)."""
    clean = docs.select("doc_id", F.col(site).alias("site"), F.col("text").cast("string").alias("text"))
    hits = _found(_lines(clean, "site"), boilerplate_lines(clean, "site", min_sites)).where("doc_id > first_doc")
    gone_id, gone_at = unused(docs, "gone_id", "gone_at")
    gone = hits.groupBy(F.col("doc_id").alias(gone_id)).agg(F.collect_set("at").alias(gone_at))
    joined = docs.withColumn("text", F.col("text").cast("string")).join(gone, F.col("doc_id") == F.col(gone_id), "left")
    lines, none = F.split("text", "\n", -1), F.col(gone_at).isNull()
    kept = F.array_join(F.filter(lines, lambda line, at: ~F.array_contains(gone_at, at)), "\n")
    own = [F.when(none, F.col("text")).otherwise(kept).alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns if c.lower() not in ("n_lines", "n_removed")]
    size = F.when(F.col("text").isNull(), F.lit(0)).otherwise(F.size(lines)).cast("long")
    removed = F.when(none, F.lit(0)).otherwise(F.size(gone_at)).cast("long")
    return joined.select(*own, size.alias("n_lines"), removed.alias("n_removed"))
