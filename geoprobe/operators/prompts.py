"""Class texts under the four prompt conditions, from words mined in the alignment corpus alone."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scalars import seeded

CONDITIONS = ("baseline", "padded", "visual_only", "swapped")
WORDS = 20


def alignment_corpus(pages: DataFrame, conversations: DataFrame) -> DataFrame:
    """text, lang (null for conversations): half A of the pages and all conversations, never the evaluation documents."""
    half = pages.where(seeded(42, "a", F.col("page_id")) < 0.5)
    return half.select(visible(F.col("html")).alias("text"), F.regexp_extract("html", '<html[^>]*lang="([a-z]+)"', 1).alias("lang")).unionByName(conversations.select("text", F.lit(None).cast("string").alias("lang")))


#: The text of the control's additional background label, and the control's stated size.
BACKGROUND, CONTROL_SIZE = "an empty background without any text or words", 2000


def control_ids(pages: DataFrame, n: int = CONTROL_SIZE, seed: int = 42) -> DataFrame:
    """place, page_id: the recorded sample, at most n pages of half B in seeded hash order."""
    rest = pages.where(seeded(seed, "a", F.col("page_id")) >= 0.5).select("page_id", seeded(seed, "n", F.col("page_id")).alias("u"))
    order = Window.orderBy("u", "page_id")
    return rest.orderBy("u", "page_id").limit(n).select(F.row_number().over(order).alias("place"), "page_id")


def control_set(pages: DataFrame, n: int = CONTROL_SIZE, seed: int = 42) -> DataFrame:
    """doc_id, text, lang of the recorded sample."""
    drawn = F.broadcast(control_ids(pages, n, seed).select(F.col("page_id").alias("drawn")))
    return pages.join(drawn, F.col("page_id") == F.col("drawn")).select(F.col("page_id").alias("doc_id"), visible(F.col("html")).alias("text"), F.regexp_extract("html", '<html[^>]*lang="([a-z]+)"', 1).alias("lang"))


def visible(html):
    """Text between tags, scripts, styles and navigation taken out."""
    bare = F.regexp_replace(html, r"(?is)<(script|style|nav|head)\b.*?</\1>", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(bare, r"<[^>]*>", " "), r"\s+", " "))


def descriptors(corpus: DataFrame, words: int = WORDS) -> DataFrame:
    """region (class number in alphabetical order), name, words: the words of each class's texts with the highest tf-idf
    between classes."""
    terms = corpus.where("lang <> ''").select("lang", F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("word")).where("length(word) > 1")
    counts = terms.groupBy("lang", "word").agg(F.count("*").alias("tf"))
    spread = counts.groupBy(F.col("word").alias("w")).agg(F.count("*").alias("classes"))
    total = corpus.where("lang <> ''").agg(F.countDistinct("lang").alias("k"))
    score = F.col("tf") * F.log((F.col("k") + 1) / F.col("classes"))
    ranked = counts.join(spread, F.col("word") == F.col("w")).crossJoin(total).withColumn("place", F.row_number().over(Window.partitionBy("lang").orderBy(score.desc(), "word")))
    top = ranked.where(F.col("place") <= words).groupBy("lang").agg(F.array_sort(F.collect_list(F.struct("place", "word"))).alias("rows"))
    numbered = top.withColumn("region", (F.row_number().over(Window.orderBy("lang")) - 1).cast("int"))  # a row per class
    return numbered.select("region", F.col("lang").alias("name"), F.concat_ws(" ", F.transform("rows", lambda r: r["word"])).alias("words"))


def prompts(condition: str, described: DataFrame, filler: str = "a text with words in some language", shift: int = 1) -> DataFrame:
    """region, text: the name in a template with its descriptors; with neutral filler; descriptors only; or the descriptors of the class `shift` before."""
    if condition == "baseline":
        return described.select("region", F.format_string("a page written in %s : %s", "name", "words").alias("text"))
    if condition == "padded":
        return described.select("region", F.concat_ws(" ", F.lit(filler), F.format_string("a page written in %s : %s", "name", "words"), F.lit(filler)).alias("text"))
    if condition == "visual_only":
        return described.select("region", F.col("words").alias("text"))
    size = described.agg(F.count("*").alias("k"))
    return described.crossJoin(size).select(F.pmod(F.col("region") + shift, F.col("k")).cast("int").alias("region"), F.col("words").alias("text"))


def plain_words(text: str) -> list[str]:
    return re.findall(r"[^\W\d_]+", text.lower())
