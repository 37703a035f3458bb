"""Cues in documents: what is covered, and the text without it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Sparse, object-like cues as lines or spans; broad, environment-like cues as words.
LICENSE = r"(?im)^[^\n]*(?:license|licence|copyright|spdx)[^\n]*$"
CONTACT = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+|\d[\d.\-]{7,}\d"
SHORT, HEAD, EDGE = r"\p{L}{1,3}", r"\p{Lu}\p{L}*", r"[^\p{L}]+"
CUES = ("short_word", "sentence_head", "license_line", "contact_secret")
#: Two more cues that no model is probed with: runs of signs and digits, and lines that a text repeats so often.
JUNK, REPEATS = r"[^\p{L}\s]{8,}", 3
EXTRA_CUES = ("junk_run", "repeated_line")


def covered(text: Column, cue: str) -> Column:
    """Characters of a text that a cue covers."""
    if cue in ("short_word", "sentence_head"):
        wanted = (lambda w: F.char_length(w).between(1, 3)) if cue == "short_word" else (lambda w: w.rlike(r"^\p{Lu}"))
        return F.aggregate(F.filter(F.split(text, EDGE), wanted), F.lit(0), lambda n, w: n + F.char_length(w))
    if cue == "junk_run":
        return F.aggregate(F.regexp_extract_all(text, F.lit(JUNK), F.lit(0)), F.lit(0), lambda n, w: n + F.char_length(w))
    if cue == "repeated_line":
        # Sorted, equal lines stand together; each is counted with how often it has come, and a run's last one decides.
        lines = F.array_sort(F.filter(F.transform(F.split(text, "\n"), lambda x: F.trim(x)), lambda x: x != ""))
        start = F.struct(F.lit("").alias("line"), F.lit(0).alias("n"), F.lit(0).alias("sum"))
        closed = lambda s: s["sum"] + F.when(s["n"] >= REPEATS, s["n"] * F.char_length(s["line"])).otherwise(0)
        step = lambda s, x: F.when(s["line"] == x, F.struct(x.alias("line"), (s["n"] + 1).alias("n"), s["sum"].alias("sum"))).otherwise(F.struct(x.alias("line"), F.lit(1).alias("n"), closed(s).alias("sum")))
        return F.aggregate(lines, start, step, closed)
    return F.aggregate(F.regexp_extract_all(text, F.lit(LICENSE if cue == "license_line" else CONTACT), F.lit(0)), F.lit(0), lambda n, w: n + F.char_length(w))


def coverage(docs: DataFrame, cues: tuple[str, ...] = CUES) -> DataFrame:
    """doc_id, lang, source, cue, masked, coverage: one scan for all cues."""
    text = F.coalesce("text", F.lit(""))
    each = F.array(*(F.struct(F.lit(c).alias("cue"), covered(text, c).cast("long").alias("masked")) for c in cues))
    rows = docs.select("doc_id", "lang", "source", F.char_length(text).alias("length"), F.explode(each).alias("c"))
    return rows.select("doc_id", "lang", "source", "c.cue", "c.masked", F.coalesce(F.expr("try_divide(CAST(c.masked AS DOUBLE), length)"), F.lit(0.0)).alias("coverage"))


def summary(cover: DataFrame, group: str) -> DataFrame:
    """Documents, documents with a mask and masked characters by cue and group, with totals (cube)."""
    made = cover.cube("cue", group).agg(F.count("*").alias("n"), F.count_if(F.col("masked") > 0).alias("with_mask"), F.sum("masked").alias("masked"))
    return made


def removed(text: Column, cue: str) -> Column:
    """The text with the cue's spans blanked by a full stop of the same length class (words) or dropped (lines, spans)."""
    if cue == "license_line":
        return F.regexp_replace(text, LICENSE, "")
    if cue == "contact_secret":
        return F.regexp_replace(text, CONTACT, "")
    return F.regexp_replace(text, rf"(?<!\p{{L}}){SHORT if cue == 'short_word' else HEAD}(?!\p{{L}})", "_")


def benchmark_coverage(found: DataFrame, passages: DataFrame) -> DataFrame:
    """doc, masked: characters of benchmark passages in each document, from (doc, item) and (item, passage); a passage counts once."""
    return found.join(passages.select("item", F.char_length("passage").alias("n")), "item").groupBy("doc").agg(F.sum("n").cast("long").alias("masked"))
