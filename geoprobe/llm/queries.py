"""The driver's queries over the corpus tables, one for each operator, with their SQL twins where SQL can say them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, decontamination, html_extraction, language_id, line_dedup, media, near_dedup, pii, substring_dedup, toxicity
from .common import digest_of, held_out, load


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontamination.find_contamination(load(spark, sf_dir, "documents", "doc_id", "text"), load(spark, sf_dir, "benchmark", "item_id", "text"))
    hit = F.aggregate("hits", F.lit(0).cast("long"), lambda n, h: n + h["last"] - h["first"] + 1)
    return found.select("doc_id", "n_words", hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), digest_of(F.array_sort("items")).alias("items_sha256"), (F.size("hits") > 0).alias("contaminated"))


def op2_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = media.read_media(media.store_media(load(spark, sf_dir, "documents", "doc_id", "text")))
    return made.withColumn("feature", F.lower(F.hex("cosine_hash"))).drop("cosine_hash")


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.without_repeats(load(spark, sf_dir, "documents", "doc_id", "text"), texts=False)


def op4_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extraction.extracted(load(spark, sf_dir, "pages", "page_id", "url", "html"))


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find_personal_data(load(spark, sf_dir, "documents", "doc_id", "text"))
    kinds = F.transform("spans", lambda s: s["kind"])
    counts = [(F.size(kinds) - F.size(F.array_remove(kinds, i))).cast("long").alias(f"n_{kind}") for i, kind in enumerate(pii.KINDS)]
    base = pii.named(F.filter("spans", lambda s: s["kind"] < pii.BASE))
    return found.select("doc_id", *counts, F.sha2(base, 256).alias("base_sha256"), pii.named(F.col("spans")).alias("spans"))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", "doc_id", "text")
    scores = toxicity.scored(docs, toxicity.fit(docs, load(spark, sf_dir, "labels", "doc_id", "toxic")))
    return scores.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= toxicity.CUTOFF).cast("int").alias("predicted"))


def op7_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.token_digests(load(spark, sf_dir, "documents", "doc_id", "text"))


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", "doc_id", "text", "lang")
    found = language_id.identified(docs, language_id.fit(docs))
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = line_dedup.without_boilerplate(load(spark, sf_dir, "documents", "doc_id", "text", "source"))
    return made.select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op10_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(load(spark, sf_dir, "documents", "doc_id", "text"))


QUERIES = {
    f.__name__: f
    for f in (op1_decontamination, op2_media, op3_substring_dedup, op4_html_extraction, op5_pii, op6_toxicity, op7_bpe, op8_language_id, op9_line_dedup, op10_near_dedup)
}
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_FOLDED = f"translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}')"
_WORDS = "regexp_extract_all({}, '[^\\x20\\x09-\\x0D]+')"

ORACLE_SQLS: dict[str, str] = {
    "op1_decontamination": f"""WITH i AS (SELECT item_id, regexp_extract_all({_FOLDED}, '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM benchmark),
s AS (SELECT item_id, w, least(10, len(w)) AS size FROM i WHERE len(w) > 0), win AS (SELECT item_id, size, array_to_string(w[k:k + size - 1], ' ') AS run FROM (SELECT *, unnest(range(1, len(w) - size + 2)) AS k FROM s)),
d AS (SELECT doc_id, regexp_extract_all({_FOLDED}, '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM documents), sizes AS (SELECT DISTINCT size FROM win),
dw AS (SELECT doc_id, size, k, array_to_string(w[k:k + size - 1], ' ') AS run FROM (SELECT doc_id, w, size, unnest(range(1, len(w) - size + 2)) AS k FROM d, sizes)),
hit AS (SELECT doc_id, item_id, size, k FROM dw JOIN win USING (size, run)), words AS (SELECT DISTINCT doc_id, unnest(range(k, k + size)) AS at FROM hit),
h AS (SELECT doc_id, count(*) AS n_hit FROM words GROUP BY doc_id), t AS (SELECT doc_id, list_sort(list(DISTINCT item_id::VARCHAR)) AS items FROM hit GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(len(items), 0)::BIGINT AS n_items, sha256(coalesce(array_to_string(items, ','), '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN t USING (doc_id)""",
    "op3_substring_dedup": f"""WITH d AS (SELECT doc_id, {_WORDS.format("coalesce(text, '')")} AS w FROM documents),
win AS (SELECT doc_id, k, md5(array_to_string(w[k:k + 49], ' ')) AS run FROM (SELECT doc_id, w, unnest(range(1, len(w) - 48)) AS k FROM d)), lowest AS (SELECT run, min(doc_id) AS least FROM win GROUP BY run),
gone AS (SELECT DISTINCT doc_id, unnest(range(k, k + 50)) AS pos FROM win JOIN lowest USING (run) WHERE least < doc_id), kept AS (SELECT doc_id, w[pos] AS word, pos FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS pos FROM d) WHERE (doc_id, pos) NOT IN (SELECT doc_id, pos FROM gone)),
k AS (SELECT doc_id, count(*) AS n, string_agg(word, ' ' ORDER BY pos) AS text FROM kept GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(text, '')) AS kept_sha256 FROM d LEFT JOIN k USING (doc_id)""",
    "op9_line_dedup": f"""WITH l AS (SELECT doc_id, coalesce(source, '') AS site, i, lines[i] AS line FROM (SELECT doc_id, source, lines, unnest(range(1, len(lines) + 1)) AS i FROM (SELECT *, string_split(text, chr(10)) AS lines FROM documents WHERE text IS NOT NULL))),
b AS (SELECT trim(line) AS key, min(doc_id) AS first_doc FROM l WHERE trim(line) <> '' GROUP BY trim(line) HAVING count(DISTINCT site) >= {line_dedup.MIN_SITES}),
m AS (SELECT l.*, b.key IS NOT NULL AND doc_id > first_doc AS gone FROM l LEFT JOIN b ON trim(line) = key), g AS (SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_removed, string_agg(line, chr(10) ORDER BY i) FILTER (WHERE NOT gone) AS kept FROM m GROUP BY doc_id)
SELECT d.doc_id, coalesce(n_lines, 0)::BIGINT AS n_lines, coalesce(n_removed, 0)::BIGINT AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM documents d LEFT JOIN g USING (doc_id)""",
    "op10_near_dedup": f"""WITH RECURSIVE d AS (SELECT doc_id, {_WORDS.format(_FOLDED)} AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[k:k + 4], ' ') AS shingle FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 2))) AS k FROM d WHERE len(w) > 0)), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.shingle = b.shingle AND a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id),
e AS (SELECT a, b FROM p JOIN n x ON a = x.doc_id JOIN n y ON b = y.doc_id WHERE 100 * c >= {near_dedup.THRESHOLD} * (x.n + y.n - c)), r(node, seen) AS (SELECT DISTINCT a, a FROM e UNION SELECT e.b, r.seen FROM r JOIN e ON r.node = e.a),
c AS (SELECT node, min(seen) AS component FROM r GROUP BY node)
SELECT d.doc_id, coalesce(n, 0)::BIGINT AS n_shingles, least(d.doc_id, coalesce(component, d.doc_id)) AS component_id, least(d.doc_id, coalesce(component, d.doc_id)) = d.doc_id AS kept FROM d LEFT JOIN n USING (doc_id) LEFT JOIN c ON node = d.doc_id""",
}
