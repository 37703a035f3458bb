"""The pipeline against its stages' own decisions and a brute-force view of what must be gone or kept."""

import corpus_pipeline
import pytest

from geoprobe.llm import bpe, decontamination, line_dedup, near_dedup, toxicity

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def stages(spark, sf_dir, tmp_path_factory):
    folder = tmp_path_factory.mktemp("stages")
    docs, kept = spark.read.parquet(f"{sf_dir}/documents.parquet"), []
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf_dir)
        out.write.parquet(str(folder / name))
        kept.append((name, docs, spark.read.parquet(str(folder / name))))
        docs = kept[-1][2]
    return kept


def test_order_and_columns(stages):
    assert [s[0] for s in stages] == ["toxicity", "line_dedup", "minhash_near_dedup", "benchmark_decontamination", "bpe_encoding"]
    assert all(sorted(s[2].columns) == sorted(COLUMNS) for s in stages[:-1])


def test_each_stage_takes_effect(spark, sf_dir, stages):
    ids = lambda df: {r["doc_id"] for r in df.select("doc_id").collect()}
    _, docs, clean = stages[0]
    model = toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    assert ids(clean) == ids(toxicity.scored(docs, model).where(f"score < {toxicity.CUTOFF}"))
    _, docs, lines = stages[1]
    assert ids(lines) == ids(docs)
    assert {tuple(r) for r in lines.select("doc_id", "text").collect()} == {tuple(r) for r in line_dedup.without_boilerplate(docs).select("doc_id", "text").collect()}
    _, docs, single = stages[2]
    assert ids(single) == ids(near_dedup.near_duplicates(docs).where("kept"))
    _, docs, free = stages[3]
    hit = ids(decontamination.find_contamination(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).where("size(hits) > 0"))
    assert hit and ids(free) == ids(docs) - hit
    _, docs, tokens = stages[4]
    own = bpe.Encoder(bpe.default_path())
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert all((r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) == own.summary(texts[r["doc_id"]] or "") for r in tokens.collect())


def test_run_equals_stages(spark, sf_dir, stages):
    assert sorted(map(tuple, corpus_pipeline.run(spark, sf_dir).collect())) == sorted(map(tuple, stages[-1][2].collect()))
