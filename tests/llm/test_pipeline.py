"""The pipeline's stages on their own inputs, against plain versions."""

import re

import corpus_pipeline
from dp_itemsets.llm import decontamination, lines, quality, simhash

from .test_nearcopies import brute_heads
from .test_operators import brute_lines, check_packed, empty, judged


def test_stages_one_after_another(spark, tiny, tmp_path):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    columns = docs.columns
    outputs = []
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, tiny)
        out.write.parquet(str(tmp_path / name))
        outputs.append((docs, spark.read.parquet(str(tmp_path / name))))
        docs = outputs[-1][1]
        assert k == len(corpus_pipeline.STAGES) - 1 or docs.columns == columns
    rows = lambda df: [(r["doc_id"], r["text"]) for r in df.collect()]
    before, good = outputs[0]
    scores = {r["doc_id"]: r["predicted"] for r in quality.classify(before, spark.read.parquet(f"{tiny}/labels.parquet")).collect()}
    assert sorted(r["doc_id"] for r in good.collect()) == sorted(d for d, p in scores.items() if p)
    assert sorted(rows(outputs[1][1])) == sorted(brute_lines(rows(outputs[1][0])))
    assert sorted(d for d, _ in rows(outputs[2][1])) == brute_heads(sorted(rows(outputs[2][0])))
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{tiny}/benchmark.parquet").collect()]
    assert sorted(d for d, _ in rows(outputs[3][1])) == sorted(d for d, t in rows(outputs[3][0]) if not judged(t, items)[4])
    check_packed(outputs[4][1].collect(), rows(outputs[4][0]))


def test_stages_on_empty_tables(spark, tiny):
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, empty(spark), tiny)
        assert out.columns == empty(spark).columns and out.count() == 0
    assert corpus_pipeline.STAGES[-1][1](spark, empty(spark), tiny).count() == 0


def test_run_equals_stages(spark, tiny):
    got = corpus_pipeline.run(spark, tiny)
    assert got.count() > 0 and {"doc_id", "sequence_id", "offset"} <= set(got.columns)


def test_operators_dont_swallow_import_errors():
    for module in (corpus_pipeline, decontamination, lines, simhash, quality):
        assert not re.search(r"except (ImportError|ModuleNotFoundError)", open(module.__file__).read())
