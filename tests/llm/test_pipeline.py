"""The pipeline, stage by stage, against brute force."""

import corpus_pipeline
from rpqframe.llm import sp_sampling, toxicity
from tests.llm.test_operators import brute_contamination, brute_lines
from tests.llm.test_shingle_dedup import brute_similar

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels, items = spark.read.parquet(f"{SF}/labels.parquet"), [(x.item_id, x.text) for x in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line_dedup", "simhash", "decontamination", "sentencepiece"]
    rows = [(x.doc_id, x.text) for x in docs.collect()]
    bad = {x.doc_id for x in toxicity.score(docs, toxicity.train_model(docs, labels)).where("predicted = 1").collect()}
    want = [(i, t) for i, t in rows if i not in bad]
    exact, near = brute_lines(want)
    cut = []
    for i, t in want:
        gone = {k for j, k in exact | near if j == i}
        left = "\n".join(x for k, x in enumerate(t.split("\n")) if k not in gone)
        if not gone or left.strip():
            cut.append((i, left))
    least = brute_similar(cut)
    cut = [x for x in cut if least[x[0]] == x[0]]
    dirty = {x[0] for x in brute_contamination(cut, items) if x[-1]}
    final = {i: t for i, t in cut if i not in dirty}
    at = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        at = stage(spark, at, SF)
        assert at.columns == docs.columns, name
    assert {x.doc_id: x.text for x in at.collect()} == final
    out = corpus_pipeline.run(spark, SF).collect()
    assert {x.doc_id: sp_sampling.decode([list(x.samples[0].ids)])[0] for x in out} == final
