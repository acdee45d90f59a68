"""The pipeline's stages one by one, and as a whole."""

import corpus_pipeline as pipeline
from peakgroups.functions.storage import materialize
from peakgroups.llm import decontaminate, linededup, quality, simhash

SF = "/root/testdata/sf0.001"


def test_stages_and_run_agree(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    benchmark = spark.read.parquet(f"{SF}/benchmark.parquet")
    for name, stage in pipeline.STAGES[:-1]:
        before, docs = docs, materialize(stage(spark, docs, SF), "stage")
        assert docs.columns == columns, name
        old, new = ({r.doc_id: r.text for r in d.collect()} for d in (before, docs))
        assert set(new) <= set(old)
        if name == "quality rules":
            kept = {r.doc_id for r in quality.judge(before).where("kept").collect()}
            assert new == {i: old[i] for i in old if i in kept}
        elif name == "line dedup":
            gone = {r.doc_id: r.n_eligible - len(r.kept) for r in linededup.kept_lines(before).collect()}
            assert set(new) == set(old) and all(old[i].count("\n") + 1 - (len(new[i].split("\n")) if new[i] else 0) >= gone[i] - 1 for i in old)
        elif name == "SimHash near-dedup":
            groups = {r.doc_id: r.component_id for r in simhash.near_duplicates(before).collect()}
            assert set(new) == set(groups.values())
        else:
            hit = {r.doc_id for r in decontaminate.contamination(decontaminate.find_hits(before, benchmark)).where("contaminated").collect()}
            assert set(new) == set(old) - hit
    last = pipeline.STAGES[-1][1](spark, docs, SF)
    key = lambda d: sorted((r.doc_id, r.mix_epoch, r.mix_key, r.text) for r in d.collect())
    assert key(pipeline.run(spark, SF)) == key(last)
