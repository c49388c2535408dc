"""The pipeline's stages against the operators' own brute-force checks, each on its own input."""

import corpus_pipeline
from test_near_dedup import similarity

from vgraph.llm import decontam, pii
from vgraph.llm.common import read, stored


def test_stages(spark, sf):
    docs = read(spark, sf, "documents")
    cols, seen = docs.columns, {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stored(stage(spark, docs, sf))
        assert docs.columns == cols
        seen[name] = docs
    first = seen["quality_rules"].collect()
    kept = {r.doc_id for r in seen["near_dedup"].collect()}
    text = {r.doc_id: r.text for r in first}
    gone = set(text) - kept
    for i in gone:  # each removed document reaches a kept one over links
        group, todo = {i}, [i]
        while todo:
            x = todo.pop()
            for j in text:
                if j not in group and (text[x] == text[j] or similarity(text[x], text[j]) >= 0.8):
                    group.add(j)
                    todo.append(j)
        assert len(group & kept) == 1 and min(group) in kept
    bench = read(spark, sf, "benchmark")
    assert decontam.overlaps(seen["decontamination"], bench).count() == 0
    assert all(not pii.base_spans(r.text) for r in seen["pii"].collect())
    last = corpus_pipeline.STAGES[-1][1](spark, docs, sf).collect()
    assert len(last) == docs.count() and all(r.round_trip for r in last)


def test_run_and_empty(spark, sf, tmp_path):
    assert corpus_pipeline.run(spark, sf).count() > 0
    d = read(spark, sf, "documents").where("false")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, d, sf).count() == 0
