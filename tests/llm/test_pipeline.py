"""The pipeline against plain versions of its stages."""

from __future__ import annotations

import random

import corpus_pipeline
from matkeep.llm import quality_net

from . import brute
from .test_operators import labelled, near_copies, prose


def test_pipeline(spark, tmp_path):
    rng = random.Random(12)
    rows = [(d, t, "en", "src", len(t)) for d, t, _, _ in labelled(rng, 160)]
    shared, leak = prose(rng, 20), prose(rng, 14)
    for d in range(200, 212):
        rows.append((d, f"{prose(rng, 30)}\n{shared}\n{prose(rng, 12)}", "en", "src", 1))
    base = prose(rng, 90)
    rows += [(300 + i, near_copies(rng, base, 0.01), "en", "src", 1) for i in range(6)]
    rows += [(400, prose(rng, 30) + " " + leak, "en", "src", 1), (401, shared, "en", "src", 1)]
    labels = [(d, x, y) for d, _, x, y in labelled(random.Random(12), 160)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, toxic int, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, leak)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    net = quality_net.fit_on(docs, spark.read.parquet(f"{tmp_path}/labels.parquet"))
    pooler = quality_net.Pooler(net.table)
    good = [(d, t) for d, t, *_ in rows if net.probability(pooler.pooled(t)[None, :])[0] >= quality_net.THRESHOLD]
    lines = brute.line_dedup(good)
    whole = dict(good)
    left = [(d, t) for d, t in sorted(lines.items()) if t == whole[d] or t.split()]
    group = brute.similar_components(left)
    kept = [(d, t) for d, t in left if group[d] == d]
    clean = [d for d, t in kept if not brute.contaminated(t, [(1, leak)])[1]]
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert sorted(r["doc_id"] for r in got) == clean
    assert all(r["round_trip"] for r in got)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_classifier", "line_dedup", "ngram_jaccard_join", "benchmark_decontamination", "sentencepiece"]
