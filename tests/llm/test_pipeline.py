"""The pipeline's stages against brute force on their own inputs."""

from collections import Counter

import corpus_pipeline
from learned_upkeep.llm import quality_rules

from .test_operators import brute_near, check_packing, plain


def test_stages(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, frames = docs.columns, [docs]
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, frames[-1], sf)
        out.write.parquet(str(tmp_path / str(k)))
        frames.append(spark.read.parquet(str(tmp_path / str(k))))
    start, good, unique, distinct, mixed, packed = frames
    assert all(f.columns == columns for f in frames[:-1])
    kept = {r["doc_id"] for r in quality_rules.judged(start).where("kept").collect()}
    assert {i for i, _ in plain(good)} == kept
    last = {}
    for i, t in plain(good):
        last[t] = max(i, last.get(t, i))
    assert sorted(plain(unique)) == sorted((i, t) for t, i in last.items())
    assert sorted(i for i, _ in plain(distinct)) == sorted(i for i, _, _, stays in brute_near(plain(unique), 5) if stays)
    n = Counter(i for i, _ in plain(mixed))
    assert set(n) <= {i for i, _ in plain(distinct)} and max(n.values()) <= 2
    used, least = check_packing(packed.collect(), plain(mixed))
    assert used <= 1.02 * least + 2


def test_run_gives_the_last_stage(spark, sf):
    assert set(corpus_pipeline.run(spark, sf).columns) >= {"doc_id", "piece", "sequence_id", "offset"}
