import corpus_pipeline as pipeline
from gossipkit.llm import decontaminate, mixing, quality, sharding
from gossipkit.llm.queries import SHARDS
from test_text_operators import WORDS, groups_by_hand


def test_stages_one_by_one(spark, sf):
    """Every stage against a plain version of its decision, on what the stage before it kept."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, {}
    for name, stage in pipeline.STAGES:
        before = {r.doc_id: r for r in docs.collect()}
        docs = stage(spark, docs, sf).cache()
        seen[name] = (before, {r.doc_id: r for r in docs.collect()})
        if name != "sharding":
            assert docs.columns == columns and all(before[d] == r for d, r in seen[name][1].items())
    before, after = seen["quality_rules"]
    short = {d for d, r in before.items() if len(WORDS.findall(r.text or "")) < 20}
    assert short and not short & set(after)
    before, after = seen["near_duplicates"]
    ids = sorted(before)
    group = groups_by_hand([before[d].text for d in ids])
    assert set(after) == {d for i, d in enumerate(ids) if group[i][1] == i}
    before, after = seen["benchmark_passages"]
    items = [r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    leaks = {d for d, r in before.items() if any(t in r.text for t in items)}
    assert leaks and not leaks & set(after) and len(before) - len(after) <= 2 * len(leaks)
    before, after = seen["target_mix"]
    assert set(after) < set(before) and len(after) > len(before) / 2
    before, after = seen["sharding"]
    table = sharding.fill(SHARDS)
    assert set(before) == set(after) and all(r.shard == table[r.slot] for r in after.values())
    assert {r.doc_id for r in pipeline.run(spark, sf).collect()} == set(after)
    assert quality and decontaminate and mixing
