"""The mixed order reaches the pipeline's result."""

from collections import Counter

from pyspark.sql import functions as F

import corpus_pipeline
from sheetgraph.llm import pfair
from sheetgraph.llm._shared import Scratch

BLOCK = 64


def test_positions_of_the_last_stages_hold_the_lag_bound(spark, sf):
    quanta = corpus_pipeline.MIX | {pfair.REST: 1}
    source = F.when(F.col("id") % 3 == 0, "src3").when(F.col("id") % 3 == 1, "src1").otherwise("elsewhere")
    docs = spark.range(1500).select(F.col("id").alias("doc_id"), F.lit("a b").alias("text"), F.lit("en").alias("lang"), source.alias("source"), F.lit(3).alias("n_chars"))
    scratch = Scratch(spark, "t")
    for _, stage in corpus_pipeline.STAGES[3:]:  # written and read between stages, as run() does
        docs = scratch.keep(stage(spark, docs, sf))
    rows = sorted(docs.select("position", "source", "doc_id").collect())
    assert len({r.doc_id for r in rows}) == len({r.position for r in rows}) == 1500
    pool = {}
    for r in rows:
        name = r.source if r.source in corpus_pipeline.MIX else pfair.REST
        assert pool.setdefault(r.position // BLOCK, name) == name
    left, done, total = Counter(pool.values()), Counter(), sum(quanta[s] for s in set(pool.values()))
    assert sorted(pool) == list(range(len(pool)))
    for slot in sorted(pool):
        done[pool[slot]] += 1
        assert all(abs(done[s] - (slot + 1) * quanta[s] / total) < 1 for s in left)
        if done[pool[slot]] == left[pool[slot]]:
            break  # the first epoch ends with the first source
    assert slot > 8
