"""The five stages on the smallest tables: what one keeps is what the next works on."""

import gc
import weakref

import corpus_pipeline
from hyperpattern.llm.queries import ORACLES, QUERIES
from hyperpattern.llm.shared import written


def test_stages(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    columns, n = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = written(stage(spark, docs, data), name)
        assert docs.columns == columns and docs.count() <= n
        n = docs.count()
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, data)
    assert packed.select("doc_id").distinct().count() == n > 0


def test_names():
    assert {f"op{i}_" for i in range(1, 11)} == {x[: x.index("_") + 1] for x in QUERIES if x.startswith("op")}
    assert "pipeline" in QUERIES and set(ORACLES) <= set(QUERIES)


def test_the_driver_lets_a_stage_go_before_the_next(spark, data, monkeypatch):
    """What the toxicity stage left on the driver stood beside the line stage's broadcasts."""
    left, seen = [], []

    class Model:
        pass

    def first(spark, docs, sf_dir):
        model = Model()
        model.itself = model
        left.append(weakref.ref(model))
        return docs

    def second(spark, docs, sf_dir):
        seen.append(left[0]())
        return docs

    monkeypatch.setattr(corpus_pipeline, "STAGES", [("first", first), ("second", second)])
    gc.disable()
    try:
        assert corpus_pipeline.run(spark, data).count() > 0 and seen == [None]
    finally:
        gc.enable()
