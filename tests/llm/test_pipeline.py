"""Every stage keeps columns and takes effect; the stages' decisions equal those of their operators."""

import corpus_pipeline
from catchment.llm import common, decontaminate, language_id, ngram_join, quality
from catchment.llm.common import materialize

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    kept = []
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        docs = materialize(stage(spark, docs, SF), "stage")
        kept.append({r[0] for r in docs.select("doc_id").distinct().collect()})
        if name != "best-fit packing":
            assert docs.columns == columns
        if name == "n-gram Jaccard join":
            found = ngram_join.jaccard_join(before).filter("doc_id = component_id").collect()
            assert kept[-1] == {r["doc_id"] for r in found}
        if name == "benchmark decontamination":
            found = decontaminate.with_matches(before, spark.read.parquet(f"{SF}/benchmark.parquet")).filter("size(matches) = 0").collect()
            assert kept[-1] == {r["doc_id"] for r in found}
        if name == "language ID":
            found = language_id.identify(before, language_id.fit_languages(before)).filter("lang_pred <> 'und'").collect()
            assert kept[-1] <= {r["doc_id"] for r in found}
        if name == "quality classifier":
            model = quality.fit_quality(before, spark.read.parquet(f"{SF}/labels.parquet"))
            assert kept[-1] == {r["doc_id"] for r in quality.judge_quality(before, model).filter("predicted = 1").collect()}
    assert all(b <= a for a, b in zip(kept, kept[1:])) and kept[-1] == kept[-2]


def test_empty_and_odd(spark):
    kind = "doc_id long, text string, lang string, source string, n_chars long, score double"
    odd = spark.createDataFrame([(None, None, None, None, None, None), (1, None, "en", "s", 0, 0.1), (2, "", None, "s", 0, 0.1), (3, "plain words of a text", "en", "s", 21, 0.1), (3, "plain words of a text", "en", "s", 21, 0.1)], kind)
    for docs in (odd, odd.limit(0)):
        for _, stage in corpus_pipeline.STAGES:
            docs = materialize(stage(spark, docs, SF), "stage")
        ids = [r["doc_id"] for r in docs.collect()]
        # texts without a letter are no language, so they go in the first stage; what is left is packed or was poor
        assert set(ids) <= {3} and all(c in docs.columns for c in ("doc_id", "piece", "sequence_id", "offset"))


def test_heaps_are_handed_back(spark, monkeypatch):
    """Every stage begins with a collection in the JVMs that run tasks: their heaps would only grow from stage to stage."""
    beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans
    collections = lambda: sum(max(0, b.getCollectionCount()) for b in beans())
    before = collections()
    common.hand_back(spark)
    assert collections() > before
    calls = []
    monkeypatch.setattr(corpus_pipeline, "hand_back", calls.append)
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        stage(spark, docs, SF)
    assert len(calls) == len(corpus_pipeline.STAGES)


def test_driver_hands_back(spark):
    """A stage begins with a driver's heap that is mostly in use; a plain collection leaves up to 70 % of it free. The JVM's bounds stay as they were."""
    jvm = spark._jvm
    bean = jvm.java.lang.management.ManagementFactory.getPlatformMXBean(jvm.java.lang.Class.forName("com.sun.management.HotSpotDiagnosticMXBean"))
    bounds = lambda: [bean.getVMOption(name).getValue() for name in common.FREE]
    memory = jvm.java.lang.Runtime.getRuntime()
    was = bounds()
    for _ in range(2):  # what Python has let go is free in the JVM only after the next call
        common.hand_back(spark)
    assert memory.freeMemory() < 0.55 * memory.totalMemory()
    assert bounds() == was
