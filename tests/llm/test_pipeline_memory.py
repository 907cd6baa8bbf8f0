"""What a stage of the pipeline leaves behind in executors."""

import corpus_pipeline


def test_stages_start_with_collected_executors(spark):
    """Local tasks run in the driver's JVM; a stage's plan alone collects nothing."""
    docs = spark.createDataFrame([(1, "one two", "en", "s", 7)], "doc_id long, text string, lang string, source string, n_chars long")
    beans = list(spark.sparkContext._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans())
    heap = spark.sparkContext._jvm.java.lang.Runtime.getRuntime()
    before = sum(b.getCollectionCount() for b in beans if "Old" in b.getName() or "MarkSweep" in b.getName())
    out = dict(corpus_pipeline.STAGES)["pii"](spark, docs, "")
    after = sum(b.getCollectionCount() for b in beans if "Old" in b.getName() or "MarkSweep" in b.getName())
    assert after > before and heap.totalMemory() > 0 and out.columns == docs.columns
