"""Tables written between jobs."""

from pyspark.sql import functions as F

from peakgroups.functions import storage
from peakgroups.sources import networks


def _shuffled(spark):
    files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {f for f in (files.apply(i).getName() for i in range(files.size())) if f.startswith("shuffle_")}


def test_shuffle_files_go_with_the_job_that_wrote_the_table(spark):
    before = _shuffled(spark)
    df = spark.range(1000).groupBy(F.pmod("id", F.lit(7)).alias("k")).agg(F.count("id").alias("n"))
    table = storage.materialize(df, "counts")
    assert not _shuffled(spark) - before
    assert sorted(map(tuple, table.collect())) == sorted(map(tuple, df.collect()))
    assert spark.conf.get(storage._CLEANUP, "false") == "false"


def test_no_slice_of_shingles_stays_on_disk_for_the_next(spark, monkeypatch):
    docs = spark.createDataFrame([(i, f"a b c d e n{i}") for i in range(9)], "doc_id long, text string")
    before, seen = _shuffled(spark), []
    pairs = networks._slice_pairs
    monkeypatch.setattr(networks, "_slice_pairs", lambda *a: (seen.append(_shuffled(spark) - before), pairs(*a))[1])
    monkeypatch.setattr(networks, "collect_garbage", lambda spark: None)
    assert networks.doc_links(docs, 1, 3).count() == 36 and seen == [set()] * 3
