"""The order of the mix: copies by virtual finish time."""

from pyspark.sql import functions as F

from pathmeet.llm import source_mixing


def test_copies_come_in_finish_order(spark):
    rows = [(i, " ".join([f"d{i}"] * (1 + i % 7)), "abc"[i % 20 // 9]) for i in range(200)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)
    allotted = {r.doc_id: r for r in source_mixing.allotments(spark, docs).collect()}
    mix = source_mixing.mixed_documents(spark, docs).withColumn("part", F.spark_partition_id()).collect()
    assert max(r.part for r in mix) > 0 and [r.part for r in mix] == sorted(r.part for r in mix)
    copies, times = {}, []
    for r in mix:
        a, n = allotted[r.doc_id], len(r.text.split())
        copy = copies[r.doc_id] = copies.get(r.doc_id, -1) + 1
        assert n == a.copies[copy]
        times.append((copy * a.source_size + a.start + n) * a.rate)
    assert times == sorted(times)
    assert sum(len(r.text.split()) for r in mix) == sum(a.taken for a in allotted.values())
    assert max(copies.values()) > 0
