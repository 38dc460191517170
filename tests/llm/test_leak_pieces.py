"""Removal with a benchmark in several pieces gives what one piece gives."""

from mfaccel.llm import decontaminate
from pyspark.sql import functions as F


def test_pieces_remove_the_same(spark):
    bench = spark.createDataFrame([(1, "one two three four"), (2, "three four five six"), (3, "lonely"), (3, "lonely"), (None, "nobody owns this"), (4, None)], "item_id long, text string")
    texts = ["Well, One two; three FOUR five six, end.", "clean é text", None, "", "a lonely word", "nobody owns THIS now", "three four five six"]
    docs = spark.createDataFrame([(k, t, "x", [k]) for k, t in enumerate(texts)], "doc_id long, text string, _row string, items array<long>")
    for mode in ("documents", "spans"):
        whole, parts = (decontaminate.remove(docs, bench, mode=mode, piece_bytes=n) for n in (1 << 20, 12))
        assert whole.columns == parts.columns == docs.columns and whole.schema == parts.schema
        assert sorted(map(repr, whole.collect())) == sorted(map(repr, parts.collect()))
    spans = {r.doc_id: r.text for r in decontaminate.remove(docs, bench, mode="spans", piece_bytes=12).collect()}
    assert spans[0] == "Well, , end." and spans[1] == "clean é text" and spans[2] is None and spans[6] == ""


def test_copies_of_an_item_are_one(spark):
    many = spark.range(500).select(F.lit(7).cast("long").alias("item_id"), F.lit("the very same question again and again").alias("text"))
    assert sum(p.count() for p in decontaminate.pieces_of(many, "item_id", "text", 100)) == 1
