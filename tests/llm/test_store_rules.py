"""Tiers, merges and vacuum of the shard store."""

import random

import pytest
from mfaccel.llm import sharding
from pyspark.sql import functions as F


def test_a_merge_takes_one_tier():
    sizes = [1, 1, 2, 3, 300, 310, 320, 1000, 5_000]
    shards = [sharding.Shard(str(k), s, "") for k, s in enumerate(sizes)]
    assert [[s.bytes for s in t] for t in sharding.ShardStore.full_tiers(shards, 4000, 3)] == [[1, 1, 2, 3], [300, 310, 320, 1000]]
    assert sharding.ShardStore.full_tiers(shards, 4000, 5) == []


def test_compaction_merges_the_smallest_tier_first_and_never_two_at_once(spark, tmp_path, monkeypatch):
    dice = random.Random(1)
    docs = spark.createDataFrame([(k, "".join(dice.choice("abcdefgh ") for _ in range(400 if k < 40 else 4000))) for k in range(80)], "doc_id long, text string")
    store, merged = sharding.ShardStore(spark, str(tmp_path / "tiers"), docs.schema), []
    for k in range(4):
        store.append(docs.where((F.col("doc_id") < 40) & (F.col("doc_id") % 4 == k)).coalesce(1), f"small {k}")
        store.append(docs.where((F.col("doc_id") >= 40) & (F.col("doc_id") % 4 == k)).coalesce(1), f"large {k}")
    plain = sharding.ShardStore._merge
    monkeypatch.setattr(sharding.ShardStore, "_merge", lambda self, old, target: merged.append([s.bytes for s in old]) or plain(self, old, target))
    store.compact(target=1 << 20)
    assert len(merged) >= 2 and all(max(m) < sharding.TIER_RATIO**2 * min(m) for m in merged)
    assert max(merged[0]) < min(merged[1]) and sorted(map(tuple, store.read().collect())) == sorted(map(tuple, docs.collect()))


def test_a_merge_that_lessens_nothing_changes_nothing(spark, tmp_path):
    docs = spark.createDataFrame([(k, f"text {k}") for k in range(40)], "doc_id long, text string")
    store = sharding.ShardStore(spark, str(tmp_path / "stuck"), docs.schema)
    for k in range(4):
        store.append(docs.where(F.col("doc_id") % 4 == k).coalesce(1), str(k))
    size = min(s.bytes for s in store.shards())
    before = store.version()
    assert store.compact(target=int(size * 1.5)) == before and len(store.shards()) == 4


def test_vacuum_spares_files_that_have_yet_to_be_committed(spark, tmp_path):
    docs = spark.createDataFrame([(k, f"text {k}") for k in range(20)], "doc_id long, text string")
    store = sharding.ShardStore(spark, str(tmp_path / "pending"), docs.schema)
    for k in range(4):
        store.append(docs.where(F.col("doc_id") % 4 == k).coalesce(1), str(k))
    folder = f"{store.root}/data/pending"
    docs.write.parquet(folder)  # an append before its commit
    store.compact()
    assert store.vacuum() == 4
    new = store._written(folder, "late")
    store._change("append late", lambda old: old + new)
    assert store.read().count() == 40
    docs.write.parquet(f"{store.root}/data/left")
    assert store.vacuum(grace=-1) > 0 and store.read().count() == 40
    with pytest.raises(ValueError):
        sharding.ShardStore(spark, str(tmp_path / "none"))
