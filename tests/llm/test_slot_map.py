"""The stored slot map is edited, not made anew."""

from starwatch.llm import sharding


def test_next_version_edits_the_stored_owners(spark, tmp_path):
    path = f"file://{tmp_path}/map"
    docs = spark.createDataFrame([(i, "x" * (i * 37 % 400)) for i in range(600)], "doc_id long, text string")
    raw = docs.selectExpr("doc_id", "cast(length(text) + 1 as long) AS size").withColumn("virtual_slot", sharding.virtual_slot(docs.doc_id, 64))
    loads = sharding.slot_loads(raw, 64)
    by_hand = sharding.rebalance([s % 4 for s in range(64)], loads, 4)  # another balanced map than assign_slots() makes
    assert by_hand != sharding.assign_slots(loads, 4)
    sharding.save_map(spark, path, by_hand, loads, 1)
    sharding.shard_rows(docs, 4, 64, map_path=path).count()
    assert sharding.load_map(spark, path, 2) == by_hand
    sharding.shard_rows(docs, 5, 64, map_path=path).count()
    assert sharding.load_map(spark, path, 3) == sharding.rebalance(sharding.grow(by_hand, loads, 4), loads, 5)
    sharding.shard_rows(docs, 3, 64, map_path=path).count()
    assert set(sharding.load_map(spark, path, 4)) == {0, 1, 2}
