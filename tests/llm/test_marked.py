"""The map of keys: no key is missed, and few others are marked."""

from __future__ import annotations

from motifjoin.llm import groups


def test_map_of_keys_misses_none(spark):
    rows = spark.range(20_000).withColumnRenamed("id", "row")
    keys = rows.filter("row % 7 = 0")
    told = {r["row"]: r["hit"] for r in groups.marked(rows, keys, "row", "hit").collect()}
    assert len(told) == 20_000
    assert all(told[k] for k in range(0, 20_000, 7))
    assert sum(hit for k, hit in told.items() if k % 7) < 100


def test_map_of_no_keys_marks_nothing(spark):
    rows = spark.range(100).withColumnRenamed("id", "row")
    assert groups.marked(rows, rows.limit(0), "row", "hit").filter("hit").count() == 0


def test_full_map_marks_all_keys(spark, monkeypatch):
    monkeypatch.setattr(groups, "MAP_BITS", groups.PAGE_BITS)
    rows = spark.range(300_000).withColumnRenamed("id", "row")
    assert groups.marked(rows, rows, "row", "hit").filter("not hit").count() == 0
