"""The gathered extension: equal to the plain one, and no proposal moves."""

import pytest

from motifjoin.baselines.plans import binary_join, hypercube_join
from motifjoin.operators import gathered
from motifjoin.operators.delta import delta_join
from motifjoin.operators.static_join import static_join
from motifjoin.plans import rewrites as rw
from motifjoin.plans.query import PATTERNS as P
from motifjoin.sources import graphs as g
from motifjoin.workspace import materialize


@pytest.fixture(scope="module")
def edges(spark, sf):
    return materialize(g.whole_basket_edges(spark, sf).filter("src % 3 > 0").coalesce(1), "edges")


@pytest.fixture()
def ranges(monkeypatch):
    monkeypatch.setattr(gathered, "GATHER_ROWS", 10)
    monkeypatch.setattr(gathered, "RANGE_ROWS", 2000)


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("name,order", [("triangle", None), ("four_clique", None), ("five_clique", None), ("house", None), ("diamond", None), ("diamond", ("a4", "a1", "a3", "a2"))])
def test_equal_to_the_plain_join(spark, edges, ranges, monkeypatch, name, order):
    part = edges.filter("(src + dst) % 5 = 0") if name == "diamond" else edges
    found = static_join(P[name], {"e": part}, order=order)
    assert "MapInArrow" in found._jdf.queryExecution().executedPlan().toString()
    counted = static_join(P[name], {"e": part}, order=order, output="count")
    monkeypatch.setattr(gathered, "GATHER_ROWS", 1 << 40)
    assert rows(found) == rows(static_join(P[name], {"e": part}, order=order))
    assert counted.first().n == found.count()


@pytest.mark.parametrize("name", ["triangle", "diamond"])
def test_filters_both_directions_and_loops(spark, edges, ranges, monkeypatch, name):
    both = g.symmetric(edges.filter("(src * 7 + dst) % 9 = 0"))
    looped = both.union(spark.createDataFrame([(1, 1), (5, 5), (-3, 1), (1, -3), (1 << 40, 1), (1, 1 << 40)], "src long, dst long"))
    for query in (rw.undirected(P[name]), P[name], P["cyclic_triangle"]):
        found = static_join(query, {"e": looped})
        monkeypatch.setattr(gathered, "GATHER_ROWS", 1 << 40)
        assert rows(found) == rows(static_join(query, {"e": looped}))
        monkeypatch.setattr(gathered, "GATHER_ROWS", 10)


@pytest.mark.parametrize("name", ["triangle", "diamond"])
def test_changes_and_binary_plans(spark, edges, ranges, monkeypatch, name):
    old, changes = g.mixed_batch(edges.filter("(src * 7 + dst) % 5 = 0"))
    found = delta_join(P[name], {"e": old}, {"e": changes})
    binary = binary_join(P[name], {"e": old})
    assert all("MapInArrow" in df._jdf.queryExecution().executedPlan().toString() for df in (found, binary))
    monkeypatch.setattr(gathered, "GATHER_ROWS", 1 << 40)
    assert rows(found) == rows(delta_join(P[name], {"e": old}, {"e": changes}))
    assert rows(binary) == rows(static_join(P[name], {"e": old}))


@pytest.mark.parametrize("name,groups", [("four_clique", [[0, 1, 3], [2, 4, 5]]), ("diamond", [[0, 1], [2, 3]]), ("house", [[0, 1, 3], [2, 4, 5], [0, 6, 7]]), ("five_clique", [[0, 1, 4], [2, 5, 7], [3, 6, 8, 9]])])
def test_groups_of_a_binary_plan_meet_in_the_task(spark, edges, ranges, monkeypatch, name, groups):
    part = edges.filter("(src + dst) % 5 = 0") if name == "diamond" else edges
    monkeypatch.setattr(gathered, "CHUNK", 700)
    found = binary_join(P[name], {"e": part}, decompose=groups)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "a4" not in plan.split("Exchange", 1)[1]  # a group's rows do not move
    monkeypatch.setattr(gathered, "GATHER_ROWS", 1 << 40)
    assert rows(found) == rows(static_join(P[name], {"e": part}))


@pytest.mark.parametrize("name,workers", [("triangle", 8), ("diamond", 6), ("cyclic_triangle", 1), ("four_clique", 5)])
def test_cells_of_a_hypercube_join_in_the_task(spark, edges, ranges, monkeypatch, name, workers):
    both = g.symmetric(edges.filter("(src * 7 + dst) % 9 = 0")).union(spark.createDataFrame([(5, 5), (-3, 1), (1 << 40, 1), (1, 1 << 40)], "src long, dst long"))
    found = hypercube_join(P[name], {"e": both}, workers=workers)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "Join" not in plan
    monkeypatch.setattr(gathered, "GATHER_ROWS", 1 << 40)
    assert rows(found) == rows(static_join(P[name], {"e": both}))


def test_one_worker_and_a_hub(spark, sf, ranges, monkeypatch):
    wheel = g.wheel_edges(spark, sf)
    found = static_join(P["triangle"], {"e": wheel}, parallelism=1)
    assert found.rdd.getNumPartitions() == 1
    monkeypatch.setattr(gathered, "GATHER_ROWS", 1 << 40)
    assert rows(found) == rows(static_join(P["triangle"], {"e": wheel}))


def test_nothing_is_found_in_an_empty_relation(spark, edges, monkeypatch):
    monkeypatch.setattr(gathered, "GATHER_ROWS", -1)
    assert static_join(P["triangle"], {"e": edges.limit(0)}).count() == 0
    assert static_join(P["triangle"], {"e": edges.limit(0)}, output="count").first().n == 0
