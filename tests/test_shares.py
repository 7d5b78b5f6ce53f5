"""Balanced rounds over large relations: even shares, equal results, few rounds."""

import pytest
from pyspark.sql import functions as F

from motifjoin.operators import gathered, scheduler, shares
from motifjoin.operators.balanced import balanced_join
from motifjoin.operators.delta import delta_join
from motifjoin.operators.index import IndexCatalog
from motifjoin.operators.static_join import plan, seeds, static_join
from motifjoin.plans.query import PATTERNS as P
from motifjoin.sources import graphs as g
from motifjoin.workspace import materialize


@pytest.fixture(scope="module")
def edges(spark, sf):
    return materialize(g.whole_basket_edges(spark, sf).filter("src % 3 > 0").coalesce(1), "edges")


@pytest.fixture()
def large(monkeypatch):
    monkeypatch.setattr(gathered, "GATHER_ROWS", 10)
    monkeypatch.setattr(gathered, "RANGE_ROWS", 1500)
    monkeypatch.setattr(shares, "SHARE", 3000)


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_a_hub_is_dealt_evenly(spark, sf, large):
    wheel = materialize(g.wheel_edges(spark, sf), "wheel")
    catalog = IndexCatalog(P["triangle"].bind({"e": wheel}), cut=True)
    order, stages = plan(P["triangle"])
    items, n = shares.dealt(seeds(P["triangle"], catalog, order), stages[0], catalog, 4)
    loads = [r.load for r in items.groupBy("__share").agg(F.sum(F.col("__end") - F.col("__start") + 1).alias("load")).collect()]
    assert len(loads) == n and n % 4 == 0 and max(loads) - min(loads) <= 1
    assert rows(balanced_join(P["triangle"], {"e": wheel}, workers=4)) == rows(static_join(P["triangle"], {"e": wheel}))


def test_batches_take_no_turns_of_the_driver(edges, large, monkeypatch):
    monkeypatch.setattr(scheduler.Scheduler, "choose", lambda *a: pytest.fail("a turn of the driver"))
    for batch in (7, 1000):
        assert rows(balanced_join(P["triangle"], {"e": edges}, workers=4, batch=batch)) == rows(static_join(P["triangle"], {"e": edges}))


@pytest.mark.parametrize("name", ["triangle", "diamond"])
def test_changes_broadcast_nothing(edges, large, monkeypatch, name):
    old, changes = g.mixed_batch(edges.filter("(src * 7 + dst) % 5 = 0"))
    plans = []
    stored = shares.materialize
    monkeypatch.setattr(shares, "materialize", lambda df, name: plans.append(df._jdf.queryExecution().executedPlan().toString()) or stored(df, name))
    found = delta_join(P[name], {"e": old}, {"e": changes}, engine="balanced")
    assert plans and not any("Broadcast" in p for p in plans)
    monkeypatch.setattr(gathered, "GATHER_ROWS", 1 << 40)
    assert rows(found) == rows(delta_join(P[name], {"e": old}, {"e": changes}))


def test_nothing_is_dealt_of_an_empty_relation(edges, monkeypatch):
    monkeypatch.setattr(gathered, "GATHER_ROWS", -1)
    assert balanced_join(P["triangle"], {"e": edges.limit(0)}).count() == 0
