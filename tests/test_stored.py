"""Indices stored once as mapped arrays: equal to the plain join, and neither proposals nor lists move."""

import numpy as np
import pytest

from motifjoin.baselines.plans import clique_star_join, recompute_diff
from motifjoin.operators import delta, gathered, pairs
from motifjoin.operators.static_join import static_join
from motifjoin.plans.query import PATTERNS as P
from motifjoin.sources import graphs as g


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("wide", [False, True])
def test_pairs_move_as_differences(wide):
    draw = np.random.default_rng(5)
    k, x = draw.integers(-50, 50, 4000), draw.integers(0, 300, 4000)
    if wide:
        k[0], x[:2] = 1 << 62, (-(1 << 62), 1 << 62)
    want = sorted(set(zip(k.tolist(), x.tolist())))
    sent = list(pairs.blobs(iter([(k[:2500], x[:2500]), (k[2500:], x[2500:])]), pairs.by_bounds([-20, 7])))
    got = list(pairs.parts_of(iter(sent)))
    assert [b for b, _, _ in got] == [0, 1, 2] and [t for _, k, x in got for t in zip(k.tolist(), x.tolist())] == want


def test_large_baskets_give_the_same_graph(spark, sf, monkeypatch):
    want = rows(g.whole_basket_edges(spark, sf))
    monkeypatch.setattr(g, "LARGE", 10)
    monkeypatch.setattr(pairs, "BUFFER", 300)
    found = g.whole_basket_edges(spark, sf)
    assert rows(found) == want and "blob" in found._jdf.queryExecution().executedPlan().toString()


def test_lists_do_not_move_and_repeated_rows_count_once(spark, monkeypatch):
    far = [(int(a), int(b)) for a, b in np.random.default_rng(3).integers(0, 60, (900, 2))]
    edges = spark.createDataFrame([*far, *far[:200], (1 << 40, 3), (3, 1 << 40), (None, 3)], "src long, dst long")
    want = {n: rows(static_join(P[n], {"e": edges})) for n in ("triangle", "diamond")}
    for name, value in (("GATHER_ROWS", 10), ("RANGE_ROWS", 70), ("PART_ROWS", 100), ("CHUNK", 500)):
        monkeypatch.setattr(gathered, name, value)
    for name, there in want.items():
        found = static_join(P[name], {"e": edges})
        plan = found._jdf.queryExecution().executedPlan().toString()
        assert "MapInArrow" in plan and "xs" not in plan and "Join" not in plan
        assert rows(found) == there


@pytest.fixture()
def dense(spark, monkeypatch):
    for name, value in (("RANGE_ROWS", 170), ("PART_ROWS", 300), ("CHUNK", 500)):
        monkeypatch.setattr(gathered, name, value)
    far = [(int(a), int(b)) for a, b in np.random.default_rng(4).integers(0, 45, (1100, 2)) if a < b]
    return spark.createDataFrame([*far, *far[:50]], "src long, dst long")


def test_neighbourhoods_are_cut_in_their_task(spark, dense, monkeypatch):
    cases = [(4, False), (5, False), (4, True)]
    listed = lambda df: sorted((tuple(tuple(sorted(c)) if isinstance(c, list) else c for c in r) for r in df.collect()))
    want = [listed(clique_star_join(k, dense, compact)) for k, compact in cases]
    monkeypatch.setattr(gathered, "GATHER_ROWS", 10)
    for (k, compact), there in zip(cases, want):
        found = clique_star_join(k, dense, compact)
        plan = found._jdf.queryExecution().executedPlan().toString()
        assert "MapInArrow" in plan and "Join" not in plan and there and listed(found) == there


@pytest.mark.parametrize("name", ["triangle", "diamond"])
def test_versions_are_compared_in_a_task(spark, dense, monkeypatch, name):
    old, new = dense.filter("(src + dst) % 7 > 0"), dense.filter("(src + dst) % 5 > 0 and src <> 11")
    want = rows(recompute_diff(P[name], {"e": old}, {"e": new}))
    monkeypatch.setattr(gathered, "GATHER_ROWS", 10)
    found = recompute_diff(P[name], {"e": old}, {"e": new})
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "Join" not in plan and want and rows(found) == want


@pytest.mark.parametrize("name", ["four_clique", "diamond"])
def test_versions_are_read_from_one_table(spark, dense, monkeypatch, name):
    old = dense.filter("(src + dst) % 7 > 0")
    changes = dense.filter("(src + dst) % 3 = 0").selectExpr("src", "dst", "case when (src + dst) % 7 = 0 then 2 when src % 2 = 0 then -1 else 1 end as w")
    noise = spark.createDataFrame([(3, 900, -1), (4, 900, 1), (4, 900, -1), (None, 2, 1)], "src long, dst long, w int")
    want = rows(delta.delta_join(P[name], {"e": old}, {"e": changes.union(noise)}))
    monkeypatch.setattr(gathered, "GATHER_ROWS", 10)
    monkeypatch.setattr(delta, "normalize_delta", None)  # no version is made by joins
    found = delta.delta_join(P[name], {"e": old}, {"e": changes.union(noise)})
    assert want and {r[-1] for r in want} == {1, -1} and rows(found) == want
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
