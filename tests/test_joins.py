import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from motifjoin import meters
from motifjoin.baselines import plans as bp
from motifjoin.baselines.serial import count_triangles, list_triangles, serial_generic_join, vertex_match
from motifjoin.operators.balanced import balanced_join, received
from motifjoin.operators.delta import DeltaEngine, delta_join
from motifjoin.operators.index import IndexCatalog, build_index
from motifjoin.operators.scheduler import Scheduler
from motifjoin.operators.static_join import explain_match, static_join
from motifjoin.operators.versions import VersionedRelation
from motifjoin.plans.query import PATTERNS, parse_query
from motifjoin.sources import graphs as g
from motifjoin.sources.io import edges_of, read_edges, write_matches
from motifjoin.workspace import materialize

K5 = [(a, b) for a in range(5) for b in range(a + 1, 5)]


def rows(df):
    return sorted(map(tuple, df.collect()))


def random_edges(seed, n=14, m=60):
    rng = random.Random(seed)
    return sorted({(a, b) for a, b in ((rng.randrange(n), rng.randrange(n)) for _ in range(m)) if a != b})


@pytest.fixture(scope="module")
def basket(spark, sf):
    return materialize(g.basket_edges(spark, sf))


@pytest.mark.parametrize("name, n", [("triangle", 10), ("four_clique", 5), ("five_clique", 1), ("house", 7), ("diamond", 5)])
def test_complete_graph(spark, name, n):
    assert static_join(PATTERNS[name], {"e": edges_of(spark, K5)}).count() == n


def test_injective_house(spark):
    assert static_join(PATTERNS["house"].injective(), {"e": edges_of(spark, K5)}).count() == 2


@pytest.mark.parametrize("name", list(PATTERNS))
def test_serial_joins_agree_with_nested_loops(name):
    edges = random_edges(3, 8, 30)
    q = PATTERNS[name]
    have = set(edges)
    want = sorted(t for t in itertools.product(range(8), repeat=len(q.order)) if all((t[q.order.index(a.attrs[0])], t[q.order.index(a.attrs[1])]) in have for a in q.atoms))
    for how in ("hash", "seek"):
        assert sorted(serial_generic_join(q, {"e": edges}, intersect=how)) == want
    assert sorted(vertex_match(q, edges)) == want


@pytest.mark.parametrize("seed", range(6))
@pytest.mark.parametrize("probes", [1, 7, 1 << 22])
def test_triangle_lister(seed, probes):
    edges = random_edges(seed, 12, 50) + [(3, 3), (1, 2), (2, 1)]
    near = {frozenset(x) for x in edges if len(set(x)) == 2}
    want = [t for t in itertools.combinations(range(12), 3) if all(frozenset(x) in near for x in itertools.combinations(t, 2))]
    src, dst = np.array(edges, np.int64).T
    assert sorted(tuple(map(int, r)) for found in list_triangles(src, dst, probes) for r in found) == want
    assert count_triangles(src, dst) == len(want)


def test_triangle_lister_without_edges():
    none = np.zeros(0, np.int64)
    assert count_triangles(none, none) == 0 and count_triangles(np.array([4]), np.array([4])) == 0


@pytest.mark.parametrize("k", [3, 4, 5])
def test_clique_index(spark, k):
    for edges in (K5, random_edges(8, 9, 45)):
        e = edges_of(spark, edges)
        want = sorted(serial_generic_join(PATTERNS[{3: "triangle", 4: "four_clique", 5: "five_clique"}[k]], {"e": edges}))
        assert rows(bp.clique_star_join(k, e)) == want
        assert sum(len(r.tail) for r in bp.clique_star_join(k, e, compact=True).collect()) == len(want)


@pytest.mark.parametrize("name", ["triangle", "cyclic_triangle", "diamond", "house"])
@pytest.mark.parametrize("options", [{}, {"seed": "unit"}, {"layout": "list"}, {"counts": "carried"}, {"propose": "branches"}, {"unbound": "always"}], ids=str)
def test_variants_agree(spark, name, options):
    edges = random_edges(5)
    assert rows(static_join(PATTERNS[name], {"e": edges_of(spark, edges)}, **options)) == sorted(serial_generic_join(PATTERNS[name], {"e": edges}))


def test_every_order(spark):
    edges = random_edges(6)
    want = sorted(serial_generic_join(PATTERNS["diamond"], {"e": edges}))
    e = edges_of(spark, edges)
    for order in list(itertools.permutations(PATTERNS["diamond"].order))[::5]:
        assert rows(static_join(PATTERNS["diamond"], {"e": e}, order=order)) == want


def test_batched_joins_keep_their_bound(spark):
    edges = random_edges(7)
    want = sorted(serial_generic_join(PATTERNS["triangle"], {"e": edges}))
    from motifjoin.operators.scheduler import batched_join
    from motifjoin.operators.static_join import plan, seeds

    q = PATTERNS["triangle"]
    catalog = IndexCatalog(q.bind({"e": edges_of(spark, edges)}))
    order, stages = plan(q)
    turns = Scheduler("deepest_any")
    out = batched_join(seeds(q, catalog, order), stages, catalog, batch=25, workers=2, scheduler=turns)
    assert rows(out.select(*q.order)) == want and all(n <= 50 for _, n in turns.history) and len(turns.history) > 1


def test_scheduler_policies():
    any_, all_ = Scheduler("deepest_any"), Scheduler("deepest_all")
    pending = [{0: 5, 1: 5}, {0: 5, 1: 1}]
    assert any_.choose(pending, 5, 2) == 1 and all_.choose(pending, 5, 2) == 0
    assert any_.choose([{0: 1}, {}], 5, 2) == 0 and all_.choose([{}, {}], 5, 2) is None


@pytest.mark.parametrize("seed", [1, 2])
def test_changes_equal_the_difference(spark, seed):
    rng = random.Random(seed)
    old = random_edges(seed)
    delta = [(*e, -1) for e in old if rng.random() < 0.2] + [(a, b, 1) for a, b in random_edges(seed + 50, m=20)]
    delta += [(99, 98, -1), (1, 2, 1), (1, 2, -1)]
    net = {}
    for a, b, w in delta:
        net[a, b] = net.get((a, b), 0) + w
    new = sorted((set(old) | {e for e, w in net.items() if w > 0}) - {e for e, w in net.items() if w < 0})
    e, d = edges_of(spark, old), spark.createDataFrame(delta, "src long, dst long, w int")
    for name in ("triangle", "diamond"):
        before, after = (set(serial_generic_join(PATTERNS[name], {"e": x})) for x in (old, new))
        want = sorted([(*t, 1) for t in after - before] + [(*t, -1) for t in before - after])
        assert rows(delta_join(PATTERNS[name], {"e": e}, {"e": d})) == want


def test_engine_versions_and_inverse(spark):
    old = random_edges(11)
    q, store = PATTERNS["triangle"], VersionedRelation(spark)
    engine = DeltaEngine(q, {"e": store})
    engine.preload({"e": edges_of(spark, old)})
    delta = spark.createDataFrame([(*x, -1) for x in old[:6]] + [(3, 100, 1), (100, 4, 1)], "src long, dst long, w int")
    one = engine.apply(1, {"e": delta})
    assert engine.apply(1, {"e": delta}).count() == 0  # a replayed version changes nothing
    two = engine.apply(2, {"e": delta.withColumn("w", -F.col("w"))})
    assert one.unionByName(two).groupBy("a1", "a2", "a3").agg(F.sum("w").alias("w")).filter("w <> 0").count() == 0
    assert rows(store.as_of(store.version)) == old
    reopened = VersionedRelation(spark, store.path)
    assert reopened.version == 2 and rows(reopened.as_of(2)) == old
    assert {r.c0: r.n for r in store.counts(2, ["c0"]).collect()} == {a: sum(x == a for x, _ in old) for a, _ in old}


@pytest.mark.parametrize("name", ["triangle", "diamond"])
def test_balanced_agrees(spark, name):
    edges = random_edges(8)
    assert rows(balanced_join(PATTERNS[name], {"e": edges_of(spark, edges)}, workers=3)) == sorted(serial_generic_join(PATTERNS[name], {"e": edges}))


def test_balance_on_a_hub(spark, sf):
    e = materialize(g.wheel_edges(spark, sf))
    ratio = lambda how: (lambda w: max(w) * len(w) / sum(w))([r.work for r in received(PATTERNS["triangle"], {"e": e}, 8, 0, how).collect()])
    assert ratio("balanced") <= 1.08 < ratio("hash")
    with pytest.raises(ValueError):
        balanced_join(PATTERNS["triangle"], {"e": e}, workers=8, batch=2, check=(449, 449**1.5))


def test_work_stays_within_the_bound(spark, sf):
    e = materialize(g.wheel_edges(spark, sf))
    _, m = meters.metered_join(PATTERNS["triangle"], {"e": e}, workers=4)
    assert m.proposals == 895 and meters.open_wedges(e).first().n == 23_096
    assert meters.agm_ratio(PATTERNS["triangle"], {"e": e}, m) <= 1 and m.rounds == 4 and m.communication >= m.load


def test_baselines_agree(spark, basket):
    q = PATTERNS["triangle"]
    want = rows(static_join(q, {"e": basket}))
    assert len(want) == 1355
    for other in (bp.binary_join(q, {"e": basket}), bp.hypercube_join(q, {"e": basket}, workers=1), bp.hypercube_join(q, {"e": basket}, workers=4, local="generic"), bp.embedding_explore(q, basket), bp.decomposed_join(q, {"e": basket})):
        assert rows(other) == want
    e = basket.toPandas()
    assert count_triangles(e.src.to_numpy(), e.dst.to_numpy()) == 1355
    assert bp.optimal_shares(q, {"e": 1000}, 8) == {"a1": 2, "a2": 2, "a3": 2}


def test_edge_cases(spark):
    none = edges_of(spark, [])
    assert static_join(PATTERNS["triangle"], {"e": none}).count() == 0 and balanced_join(PATTERNS["triangle"], {"e": none}).count() == 0
    odd = spark.createDataFrame([(1, 1), (1, 2), (2, 1), (2, 2), (None, 3), (1, 2)], "src int, dst int")
    assert rows(static_join(parse_query("loop(a) := e(a,a)"), {"e": odd})) == [(1,), (2,)]
    assert static_join(parse_query("t(a,b,c) := e(a,b), e(b,c), e(c,a)"), {"e": odd}).count() == 8
    names = spark.createDataFrame([("x", "y"), ("y", "z"), ("x", "z")], "a string, b string")
    assert rows(static_join(PATTERNS["triangle"], {"e": names})) == [("x", "y", "z")]
    assert static_join(parse_query("p(a,b,c,d) := e(a,b), e(c,d)"), {"e": edges_of(spark, K5)}).count() == 100


def test_catalog_is_shared_stored_and_read(spark, tmp_path):
    q = PATTERNS["four_clique"]
    catalog = IndexCatalog(q.bind({"e": edges_of(spark, K5)}))
    assert static_join(q, catalog).count() == 5 and len(catalog) == 1
    catalog.save(str(tmp_path / "c"))
    again = IndexCatalog.load(spark, str(tmp_path / "c"))
    assert len(again) == 1 and static_join(q, again).count() == 5
    assert meters.bytes_per_edge(spark, str(tmp_path / "c/index"), 10) > 0


def test_resolver_numbers_every_value_once(spark):
    e = edges_of(spark, [(1, k) for k in range(200)] + [(2, 5)])
    got = build_index(e, ["src"], "dst").resolver.collect()
    assert sorted(r["__no"] for r in got if r["__k0"] == 1) == list(range(1, 201)) and {r["__ext"] for r in got if r["__k0"] == 1} == set(range(200))


def test_readers_and_writers(spark, tmp_path):
    e = edges_of(spark, K5)
    for fmt in ("parquet", "orc", "json", "csv"):
        write_matches(e, str(tmp_path / fmt), fmt)
        assert rows(read_edges(spark, str(tmp_path / fmt), fmt)) == sorted(K5)
    (tmp_path / "t.txt").write_text("# graph\n1 2\n2,3\n\n1 2\n4 4\nx y\n")
    assert rows(read_edges(spark, str(tmp_path / "t.txt"), "text")) == [(1, 2), (2, 3)]
    write_matches(e, "", "noop")


def test_explanation(spark, basket):
    text = explain_match(PATTERNS["triangle"], {"e": basket})
    assert text.startswith("order: a1, a2, a3") and "Physical Plan" in text and "CartesianProduct" not in text


def test_streams_equal_the_batch(spark, sf, tmp_path):
    from motifjoin.streaming import updates

    events = spark.read.parquet(f"{sf}/events.parquet")
    for k in range(3):
        events.filter(F.col("event_id") % 3 == k).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    store = VersionedRelation(spark)
    engine = DeltaEngine(PATTERNS["triangle"], {"e": store})
    engine.preload({"e": edges_of(spark, [])})
    for _ in range(2):  # the second run finds nothing new
        updates.run_changes(updates.read_events(spark, str(tmp_path / "in")), engine, str(tmp_path / "out"), str(tmp_path / "check"), delay="60 days")
    final = spark.read.parquet(str(tmp_path / "out")).groupBy("a1", "a2", "a3").agg(F.sum("w").alias("w")).filter("w <> 0")
    assert final.filter("w <> 1").count() == 0
    assert rows(final.drop("w")) == rows(static_join(PATTERNS["triangle"], {"e": store.as_of(store.version)}))


@pytest.mark.parametrize("name", ["triangle", "diamond"])
def test_lifetimes_give_the_changes_of_every_day(spark, name):
    from motifjoin.streaming import updates

    rng = random.Random(3)
    ops = {(day, a, b): rng.choice((1, 1, -1)) for day in range(6) for a, b in ((rng.randrange(7), rng.randrange(7)) for _ in range(25)) if a != b}
    table = spark.createDataFrame([(d, a, b, w) for (d, a, b), w in ops.items()], "day int, src long, dst long, w int")
    query, edges, before, expected = PATTERNS[name], set(), set(), []
    for day in range(6):
        for (d, a, b), w in ops.items():
            if d == day:
                (edges.add if w > 0 else edges.discard)((a, b))
        now = set(map(tuple, serial_generic_join(query, {"e": sorted(edges)})))
        expected += [(*m, day, 1) for m in now - before] + [(*m, day, -1) for m in before - now]
        before = now
    found = updates.pattern_changes(query, updates.lifetimes(table)).groupBy(*query.order, "day").agg(F.sum("w").alias("w")).filter("w <> 0")
    assert any(w < 0 for *_, w in expected) and rows(found) == sorted(expected)


def test_versions_do_not_move_the_base(spark, basket):
    store = VersionedRelation(spark, compact_share=100)
    store.preload(basket)
    store.stage(1, basket.filter("(src + dst) % 50 = 0").withColumn("w", F.lit(-1)))
    store.commit(1)
    store.stage(2, basket.filter("(src + dst) % 100 = 0").withColumn("w", F.lit(1)))
    store.commit(2)
    view = store.as_of(2)
    assert rows(view) == rows(basket.filter("(src + dst) % 50 <> 0 or (src + dst) % 100 = 0"))
    assert "base-" not in "".join(x for x in view._jdf.queryExecution().executedPlan().toString().split("\n") if "Exchange hash" in x)
    assert {r.c0: r.n for r in store.counts(2, ["c0"]).collect()} == {r.c0: r["count"] for r in view.groupBy("c0").count().collect()}
    keys = sorted(r.c0 for r in view.select("c0").distinct().collect())[:5]
    some = spark.createDataFrame([(k,) for k in keys], "c0 long")
    assert {r.c0: r.n for r in store.counts(2, ["c0"], some).collect()} == {k: n for k, n in ((r.c0, r["count"]) for r in view.groupBy("c0").count().collect()) if k in keys}


@pytest.mark.parametrize("name,few", [("four_clique", 500_000), ("diamond", 40)])
def test_rules_that_grow_from_changes_agree(spark, basket, name, few):
    old, changes = basket.filter("(src + dst) % 10 <> 0"), g.mixed_batch(basket)[1]
    want = rows(delta_join(PATTERNS[name], {"e": old}, {"e": changes}, engine="joined"))
    assert rows(delta_join(PATTERNS[name], {"e": old}, {"e": changes}, engine="pipelined", few=few)) == want
    engine = DeltaEngine(PATTERNS[name], {"e": VersionedRelation(spark)}, engine="pipelined", few=few)
    engine.preload({"e": old})
    assert rows(engine.apply(1, {"e": changes})) == want
    assert name == "diamond" or len(engine.shared) < len(PATTERNS[name].atoms)  # symmetric rules share their first extension


def test_a_commit_that_broke_off_is_finished(spark):
    q = parse_query("q(a,b,c) := R(a,b), S(b,c)")
    r, s = (spark.createDataFrame(x, "x long, y long") for x in ([(1, 2)], [(2, 3)]))
    stores = {n: VersionedRelation(spark) for n in "RS"}
    engine = DeltaEngine(q, stores)
    engine.preload({"R": r, "S": s})
    batch = {"R": spark.createDataFrame([(5, 2, 1)], "x long, y long, w int"), "S": spark.createDataFrame([(2, 9, 1)], "x long, y long, w int")}
    want = rows(engine.stage(1, batch))
    stores["R"].commit(1, compact=False)  # and here the process ends
    again = DeltaEngine(q, {n: VersionedRelation(spark, st.path) for n, st in stores.items()})
    assert again.stores["R"].version == 1 and again.stores["S"].version == 0
    assert rows(again.apply(1, batch)) == want and again.apply(1, batch).count() == 0
    assert rows(again.apply(2, {"S": spark.createDataFrame([(2, 9, -1)], "x long, y long, w int")})) == [(1, 2, 9, -1), (5, 2, 9, -1)]
    assert {st.version for st in again.stores.values()} == {2}
