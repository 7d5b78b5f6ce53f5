"""Experiments with a parameter that moves: ``python -m motifjoin.workloads.experiments NAME [folder]``.

Each prints one JSON line per setting: seconds, intermediate rows, peak memory.
Times depend on the machine; orders of counts and ratios do not.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifjoin import meters
from motifjoin.baselines import plans as bp
from motifjoin.baselines.serial import serial_triangles
from motifjoin.operators.delta import DeltaEngine, delta_bootstrap, delta_join
from motifjoin.operators.static_join import static_join
from motifjoin.operators.versions import VersionedRelation
from motifjoin.plans import rewrites as rw
from motifjoin.plans.query import PATTERNS
from motifjoin.sources import graphs as g
from motifjoin.workspace import materialize


def _say(**row: object) -> None:
    print(json.dumps(row), flush=True)


def _count(df: DataFrame) -> tuple[int, float]:
    start = time.perf_counter()
    n = df.count()
    return n, round(time.perf_counter() - start, 3)


def break_even(spark: SparkSession, sf: str) -> None:
    """Fewest cores at which the static and the bootstrapped delta join beat the serial lister; a session per core count."""
    e = materialize(g.basket_edges(spark, sf))
    base = _count(serial_triangles(e))[1]
    _say(method="serial", seconds=base)
    for method in ("static", "delta"):
        took = {}
        for cores in (1, 2, 4, 8):
            out = subprocess.run([sys.executable, "-m", __spec__.name, "_one", sf, method, str(cores)], capture_output=True, text=True, check=True, env=os.environ)
            took[cores] = float(out.stdout.strip().splitlines()[-1])
            _say(method=method, cores=cores, seconds=took[cores])
        _say(method=method, break_even=meters.break_even_cores(took.__getitem__, base, list(took)))


def _one(sf: str, method: str, cores: int) -> None:
    from motifjoin.session import local_session

    spark = local_session(cores)
    e = materialize(g.basket_edges(spark, sf))
    static_join(PATTERNS["triangle"], {"e": e}).count()
    start = time.perf_counter()
    (static_join(PATTERNS["triangle"], {"e": e}) if method == "static" else delta_bootstrap(PATTERNS["triangle"], e, 1)).count()
    print(time.perf_counter() - start)


def rivals(spark: SparkSession, sf: str) -> None:
    """Seconds and intermediate rows of the static join, exploration, binary plan, hypercube and decomposition."""
    e = materialize(g.basket_edges(spark, sf))
    for name in ("triangle", "four_clique", "diamond"):
        q = PATTERNS[name]
        _, m = meters.metered_join(q, {"e": e})
        n, s = _count(static_join(q, {"e": e}))
        _say(pattern=name, method="static", rows=n, seconds=s, index_seconds=round(m.index_s, 3), intermediates=m.intermediates)
        n, s = _count(bp.embedding_explore(q, e))
        _say(pattern=name, method="exploration", rows=n, seconds=s, intermediates=sum(d.count() for d in bp.explore_steps(q, e)))
        for method, df in (("binary", bp.binary_join(q, {"e": e})), ("hypercube", bp.hypercube_join(q, {"e": e})), ("decomposition", bp.decomposed_join(q, {"e": e}))):
            n, s = _count(df)
            _say(pattern=name, method=method, rows=n, seconds=s)


def scaling(spark: SparkSession, sf: str) -> None:
    """Updates per second and index rows per worker as the preloaded share and the workers grow."""
    e = materialize(g.basket_edges(spark, sf))
    for sixteenths, workers in ((1, 4), (2, 8), (4, 16), (8, 32), (16, 64)):
        part = g.fraction(e, sixteenths)
        base, log = g.batch_sequence(part, 20)
        store = VersionedRelation(spark)
        engine = DeltaEngine(PATTERNS["triangle"], {"e": store})
        engine.preload({"e": base})
        log, n, changed, took = materialize(log, "log"), 0, 0, 0.0
        with meters.PeakMemory() as memory:
            for v in range(1, 21):
                one = log.filter(F.col("ver") == v).select("src", "dst", "w")
                n += one.count()
                start = time.perf_counter()
                changed += engine.apply(v, {"e": one}).count()
                took += time.perf_counter() - start
        index = meters.max_index_rows(store.as_of(20), workers)
        _say(sixteenths=sixteenths, workers=workers, updates=n, changes=changed, updates_per_s=round(meters.rate(n, took), 1), changes_per_s=round(meters.rate(changed, took), 1), max_index_rows=index, peak_mb=memory.peak_bytes >> 20)


def maintenance(spark: SparkSession, sf: str) -> None:
    """Seconds per batch, changes per second and matches per changed edge over 20 batches through the engine."""
    e = materialize(g.basket_edges(spark, sf))
    n_edges = e.count()
    base, log = g.batch_sequence(e, 20)
    log = materialize(log, "log")
    for name in ("triangle", "four_clique", "diamond"):
        engine = DeltaEngine(PATTERNS[name], {"e": VersionedRelation(spark)})
        engine.preload({"e": base})
        changed, start = 0, time.perf_counter()
        with meters.PeakMemory() as memory:
            for v in range(1, 21):
                changed += engine.apply(v, {"e": log.filter(F.col("ver") == v).select("src", "dst", "w")}).count()
        took = time.perf_counter() - start
        _say(pattern=name, batches=20, changes=changed, seconds_per_batch=round(took / 20, 3), changes_per_s=round(meters.rate(changed, took), 1), estimate=round(meters.estimate_total(changed, log.count(), n_edges)), peak_mb=memory.peak_bytes >> 20)


def ablation(spark: SparkSession, sf: str) -> None:
    """Plain, with symmetry broken, and with triangles reused too: the same instances of the undirected graph in all."""
    dag = materialize(g.basket_edges(spark, sf))
    e = materialize(g.symmetric(dag))
    tri, ordered = rw.materialize_triangles(e), materialize(rw.degree_relabel(dag)[0])
    for name in ("four_clique", "house", "five_clique"):
        q, once = PATTERNS[name], rw.undirected(PATTERNS[name])
        symmetries = len(rw.automorphisms(q))
        for case, df, each in (("plain", static_join(q.injective(), {"e": e}), symmetries), ("symmetry", static_join(once, {"e": e}), 1), ("symmetry+triangles", static_join(rw.rewrite_with_triangles(once), {"e": e, "tri": tri}), 1)):
            n, s = _count(df)
            _say(pattern=name, case=case, instances=n // each, seconds=s)
        if name != "house":
            n, s = _count(bp.clique_star_join(len(q.order), ordered))
            _say(pattern=name, case="clique index", instances=n, seconds=s)


def batch_size(spark: SparkSession, sf: str) -> None:
    """Seconds and memory for the same updates in batches of growing size."""
    e = materialize(g.basket_edges(spark, sf))
    base, log = g.batch_sequence(e, 20, deletes=False)
    log = materialize(log)
    total = log.count()
    for size in (10, 100, 1000, 10_000, total):
        batches = -(-total // size)
        if batches > 200:  # a batch costs seconds, however small
            _say(batch=size, batches=batches, skipped=True)
            continue
        store = VersionedRelation(spark)
        engine = DeltaEngine(PATTERNS["triangle"], {"e": store})
        engine.preload({"e": base})
        start, changed = time.perf_counter(), 0
        with meters.PeakMemory() as memory:
            for k in range(batches):
                part = log.filter(F.pmod(F.xxhash64("src", "dst"), F.lit(batches)) == k).select("src", "dst", "w")
                changed += engine.apply(k + 1, {"e": part}).count()
        _say(batch=size, batches=batches, seconds=round(time.perf_counter() - start, 3), changes=changed, peak_mb=memory.peak_bytes >> 20)


EXPERIMENTS: dict[str, Callable[[SparkSession, str], None]] = {f.__name__: f for f in (break_even, rivals, scaling, maintenance, ablation, batch_size)}


def main(args: list[str]) -> None:
    sf = args[1] if len(args) > 1 else "/root/testdata/sf0.01"
    if args[0] == "_one":
        return _one(sf, args[2], int(args[3]))
    from motifjoin.session import local_session

    EXPERIMENTS[args[0]](local_session(8), sf)
    return None


if __name__ == "__main__":
    main(sys.argv[1:])
