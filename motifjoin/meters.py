"""Costs of a join: rounds, load, communication, memory, intermediates, times, rates."""

from __future__ import annotations

import re
import threading
import time
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass, field
from pathlib import Path

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifjoin.operators import extend as ex
from motifjoin.operators.index import IndexCatalog
from motifjoin.operators.static_join import plan, seeds
from motifjoin.plans.agm import agm_bound
from motifjoin.plans.query import JoinQuery
from motifjoin.workspace import materialize


@dataclass
class StageCost:
    """One extension: rows in, lookups of counts, proposals, rows out."""

    attr: str
    prefixes: int
    lookups: int
    proposals: int
    probes: int
    out: int


@dataclass
class Meter:
    """What a run has cost, in tuples and seconds."""

    stages: list[StageCost] = field(default_factory=list)
    loads: list[list[int]] = field(default_factory=list)
    index_rows: int = 0
    index_s: float = 0.0
    run_s: float = 0.0

    @property
    def rounds(self) -> int:
        return len(self.loads)

    @property
    def load(self) -> int:
        return max((max(r, default=0) for r in self.loads), default=0)

    @property
    def communication(self) -> int:
        return sum(sum(r) for r in self.loads)

    @property
    def memory(self) -> int:
        """Index tuples and the largest round's tuples, over all workers; results do not count."""
        return self.index_rows + max((sum(r) for r in self.loads), default=0)

    @property
    def intermediates(self) -> int:
        """All prefixes and proposals."""
        return sum(s.prefixes + s.proposals for s in self.stages)

    @property
    def proposals(self) -> int:
        return sum(s.proposals for s in self.stages)

    @property
    def balance(self) -> float:
        """The worst round's largest load over its mean."""
        return max((max(r) * len(r) / sum(r) for r in self.loads if sum(r)), default=1.0)


def worker_loads(rows: DataFrame, key: Sequence[str], workers: int, by_value: bool = False) -> list[int]:
    """Rows that each worker would receive when ``rows`` are sent by the hash of ``key``, or by its value."""
    spread = F.xxhash64(*key)
    if by_value:
        spread = F.col(key[0])
        for k in key[1:]:
            spread = spread * 31 + F.col(k)
    got = {r["w"]: r["count"] for r in rows.groupBy(F.pmod(spread, F.lit(workers)).alias("w")).count().collect()}
    return [got.get(w, 0) for w in range(workers)]


def metered_join(query: JoinQuery, relations: Mapping[str, DataFrame], workers: int = 8, order: Sequence[str] | None = None, by_value: bool = False) -> tuple[DataFrame, Meter]:
    """Run the static join step by step, counting what every step sends."""
    meter, start = Meter(), time.perf_counter()
    catalog = IndexCatalog(query.bind(relations), cut=True)
    order, stages = plan(query, order=order)
    catalog.cut(stages)
    meter.index_rows = catalog.rows()
    meter.index_s = time.perf_counter() - start
    start = time.perf_counter()
    prefixes = materialize(seeds(query, catalog, order), "prefixes")
    for stage in stages:
        n = prefixes.count()
        for use in stage.uses:
            meter.loads.append(worker_loads(prefixes, ex._keys(use), workers, by_value) if use.key_attrs else [n] + [0] * (workers - 1))
        triples = ex.init_triples(prefixes)
        if len(stage.uses) > 1:
            triples = ex.minimise_counts(triples, stage, catalog)
        candidates = materialize(ex.propose(triples, stage, catalog), "candidates")
        proposals = candidates.count()
        for use in stage.uses if len(stage.uses) > 1 else ():
            meter.loads.append(worker_loads(candidates, [*ex._keys(use), stage.attr], workers, by_value))
        prefixes = materialize(ex.apply_filters(ex.intersect(candidates, stage, catalog), stage), "prefixes")
        meter.stages.append(StageCost(stage.attr, n, n * len(stage.uses), proposals, proposals * (len(stage.uses) - 1), prefixes.count()))
    meter.run_s = time.perf_counter() - start
    return prefixes.select(*(query.order or query.attrs)), meter


def agm_ratio(query: JoinQuery, relations: Mapping[str, DataFrame], meter: Meter) -> float:
    """The largest stage's proposals over the bound: at most 1."""
    bound = agm_bound(query, {n: d.distinct().count() for n, d in relations.items()})
    return max((s.proposals for s in meter.stages), default=0) / bound.value if bound.value else 0.0


def stage_proposals(query: JoinQuery, relations: Mapping[str, DataFrame], order: Sequence[str] | None = None) -> DataFrame:
    """``(stage, attr, prefixes, proposals)`` as one plan: what each stage would propose."""
    catalog = IndexCatalog(query.bind(relations))
    order, stages = plan(query, order=order)
    prefixes, out = seeds(query, catalog, order), None
    for k, stage in enumerate(stages):
        triples = ex.minimise_counts(ex.init_triples(prefixes), stage, catalog)
        row = triples.agg(F.lit(k).cast("long").alias("stage"), F.lit(stage.attr).alias("attr"), F.count(F.lit(1)).alias("prefixes"), F.coalesce(F.sum(ex.MIN_C), F.lit(0)).cast("long").alias("proposals"))
        out = row if out is None else out.unionByName(row)
        prefixes = ex.extend(prefixes, stage, catalog)
    return out


def open_wedges(edges: DataFrame) -> DataFrame:
    """``n``: paths of two edges, what a binary plan makes before it closes triangles."""
    into = edges.groupBy(F.col("dst").alias("v")).agg(F.count(F.lit(1)).alias("i"))
    out_of = edges.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("o"))
    return into.join(out_of, "v").agg(F.coalesce(F.sum(F.col("i") * F.col("o")), F.lit(0)).cast("long").alias("n"))


def exchanges(df: DataFrame) -> int:
    """Shuffles in a plan, reused ones not counted again."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return len(re.findall(r"(?<!Reused)(?<!Broadcast)Exchange (?:hash|range|round|single)", text, re.I))


def bytes_per_edge(spark, path: str, edges: int) -> float:
    """Stored bytes of an index per edge."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    fs = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return fs.getContentSummary(where).getLength() / max(1, edges)


def timed(fn: Callable[[], object]) -> tuple[object, float]:
    start = time.perf_counter()
    out = fn()
    return out, time.perf_counter() - start


def rate(n: int, seconds: float) -> float:
    """Updates taken in, or changes given out, per second."""
    return n / seconds if seconds else 0.0


def max_index_rows(edges: DataFrame, workers: int, by_value: bool = False) -> int:
    """Index tuples of the fullest worker: forward by source and reverse by target."""
    a, b = edges.columns[:2]
    return max(x + y for x, y in zip(worker_loads(edges, [a], workers, by_value), worker_loads(edges, [b], workers, by_value)))


def break_even_cores(run: Callable[[int], float], baseline_s: float, cores: Sequence[int]) -> int | None:
    """The fewest of ``cores`` at which ``run(cores)``, in seconds, beats the baseline."""
    return next((c for c in sorted(cores) if run(c) < baseline_s), None)


def estimate_total(changes: int, changed_edges: int, edges: int) -> float:
    """Matches of the whole graph, extrapolated from changes per changed edge."""
    return changes / changed_edges * edges if changed_edges else 0.0


class PeakMemory:
    """Samples the resident memory of this process and its children once a second."""

    def __init__(self, every: float = 1.0) -> None:
        self.every, self.peak_bytes, self._stop = every, 0, threading.Event()

    def _rss(self) -> int:
        import os

        pids, total = [os.getpid()], 0
        while pids:
            pid = pids.pop()
            try:
                total += int(Path(f"/proc/{pid}/statm").read_text().split()[1]) * os.sysconf("SC_PAGE_SIZE")
                for task in Path(f"/proc/{pid}/task").iterdir():
                    pids += map(int, (task / "children").read_text().split())
            except OSError:
                continue
        return total

    def __enter__(self) -> PeakMemory:
        def sample() -> None:
            while not self._stop.wait(self.every):
                self.peak_bytes = max(self.peak_bytes, self._rss())

        self.peak_bytes = self._rss()
        self._thread = threading.Thread(target=sample, daemon=True)
        self._thread.start()
        return self

    def __exit__(self, *_: object) -> None:
        self._stop.set()
        self._thread.join()
        self.peak_bytes = max(self.peak_bytes, self._rss())
