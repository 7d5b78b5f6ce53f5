"""Batched extension: a bounded number of live proposals, deepest stage first.

The driver holds, per depth, the stored work items (a prefix, its proposer and
the range of candidates not proposed yet). Each turn it takes the deepest depth
at which some worker (or, for the balanced join, every worker) holds a full
batch, or the deepest one that holds anything when none does; at most ``batch``
proposals per worker are made, and what remains of an item is kept.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from motifjoin.operators import balanced as bal
from motifjoin.operators.extend import MIN_C, apply_filters
from motifjoin.operators.index import IndexCatalog
from motifjoin.operators.shares import can_share, share_stage
from motifjoin.plans.stages import Stage
from motifjoin.workspace import materialize, new_path

WORKER, START, END, AT = bal.WORKER, bal.START, bal.END, "__at"
#: Parts in which a worker's items are numbered.
PARTS = 64


@dataclass
class Scheduler:
    """Which depth runs next: ``policy`` is ``deepest_any`` or ``deepest_all``."""

    policy: str = "deepest_any"
    history: list[tuple[int, int]] = field(default_factory=list)

    def choose(self, pending: Sequence[dict[int, int]], batch: int, workers: int) -> int | None:
        """``pending[depth]``: proposals per worker; the depth to run, or None at the end."""
        full = any if self.policy == "deepest_any" else all
        for depth in reversed(range(len(pending))):
            if pending[depth] and full(pending[depth].get(w, 0) >= batch for w in range(workers)):
                return depth
        return max((d for d, p in enumerate(pending) if p), default=None)


def _size() -> F.Column:
    return F.col(END) - F.col(START) + 1


def numbered(items: DataFrame) -> DataFrame:
    """``items`` with ``AT``, the number of proposals of its worker before each: sums within parts, then over parts."""
    payload = [c for c in items.columns if c not in (WORKER, START, END)]
    dealt = items.withColumn("__part", F.pmod(F.xxhash64(*payload, START), F.lit(PARTS)))
    before = Window.rowsBetween(Window.unboundedPreceding, -1)
    inside = before.partitionBy(WORKER, "__part").orderBy(*payload, START)
    placed = dealt.withColumn(AT, F.coalesce(F.sum(_size()).over(inside), F.lit(0)))
    sums = dealt.groupBy(WORKER, "__part").agg(F.sum(_size()).alias("__all"))
    base = F.coalesce(F.sum("__all").over(before.partitionBy(WORKER).orderBy("__part")), F.lit(0))
    tops = sums.select(WORKER, "__part", base.alias("__base"))
    return placed.join(tops, [WORKER, "__part"]).withColumn(AT, F.col(AT) + F.col("__base")).drop("__part", "__base")


@dataclass
class Pending:
    """The stored work items of one depth.

    Items are numbered once, when they come, and never rewritten: a turn reads the next
    range of numbers of every worker, from the segments that it reaches into.
    """

    segments: list[tuple[DataFrame, dict[int, int], dict[int, int]]] = field(default_factory=list)
    given: dict[int, int] = field(default_factory=dict)
    taken: dict[int, int] = field(default_factory=dict)

    def left(self) -> dict[int, int]:
        """Proposals per worker that are not taken yet."""
        return {w: n - self.taken.get(w, 0) for w, n in self.given.items() if n > self.taken.get(w, 0)}

    def add(self, items: DataFrame) -> None:
        stored = materialize(numbered(items), "items")
        load = {r[WORKER]: r["n"] for r in stored.groupBy(WORKER).agg(F.max(F.col(AT) + _size()).alias("n")).collect()}  # a row per worker
        if load:
            self.segments.append((stored, {w: self.given.get(w, 0) for w in load}, load))
            self.given |= {w: self.given.get(w, 0) + n for w, n in load.items()}

    def take(self, batch: int) -> DataFrame:
        """The next ``batch`` proposals of every worker; an item may be split."""
        upto = {w: min(self.taken.get(w, 0) + batch, n) for w, n in self.given.items()}
        out, rest = None, []
        for stored, start, load in self.segments:
            span = [(w, max(0, self.taken.get(w, 0) - start[w]), min(n, upto[w] - start[w])) for w, n in load.items()]
            span = [x for x in span if x[1] < x[2]]
            if span:
                reach = F.broadcast(stored.sparkSession.createDataFrame(span, f"{WORKER} int, __lo long, __hi long"))
                met = stored.join(reach, WORKER).filter((F.col(AT) < F.col("__hi")) & (F.col(AT) + _size() > F.col("__lo")))
                first = F.col(START) + F.greatest(F.lit(0), F.col("__lo") - F.col(AT))
                last = F.col(END) - F.greatest(F.lit(0), F.col(AT) + _size() - F.col("__hi"))
                part = met.select(*(first.alias(c) if c == START else last.alias(c) if c == END else c for c in stored.columns if c != AT))
                out = part if out is None else out.unionByName(part)
            if any(start[w] + n > upto[w] for w, n in load.items()):
                rest.append((stored, start, load))
        self.segments, self.taken = rest, upto
        return out


def _items(prefixes: DataFrame, stage: Stage, catalog: IndexCatalog, workers: int, balanced: bool) -> DataFrame:
    triples = bal.probe_counts(prefixes, stage, catalog)
    triples = materialize(triples, "counted")
    if balanced:
        return bal.balance(triples, workers)
    return triples.withColumn(START, F.lit(1).cast("long")).withColumn(END, F.col(MIN_C)).drop(MIN_C)


def batched_join(prefixes: DataFrame, stages: Sequence[Stage], catalog: IndexCatalog, *, batch: int, workers: int = 8, policy: str = "deepest_any", balanced: bool = False, scheduler: Scheduler | None = None) -> DataFrame:
    """Run the stages under the batch bound; matches are appended to storage as they are found.

    One balanced stage over large relations takes its turns inside tasks, each a worker with a share of its own.
    """
    if not stages:
        return prefixes
    if balanced and scheduler is None and len(stages) == 1 and can_share(prefixes, stages, catalog):
        return share_stage(prefixes, stages[0], catalog, workers, batch)
    catalog.cut(stages)
    scheduler = scheduler or Scheduler(policy)
    cols = prefixes.columns
    held = prefixes.withColumn(WORKER, (F.pmod(F.xxhash64(*cols), F.lit(workers)) if cols else F.lit(0)).cast("int"))
    spark, out_path, outputs = prefixes.sparkSession, new_path(prefixes.sparkSession, "matches"), 0
    queue = [Pending() for _ in stages]
    queue[0].add(_items(held, stages[0], catalog, workers, balanced))
    while (depth := scheduler.choose(pending := [q.left() for q in queue], batch, workers)) is not None:
        scheduler.history.append((depth, sum(min(batch, n) for n in pending[depth].values())))
        stage = stages[depth]
        now = materialize(queue[depth].take(batch), "now")  # read twice below, to ask and to be answered
        found = materialize(apply_filters(bal.probe_intersect(materialize(bal.resolve(now, stage, catalog), "candidates"), stage, catalog), stage), "found")
        if depth + 1 == len(stages):
            found.drop(WORKER).write.parquet(f"{out_path}/turn={outputs}")
            outputs += 1
        else:
            queue[depth + 1].add(_items(found, stages[depth + 1], catalog, workers, balanced))
    if not outputs:
        rows = held.limit(0)
        for stage in stages:
            rows = bal.balanced_extend(rows, stage, catalog, workers)
        return rows.drop(WORKER)
    return spark.read.parquet(out_path).drop("turn")
