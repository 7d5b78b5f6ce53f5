"""The balanced join: every index entry, lookup and proposal spread evenly over workers.

Workers are a column. A work item is a prefix, the index that proposes for it
and a range of candidate numbers. Candidates are fetched by number from the
resolver; lookups travel as requests, deduplicated per worker, and their
answers travel back to where the prefix stayed, so a key that very many
prefixes share costs one request per worker. After counting, every worker
splits its work into equal contiguous shares for all workers.
"""

from __future__ import annotations

import math
from collections.abc import Mapping, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from motifjoin.operators.extend import MIN_C, MIN_I, _keys, apply_filters, init_triples
from motifjoin.operators.index import IndexCatalog
from motifjoin.operators.shares import can_share, share_stage
from motifjoin.operators.static_join import plan, seeds
from motifjoin.plans.query import JoinQuery
from motifjoin.plans.stages import AtomUse, Stage
from motifjoin.workspace import materialize

WORKER, START, END = "__worker", "__start", "__end"


def min_batch(workers: int, in_size: int, max_out: float) -> int:
    """The least batch per worker for which the balance holds with high probability."""
    return math.ceil(workers * max(workers, math.log(max(2.0, in_size * max(1.0, max_out)))))


def _requests(rows: DataFrame, cols: Sequence[str]) -> DataFrame:
    """Distinct lookups per worker: combined in each task before they travel."""
    return rows.select(WORKER, *cols).distinct()


def _named(use: AtomUse, df: DataFrame) -> DataFrame:
    for i, attr in enumerate(use.key_attrs):
        df = df.withColumnRenamed(f"__k{i}", attr)
    return df


def probe_counts(prefixes: DataFrame, stage: Stage, catalog: IndexCatalog) -> DataFrame:
    """Count minimisation by requests: the prefix stays where it is, its key asks."""
    rows = init_triples(prefixes)
    for i, use in enumerate(stage.uses):
        counts = _named(use, catalog.get(use.index_id).counts)
        if not use.key_attrs:
            answered = rows.crossJoin(F.broadcast(counts.filter("__cnt > 0")))
        else:
            keys = _keys(use)
            answers = _requests(rows, keys).join(counts, keys)
            answered = rows.join(answers, [WORKER, *keys])
        smaller = F.col("__cnt") < F.col(MIN_C)
        rows = answered.withColumn(MIN_I, F.when(smaller, F.lit(i)).otherwise(F.col(MIN_I))).withColumn(MIN_C, F.least(MIN_C, "__cnt")).drop("__cnt")
    return rows


def balance(triples: DataFrame, workers: int) -> DataFrame:
    """Split each worker's proposals into contiguous shares that differ by at most one; ranges move."""
    payload = [c for c in triples.columns if c not in (WORKER, MIN_C)]
    order = Window.partitionBy(WORKER).orderBy(*payload).rowsBetween(Window.unboundedPreceding, -1)
    placed = triples.withColumn("__at", F.coalesce(F.sum(MIN_C).over(order), F.lit(0))).withColumn("__total", F.sum(MIN_C).over(Window.partitionBy(WORKER)))
    bound = lambda share: F.expr(f"({share} * __total) div {workers}")
    first = F.expr(f"((__at + 1) * {workers} - 1) div __total")
    last = F.expr(f"((__at + {MIN_C}) * {workers} - 1) div __total")
    cut = placed.withColumn("__s", F.explode(F.sequence(first, last)))
    low, high = F.greatest(bound("__s"), F.col("__at")), F.least(bound("(__s + 1)"), F.col("__at") + F.col(MIN_C))
    # each sender starts its shares at another receiver, so that rounding does not favour one
    return cut.withColumn(START, low - F.col("__at") + 1).withColumn(END, high - F.col("__at")).filter(F.col(END) >= F.col(START)).withColumn(WORKER, F.pmod(F.col("__s") + F.col(WORKER), F.lit(workers)).cast("int")).drop("__at", "__total", "__s", MIN_C)


def resolve(items: DataFrame, stage: Stage, catalog: IndexCatalog) -> DataFrame:
    """Work items to candidates: numbers are asked for once per worker and answered by the resolver."""
    each = items.withColumn("__no", F.explode(F.sequence(F.col(START), F.col(END)))).drop(START, END)
    parts = []
    for i, use in enumerate(stage.uses):
        mine = each.filter(F.col(MIN_I) == i)
        keys = _keys(use)
        resolver = _named(use, catalog.get(use.index_id).resolver).withColumnRenamed("__ext", stage.attr)
        answers = _requests(mine, [*keys, "__no"]).join(resolver, [*keys, "__no"])
        parts.append(mine.join(answers, [WORKER, *keys, "__no"]).drop("__no"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def probe_intersect(candidates: DataFrame, stage: Stage, catalog: IndexCatalog) -> DataFrame:
    """Candidates stay; their distinct (key, value) pairs ask each index and the yes comes back."""
    if len(stage.uses) > 1:
        for use in stage.uses:
            cols = [*_keys(use), stage.attr]
            members = _named(use, catalog.get(use.index_id).members).withColumnRenamed("__ext", stage.attr)
            yes = _requests(candidates, cols).join(members, cols, "left_semi")
            candidates = candidates.join(yes, [WORKER, *cols], "left_semi")
    return candidates.drop(MIN_I)


def balanced_extend(prefixes: DataFrame, stage: Stage, catalog: IndexCatalog, workers: int) -> DataFrame:
    """One more attribute; rows carry their worker in and out.

    Rounds are synchronised: what a round made is stored before the next asks about it, as
    every row is read twice there, to ask and to be answered.
    """
    items = materialize(balance(materialize(probe_counts(prefixes, stage, catalog), "counted"), workers), "items")
    candidates = materialize(resolve(items, stage, catalog), "candidates")
    return materialize(apply_filters(probe_intersect(candidates, stage, catalog), stage), "prefixes")


def balanced_stages(prefixes: DataFrame, stages: Sequence[Stage], catalog: IndexCatalog, *, workers: int = 8) -> DataFrame:
    if can_share(prefixes, stages, catalog):  # large relations: lists travel, not candidates
        for stage in stages:
            prefixes = share_stage(prefixes, stage, catalog, workers)
        return prefixes
    cols = prefixes.columns
    rows = prefixes.withColumn(WORKER, (F.pmod(F.xxhash64(*cols), F.lit(workers)) if cols else F.lit(0)).cast("int"))
    rows = materialize(rows, "seeds")
    for stage in stages:
        rows = balanced_extend(rows, stage, catalog, workers)
    return rows.drop(WORKER)


def balanced_join(query: JoinQuery, relations: Mapping[str, DataFrame] | IndexCatalog, *, workers: int = 8, batch: int | None = None, order: Sequence[str] | None = None, check: tuple[int, float] | None = None) -> DataFrame:
    """All matches, with even work. ``batch`` bounds proposals per worker and round; ``check`` = (input size, bound) verifies that it is large enough."""
    catalog = relations if isinstance(relations, IndexCatalog) else IndexCatalog(query.bind(relations), cut=True)
    order, stages = plan(query, order=order)
    if batch and check and batch < min_batch(workers, *check):
        raise ValueError(f"batches below {min_batch(workers, *check)} void the balance guarantee")
    prefixes = seeds(query, catalog, order)
    if not batch and not can_share(prefixes, stages, catalog):
        catalog.cut(stages)
    if batch:
        from motifjoin.operators.scheduler import batched_join

        found = batched_join(prefixes, stages, catalog, batch=batch, workers=workers, policy="deepest_all", balanced=True)
    else:
        found = balanced_stages(prefixes, stages, catalog, workers=workers)
    return found.select(*(query.order or query.attrs))


def received(query: JoinQuery, relations: Mapping[str, DataFrame], workers: int, stage_no: int = 0, how: str = "balanced") -> DataFrame:
    """``(worker, work)``: proposals that every worker makes in a stage, balanced or by the hash of the proposing key."""
    catalog = IndexCatalog(query.bind(relations))
    order, stages = plan(query)
    rows = seeds(query, catalog, order)
    cols = rows.columns
    rows = rows.withColumn(WORKER, F.pmod(F.hash(*cols), F.lit(workers)).cast("int"))
    for stage in stages[:stage_no]:
        rows = balanced_extend(rows, stage, catalog, workers)
    triples = probe_counts(rows, stages[stage_no], catalog)
    if how == "balanced":
        work = balance(triples, workers).groupBy(WORKER).agg(F.sum(F.col(END) - F.col(START) + 1).alias("work"))
    else:
        key = F.lit(None).cast("long")
        for i, use in enumerate(stages[stage_no].uses):
            key = F.when(F.col(MIN_I) == i, F.col(use.key_attrs[0])).otherwise(key)
        work = triples.withColumn(WORKER, F.pmod(F.hash(key), F.lit(workers)).cast("int")).groupBy(WORKER).agg(F.sum(MIN_C).alias("work"))
    return work.select(F.col(WORKER).alias("worker"), "work")
