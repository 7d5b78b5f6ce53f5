"""The static dataflow join: seeds, then one extension per remaining attribute."""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifjoin.operators import extend as ex
from motifjoin.operators.gathered import can_gather, gathered_stages
from motifjoin.operators.index import IndexCatalog
from motifjoin.plans.ordering import attribute_order
from motifjoin.plans.query import JoinQuery
from motifjoin.plans.stages import Stage, compile_stages
from motifjoin.workspace import materialize, new_path, open_folder


def seed_atoms(query: JoinQuery, order: Sequence[str]) -> tuple[int, list[int]]:
    """``(attributes, atoms)``: the widest atom over a head of the order, then all others inside that head."""
    for n in range(max(len(set(a.attrs)) for a in query.atoms), 0, -1):
        head = set(order[:n])
        exact = [i for i, a in enumerate(query.atoms) if set(a.attrs) == head]
        if exact:
            return n, exact + [i for i, a in enumerate(query.atoms) if set(a.attrs) < head]
    return 0, []


def seeds(query: JoinQuery, catalog: IndexCatalog, order: Sequence[str], seed: str = "edge") -> DataFrame:
    """Prefixes to start from: the matches of the atoms over the first attributes, or the empty tuple."""
    n, fits = seed_atoms(query, order) if seed == "edge" else (0, [])
    if not fits:
        return catalog.relation(query.atoms[0].relation).sparkSession.range(1).select()
    out = None
    for i in fits:
        rows = _as_prefixes(query.atoms[i].attrs, catalog.relation(query.atoms[i].relation))
        out = rows if out is None else out.join(rows, rows.columns, "left_semi")
    out = out.select(*order[:n])
    for left, op, right in query.filters:
        if {left, right} <= set(order[:n]):
            out = out.filter(F.expr(f"`{left}` {op} `{right}`"))
    return out


def _as_prefixes(attrs: Sequence[str], rows: DataFrame) -> DataFrame:
    """A relation's rows as prefixes; columns of a repeated attribute must agree."""
    for k, a in enumerate(attrs):
        if attrs.index(a) < k:
            rows = rows.filter(F.col(f"c{attrs.index(a)}") == F.col(f"c{k}"))
    return rows.select(*[F.col(f"c{list(attrs).index(a)}").alias(a) for a in dict.fromkeys(attrs)])


def plan(query: JoinQuery, *, order: Sequence[str] | None = None, seed: str = "edge", unbound: str = "auto") -> tuple[tuple[str, ...], list[Stage]]:
    """The order and the stages that a join will run, for explanation and meters."""
    order = tuple(order or attribute_order(query, "edge_seed" if seed == "edge" and any(len(set(a.attrs)) > 1 for a in query.atoms) else "given"))
    start, applied = seed_atoms(query, order) if seed == "edge" else (0, [])
    return order, compile_stages(query, order, start, unbound=unbound, seed_atoms=applied)


def run_stages(prefixes: DataFrame, stages: Sequence[Stage], catalog: IndexCatalog, *, counts: str = "chain", **options) -> DataFrame:
    carried = counts == "carried"
    if carried:
        for a in [c for c in prefixes.columns if stages and c in stages[0].bound]:
            prefixes = ex.carry_counts(prefixes, a, list(stages), catalog)
    for k, stage in enumerate(stages):
        prefixes = ex.extend(prefixes, stage, catalog, counts=counts, **options)
        if carried:
            prefixes = ex.carry_counts(prefixes, stage.attr, list(stages[k + 1 :]), catalog)
    return prefixes.drop(*[c for c in prefixes.columns if c.startswith("c:")]) if carried else prefixes


def static_join(query: JoinQuery, relations: Mapping[str, DataFrame] | IndexCatalog, *, order: Sequence[str] | None = None, seed: str = "edge", mode: str = "pipelined", layout: str = "flat", counts: str = "chain", propose: str = "auto", unbound: str = "auto", output: str = "tuples", batch: int | None = None, workers: int = 8, seed_batch: int | None = None, broadcast_index: bool = False, parallelism: int | None = None, cut: bool = True) -> DataFrame:
    """All matches of ``query``.

    ``output``: ``tuples`` (columns in the order of the query), ``count`` (one row ``n``,
    the last attribute never enumerated beyond its stage), or ``lists`` (the last attribute as
    an array). ``batch`` bounds live proposals per worker by the batched scheduler;
    ``seed_batch`` feeds seeds in chunks of about that many and drains each.
    ``broadcast_index`` replicates the indices, where Spark's own threshold allows;
    ``parallelism=1`` sends all to one worker. ``cut`` stores the deduplicated relations once,
    so that no index derives them again. Of large binary relations the plain join gathers lists by
    ranges of the first attribute (``gathered_stages``), so that no proposal moves.
    """
    given = isinstance(relations, IndexCatalog)
    order, stages = plan(query, order=order, seed=seed, unbound=unbound)
    usual = (seed, mode, layout, counts, propose, batch, seed_batch, broadcast_index) == ("edge", "pipelined", "flat", "chain", "auto", None, None, False) and output in ("tuples", "count")
    if usual and not given and cut and can_store(query, relations) and can_gather(stages, raw := IndexCatalog(query.bind(relations, distinct=False))):
        return _gathered(query, raw, order, stages, output == "count", parallelism)
    catalog = relations if given else IndexCatalog(query.bind(relations), cut=cut)
    if usual and not given and cut and not can_store(query, relations) and can_gather(stages, catalog):
        return _gathered(query, catalog, order, stages, output == "count", parallelism)
    prefixes = seeds(query, catalog, order, seed)
    if parallelism:
        prefixes = prefixes.coalesce(parallelism)
    options = {"mode": mode, "layout": layout, "counts": counts, "propose_how": propose, "hint": "broadcast" if broadcast_index and _small(catalog) else None}
    if batch:
        from motifjoin.operators.scheduler import batched_join

        found = batched_join(prefixes, stages, catalog, batch=batch, workers=workers)
    elif seed_batch:
        found = _chunked(prefixes, stages, catalog, seed_batch, options)
    elif output == "lists" and stages:
        *init, last = stages
        rows = run_stages(prefixes, init, catalog, **options)
        triples = ex.init_triples(rows)
        triples = ex.minimise_counts(triples, last, catalog) if len(last.uses) > 1 else triples
        return ex.intersect_lists(ex.propose_lists(triples, last, catalog), last, catalog).withColumnRenamed("__exts", last.attr + "s")
    else:
        found = run_stages(prefixes, stages, catalog, **options)
    if output == "count":
        return found.agg(F.count(F.lit(1)).alias("n"))
    return found.select(*(query.order or query.attrs))


def can_store(query: JoinQuery, relations: Mapping[str, DataFrame]) -> bool:
    """Whether indices can be stored as files that tasks open, for which duplicates are dropped where lists are sorted."""
    return open_folder(relations[query.atoms[0].relation].sparkSession) is not None if query.atoms[0].relation in relations else False


def _gathered(query: JoinQuery, catalog: IndexCatalog, order: Sequence[str], stages: Sequence[Stage], count: bool, parallelism: int | None) -> DataFrame:
    """The stages by ``gathered_stages``, over the seeds' index itself where one atom alone gives the seeds."""
    n, fits = seed_atoms(query, order)
    attrs = query.order or query.attrs
    if n == 2 and len(fits) == 1:
        atom = query.atoms[fits[0]]
        at = atom.attrs.index(order[0])
        inside = [f for f in query.filters if {f[0], f[2]} <= set(order[:2])]
        return gathered_stages(stages, catalog, attrs, seed=(atom.relation, "new", (at,), 1 - at), filters=inside, count=count, parallelism=parallelism)
    return gathered_stages(stages, catalog, attrs, prefixes=materialize(seeds(query, catalog, order).dropDuplicates(), "seeds"), count=count, parallelism=parallelism)


#: Rows up to which indices may be replicated to every worker.
BROADCAST_ROWS = 500_000


def _small(catalog: IndexCatalog) -> bool:
    """Whether every relation is within the bound for replication; checked by counting at most that many rows."""
    return all(df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS for df in catalog.relations.values())


def _chunked(prefixes: DataFrame, stages: Sequence[Stage], catalog: IndexCatalog, seed_batch: int, options: dict) -> DataFrame:
    """Seeds in hashed chunks, each drained to storage before the next one starts."""
    held = materialize(prefixes, "seeds")
    chunks = max(1, -(-held.count() // seed_batch))
    path = new_path(held.sparkSession, "matches")
    for k in range(chunks):
        mine = held.filter(F.pmod(F.xxhash64(*held.columns), F.lit(chunks)) == k) if held.columns else held
        run_stages(mine, stages, catalog, **options).write.parquet(f"{path}/chunk={k}")
    return held.sparkSession.read.parquet(path).drop("chunk")


def explain_match(query: JoinQuery, relations: Mapping[str, DataFrame], **options) -> str:
    """Order, stages and the physical plan of a join."""
    from motifjoin.plans.stages import describe

    order, stages = plan(query, **{k: v for k, v in options.items() if k in ("order", "seed", "unbound")})
    df = static_join(query, relations, **options)
    text = df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    return f"order: {', '.join(order)}\n{describe(stages)}\n{text}"


def spark_of(relations: Mapping[str, DataFrame]) -> SparkSession:
    return next(iter(relations.values())).sparkSession
