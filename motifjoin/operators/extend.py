"""The extension primitive: bind one more attribute in every prefix.

Per prefix the index with the fewest candidates proposes, all others filter:
count minimisation joins each index's counts; one join with the proposing
indices enumerates, and is the only step that makes rows; left-semi joins drop
candidates that any other index lacks. Rows carry whatever further columns they
came with (signs of changes, worker numbers).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifjoin.operators.index import IndexCatalog
from motifjoin.plans.stages import AtomUse, Stage
from motifjoin.workspace import materialize

_MAX = 9223372036854775807
MIN_C, MIN_I = "__min_c", "__min_i"


def _on(use: AtomUse, df: DataFrame) -> DataFrame:
    """An index's frame with its key columns named by the attributes bound to them."""
    for i, attr in enumerate(dict.fromkeys(use.key_attrs)):
        positions = [j for j, a in enumerate(use.key_attrs) if a == attr]
        for j in positions[1:]:
            df = df.filter(F.col(f"__k{positions[0]}") == F.col(f"__k{j}")).drop(f"__k{j}")
        df = df.withColumnRenamed(f"__k{positions[0]}", attr)
    return df


def _keys(use: AtomUse) -> list[str]:
    return list(dict.fromkeys(use.key_attrs))


def _hinted(df: DataFrame, hint: str | None) -> DataFrame:
    return df.hint(hint) if hint else df


def _members(use: AtomUse, stage: Stage, catalog: IndexCatalog) -> DataFrame:
    rows = _on(use, catalog.get(use.index_id).members)
    return rows.withColumnRenamed("__ext", stage.attr)


def init_triples(prefixes: DataFrame) -> DataFrame:
    """Every prefix with an infinite smallest count and no proposer."""
    return prefixes.withColumn(MIN_C, F.lit(_MAX)).withColumn(MIN_I, F.lit(None).cast("int"))


def minimise_counts(triples: DataFrame, stage: Stage, catalog: IndexCatalog, how: str = "chain", hint: str | None = None) -> DataFrame:
    """The smallest count and its index per prefix; prefixes that an index lacks go.

    ``chain`` updates count and proposer index by index; ``fused`` joins all counts and
    takes the least (count, index) once; ``carried`` uses counts that the rows carry as
    ``c:attribute:index`` columns (see ``carry_counts``) and joins nothing.
    """
    if how == "fused" or how == "carried":
        names = [f"__c{i}" for i in range(len(stage.uses))]
        for i, use in enumerate(stage.uses):
            if how == "carried":
                triples = triples.withColumn(names[i], F.col(carried_name(use)))
            else:
                triples = _with_count(triples, use, catalog, names[i], hint)
        best = F.least(*[F.struct(F.col(c).alias("c"), F.lit(i).alias("i")) for i, c in enumerate(names)]) if len(names) > 1 else F.struct(F.col(names[0]).alias("c"), F.lit(0).alias("i"))
        if how == "carried":
            triples = triples.na.drop(subset=names)
        return triples.withColumn("__b", best).withColumn(MIN_C, F.col("__b.c")).withColumn(MIN_I, F.col("__b.i")).drop("__b", *names)
    for i, use in enumerate(stage.uses):
        triples = _with_count(triples, use, catalog, "__c", hint)
        smaller = F.col("__c") < F.col(MIN_C)
        triples = triples.withColumn(MIN_I, F.when(smaller, F.lit(i)).otherwise(F.col(MIN_I))).withColumn(MIN_C, F.least(MIN_C, "__c")).drop("__c")
    return triples


def _with_count(rows: DataFrame, use: AtomUse, catalog: IndexCatalog, name: str, hint: str | None) -> DataFrame:
    counts = _on(use, catalog.get(use.index_id).counts).withColumnRenamed("__cnt", name)
    if not use.key_attrs:
        return rows.crossJoin(F.broadcast(counts.filter(F.col(name) > 0)))  # one row
    return rows.join(_hinted(counts, hint), _keys(use))


def carried_name(use: AtomUse) -> str:
    return f"c:{use.key_attrs[0]}:{use.relation}_{use.version}_{use.key_pos[0]}_{use.ext_pos}"


def carry_counts(rows: DataFrame, attr: str, stages: list[Stage], catalog: IndexCatalog) -> DataFrame:
    """Attach, when ``attr`` is bound, every count that later stages look up by it alone."""
    for use in {carried_name(u): u for s in stages for u in s.uses if u.key_attrs == (attr,)}.values():
        counts = _on(use, catalog.get(use.index_id).counts).withColumnRenamed("__cnt", carried_name(use))
        rows = rows.join(counts, [attr], "left")
    return rows


def propose(triples: DataFrame, stage: Stage, catalog: IndexCatalog, how: str = "auto", hint: str | None = None, few: str | None = None) -> DataFrame:
    """Candidates from the smallest set of each prefix.

    ``tagged``: one join of all prefixes with all proposing indices together, on the
    proposer's number and key, composite keys as one struct; ``branches``: a filter,
    a join and a union branch per index; ``auto``: the first. ``few`` is a hint for the prefixes.
    """
    uses = stage.uses
    if len(uses) == 1:
        return _enumerate(_hinted(triples.drop(MIN_C, MIN_I), few), uses[0], stage, catalog, hint).withColumn(MIN_I, F.lit(0))
    if how == "branches" or any(not _keys(u) for u in uses):
        parts = [_enumerate(_hinted(triples.filter(F.col(MIN_I) == i).drop(MIN_C), few), u, stage, catalog, hint) for i, u in enumerate(uses)]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out
    # uses of one index share its rows: number the distinct indices; keys of fewer columns are filled up with nulls
    ids = list(dict.fromkeys((u.index_id, _repeats(u)) for u in uses))
    width = max(len(_keys(u)) for u in uses)
    fill = [F.lit(None)]
    number = F.lit(None).cast("int")
    keys = fill * width
    for i, u in enumerate(uses):
        mine = [F.col(a) for a in _keys(u)] + fill * width
        number = F.when(F.col(MIN_I) == i, F.lit(ids.index((u.index_id, _repeats(u))))).otherwise(number)
        keys = [F.when(F.col(MIN_I) == i, m).otherwise(k) for m, k in zip(mine, keys)]
    names = [f"__key{k}" for k in range(width)]
    frames = []
    for n, (index_id, _) in enumerate(ids):
        use = next(u for u in uses if (u.index_id, _repeats(u)) == ids[n])
        rows = _members(use, stage, catalog)
        cols = ([F.col(a) for a in _keys(use)] + fill * width)[:width]
        frames.append(rows.select(F.lit(n).alias("__n"), *(c.alias(k) for c, k in zip(cols, names)), F.col(stage.attr)))
    rows = frames[0]
    for f in frames[1:]:
        rows = rows.unionByName(f)
    tagged = triples.drop(MIN_C).withColumn("__n", number).withColumns(dict(zip(names, keys)))
    rows = rows.toDF("__rn", *(f"__r{k}" for k in names), stage.attr)
    same = F.col("__n") == F.col("__rn")
    for k, name in enumerate(names):  # a key column that an index lacks is null on both sides
        same = same & (F.col(name) == F.col(f"__r{name}") if k == 0 else F.col(name).eqNullSafe(F.col(f"__r{name}")))
    return _hinted(tagged, few).join(_hinted(rows, hint), same).drop("__n", "__rn", *names, *(f"__r{k}" for k in names))


def _repeats(use: AtomUse) -> tuple[int, ...]:
    """Where the key's attributes repeat: uses of one index differ if that differs."""
    return tuple(use.key_attrs.index(a) for a in use.key_attrs)


def _enumerate(rows: DataFrame, use: AtomUse, stage: Stage, catalog: IndexCatalog, hint: str | None) -> DataFrame:
    members = _members(use, stage, catalog)
    return rows.join(_hinted(members, hint), _keys(use)) if use.key_attrs else rows.crossJoin(members)


def intersect(candidates: DataFrame, stage: Stage, catalog: IndexCatalog, hint: str | None = None) -> DataFrame:
    """Candidates that every index holds."""
    if len(stage.uses) > 1:
        for use in stage.uses:
            candidates = candidates.join(_hinted(_members(use, stage, catalog), hint), [*_keys(use), stage.attr], "left_semi")
    return candidates.drop(MIN_I)


def extend_few(prefixes: DataFrame, stage: Stage, catalog: IndexCatalog, most: int) -> DataFrame:
    """``extend`` for stored prefixes that are few: up to ``most`` rows go to the indices, which stay where they are.

    Counts are looked up for the prefixes' distinct keys; candidates are stored and counted, and
    sent to the other indices if they are few too, else joined as usual.
    """
    triples = init_triples(prefixes)
    if len(stage.uses) > 1:
        for i, use in enumerate(stage.uses):
            if not use.key_attrs:
                triples = _with_count(triples, use, catalog, "__c", None)
            else:
                index, keys = catalog.get(use.index_id), prefixes.select(*(F.col(a).alias(k) for a, k in zip(use.key_attrs, (f"__k{j}" for j in range(len(use.key_attrs)))))).distinct()
                triples = triples.join(_on(use, index.counts_of(F.broadcast(keys))).withColumnRenamed("__cnt", "__c"), _keys(use))
            smaller = F.col("__c") < F.col(MIN_C)
            triples = triples.withColumn(MIN_I, F.when(smaller, F.lit(i)).otherwise(F.col(MIN_I))).withColumn(MIN_C, F.least(MIN_C, "__c")).drop("__c")
    found = materialize(propose(triples, stage, catalog, few="broadcast"), "candidates")
    if len(stage.uses) > 1 and found.count() <= most:
        for use in stage.uses:  # members are distinct, so an inner join keeps each candidate once
            found = F.broadcast(found).join(_members(use, stage, catalog), [*_keys(use), stage.attr])
        return apply_filters(found.drop(MIN_I), stage)
    return apply_filters(intersect(found, stage, catalog), stage)


def apply_filters(rows: DataFrame, stage: Stage) -> DataFrame:
    for left, op, right in stage.filters:
        rows = rows.filter(F.expr(f"`{left}` {op} `{right}`"))
    return rows


def propose_lists(triples: DataFrame, stage: Stage, catalog: IndexCatalog) -> DataFrame:
    """Compact proposals: an ``exts`` array per prefix and chunk of its smallest set."""
    parts = []
    for i, use in enumerate(stage.uses):
        lists = _on(use, catalog.get(use.index_id).lists)
        mine = triples.filter(F.col(MIN_I) == i) if len(stage.uses) > 1 else triples.withColumn(MIN_I, F.lit(0))
        parts.append(mine.drop(MIN_C).join(lists, _keys(use)) if use.key_attrs else mine.drop(MIN_C).crossJoin(lists))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.drop("__chunk")


def intersect_lists(rows: DataFrame, stage: Stage, catalog: IndexCatalog, op: Callable | None = None) -> DataFrame:
    """Cut ``exts`` down to what every index holds: array against array, chunk by chunk."""
    meet = op or F.array_intersect
    prefix = [c for c in rows.columns if c not in ("__exts", MIN_I)]
    if len(stage.uses) > 1:
        for use in stage.uses:
            lists = _on(use, catalog.get(use.index_id).lists).withColumnRenamed("__exts", "__o").drop("__chunk")
            joined = rows.join(lists, _keys(use)) if use.key_attrs else rows.crossJoin(lists)
            rows = joined.withColumn("__exts", meet(F.col("__exts"), F.col("__o"))).drop("__o").filter(F.size("__exts") > 0)
    return rows.groupBy(*prefix).agg(F.array_sort(F.flatten(F.collect_list("__exts"))).alias("__exts")) if prefix else rows.agg(F.array_sort(F.flatten(F.collect_list("__exts"))).alias("__exts"))


def flatten(rows: DataFrame, stage: Stage) -> DataFrame:
    """Arrays of candidates to rows."""
    return rows.withColumn(stage.attr, F.explode("__exts")).drop("__exts")


def extend(prefixes: DataFrame, stage: Stage, catalog: IndexCatalog, *, mode: str = "pipelined", layout: str = "flat", counts: str = "chain", propose_how: str = "auto", hint: str | None = None) -> DataFrame:
    """Prefixes over ``stage.bound`` to prefixes with ``stage.attr`` bound too.

    ``mode="sync"`` stores the outcome of each step before the next one starts;
    ``pipelined`` leaves one plan to Catalyst.
    """
    step = (lambda df: materialize(df, "step")) if mode == "sync" else (lambda df: df)
    triples = init_triples(prefixes)
    if len(stage.uses) > 1:
        triples = step(minimise_counts(triples, stage, catalog, counts, hint))
    if layout == "list":
        found = flatten(intersect_lists(step(propose_lists(triples, stage, catalog)), stage, catalog), stage)
    else:
        found = intersect(step(propose(triples, stage, catalog, propose_how, hint)), stage, catalog, hint)
    return step(apply_filters(found, stage))
