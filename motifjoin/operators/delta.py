"""Delta joins: the changes of a join's result from the changes of its relations.

Rule i joins the changes of atom i with the new versions of the atoms before it
and the old versions of those after it. Its order starts with the changed
atom's attributes, so its seeds are the changes, and prefixes carry their sign.
The union of the rules, summed by match, is new result minus old result.

Rules grow from the changes: as long as prefixes are few they are sent to the indices,
which are base and log of each relation and stay where they are, so that what moves
follows the changes and not the relations. Rules whose first extension is the same but
for names (symmetric atoms of one relation) compute it once.
"""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from motifjoin.operators import extend as ex
from motifjoin.operators import gathered, pairs
from motifjoin.operators.gathered import can_gather, gathered_stages
from motifjoin.operators.index import IndexCatalog
from motifjoin.operators.static_join import _as_prefixes, run_stages
from motifjoin.operators.versions import BROADCAST_ROWS, VersionedRelation, apply_delta, normalize_delta
from motifjoin.plans.query import JoinQuery, clean
from motifjoin.plans.stages import DeltaRule, Stage, compile_stages, delta_rules
from motifjoin.workspace import materialize, open_folder


#: Share of a relation up to which changes are few.
SMALL_SHARE = 0.02


def rule_changes(query: JoinQuery, rule: DeltaRule, catalog: IndexCatalog, changes: Mapping[str, DataFrame], *, counts: str = "chain", engine: str = "pipelined", shared: dict | None = None, few: int = BROADCAST_ROWS, **options) -> DataFrame:
    """Signed matches of one rule: the query's attributes and ``w``.

    ``engine``: ``pipelined`` (small prefixes go to the indices, ``few`` at most), ``joined`` (one
    plan of ordinary joins; of large relations, lists gathered by ranges) or ``balanced``. ``shared`` keeps first extensions for other rules.
    """
    atom = query.atoms[rule.lead]
    delta = changes[atom.relation]
    cols = [f"c{k}" for k in range(len(atom.attrs))]
    names = list(dict.fromkeys(atom.attrs))
    signed = delta.toDF(*cols, "w")
    rows = None
    for sign in ((1, -1) if len(names) < len(atom.attrs) else (None,)):
        part = signed if sign is None else signed.filter(F.col("w") == sign)
        one = part.select(*[F.col(cols[list(atom.attrs).index(a)]).alias(a) for a in names], "w") if sign is None else _as_prefixes(atom.attrs, part).withColumn("w", F.lit(sign))
        rows = one if rows is None else rows.unionByName(one)
    head = set(names)
    inside = [i for i, a in enumerate(query.atoms) if i != rule.lead and set(a.attrs) <= head]
    for i in inside:  # other atoms over the same attributes check the seeds
        other = _as_prefixes(query.atoms[i].attrs, catalog.relation(query.atoms[i].relation, rule.versions[i]))
        rows = rows.join(other, other.columns, "left_semi")
    for left, op, right in query.filters:
        if {left, right} <= head:
            rows = rows.filter(F.expr(f"`{left}` {op} `{right}`"))
    stages = compile_stages(query, rule.order, len(names), versions=rule.versions, seed_atoms=[rule.lead, *inside])
    if engine == "balanced":
        from motifjoin.operators.balanced import balanced_stages

        return balanced_stages(rows, stages, catalog, **options).select(*(query.order or query.attrs), "w")
    if engine == "pipelined" and counts == "chain" and not options:
        plain = len(names) == len(atom.attrs) and not inside and not (stages and stages[0].filters) and not any({f[0], f[2]} <= head for f in query.filters)
        rows = grow(rows, stages, catalog, names if plain else None, atom.relation, {} if shared is None else shared, few)
    elif engine == "joined" and counts == "chain" and not options and can_gather(stages, catalog):
        rows = gathered_stages(stages, catalog, query.order or query.attrs, prefixes=rows)
    else:
        rows = run_stages(rows, stages, catalog, counts=counts, **options)
    return rows.select(*(query.order or query.attrs), "w")


def grow(rows: DataFrame, stages: list[Stage], catalog: IndexCatalog, names: list[str] | None, relation: str, shared: dict, few: int) -> DataFrame:
    """Run stages from changes; the first one is looked up in ``shared`` by what it reads, with ``names`` as positions."""
    for k, stage in enumerate(stages):
        key = None
        if k == 0 and names:
            key = (relation, tuple(sorted((u.index_id, tuple(names.index(a) for a in u.key_attrs)) for u in stage.uses)))
            if key in shared:
                rows = shared[key].toDF(*names, "w", stage.attr)
                continue
        rows = materialize(rows, "prefixes")
        rows = ex.extend_few(rows, stage, catalog, few) if rows.count() <= few else ex.extend(rows, stage, catalog)
        if key:
            shared[key] = materialize(rows.select(*names, "w", stage.attr), "first")
            rows = shared[key]
    return rows


def delta_join(query: JoinQuery, old: Mapping[str, DataFrame], changes: Mapping[str, DataFrame], *, net: bool = True, normalized: bool = False, share: bool = True, **options) -> DataFrame:
    """Signed changes of the result for changes (relation columns and ``w``) of old relations.

    ``net=False`` returns a ``rule`` column too, and the rules' rows as they are.
    ``share``: old relations and the normalised changes, which all rules read, are computed once.
    ``engine``: as in ``rule_changes``; by default ``pipelined`` for changes of up to a share of
    ``SMALL_SHARE`` of the relations, beyond which reading whole relations once in one plan costs less.
    """
    if net and share and options in ({}, {"engine": "joined"}) and (found := _stored_changes(query, old, changes, bool(options))) is not None:
        return found
    olds = {n: materialize(clean(df), "old") if share else clean(df) for n, df in old.items() if n in {a.relation for a in query.atoms}}
    deltas, news, small = {}, {}, True
    for name, df in olds.items():
        given = changes.get(name)
        if given is None:
            deltas[name], news[name] = df.limit(0).withColumn("w", F.lit(1)), df
            continue
        named = given.toDF(*df.columns, "w")
        deltas[name] = named if normalized else normalize_delta(df, named)
        if share:
            deltas[name] = materialize(deltas[name], "delta")
        n = deltas[name].count() if share else None
        small = small and share and n <= SMALL_SHARE * df.count()
        news[name] = apply_delta(df, deltas[name], n)
    if share and not small:
        news = {n: materialize(df, "new") if n in changes else df for n, df in news.items()}
    catalog = IndexCatalog({(n, "old"): d for n, d in olds.items()} | {(n, "new"): d for n, d in news.items()})
    rules = [r for r in delta_rules(query) if query.atoms[r.lead].relation in changes]
    first: dict = {}
    options.setdefault("engine", "pipelined" if small else "joined")
    if net and share and options in ({"engine": "joined"}, {"engine": "balanced"}) and _large(query, olds):
        # what stays is in both versions, so that each match that came or went is made once, and none is summed
        kept = {n: materialize(apply_delta(d, materialize(deltas[n].filter("w < 0"), "deleted")), "kept") if n in changes else d for n, d in olds.items()}
        catalog.relations |= {(n, "kept"): d for n, d in kept.items()}
        made = lambda sign: [rule_changes(query, r, catalog, {n: d.filter(F.col("w") == sign) for n, d in deltas.items()}, **options) for rule in rules for s, r in _net_rules(rule) if s == sign]
        came = made(1)
        if options["engine"] == "balanced":  # its rows are stored by now, and deletions look nothing up in the new version
            gathered.drop_packed(catalog, "new")
        return reduce(DataFrame.unionByName, came + made(-1))
    parts = [rule_changes(query, r, catalog, deltas, shared=first, **options).withColumn("rule", F.lit(r.lead)) for r in rules]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return net_changes(out.drop("rule")) if net else out


def _stored_changes(query: JoinQuery, old: Mapping[str, DataFrame], changes: Mapping[str, DataFrame], asked: bool) -> DataFrame | None:
    """Large changes of large binary relations: each relation and its changes are stored once, with what became of every row; versions are read from that."""
    names = {a.relation for a in query.atoms}
    if len(query.attrs) < 3 or any(len(set(a.attrs)) != 2 or len(a.attrs) != 2 for a in query.atoms) or not names <= set(old):
        return None
    olds = {n: clean(old[n], False) for n in names}
    if any([f.dataType for f in df.schema.fields] != [T.LongType()] * 2 for df in olds.values()) or open_folder(next(iter(olds.values())).sparkSession) is None:
        return None
    sizes, given = {n: d.count() for n, d in olds.items()}, {n: changes[n].toDF("c0", "c1", "w") for n in names if n in changes}
    if not given or max(sizes.values()) <= gathered.GATHER_ROWS or not asked and all(d.count() <= SMALL_SHARE * sizes[n] for n, d in given.items()):
        return None
    relations, deltas = {}, {}
    for n, df in olds.items():
        if n not in given:
            relations |= {(n, v): df for v in ("old", "new", "kept")}
            continue
        signed = given[n].select(F.col("c0").cast("long"), F.col("c1").cast("long"), "w").na.drop(subset=["c0", "c1"])
        net = signed.groupBy("c0", "c1").agg(F.sum("w").alias("w")).filter("w <> 0")
        rows = materialize(pairs.states(df, net, max(1, -(-sizes[n] // 1_000_000))), "states", "zstd")
        df.sparkSession.sparkContext._jvm.System.gc()  # so that Spark lets go of the shuffle
        relations |= {(n, v): rows.filter(test).select("c0", "c1") for v, test in (("old", "s <= 0"), ("new", "s >= 0"), ("kept", "s = 0"))}
        deltas[n] = rows.filter("s <> 0").withColumnRenamed("s", "w")
    catalog = IndexCatalog(relations)
    made = lambda sign, rule: rule_changes(query, rule, catalog, {n: d.filter(F.col("w") == sign) for n, d in deltas.items()}, engine="joined")
    parts = [made(sign, one) for rule in delta_rules(query) if query.atoms[rule.lead].relation in deltas for sign, one in _net_rules(rule)]
    return reduce(DataFrame.unionByName, parts)


def _large(query: JoinQuery, olds: Mapping[str, DataFrame]) -> bool:
    """Whether the rules will gather lists."""
    plain = all(len(set(a.attrs)) == len(a.attrs) == 2 for a in query.atoms)
    return plain and len(query.attrs) > 2 and any(d.count() > gathered.GATHER_ROWS for d in olds.values())


def _net_rules(rule: DeltaRule) -> list[tuple[int, DeltaRule]]:
    """The rule for insertions and for deletions, without matches that another rule takes back.

    A match came if all its rows are new and some inserted: it is made by the rule of the last one, with
    what was kept after it. A match went if some of its old rows are deleted: by the rule of the first one.
    """
    came = tuple("kept" if v == "old" else v for v in rule.versions)
    went = tuple("kept" if v == "new" else v for v in rule.versions)
    return [(1, replace(rule, versions=came)), (-1, replace(rule, versions=went))]


def net_changes(rows: DataFrame) -> DataFrame:
    """Signed matches summed: one row with w = 1 or -1 per match that came or went."""
    cols = [c for c in rows.columns if c != "w"]
    return rows.groupBy(*cols).agg(F.sum("w").cast("int").alias("w")).filter("w <> 0")


class DeltaEngine:
    """Keeps a query's result up to date over versioned relations.

    ``apply`` takes a batch of changes, returns the signed changes of the result, and
    commits the version; the result itself is never computed in full.
    """

    def __init__(self, query: JoinQuery, stores: Mapping[str, VersionedRelation], engine: str | None = None, **options) -> None:
        self.query, self.stores, self.engine, self.options = query, dict(stores), engine, options

    def preload(self, relations: Mapping[str, DataFrame]) -> None:
        """Start from these relations; no initial answer is computed."""
        for name, df in relations.items():
            self.stores[name].preload(df)

    def stage(self, version: int, changes: Mapping[str, DataFrame]) -> DataFrame:
        """Stage a version in every store and return its changes of the result, uncommitted.

        Stores without changes get an empty log, so that all have one version after the commit. A
        store that has the version already, from a commit that broke off, keeps its changes.
        """
        deltas = {}
        for name, store in self.stores.items():
            if store.version < version:
                given = changes.get(name)
                cols = store.as_of(store.version).columns
                store.stage(version, store.as_of(store.version).limit(0).withColumn("w", F.lit(1)) if given is None else given.toDF(*cols, "w"))
            if (log := store.changes(version)) is None:
                raise RuntimeError(f"the changes of version {version} of {name} are compacted away")
            deltas[name] = log
        catalog = IndexCatalog({}, views={(n, side): (s, v) for n, s in self.stores.items() for side, v in (("old", version - 1), ("new", version))})
        self.shared = {}
        rules = [r for r in delta_rules(self.query) if self.query.atoms[r.lead].relation in changes]
        small = all(log.count() <= SMALL_SHARE * self.stores[n].rows for n, log in deltas.items())
        engine = self.engine or ("pipelined" if small else "joined")
        parts = [rule_changes(self.query, r, catalog, deltas, shared=self.shared, engine=engine, **self.options) for r in rules]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return materialize(net_changes(out), "changes")

    def commit(self, version: int) -> None:
        """Commit the version in every store, then fold long logs: a store that is behind is found by its version."""
        for s in self.stores.values():
            s.commit(version, compact=False)
        for s in self.stores.values():
            s.compact_if_long()

    def apply(self, version: int, changes: Mapping[str, DataFrame]) -> DataFrame:
        """Changes of the result for one batch; a version that is committed everywhere already gives none."""
        if all(s.version >= version for s in self.stores.values()):
            return self.stage_empty()
        out = self.stage(version, changes)
        self.commit(version)
        return out

    def stage_empty(self) -> DataFrame:
        some = next(iter(self.stores.values()))
        attrs = self.query.order or self.query.attrs
        return some.spark.createDataFrame([], ", ".join(f"`{a}` long" for a in attrs) + ", w int")


def delta_bootstrap(query: JoinQuery, edges: DataFrame, batches: int = 4, name: str = "e") -> DataFrame:
    """The full result by loading every row as an insertion into an empty relation, in batches."""
    store = VersionedRelation(edges.sparkSession)
    store.preload(edges.limit(0))
    engine = DeltaEngine(query, {name: store})
    out = None
    for k in range(batches):
        part = edges.filter(F.pmod(F.xxhash64(*edges.columns), F.lit(batches)) == k).withColumn("w", F.lit(1))
        got = engine.apply(k + 1, {name: part})
        out = got if out is None else out.unionByName(got)
    return net_changes(out).filter("w > 0").drop("w")


__all__ = ["DeltaEngine", "delta_bootstrap", "delta_join", "ex", "grow", "net_changes", "rule_changes"]
