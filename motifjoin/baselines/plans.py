"""Plans that the joins are compared with: binary, hypercube, exploration, decomposition, clique index, recomputation."""

from __future__ import annotations

import math
from collections.abc import Iterator, Mapping, Sequence
from itertools import permutations, product

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifjoin.baselines.serial import serial_generic_join
from motifjoin.operators.gathered import can_gather, cells_stages, changed_matches, gathered_stages, neighbourhood_cliques
from motifjoin.operators.index import IndexCatalog
from motifjoin.operators.static_join import _as_prefixes, can_store, plan, seed_atoms, static_join
from motifjoin.plans.agm import agm_bound
from motifjoin.plans.query import PATTERNS, Atom, JoinQuery, clean
from motifjoin.plans.stages import compile_stages
from motifjoin.workspace import materialize


def _filtered(rows: DataFrame, query: JoinQuery, done: set) -> DataFrame:
    for f in query.filters:
        if f not in done and {f[0], f[2]} <= set(rows.columns):
            rows = rows.filter(F.expr(f"`{f[0]}` {f[1]} `{f[2]}`"))
            done.add(f)
    return rows


def connected_orders(query: JoinQuery) -> list[tuple[int, ...]]:
    """Orders of the atoms in which each shares an attribute with those before it."""
    out = []
    for perm in permutations(range(len(query.atoms))):
        bound = set(query.atoms[perm[0]].attrs)
        for i in perm[1:]:
            if not bound & set(query.atoms[i].attrs):
                break
            bound |= set(query.atoms[i].attrs)
        else:
            out.append(perm)
    return out


def best_order(query: JoinQuery, sizes: Mapping[str, int], distinct: Mapping[tuple[str, int], int]) -> tuple[int, ...]:
    """The connected order with the least estimated sum of intermediate sizes, attributes taken as independent."""

    def cost(perm: tuple[int, ...]) -> float:
        bound: dict[str, float] = {}
        rows, total = 1.0, 0.0
        for i in perm:
            atom = query.atoms[i]
            rows *= sizes[atom.relation]
            for p, a in enumerate(atom.attrs):
                d = max(1, distinct[atom.relation, p])
                if a in bound:
                    rows /= max(bound[a], d)
                bound[a] = min(bound.get(a, d), d)
            total += rows
        return total

    return min(connected_orders(query), key=cost)


def binary_join(query: JoinQuery, relations: Mapping[str, DataFrame], order: Sequence[int] | str | None = None, decompose: Sequence[Sequence[int]] | None = None, materialized: Mapping[frozenset[int], DataFrame] | None = None) -> DataFrame:
    """One join after another, edge at a time.

    ``order``: atom numbers, or ``best`` by estimate; ``decompose``: groups of atoms that are
    joined first, each on its own; ``materialized``: results of groups of atoms to reuse.
    """
    rels = {n: clean(d) for n, d in relations.items()}
    if order == "best":
        stats = {n: d.agg(F.count(F.lit(1)).alias("n"), *[F.approx_count_distinct(c).alias(c) for c in d.columns]).first() for n, d in rels.items()}
        order = best_order(query, {n: s["n"] for n, s in stats.items()}, {(n, k): s[f"c{k}"] for n, s in stats.items() for k in range(len(rels[n].columns))})
    raw = {n: clean(d, False) for n, d in relations.items()} if can_store(query, relations) else rels
    if not materialized and (found := _pipelined(query, raw, decompose or [order if order is not None else range(len(query.atoms))])) is not None:
        return found
    done: set = set()

    def chain(atoms: Sequence[int]) -> DataFrame:
        left, out = list(atoms), None
        for group, rows in (materialized or {}).items():
            if group <= set(left):
                out, left = rows, [i for i in left if i not in group]
                break
        for i in left:
            rows = _as_prefixes(query.atoms[i].attrs, rels[query.atoms[i].relation])
            if out is None:
                out = rows
            else:
                shared = [a for a in rows.columns if a in out.columns]
                out = out.join(rows, shared) if shared else out.crossJoin(rows)
            out = _filtered(out, query, done)
        return out

    groups = decompose or [order if order is not None else range(len(query.atoms))]
    out = None
    for group in groups:
        rows = chain(list(group))
        out = rows if out is None else out.join(rows, [a for a in rows.columns if a in out.columns])
    return _filtered(out, query, done).select(*(query.order or query.attrs))


def _pipelined(query: JoinQuery, rels: Mapping[str, DataFrame], groups: Sequence[Sequence[int]], shares: Mapping[str, int] | None = None) -> DataFrame | None:
    """The same plan over large binary relations: each join's rows are made in the task that closes them, and do not move.

    Groups are joined in the task too: of a later group's rows, those that agree with none of the rows so far are dropped at once.
    ``shares``: the plan runs inside the cells of a hypercube.
    """
    parts = [tuple(query.atoms[i] for i in group) for group in groups]
    first = parts[0][0]
    lead = first.attrs[0]
    if any(len(a.attrs) != 2 or len(set(a.attrs)) != 2 for atoms in parts for a in atoms):
        return None
    if any(set(a.attrs) == set(first.attrs) for a in parts[0][1:]) or any(lead not in atoms[0].attrs for atoms in parts):
        return None
    if any(not any({f[0], f[2]} <= {x for a in atoms for x in a.attrs} for atoms in parts) for f in query.filters):
        return None
    plans = []
    for atoms in parts:
        bound = {lead}
        for atom in atoms:
            if not bound & set(atom.attrs):
                return None
            bound |= set(atom.attrs)
        attrs = tuple(dict.fromkeys([lead, *(x for a in atoms for x in a.attrs)]))
        sub = JoinQuery(query.name, atoms, tuple(f for f in query.filters if {f[0], f[2]} <= bound), attrs)
        plans.append(compile_stages(sub, attrs, 1 if plans else 2, unbound="never", seed_atoms=[] if plans else [0]))
    stages, *others = plans
    if not stages or not can_gather([s for p in plans for s in p], IndexCatalog(rels)):
        return None
    catalog = IndexCatalog(rels, cut=bool(shares) or not can_store(query, rels))
    inside = [f for f in query.filters if {f[0], f[2]} <= set(first.attrs)]
    if shares:
        return cells_stages(stages, catalog, query.order or query.attrs, shares, seed=(first.relation, "new", (0,), 1), filters=inside)
    return gathered_stages(stages, catalog, query.order or query.attrs, seed=(first.relation, "new", (0,), 1), filters=inside, first=True, groups=others)


def optimal_shares(query: JoinQuery, sizes: Mapping[str, int], workers: int) -> dict[str, int]:
    """Whole numbers per attribute, their product at most ``workers``, with the least traffic."""
    attrs = list(query.order or query.attrs)
    best, shares = (math.inf, 0.0), {a: 1 for a in attrs}
    options = [s for s in product(range(1, workers + 1), repeat=len(attrs)) if math.prod(s) <= workers] if workers ** len(attrs) <= 2_000_000 else [s for s in product([1 << k for k in range(workers.bit_length())], repeat=len(attrs)) if math.prod(s) <= workers]
    for s in options:
        share = dict(zip(attrs, s))
        cells = math.prod(s)
        load = sum(sizes[t.relation] / math.prod(share[a] for a in set(t.attrs)) for t in query.atoms)
        if (load, -cells) < best:
            best, shares = (load, -cells), share
    return shares


def hypercube_parts(query: JoinQuery, relations: Mapping[str, DataFrame], shares: Mapping[str, int], by_value: bool = False) -> list[DataFrame]:
    """Every atom's rows with the ``cell`` numbers that may need them: hashed where bound, all where free."""
    attrs = list(query.order or query.attrs)
    rels = {n: clean(d) for n, d in relations.items()}
    strides, step = {}, 1
    for a in attrs:
        strides[a] = step
        step *= shares[a]
    out = []
    for atom in query.atoms:
        rows = _as_prefixes(atom.attrs, rels[atom.relation])
        at = F.lit(0).cast("long")
        for a in dict.fromkeys(atom.attrs):
            at = at + F.pmod(F.col(a) if by_value else F.xxhash64(a), F.lit(shares[a])) * strides[a]
        free = [0]
        for a in attrs:
            if a not in atom.attrs:
                free = [x + k * strides[a] for x in free for k in range(shares[a])]
        out.append(rows.withColumn("cell", F.explode(F.array(*[at + x for x in free]))))
    return out


def hypercube_join(query: JoinQuery, relations: Mapping[str, DataFrame], shares: Mapping[str, int] | None = None, workers: int = 8, local: str = "binary") -> DataFrame:
    """One round: replicate every row to the cells that may need it, join inside cells.

    ``local="binary"`` joins cells with ordinary joins on (cell, attributes), of large binary relations
    inside a task per cell, so that only the replicated rows move; ``generic`` gives
    each cell to the serial attribute-at-a-time join.
    """
    if shares is None:
        shares = optimal_shares(query, {n: d.count() for n, d in relations.items()}, workers)
    if local == "binary" and (found := _pipelined(query, {n: clean(d) for n, d in relations.items()}, [range(len(query.atoms))], shares)) is not None:
        return found
    parts = hypercube_parts(query, relations, shares)
    attrs = list(query.order or query.attrs)
    if local == "binary":
        out, done = parts[0], set()
        for rows in parts[1:]:
            out = _filtered(out.join(rows, ["cell", *[a for a in rows.columns if a in out.columns and a != "cell"]]), query, done)
        return _filtered(out, query, done).select(*attrs)
    packed = None
    for i, rows in enumerate(parts):
        cols = [c for c in rows.columns if c != "cell"]
        one = rows.select("cell", F.lit(i).alias("atom"), F.array(*[F.col(c).cast("long") for c in cols]).alias("row"))
        packed = one if packed is None else packed.unionByName(one)
    split = JoinQuery(query.name, tuple(Atom(str(i), tuple(dict.fromkeys(a.attrs))) for i, a in enumerate(query.atoms)), query.filters, tuple(attrs))

    def cell(group: pa.Table) -> pa.Table:
        tables: dict[str, list[tuple]] = {a.relation: [] for a in split.atoms}
        for atom, row in zip(group.column("atom").to_pylist(), group.column("row").to_pylist()):
            tables[str(atom)].append(tuple(row))
        found = serial_generic_join(split, tables)
        return pa.table({a: pa.array([r[k] for r in found], pa.int64()) for k, a in enumerate(attrs)})

    return packed.groupBy("cell").applyInArrow(cell, ", ".join(f"`{a}` long" for a in attrs))


def embedding_explore(query: JoinQuery, edges: DataFrame) -> DataFrame:
    """Grow embeddings by neighbours of any one member, whatever its degree, and check edges afterwards."""
    return explore_steps(query, edges)[-1].select(*(query.order or query.attrs))


def explore_steps(query: JoinQuery, edges: DataFrame) -> list[DataFrame]:
    """Unchecked and checked embeddings of every step, the result last."""
    order = list(query.order or query.attrs)
    e = clean(edges)
    both = e.select(F.col("c0").alias("__a"), F.col("c1").alias("__b")).union(e.select("c1", "c0")).dropDuplicates()
    rows, steps, done = both.select(F.col("__a").alias(order[0])).distinct(), [], set()
    for j, attr in enumerate(order[1:], 1):
        members = F.array(*order[:j])
        grown = rows.withColumn("__a", F.explode(F.array_distinct(members))).join(both, "__a").drop("__a").withColumnRenamed("__b", attr).dropDuplicates()
        steps.append(grown)
        rows = grown
        for atom in query.atoms:
            if attr in atom.attrs and set(atom.attrs) <= set(order[: j + 1]):
                rows = rows.join(_as_prefixes(atom.attrs, e), list(dict.fromkeys(atom.attrs)), "left_semi")
        rows = _filtered(rows, query, done)
        steps.append(rows)
    return steps


def decomposed_join(query: JoinQuery, relations: Mapping[str, DataFrame], bags: Sequence[Sequence[int]] | None = None) -> DataFrame:
    """Bags of atoms by the static join, bags combined by ordinary joins; without bags, the cheapest split in two or none."""
    if bags is None:
        bags = choose_bags(query)
    out, done = None, set()
    for bag in bags:
        atoms = tuple(query.atoms[i] for i in bag)
        attrs = [a for a in (query.order or query.attrs) if any(a in t.attrs for t in atoms)]
        sub = JoinQuery(f"{query.name}_bag", atoms, tuple(f for f in query.filters if {f[0], f[2]} <= set(attrs)), tuple(attrs))
        rows = static_join(sub, relations)
        out = rows if out is None else out.join(rows, [a for a in rows.columns if a in out.columns])
    return _filtered(out, query, done).select(*(query.order or query.attrs))


def choose_bags(query: JoinQuery) -> list[list[int]]:
    """Two bags whose larger bound is below the whole query's, where such are; else one bag."""
    n = len(query.atoms)
    width = lambda bag: agm_bound(JoinQuery("bag", tuple(query.atoms[i] for i in bag)), {a.relation: 100 for a in query.atoms}).exponent
    best, found = width(range(n)), [list(range(n))]
    for mask in range(1, 1 << (n - 1)):
        a, b = [i for i in range(n) if mask >> i & 1], [i for i in range(n) if not mask >> i & 1]
        shared = {x for i in a for x in query.atoms[i].attrs} & {x for i in b for x in query.atoms[i].attrs}
        if shared and max(width(a), width(b)) < best:
            best, found = max(width(a), width(b)), [a, b]
    return found


def neighbourhoods(edges: DataFrame) -> DataFrame:
    """``(x, y, zs)``: the triangle index by first vertex, ``zs`` the vertices that x and its successor y both lead to.

    The rows of one x are the edges among its successors. A row is as long as a list of
    successors: at most the root of twice the edges where edges go by degree (``rewrites``).
    """
    tri = static_join(PATTERNS["triangle"], {"e": edges}).toDF("x", "y", "z")
    return tri.groupBy("x", "y").agg(F.array_sort(F.collect_list("z")).alias("zs"))


def clique_star_join(k: int, edges: DataFrame, compact: bool = False) -> DataFrame:
    """Cliques of ``k`` inside the neighbourhoods of their first vertices.

    A clique so far is its members and the set of those that go on: one of the set joins
    the members, and its own row of the same neighbourhood cuts the set; of large graphs that happens
    in the task that makes the neighbourhood, and no row of it moves. ``compact`` leaves the last
    member as that set (``tail``), for cliques that share all others; nothing is gathered
    beyond a list of successors.
    """
    if can_store(PATTERNS["triangle"], {"e": edges}):
        catalog = IndexCatalog(PATTERNS["triangle"].bind({"e": edges}, distinct=False))
        _, stages = plan(PATTERNS["triangle"])
        if can_gather(stages, catalog):
            return neighbourhood_cliques(stages, catalog, k, compact, ("e", "new", (0,), 1))
    index = materialize(neighbourhoods(edges), "neighbourhoods")
    out = index.toDF("a1", "a2", "tail")
    for j in range(3, k):
        grown = out.withColumn(f"a{j}", F.explode("tail"))
        inner = index.toDF("x", "y", "zs")
        met = grown.join(inner, (F.col("a1") == F.col("x")) & (F.col(f"a{j}") == F.col("y")))
        out = met.select(*(f"a{i}" for i in range(1, j + 1)), F.array_intersect("tail", "zs").alias("tail")).filter(F.size("tail") > 0)
    return out if compact else out.withColumn(f"a{k}", F.explode("tail")).drop("tail")


def recompute_diff(query: JoinQuery, old: Mapping[str, DataFrame], new: Mapping[str, DataFrame]) -> DataFrame:
    """Changes by running the whole query on both versions: matches that came (1) or went (-1)."""
    if can_store(query, old) and (found := _compared(query, old, new)) is not None:
        return found
    before, after = (static_join(query, r) for r in (old, new))
    cols = before.columns
    return after.join(before, cols, "left_anti").withColumn("w", F.lit(1)).unionByName(before.join(after, cols, "left_anti").withColumn("w", F.lit(-1)))


def _compared(query: JoinQuery, old: Mapping[str, DataFrame], new: Mapping[str, DataFrame]) -> DataFrame | None:
    """The same over large binary relations: a task makes both versions' matches of its first values and compares them, none moves."""
    versions = ("old", "new")
    catalog = IndexCatalog({(n, v): d for v, r in zip(versions, (old, new)) for n, d in query.bind(r, distinct=False).items()})
    order, _ = plan(query)
    n, fits = seed_atoms(query, order)
    if n != 2 or len(fits) != 1:
        return None
    atom = query.atoms[fits[0]]
    at = atom.attrs.index(order[0])
    sides = [(compile_stages(query, order, n, versions=[v] * len(query.atoms), seed_atoms=fits), (atom.relation, v, (at,), 1 - at)) for v in versions]
    if not sides[0][0] or not can_gather([s for stages, _ in sides for s in stages], catalog):
        return None
    return changed_matches(sides, catalog, query.order or query.attrs, [f for f in query.filters if {f[0], f[2]} <= set(order[:2])])


def one_worker_join(query: JoinQuery, relations: Mapping[str, DataFrame]) -> DataFrame:
    """All prefixes in one partition at the start: optimal in total, without balance."""
    return static_join(query, relations, parallelism=1)


def batches_of(rows: DataFrame) -> Iterator[DataFrame]:
    """A changelog's versions in order, one at a time."""
    for r in rows.select("ver").distinct().orderBy("ver").toLocalIterator():
        yield rows.filter(F.col("ver") == r["ver"])
