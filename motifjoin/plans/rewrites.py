"""Rewrites: symmetry breaking, degree order, triangle reuse, factorisation."""

from __future__ import annotations

from dataclasses import dataclass, replace
from itertools import combinations, permutations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from motifjoin.operators.static_join import static_join
from motifjoin.plans.query import PATTERNS, Atom, JoinQuery


def automorphisms(query: JoinQuery, directed: bool = False) -> list[dict[str, str]]:
    """Renamings of the attributes that keep the pattern's edges."""
    edge = (lambda a, b: (a, b)) if directed else (lambda a, b: frozenset((a, b)))
    edges = {edge(*t.attrs) for t in query.atoms}
    attrs = query.order or query.attrs
    out = []
    for perm in permutations(attrs):
        to = dict(zip(attrs, perm))
        if {edge(to[t.attrs[0]], to[t.attrs[1]]) for t in query.atoms} == edges:
            out.append(to)
    return out


def break_symmetry(query: JoinQuery) -> tuple[tuple[str, str, str], ...]:
    """Filters that leave one of each set of undirected matches that are renamings of each other.

    The first attribute that the group moves is made the least of its orbit; the rest of
    the group, which keeps it in place, is broken in the same way.
    """
    group, filters = automorphisms(query), []
    for a in query.order or query.attrs:
        orbit = sorted({g[a] for g in group} - {a})
        filters += [(a, "<", b) for b in orbit]
        group = [g for g in group if g[a] == a]
    return tuple(filters)


def undirected(query: JoinQuery) -> JoinQuery:
    """The pattern for a symmetric edge relation: injective, each instance once."""
    kept = break_symmetry(query)
    ordered = {frozenset((a, b)) for a, _, b in kept}
    rest = [(a, "<>", b) for a, b in combinations(query.order or query.attrs, 2) if frozenset((a, b)) not in ordered]
    return replace(query, filters=(*query.filters, *kept, *rest))


def degree_relabel(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``(edges by rank, (vertex, rank))``: ranks by degree, then number; edges run from low to high.

    Ranks come from a range partitioning: numbers within partitions plus the sizes of the
    partitions before; no task sees all vertices.
    """
    spark = edges.sparkSession
    both = edges.select(F.col("src").alias("v")).unionAll(edges.select(F.col("dst").alias("v")))
    degree = both.groupBy("v").agg(F.count(F.lit(1)).alias("d"))
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    dealt = degree.repartitionByRange(parts, "d", "v").sortWithinPartitions("d", "v").withColumn("p", F.spark_partition_id())
    from motifjoin.workspace import materialize

    dealt = materialize(dealt, "degrees")
    local = dealt.withColumn("r", F.row_number().over(Window.partitionBy("p").orderBy("d", "v")))
    sizes = dealt.groupBy("p").agg(F.count(F.lit(1)).alias("n"))
    before = sizes.withColumn("before", F.coalesce(F.sum("n").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("p", "before")  # one row per partition
    mapping = local.join(F.broadcast(before), "p").select(F.col("v").alias("vertex"), (F.col("r") + F.col("before") - 1).alias("rank"))
    a, b = (mapping.select(F.col("vertex").alias(c), F.col("rank").alias(f"r_{c}")) for c in ("src", "dst"))
    ranked = edges.join(a, "src").join(b, "dst").select(F.least("r_src", "r_dst").alias("src"), F.greatest("r_src", "r_dst").alias("dst"))
    return ranked.dropDuplicates(), mapping


def materialize_triangles(edges: DataFrame, cut: bool = True) -> DataFrame:
    """All triangles as a ternary relation ``(x, y, z)``."""
    from motifjoin.workspace import materialize

    found = static_join(PATTERNS["triangle"], {"e": edges}).toDF("x", "y", "z")
    return materialize(found, "triangles") if cut else found


def rewrite_with_triangles(query: JoinQuery, relation: str = "tri") -> JoinQuery:
    """Replace edges by triangles that cover them, most new edges first; all triangles sharing a first edge join on it."""
    edges = {t.attrs: t for t in query.atoms}
    order = query.order or query.attrs
    triangles = [(a, b, c) for a, b, c in combinations(order, 3) if (a, b) in edges and (a, c) in edges and (b, c) in edges]
    left, used = set(edges), []
    while True:
        gain = lambda t: len({(t[0], t[1]), (t[0], t[2]), (t[1], t[2])} & left)
        best = max((t for t in triangles if t not in used), key=lambda t: (gain(t), -order.index(t[0]), -order.index(t[1])), default=None)
        if best is None or not gain(best):
            break
        used.append(best)
        left -= {(best[0], best[1]), (best[0], best[2]), (best[1], best[2])}
    return replace(query, name=query.name + "_tri", atoms=(*(Atom(relation, t) for t in used), *(edges[e] for e in edges if e in left)))


@dataclass(frozen=True)
class FactorPlan:
    """A core pattern and tails: attributes that depend on the core only, kept as lists."""

    core: JoinQuery
    tails: tuple[tuple[str, tuple[Atom, ...]], ...]


def factorize(query: JoinQuery) -> FactorPlan:
    """Split off, from the back of the order, attributes that share no atom with each other."""
    order = list(query.order or query.attrs)
    tails: list[str] = []
    for a in reversed(order[2:]):
        adjacent = {b for t in query.atoms if a in t.attrs for b in t.attrs}
        if not adjacent & set(tails) - {a}:
            tails.append(a)
    tails = tails[::-1]
    core_atoms = tuple(t for t in query.atoms if not set(t.attrs) & set(tails))
    if not core_atoms or {x for t in core_atoms for x in t.attrs} != set(order) - set(tails):
        raise ValueError("the pattern does not factorise over this order")
    core = JoinQuery(query.name + "_core", core_atoms, tuple(f for f in query.filters if not {f[0], f[2]} & set(tails)), tuple(a for a in order if a not in tails))
    return FactorPlan(core, tuple((a, tuple(t for t in query.atoms if a in t.attrs)) for a in tails))


def factorized_join(query: JoinQuery, edges: DataFrame, relation: str = "e", **options) -> DataFrame:
    """Core columns and, per tail, a list column ``<attribute>s``; the product is never formed."""
    plan = factorize(query)
    out = static_join(plan.core, {relation: edges}, **options)
    core_attrs = list(plan.core.order or plan.core.attrs)
    for attr, atoms in plan.tails:
        # the tail over the attributes it touches, each combination once
        touched = [a for a in core_attrs if any(a in t.attrs for t in atoms)]
        inner = [t for t in plan.core.atoms if set(t.attrs) <= set(touched)]
        # one list per combination of touched attributes, grown from the core's own rows
        sub = JoinQuery(f"{query.name}_{attr}", (*inner, *atoms), tuple(f for f in query.filters if attr in (f[0], f[2]) and {f[0], f[2]} <= {attr, *touched}), (*touched, attr))
        lists = static_join(sub, {relation: edges}, **options).groupBy(*touched).agg(F.array_sort(F.collect_list(attr)).alias(f"{attr}s"))
        out = out.join(lists, touched)
    return out


def factorized_count(rows: DataFrame) -> DataFrame:
    """How many matches the lists stand for."""
    lists = [c for c in rows.columns if rows.schema[c].dataType.typeName() == "array"]
    size = F.lit(1).cast("long")
    for c in lists:
        size = size * F.size(c)
    return rows.agg(F.coalesce(F.sum(size), F.lit(0)).cast("long").alias("n"))


def expand(rows: DataFrame) -> DataFrame:
    """Lists back to rows."""
    for c in rows.columns:
        if rows.schema[c].dataType.typeName() == "array":
            rows = rows.withColumn(c[:-1], F.explode(c)).drop(c)
    return rows
