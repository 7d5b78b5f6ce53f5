"""Single-threaded joins: the serial attribute-at-a-time join, its sorted form, a vertex-at-a-time matcher, and a tuned triangle lister."""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator, Mapping, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from motifjoin.plans.query import JoinQuery

_OPS = {"<": lambda a, b: a < b, "<=": lambda a, b: a <= b, "<>": lambda a, b: a != b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b, "=": lambda a, b: a == b}


def _seek_common(lists: list[list]) -> Iterator:
    """Values common to sorted lists: each list in turn seeks the largest value seen."""
    if any(not x for x in lists):
        return
    at, k, top = [0] * len(lists), 0, max(x[0] for x in lists)
    agreed = 0
    while True:
        mine = lists[k]
        at[k] = bisect_left(mine, top, at[k])
        if at[k] == len(mine):
            return
        if mine[at[k]] == top:
            agreed += 1
        else:
            top, agreed = mine[at[k]], 1
        if agreed == len(lists):
            yield top
            at[k] += 1
            if at[k] == len(mine):
                return
            top, agreed = mine[at[k]], 1
        k = (k + 1) % len(lists)


def serial_generic_join(query: JoinQuery, tables: Mapping[str, Sequence[tuple]], order: Sequence[str] | None = None, intersect: str = "hash") -> list[tuple]:
    """All matches, attribute by attribute, from the smallest extension set of every prefix.

    ``intersect``: ``hash`` looks candidates up in sets; ``seek`` seeks through sorted lists.
    """
    order = tuple(order or query.order or query.attrs)
    steps = []
    for j, attr in enumerate(order):
        bound, indices = order[:j], []
        for atom in query.atoms:
            if attr not in atom.attrs:
                continue
            keys = [a for a in bound if a in atom.attrs]
            index: dict[tuple, set] = {}
            for row in tables[atom.relation]:
                seen: dict[str, object] = {}
                if any(v is None or seen.setdefault(a, v) != v for a, v in zip(atom.attrs, row)):
                    continue
                index.setdefault(tuple(seen[k] for k in keys), set()).add(seen[attr])
            indices.append(([bound.index(k) for k in keys], index if intersect == "hash" else {k: sorted(v) for k, v in index.items()}))
        checks = [(order.index(l), _OPS[op], order.index(r)) for l, op, r in query.filters if attr in (l, r) and {l, r} <= set(order[: j + 1])]
        steps.append((indices, checks))
    out: list[tuple] = []

    def grow(prefix: tuple, j: int) -> None:
        if j == len(order):
            out.append(prefix)
            return
        indices, checks = steps[j]
        sets = [index.get(tuple(prefix[p] for p in pos)) for pos, index in indices]
        if any(not s for s in sets):
            return
        sets.sort(key=len)
        found = _seek_common(sets) if intersect == "seek" else (v for v in sets[0] if all(v in s for s in sets[1:]))
        for v in found:
            following = (*prefix, v)
            if all(op(following[a], following[b]) for a, op, b in checks):
                grow(following, j + 1)

    grow((), 0)
    want = query.order or query.attrs
    return [tuple(row[order.index(a)] for a in want) for row in out]


def serial_join(query: JoinQuery, relations: Mapping[str, DataFrame], intersect: str = "hash") -> DataFrame:
    """The serial join as one task: everything goes to one worker."""
    names = list(dict.fromkeys(a.relation for a in query.atoms))
    from pyspark.sql import functions as F

    packed = None
    for n in names:
        rows = relations[n].dropDuplicates().select(F.lit(n).alias("rel"), F.array(*[F.col(f"`{c}`").cast("long") for c in relations[n].columns]).alias("row"))
        packed = rows if packed is None else packed.unionByName(rows)
    attrs = list(query.order or query.attrs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables: dict[str, list[tuple]] = {n: [] for n in names}
        for batch in batches:
            for rel, row in zip(*(c.to_pylist() for c in batch.columns)):
                tables[rel].append(tuple(row))
        found = serial_generic_join(query, tables, intersect=intersect)
        yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in found], pa.int64()) for k in range(len(attrs))], attrs)

    return packed.repartition(1).mapInArrow(run, ", ".join(f"`{a}` long" for a in attrs))


def list_triangles(src: np.ndarray, dst: np.ndarray, probes: int = 1 << 22) -> Iterator[np.ndarray]:
    """Triangles of the undirected graph, each once, as rows of three ascending vertices.

    Edges point from the vertex of lower degree (then id) to the other, so no list of
    successors is longer than the root of twice the edges. Per edge the shorter of both
    ends' lists is looked up in the packed edges; at most ``probes`` lookups, or those of
    one edge, are made at a time. Loops, repeated and reversed edges change nothing.
    """
    names, code = np.unique(np.concatenate([src, dst]), return_inverse=True)
    n, a, b = len(names), code[: len(src)].astype(np.int64), code[len(src) :].astype(np.int64)
    pairs = np.unique((np.minimum(a, b) * n + np.maximum(a, b))[a != b])
    if not len(pairs):
        return
    a, b = pairs // n, pairs % n
    by_rank = np.argsort(np.bincount(np.concatenate([a, b]), minlength=n), kind="stable")
    rank = np.empty(n, np.int64)
    rank[by_rank] = np.arange(n)
    packed = np.sort(np.minimum(rank[a], rank[b]) * n + np.maximum(rank[a], rank[b]))
    s, d = packed // n, packed % n
    start = np.searchsorted(s, np.arange(n + 1))
    size = np.diff(start)
    short = np.where(size[s] <= size[d], s, d)
    other = s + d - short
    ends = np.cumsum(size[short])
    lo = 0
    while lo < len(s):
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + probes, "right")))
        each = np.repeat(np.arange(lo, hi), size[short[lo:hi]])
        third = d[start[short[each]] + np.arange(len(each)) - (ends[each] - size[short[each]] - (ends[lo - 1] if lo else 0))]
        wanted = other[each] * n + third
        at = np.minimum(np.searchsorted(packed, wanted), len(packed) - 1)
        hit = packed[at] == wanted
        if hit.any():
            each, third = each[hit], third[hit]
            yield np.sort(np.column_stack([names[by_rank[x]] for x in (s[each], d[each], third)]), axis=1)
        lo = hi


def count_triangles(src: np.ndarray, dst: np.ndarray) -> int:
    """Number of triangles of the undirected graph; on a graph without cycles, of matches of the directed pattern."""
    return sum(len(found) for found in list_triangles(src, dst))


def serial_triangles(edges: DataFrame, listing: bool = False) -> DataFrame:
    """One task over packed arrays: ``n``, the number of triangles, or with ``listing`` the triangles ``a1 < a2 < a3``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
        src, dst = (np.concatenate([g[k] for g in got]) if got else np.zeros(0, np.int64) for k in (0, 1))
        if listing:
            for found in list_triangles(src, dst):
                yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(found[:, k])) for k in range(3)], ["a1", "a2", "a3"])
        else:
            yield pa.RecordBatch.from_arrays([pa.array([count_triangles(src, dst)], pa.int64())], ["n"])

    known = edges.select("src", "dst").dropna()
    return known.repartition(1).mapInArrow(run, "a1 long, a2 long, a3 long" if listing else "n long")


def vertex_match(query: JoinQuery, edges: Sequence[tuple]) -> list[tuple]:
    """All matches of a pattern over one edge relation, query vertex by query vertex, by backtracking.

    A query vertex takes its candidates from the neighbours of one vertex that is matched
    already, the one with the fewest, and every other edge is then tested. The order goes from the vertex
    with the most edges to those with most edges to the ones before. Unlike the serial
    join, the candidates of a step are not bounded by the smallest of all its lists
    before the order is chosen, so the work can exceed the largest output.
    """
    follow: dict = {}
    precede: dict = {}
    known = {(s, t) for s, t in edges if s is not None and t is not None}
    for s, t in known:
        follow.setdefault(s, set()).add(t)
        precede.setdefault(t, set()).add(s)
    ties = [a.attrs for a in query.atoms]
    order: list[str] = []
    while len(order) < len(query.attrs):
        rest = [x for x in query.attrs if x not in order]
        order.append(max(rest, key=lambda x: (sum(x in t and any(y in order for y in t) for t in ties), sum(x in t for t in ties))))
    steps = []
    for j, x in enumerate(order):
        out_of = [order.index(s) for s, t in ties if t == x and s in order[:j]]
        into = [order.index(t) for s, t in ties if s == x and t in order[:j]]
        checks = [(order.index(l), _OPS[op], order.index(r)) for l, op, r in query.filters if x in (l, r) and {l, r} <= set(order[: j + 1])]
        steps.append((out_of, into, (x, x) in ties, any(s == x for s, _ in ties), any(t == x for _, t in ties), checks))
    found: list[tuple] = []
    everywhere = set(follow) | set(precede)

    def grow(prefix: tuple) -> None:
        if len(prefix) == len(order):
            found.append(prefix)
            return
        out_of, into, loop, leaves, enters, checks = steps[len(prefix)]
        regions = [follow.get(prefix[p], ()) for p in out_of] + [precede.get(prefix[p], ()) for p in into]
        for v in min(regions, key=len, default=everywhere):
            if leaves and v not in follow or enters and v not in precede or loop and (v, v) not in known:
                continue
            if all((prefix[p], v) in known for p in out_of) and all((v, prefix[p]) in known for p in into):
                following = (*prefix, v)
                if all(op(following[l], following[r]) for l, op, r in checks):
                    grow(following)

    grow(())
    want = query.order or query.attrs
    return [tuple(row[order.index(x)] for x in want) for row in found]


def serial_match(query: JoinQuery, edges: DataFrame) -> DataFrame:
    """``vertex_match`` as one task."""
    attrs = list(query.order or query.attrs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [row for b in batches for row in zip(*(c.to_pylist() for c in b.columns))]
        found = vertex_match(query, rows)
        yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in found], pa.int64()) for k in range(len(attrs))], attrs)

    return edges.select("src", "dst").repartition(1).mapInArrow(run, ", ".join(f"`{a}` long" for a in attrs))
