"""Extension for many prefixes: lists are gathered once per range of leading values, candidates never move.

The steps are those of ``extend``: per prefix the index with the fewest candidates
proposes, all others filter. But prefixes are dealt out by ranges of their first attribute,
and every list that a range can look up is sent to its task once, however many prefixes
look it up. All stages then run inside the task, over sorted arrays: what moves is the
prefixes and the lists, not the proposals. Stages are run depth first in chunks of
candidates, so a task holds its lists and one chunk per stage.

Where tasks can open the shared folder themselves, lists do not move either: an index is stored
there once, as arrays of numbered values that tasks map into memory, so that any
range looks up any list, however little locality the graph has (``_Store``). The rest of this
module's shipping of lists is for shared folders that only Spark reads.

For binary relations of long values, where each stage looks indices up by one bound value.
A value's list that is shipped is one row, so it has to fit in a row.
"""

from __future__ import annotations

import operator
import os
import uuid
from collections.abc import Callable, Iterator, Mapping, Sequence
from functools import partial, reduce
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from motifjoin.operators import pairs
from motifjoin.operators.index import IndexCatalog
from motifjoin.plans.stages import Stage
from motifjoin.workspace import drop_path, drop_stored, materialize, new_path, open_folder

#: Rows of a relation beyond which stages are gathered; prefixes of a range; candidates of a chunk.
GATHER_ROWS, RANGE_ROWS, CHUNK = 500_000, 600_000, 1 << 19
_ODD = np.uint64(0x9E3779B97F4A7C15)
_OPS = {"<": operator.lt, "<=": operator.le, "<>": operator.ne, ">": operator.gt, ">=": operator.ge, "=": operator.eq}
_SHIPPED = "b int, kind int, k long, own boolean, xs array<long>"
_RANK = "__rank"
#: Rows of a part of a stored index, which one task sorts.
PART_ROWS = 2_000_000


def can_gather(stages: Sequence[Stage], catalog: IndexCatalog, rows: int | None = None) -> bool:
    """Whether all lookups are by one value of stored binary relations of longs, one of which is large."""
    uses = [u for s in stages for u in s.uses]
    if not uses or any(len(u.key_pos) != 1 or u.key_pos[0] == u.ext_pos for u in uses):
        return False
    relations = {(u.relation, u.version): catalog.relation(u.relation, u.version) for u in uses}
    if any([f.dataType for f in df.schema.fields] != [T.LongType()] * 2 for df in relations.values()):
        return False
    return any(df.count() > (GATHER_ROWS if rows is None else rows) for df in relations.values())


def _bounds(df: DataFrame, col: str) -> list[int]:
    """Upper bounds of ranges of about ``RANGE_ROWS`` rows, the last one open."""
    n = df.count()
    parts = -(-n // RANGE_ROWS) if n > RANGE_ROWS else 1
    parts = max(parts, min(df.sparkSession.sparkContext.defaultParallelism, -(-n // 50_000)))
    if parts <= 1:
        return []
    return sorted(set(df.agg(F.percentile_approx(col, [i / parts for i in range(1, parts)])).first()[0] or []))


def _range_of(col: Column, bounds: list[int]) -> Column:
    def pick(lo: int, hi: int) -> Column:
        mid = (lo + hi) // 2
        return F.lit(lo) if lo == hi else F.when(col <= bounds[mid], pick(lo, mid)).otherwise(pick(mid + 1, hi))

    return pick(0, len(bounds)).cast("int")


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (key, value) of a partition as a sorted list per key."""
    got = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
    if sum(len(k) for k, _ in got):
        k, x = (np.concatenate(c) for c in zip(*got))
        order = np.lexsort((x, k))
        k, x = k[order], x[order]
        first = np.flatnonzero(np.append(True, k[1:] != k[:-1]))
        lists = pa.ListArray.from_arrays(pa.array(np.append(first, len(k)), pa.int32()), pa.array(x))
        batch = pa.RecordBatch.from_arrays([pa.array(k[first]), lists], ["k", "xs"])
        for at in range(0, len(first), 4096):
            yield batch.slice(at, 4096)


class _Packed:
    """An index as one row ``(k, xs)`` per value, stored by ranges of the values."""

    def __init__(self, catalog: IndexCatalog, index_id: tuple) -> None:
        relation, version, (key,), ext = index_id
        rows = catalog.relation(relation, version).select(F.col(f"c{key}").alias("k"), F.col(f"c{ext}").alias("x"))
        self.bounds = _bounds(rows, "k")
        self.rows = materialize(rows.repartitionById(len(self.bounds) + 1, _range_of(F.col("k"), self.bounds)).mapInArrow(_pack, "k long, xs array<long>"), "packed")
        rows.sparkSession.sparkContext._jvm.System.gc()  # so that Spark lets go of the shuffle that made the lists


def _packed(catalog: IndexCatalog, index_id: tuple) -> _Packed:
    kept = catalog.__dict__.setdefault("_packed", {})
    if index_id not in kept:
        kept[index_id] = _Packed(catalog, index_id)
    return kept[index_id]


def drop_packed(catalog: IndexCatalog, version: str) -> None:
    """Delete the stored lists of a version that nothing looks up any more."""
    kept = catalog.__dict__.get("_packed", {})
    for index_id in [i for i in kept if i[1] == version]:
        drop_stored(kept.pop(index_id).rows)


class _Store:
    """A catalog's binary relations in the shared folder: their values in order, and per index the lists of the values' numbers.

    Every array is one file; tasks write their parts to files of their own, which are put
    in place when their sizes are known.
    """

    def __init__(self, catalog: IndexCatalog) -> None:
        self.relations = {key: df for key, df in catalog.relations.items() if [f.dataType for f in df.schema.fields] == [T.LongType()] * 2}
        self.spark = next(iter(self.relations.values())).sparkSession
        self.path = new_path(self.spark, "lists")
        self.folder = open_folder(self.spark, self.path)
        os.makedirs(f"{self.folder}/parts", exist_ok=True)
        self._by_name: dict[str, tuple[list[int], list[int]]] = {}
        both = max((self.cuts(name) for name, _ in self.relations), key=lambda c: len(c[0]))
        self.bounds = sorted({*both[0], *both[1]})[:: 2 if both[0] else 1]
        whole = [df for (name, version), df in self.relations.items() if version != "kept" or (name, "old") not in self.relations]  # what is kept is in the old version
        sent = reduce(DataFrame.union, [df.mapInArrow(partial(_values, bounds=self.bounds), pairs.BLOBS) for df in whole])
        sizes = self._made(sent, len(self.bounds) + 1, partial(_write_values, folder=self.folder))
        self.n = sum(sizes)
        self._placed(sizes, partial(_place, folder=self.folder, name="values", size=8))
        self.sizes: dict[tuple, int] = {}

    def cuts(self, name: str) -> tuple[list[int], list[int]]:
        """Upper bounds of parts of about ``PART_ROWS`` rows by either column, the same for all versions of a relation."""
        if name not in self._by_name:
            df = self.relations.get((name, "new"))
            df = next(d for (n, _), d in self.relations.items() if n == name) if df is None else df
            parts = -(-df.count() // PART_ROWS)
            found = df.agg(*(F.percentile_approx(c, [i / parts for i in range(1, parts)]) for c in df.columns)).first() if parts > 1 else ([], [])
            self._by_name[name] = tuple(sorted(set(b or [])) for b in found)
        return self._by_name[name]

    def _made(self, sent: DataFrame, parts: int, write: Callable) -> list[int]:
        """Sizes of the parts that tasks wrote."""
        got = {r["b"]: r["n"] for r in sent.repartitionById(parts, F.col("b")).mapInArrow(write, "b int, n long").collect()}  # a row per part
        self.spark.sparkContext._jvm.System.gc()  # so that Spark lets go of the shuffle
        return [got.get(b, 0) for b in range(parts)]

    def _placed(self, sizes: list[int], place: Callable) -> None:
        parts = [(b, int(at), n) for b, (at, n) in enumerate(zip(np.cumsum([0, *sizes]), sizes))]
        tasks = min(len(parts), max(1, self.spark.sparkContext.defaultParallelism))
        self.spark.createDataFrame(parts, "b int, at long, n long").repartitionById(tasks, F.col("b") % tasks).mapInArrow(place, "b int").collect()
        drop_path(self.spark, f"{self.path}/parts")
        os.makedirs(f"{self.folder}/parts", exist_ok=True)

    def index(self, index_id: tuple) -> str:
        """The name of an index, which is stored when it is first asked for."""
        relation, version, (key,), ext = index_id
        name = f"{relation}-{version}-{key}-{ext}"
        if index_id not in self.sizes:
            bounds = self.cuts(relation)[key]
            rows = self.relations[relation, version].select(F.col(f"c{key}").alias("k"), F.col(f"c{ext}").alias("x"))
            sent = rows.mapInArrow(lambda it: pairs.blobs(pairs.of_batches(it), pairs.by_bounds(bounds)), pairs.BLOBS)
            sizes = self._made(sent, len(bounds) + 1, partial(_write_lists, folder=self.folder, name=name, bounds=bounds, n=self.n))
            self._placed(sizes, partial(_place_lists, folder=self.folder, name=name, bounds=bounds, n=self.n))
            self.sizes[index_id] = sum(sizes)
        return name


def _store(catalog: IndexCatalog) -> _Store | None:
    """A catalog's store, where tasks can open the shared folder."""
    if "_stored" not in catalog.__dict__:
        spark = next(iter(catalog.relations.values())).sparkSession
        catalog.__dict__["_stored"] = _Store(catalog) if open_folder(spark) else None
    return catalog.__dict__["_stored"]


def _values(batches: Iterator[pa.RecordBatch], bounds: list[int]) -> Iterator[pa.RecordBatch]:
    """The values of both columns, as pairs with zero."""
    each = (np.unique(np.concatenate(p)) for p in pairs.of_batches(batches))
    return pairs.blobs(((v, np.zeros(len(v), np.int64)) for v in each), pairs.by_bounds(bounds))


def _map(path: str, dtype: type) -> np.ndarray:
    """A stored array, of which only what is looked up is read."""
    return np.asarray(np.memmap(path, dtype, "r")) if os.path.exists(path) and os.path.getsize(path) else np.zeros(0, dtype)


def _number_type(n: int) -> type:
    return np.int32 if n < 1 << 31 else np.int64


def _write_part(path: str, array: np.ndarray) -> None:
    own = f"{path}.{uuid.uuid4().hex[:8]}"
    array.tofile(own)
    os.replace(own, path)  # a task that runs twice writes the same


def _write_at(path: str, at: int, array: np.ndarray) -> None:
    f = os.open(path, os.O_RDWR | os.O_CREAT, 0o666)
    data = memoryview(np.ascontiguousarray(array)).cast("B") if len(array) else b""
    while len(data):
        done = os.pwrite(f, data, at)
        data, at = data[done:], at + done
    os.close(f)


def _write_values(batches: Iterator[pa.RecordBatch], folder: str) -> Iterator[pa.RecordBatch]:
    for b, v, _ in pairs.parts_of(batches):
        _write_part(f"{folder}/parts/values-{b}", v)
        yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), pa.array([len(v)], pa.int64())], ["b", "n"])


def _place(batches: Iterator[pa.RecordBatch], folder: str, name: str, size: int) -> Iterator[pa.RecordBatch]:
    """Parts put into the file ``name`` of values of some bytes."""
    for batch in batches:
        for b, at, n in zip(*(c.to_pylist() for c in batch.columns)):
            if n:
                _write_at(f"{folder}/{name}", at * size, _map(f"{folder}/parts/{name}-{b}", np.uint8))
        yield pa.RecordBatch.from_arrays([batch.column(0)], ["b"])


def _numbers_of(part: int, values: np.ndarray, bounds: list[int]) -> tuple[int, int]:
    """The numbers of the values in a part of an index."""
    return int(np.searchsorted(values, bounds[part - 1], "right")) if part else 0, int(np.searchsorted(values, bounds[part], "right")) if part < len(bounds) else len(values)


def _write_lists(batches: Iterator[pa.RecordBatch], folder: str, name: str, bounds: list[int], n: int) -> Iterator[pa.RecordBatch]:
    values = _map(f"{folder}/values", np.int64)
    for b, k, x in pairs.parts_of(batches):
        lo, hi = _numbers_of(b, values, bounds)
        _write_part(f"{folder}/parts/{name}-{b}", np.searchsorted(values, x).astype(_number_type(n)))
        _write_part(f"{folder}/parts/{name}-count-{b}", np.bincount(np.searchsorted(values[lo:hi], k), minlength=hi - lo).astype(np.int64))
        yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), pa.array([len(k)], pa.int64())], ["b", "n"])


def _place_lists(batches: Iterator[pa.RecordBatch], folder: str, name: str, bounds: list[int], n: int) -> Iterator[pa.RecordBatch]:
    """Parts of an index put in place, with where the list of each value ends; values without one have an empty list."""
    values = _map(f"{folder}/values", np.int64)
    for batch in batches:
        for b, at, rows in zip(*(c.to_pylist() for c in batch.columns)):
            lo, hi = _numbers_of(b, values, bounds)
            count = _map(f"{folder}/parts/{name}-count-{b}", np.int64) if rows else np.zeros(hi - lo, np.int64)
            _write_at(f"{folder}/{name}-at", lo * 8 + 8, at + np.cumsum(count))
            if rows:
                _write_at(f"{folder}/{name}", at * np.dtype(_number_type(n)).itemsize, _map(f"{folder}/parts/{name}-{b}", np.uint8))
        yield pa.RecordBatch.from_arrays([batch.column(0)], ["b"])


class _Stored:
    """One index of a store, mapped."""

    def __init__(self, folder: str, name: str, n: int) -> None:
        self.n = n
        self.flat, at = _map(f"{folder}/{name}", _number_type(n)), _map(f"{folder}/{name}-at", np.int64)
        self.start, self.end = at[:-1], at[1:]

    def count_of(self, key: np.ndarray) -> np.ndarray:
        return self.end[key] - self.start[key]

    def holds(self, key: np.ndarray, value: np.ndarray) -> np.ndarray:
        """Positions of the pairs that are in the index; pairs of one key come together."""
        if not len(key):
            return np.zeros(0, np.int64)
        change = np.append(True, key[1:] != key[:-1])
        keys = key[change]
        n = self.count_of(keys)
        total = int(n.sum())
        if total > 4 * len(key) + 4096:
            return self._searched(key, value)
        if not total:
            return np.zeros(0, np.int64)
        entry = self.flat[np.arange(total) + np.repeat(self.start[keys] - (np.cumsum(n) - n), n)]
        codes = np.repeat(np.arange(len(keys)) * self.n, n) + entry
        code = (np.cumsum(change) - 1) * self.n + value
        shift = np.uint64(64 - max(10, (8 * total).bit_length()))
        table = np.zeros(1 << (64 - int(shift)), bool)
        table[((codes.view(np.uint64) * _ODD) >> shift).view(np.int64)] = True
        maybe = np.flatnonzero(table[((code.view(np.uint64) * _ODD) >> shift).view(np.int64)])
        code = code[maybe]
        return maybe[codes[np.minimum(np.searchsorted(codes, code), total - 1)] == code]

    def _searched(self, key: np.ndarray, value: np.ndarray) -> np.ndarray:
        """The same by bisection in each list."""
        lo, end = self.start[key], self.end[key]
        hi = end.copy()
        while True:
            open_ = np.flatnonzero(lo < hi)
            if not len(open_):
                break
            mid = (lo[open_] + hi[open_]) >> 1
            less = self.flat[mid] < value[open_]
            lo[open_[less]], hi[open_[~less]] = mid[less] + 1, mid[~less]
        there = np.flatnonzero(lo < end)
        return there[self.flat[lo[there]] == value[there]]


def gathered_stages(stages: Sequence[Stage], catalog: IndexCatalog, attrs: Sequence[str], *, prefixes: DataFrame | None = None, seed: tuple | None = None, filters: Sequence[tuple[str, str, str]] = (), count: bool = False, parallelism: int | None = None, first: bool = False, groups: Sequence[Sequence[Stage]] = ()) -> DataFrame:
    """Prefixes to matches ``attrs``, or to a count ``n``.

    ``first``: every stage's first index proposes, however many candidates, as in plans of binary joins.
    ``groups``: stages of further groups of atoms, each from the first attribute on; their rows are joined with
    those so far in the task, and one that agrees with none of those is dropped as soon as that shows.

    Seeds are ``prefixes`` (attributes of the first stage's head and, for changes, ``w``), or
    all rows of the index ``seed`` that pass ``filters``.
    """
    head = list(stages[0].bound)
    lead = head[0]
    every = [*stages, *(s for g in groups for s in g)]
    ids = list(dict.fromkeys([seed] * bool(seed) + [u.index_id for s in every for u in s.uses]))
    steps = lambda some: [(s.attr, [(ids.index(u.index_id), u.key_attrs[0]) for u in s.uses], s.filters) for s in some]
    if store := _store(catalog):
        spec = {"seed": seed, "filters": tuple(filters), "count": count, "first": first, "stages": steps(stages), "groups": [steps(g) for g in groups], "keys": {u.key_attrs[0] for s in every for u in s.uses}}
        return _mapped_stages(store, ids, head, attrs, spec, prefixes, parallelism)
    bounds = _packed(catalog, seed).bounds if seed else _bounds(prefixes, lead)
    bucket = _range_of(F.col("k"), bounds)
    needs: dict[str, DataFrame] = {}

    def exploded(rows: DataFrame) -> DataFrame:
        return rows.select("b", F.explode("xs").alias("k")).distinct()

    def need(attr: str) -> DataFrame:
        """``(b, k)``: a superset of the values of ``attr`` that a range can meet."""
        if attr not in needs:
            if attr in head:
                needs[attr] = exploded(_packed(catalog, seed).rows.withColumn("b", bucket)) if seed else prefixes.select(_range_of(F.col(lead), bounds).alias("b"), F.col(attr).alias("k")).distinct()
            else:
                uses = next(s for s in every if s.attr == attr).uses
                use = next((u for u in uses if u.key_attrs[0] == lead), uses[0])
                lists = _packed(catalog, use.index_id).rows
                if use.key_attrs[0] == lead and use.index_id == seed:
                    needs[attr] = need(head[1])
                elif use.key_attrs[0] == lead:
                    needs[attr] = exploded(lists.withColumn("b", bucket))
                else:
                    needs[attr] = exploded(need(use.key_attrs[0]).join(lists, "k"))
        return needs[attr]

    parts = []
    for kind, index_id in enumerate(ids):
        keys = list(dict.fromkeys(u.key_attrs[0] for s in every for u in s.uses if u.index_id == index_id))
        lists, own = _packed(catalog, index_id).rows, index_id == seed or lead in keys
        if own:
            parts.append(lists.select(bucket.alias("b"), F.lit(kind).alias("kind"), "k", F.lit(True).alias("own"), "xs"))
        frames = list(dict.fromkeys(need(a) for a in keys if a != lead))
        if frames:
            wanted = reduce(DataFrame.union, frames)
            wanted = (wanted.distinct() if len(frames) > 1 else wanted).filter(F.col("b") != bucket) if own else (wanted.distinct() if len(frames) > 1 else wanted)
            parts.append(wanted.join(lists, "k").select("b", F.lit(kind).alias("kind"), "k", F.lit(False).alias("own"), "xs"))
    more = [a for a in head[1:]] + (["w"] if prefixes is not None and "w" in prefixes.columns else [])
    if not seed:
        parts.append(prefixes.select(_range_of(F.col(lead), bounds).alias("b"), F.lit(-1).alias("kind"), F.col(lead).alias("k"), F.lit(False).alias("own"), F.array(*(F.col(a).cast("long") for a in more)).cast("array<long>").alias("xs")))
    spec = {
        "head": (lead, *more), "seed": 0 if seed else None, "filters": tuple(filters), "count": count, "first": first, "out": tuple(attrs) + (("w",) if "w" in more else ()),
        "stages": steps(stages), "groups": [steps(g) for g in groups], "kinds": len(ids),
    }
    sent = reduce(DataFrame.unionByName, parts).repartitionById(len(bounds) + 1, F.col("b"))
    if parallelism:
        sent = sent.coalesce(parallelism)
    if count:
        return sent.mapInArrow(lambda it: _run(it, spec), "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))
    return sent.mapInArrow(lambda it: _run(it, spec), ", ".join(f"`{a}` {'int' if a == 'w' else 'long'}" for a in spec["out"]))


def _mapped_stages(store: _Store, ids: list[tuple], head: list[str], attrs: Sequence[str], spec: dict, prefixes: DataFrame | None, parallelism: int | None) -> DataFrame:
    """Stages over a store: ranges of the seeds' index, or prefixes where they are, look lists up themselves."""
    signed = prefixes is not None and "w" in prefixes.columns and "w" not in attrs
    spec |= {"folder": store.folder, "n": store.n, "names": [store.index(i) for i in ids], "head": tuple(head), "signed": signed, "out": tuple(attrs) + ("w",) * signed}
    schema = spec.get("schema") or ", ".join(f"`{a}` {'int' if signed and a == 'w' else 'long'}" for a in spec["out"])
    if spec["seed"]:
        rows = store.sizes[spec["seed"]]
        spec["shares"] = (rows, max(1, -(-rows // RANGE_ROWS), min(store.spark.sparkContext.defaultParallelism, -(-rows // 50_000))))
        parts = spec["shares"][1]
        sent = store.spark.range(parts).select(F.col("id").cast("int").alias("b")).repartitionById(parts, F.col("b"))
    else:
        sent = prefixes.select(*(F.col(a).cast("long") for a in head), *(["w"] if signed else []))
    if parallelism:
        sent = sent.coalesce(parallelism)
    if spec["count"]:
        return sent.mapInArrow(lambda it: _run_mapped(it, spec), "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))
    return sent.mapInArrow(lambda it: _run_mapped(it, spec), schema)


def neighbourhood_cliques(stages: Sequence[Stage], catalog: IndexCatalog, k: int, compact: bool, seed: tuple) -> DataFrame:
    """Cliques of ``k`` inside the neighbourhoods that ``stages`` (of the triangle) make, in the task of their first vertex."""
    ids = list(dict.fromkeys([seed, *(u.index_id for s in stages for u in s.uses)]))
    names = [f"a{i}" for i in range(1, k + 1)]
    schema = ", ".join(f"{a} long" for a in names[: k - 1]) + (", tail array<long>" if compact else f", a{k} long")
    spec = {"seed": seed, "filters": (), "count": False, "first": False, "stages": [(s.attr, [(ids.index(u.index_id), u.key_attrs[0]) for u in s.uses], s.filters) for s in stages], "groups": [], "keys": set(), "schema": schema, "cliques": (k, compact)}
    return _mapped_stages(_store(catalog), ids, list(stages[0].bound), names, spec, None, None)


def changed_matches(versions: Sequence[tuple[Sequence[Stage], tuple]], catalog: IndexCatalog, attrs: Sequence[str], filters: Sequence[tuple[str, str, str]]) -> DataFrame:
    """All matches of an old and a new version (stages and seeds' index of each), and with ``w`` those that only one has; a task takes both versions of its first values."""
    ids = list(dict.fromkeys([s for _, s in versions] + [u.index_id for stages, _ in versions for s in stages for u in s.uses]))
    steps = [[(s.attr, [(ids.index(u.index_id), u.key_attrs[0]) for u in s.uses], s.filters) for s in stages] for stages, _ in versions]
    spec = {"seed": versions[0][1], "filters": tuple(filters), "count": False, "first": False, "stages": steps[0], "groups": [], "keys": set(), "versions": [(steps[i], ids.index(versions[i][1])) for i in (0, 1)]}
    spec["schema"] = ", ".join(f"`{a}` long" for a in attrs) + ", w int"
    return _mapped_stages(_store(catalog), ids, list(versions[0][0][0].bound), attrs, spec, None, None)


def _first_values(lists: _Stored, b: int, parts: int) -> tuple[int, int]:
    """The range ``b`` of all numbers, by about equal parts of an index, whole lists."""
    cut = lambda at: int(np.searchsorted(lists.start, at * len(lists.flat) // parts, "left"))
    return cut(b) if b else 0, cut(b + 1) if b + 1 < parts else len(lists.start)


def _seeds_of(lists: _Stored, lo: int, hi: int) -> list[np.ndarray]:
    """Rows of the values ``lo`` to ``hi``."""
    if lo >= hi:
        return [np.zeros(0, np.int64)] * 2
    return [np.repeat(np.arange(lo, hi), lists.end[lo:hi] - lists.start[lo:hi]), lists.flat[lists.start[lo] : lists.end[hi - 1]].astype(np.int64)]


def _run_mapped(batches: Iterator[pa.RecordBatch], spec: dict) -> Iterator[pa.RecordBatch]:
    indices = None
    held, rows = [], 0
    for batch in batches:
        indices = indices or ([_Stored(spec["folder"], name, spec["n"]) for name in spec["names"]], _map(f"{spec['folder']}/values", np.int64))
        if spec["seed"]:
            for b in batch.column(0).to_pylist():
                total, parts = spec["shares"]
                lists = indices[0][0]
                if "cliques" in spec:
                    yield from _Cliques(_seeds_of(lists, *_first_values(lists, b, parts)), indices, spec).matches()
                    continue
                if "versions" in spec:
                    yield from _changed(*_first_values(lists, b, parts), indices, spec)
                    continue
                lo, hi = b * total // parts, (b + 1) * total // parts
                if lo < hi:
                    i, j = np.searchsorted(lists.end, lo, "right"), np.searchsorted(lists.end, hi, "left") + 1
                    n = np.minimum(lists.end[i:j], hi) - np.maximum(lists.start[i:j], lo)
                    yield from _Mapped([np.repeat(np.arange(i, j), n), lists.flat[lo:hi].astype(np.int64)], indices, spec).matches()
            continue
        held.append(batch)
        rows += batch.num_rows
        if rows >= RANGE_ROWS:
            yield from _numbered(held, indices, spec).matches()
            held, rows = [], 0
    if rows:
        yield from _numbered(held, indices, spec).matches()


def _numbered(batches: list[pa.RecordBatch], indices: tuple, spec: dict) -> _Mapped:
    """Prefixes by numbers, in order. A value that no relation has finds nothing."""
    cols = [np.concatenate([b.column(i).to_numpy() for b in batches]) for i in range(batches[0].num_columns)]
    n, values = len(spec["head"]), indices[1]
    found = [np.minimum(np.searchsorted(values, c), max(len(values) - 1, 0)) for c in cols[:n]]
    there = [values[at] == c if len(values) else np.zeros(len(c), bool) for at, c in zip(found, cols)]
    keep = np.logical_and.reduce([t for a, t in zip(spec["head"], there) if a in spec["keys"]] or [np.ones(len(cols[0]), bool)])
    if not all(t[keep].all() for t in there):
        raise ValueError("a prefix has a value that no relation of the catalog has")
    keep = np.flatnonzero(keep)
    keep = keep[np.lexsort([c[keep] for c in reversed(found)])]
    return _Mapped([c[keep] for c in (*found, *cols[n:])], indices, spec)


def _run(batches: Iterator[pa.RecordBatch], spec: dict, kind: type[_Range] | None = None) -> Iterator[pa.RecordBatch]:
    """Range after range of a partition, which holds the rows of each range together."""
    kind = kind or _Range
    at, held = None, []
    for batch in batches:
        b = batch.column(0).to_numpy()
        cuts = [0, *(np.flatnonzero(b[1:] != b[:-1]) + 1).tolist(), len(b)]
        for lo, hi in zip(cuts, cuts[1:]):
            if lo == hi:
                continue
            if held and b[lo] != at:
                yield from kind(held, spec).matches()
                held = []
            at = b[lo]
            held.append(batch.slice(lo, hi - lo))
    if held:
        yield from kind(held, spec).matches()


def _class_of(values: np.ndarray, share: int) -> np.ndarray:
    x = values.view(np.uint64) * _ODD
    x = (x ^ (x >> np.uint64(32))) * _ODD
    return ((x >> np.uint64(33)) % np.uint64(share)).astype(np.int64)


def cells_stages(stages: Sequence[Stage], catalog: IndexCatalog, attrs: Sequence[str], shares: Mapping[str, int], *, seed: tuple, filters: Sequence[tuple[str, str, str]] = ()) -> DataFrame:
    """A plan of binary joins inside the cells of a hypercube: lists go to all cells that may need them, once, and nothing else moves.

    A cell has a class of each attribute's values; it binds only those, so that a match is made in one cell.
    """
    head = list(stages[0].bound)
    names = [*head, *(s.attr for s in stages)]
    ids = list(dict.fromkeys([seed, *(u.index_id for s in stages for u in s.uses)]))
    cells = list(product(*(range(shares[a]) for a in names)))
    parts = []
    for kind, index_id in enumerate(ids):
        pairs = [(head[0], head[1])] * (index_id == seed) + [(u.key_attrs[0], s.attr) for s in stages for u in s.uses if u.index_id == index_id]
        pairs = [(names.index(a), names.index(b)) for a, b in dict.fromkeys(pairs)]
        parts.append(_packed(catalog, index_id).rows.mapInArrow(partial(_to_cells, kind=kind, pairs=pairs, cells=cells, shares=[shares[a] for a in names]), _SHIPPED))
    spec = {
        "head": tuple(head), "seed": 0, "filters": tuple(filters), "count": False, "first": True, "out": tuple(attrs), "groups": [], "kinds": len(ids), "cells": (names, cells, [shares[a] for a in names]),
        "stages": [(s.attr, [(ids.index(u.index_id), u.key_attrs[0]) for u in s.uses], s.filters) for s in stages],
    }
    sent = reduce(DataFrame.unionByName, parts).repartitionById(len(cells), F.col("b"))
    return sent.mapInArrow(lambda it: _run(it, spec), ", ".join(f"`{a}` long" for a in attrs))


def _to_cells(batches: Iterator[pa.RecordBatch], kind: int, pairs: list[tuple[int, int]], cells: list[tuple[int, ...]], shares: list[int]) -> Iterator[pa.RecordBatch]:
    """Lists ``(k, xs)`` cut by the classes of their values, each part to the cells that may look it up."""
    for batch in batches:
        k, flat = batch.column(0).to_numpy(), batch.column(1).flatten().to_numpy()
        row = np.repeat(np.arange(len(k)), np.diff(batch.column(1).offsets.to_numpy()))
        sides = [(_class_of(k, shares[i])[row], _class_of(flat, shares[j])) for i, j in pairs]
        for b, cell in enumerate(cells):
            mine = np.flatnonzero(reduce(np.logical_or, ((hk == cell[i]) & (hx == cell[j]) for (i, j), (hk, hx) in zip(pairs, sides))))
            if not len(mine):
                continue
            first = np.flatnonzero(np.append(True, np.diff(row[mine]) > 0))
            lists = pa.ListArray.from_arrays(pa.array(np.append(first, len(mine)), pa.int32()), pa.array(flat[mine]))
            n = len(first)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(n, b, np.int32)), pa.array(np.full(n, kind, np.int32)), pa.array(k[row[mine[first]]]), pa.array(np.ones(n, bool)), lists], ["b", "kind", "k", "own", "xs"])


class _Lists:
    """One index of a range: lists by number of the value, and a table that tells most pairs that are not there."""

    def __init__(self, codes: np.ndarray, n_values: int, lists: bool = True) -> None:
        codes.sort()
        self.codes, self.n = codes, n_values
        if lists:
            key, flat = np.divmod(codes, n_values)
            self.flat = flat.astype(np.int32)
            self.count = np.bincount(key, minlength=n_values)
            self.start = np.cumsum(self.count) - self.count
        bits = min(28, max(10, (8 * len(codes)).bit_length()))
        self.shift = np.uint64(64 - bits)
        self.table = np.zeros(1 << bits, bool)
        self.table[self._slot(codes)] = True

    def count_of(self, key: np.ndarray) -> np.ndarray:
        return self.count[key]

    def _slot(self, codes: np.ndarray) -> np.ndarray:
        return ((codes.view(np.uint64) * _ODD) >> self.shift).view(np.int64)

    def holds(self, key: np.ndarray, value: np.ndarray) -> np.ndarray:
        """Positions of the pairs that are in the index."""
        return self.find(key, value)[0]

    def find(self, key: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions of the pairs that are in the index, and their numbers there."""
        if not len(self.codes):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        code = key.astype(np.int64) * self.n + value
        maybe = np.flatnonzero(self.table[self._slot(code)])
        code = code[maybe]
        at = np.minimum(np.searchsorted(self.codes, code), len(self.codes) - 1)
        same = self.codes[at] == code
        return maybe[same], at[same]


class _Range:
    """The lists and prefixes of one range, with values numbered in their order."""

    def __init__(self, batches: list[pa.RecordBatch], spec: dict) -> None:
        self.spec = spec
        table = pa.Table.from_batches(batches).combine_chunks()
        kind, k, own = (table.column(i).to_numpy() for i in (1, 2, 3))
        xs = pa.concat_arrays(table.column(4).chunks)
        flat, size = xs.flatten().to_numpy(), np.diff(xs.offsets.to_numpy())
        self.values = np.unique(np.concatenate([flat, k]))
        n = len(self.values)
        flat, k = np.searchsorted(self.values, flat), np.searchsorted(self.values, k)
        each_kind, each_k = np.repeat(kind, size), np.repeat(k, size)
        self.lists = [_Lists(each_k[m] * n + flat[m], n) for m in (each_kind == i for i in range(spec["kinds"]))]
        if spec["seed"] is not None:
            m = (each_kind == spec["seed"]) & np.repeat(own, size)
            cols = [each_k[m], flat[m]]
        else:
            m = kind == -1
            width = len(spec["head"]) - 1
            cols = [k[m], *flat[each_kind == -1].reshape(-1, width).T] if width else [k[m]]
        self.seeds = dict(zip(spec["head"], (c.astype(np.int32) for c in cols)))
        self.allowed: dict[str, np.ndarray] = {}
        if "cells" in spec:
            names, cells, shares = spec["cells"]
            at = cells[table.column(0)[0].as_py()]
            self.allowed = {a: _class_of(self.values, s) == c for a, s, c in zip(names, shares, at)}
            keep = np.flatnonzero(np.logical_and.reduce([self.allowed[a][c] for a, c in self.seeds.items()]))
            self.seeds = {a: c[keep] for a, c in self.seeds.items()}

    def matches(self) -> Iterator[pa.RecordBatch]:
        spec, cols = self.spec, self.seeds
        for left, op, right in spec["filters"]:
            keep = np.flatnonzero(_OPS[op](cols[left], cols[right]))
            cols = {a: c[keep] for a, c in cols.items()}
        if spec["count"]:
            n = sum(len(next(iter(c.values()))) for c in self._found(cols))
            yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], ["n"])
            return
        held, rows = [], 0
        for found in self._found(cols):
            held.append(found)
            rows += len(found[spec["out"][0]])
            if rows >= 1 << 17:
                yield self._batch(held)
                held, rows = [], 0
        if rows:
            yield self._batch(held)

    def _output(self, attr: str, numbers: np.ndarray) -> np.ndarray:
        return self.values[numbers]

    def _batch(self, found: list[dict[str, np.ndarray]]) -> pa.RecordBatch:
        out = self.spec["out"]
        cols = [self._output(a, np.concatenate([f[a] for f in found])) for a in out]
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int32() if a == "w" and self.spec.get("signed", True) else pa.int64()) for a, c in zip(out, cols)], list(out))

    def _found(self, cols: dict[str, np.ndarray]) -> Iterator[dict[str, np.ndarray]]:
        found = self._grow(cols, self.spec["stages"])
        for stages in self.spec["groups"]:
            found = self._meet(found, stages)
        return found

    def _meet(self, found: Iterator[dict[str, np.ndarray]], stages: list[tuple]) -> Iterator[dict[str, np.ndarray]]:
        """Rows so far joined with a group's, about a chunk of them at a time."""
        held, rows = [], 0
        for part in found:
            held.append(part)
            rows += len(next(iter(part.values())))
            if rows >= CHUNK:
                yield from self._met(held, stages)
                held, rows = [], 0
        if rows:
            yield from self._met(held, stages)

    def _met(self, held: list[dict[str, np.ndarray]], stages: list[tuple]) -> Iterator[dict[str, np.ndarray]]:
        cols = {a: np.concatenate([p[a] for p in held]) for a in held[0]}
        lead = self.spec["head"][0]
        top, rank = np.unique(cols[lead], return_inverse=True)
        levels = {}
        for attr in (s[0] for s in stages if s[0] in cols):  # rows so far, numbered by more and more of the shared attributes
            codes, numbers = np.unique(rank.astype(np.int64) * len(self.values) + cols[attr], return_inverse=True)
            levels[attr], rank = _Lists(codes, len(self.values), False), numbers
        order, count = np.argsort(rank, kind="stable"), np.bincount(rank)
        start = np.cumsum(count) - count
        for part in self._grow({lead: top, _RANK: np.arange(len(top))}, stages, levels):
            at = part.pop(_RANK)
            ends = np.cumsum(count[at])
            cuts = np.searchsorted(ends, np.arange(CHUNK, ends[-1] if len(ends) else 0, CHUNK))
            for lo, hi in zip([0, *cuts], [*cuts, len(at)]):
                n = count[at[lo:hi]]
                row = np.repeat(np.arange(lo, hi), n)
                other = order[np.arange(len(row)) + np.repeat(start[at[lo:hi]] - (np.cumsum(n) - n), n)]
                if len(row):
                    yield {**{a: c[row] for a, c in part.items()}, **{a: c[other] for a, c in cols.items()}}

    def _grow(self, cols: dict[str, np.ndarray], stages: list[tuple], levels: dict[str, _Lists] | None = None) -> Iterator[dict[str, np.ndarray]]:
        if not stages:
            yield cols
            return
        attr, uses, filters = stages[0]
        counts = np.stack([self.lists[kind].count_of(cols[key]) for kind, key in uses])
        best, least = (np.zeros(counts.shape[1], int), counts[0]) if self.spec["first"] else (counts.argmin(0), counts.min(0))
        ends = np.cumsum(least)
        cuts = np.searchsorted(ends, np.arange(CHUNK, ends[-1] if len(ends) else 0, CHUNK))
        for lo, hi in zip([0, *cuts], [*cuts, len(least)]):
            pieces = []
            for i, (kind, key) in enumerate(uses):
                rows = lo + np.flatnonzero((best[lo:hi] == i) & (least[lo:hi] > 0))
                if not len(rows):
                    continue
                n = least[rows]
                row = np.repeat(rows, n)
                value = self.lists[kind].flat[np.arange(len(row)) + np.repeat(self.lists[kind].start[cols[key][rows]] - (np.cumsum(n) - n), n)]
                if attr in self.allowed:
                    keep = np.flatnonzero(self.allowed[attr][value])
                    row, value = row[keep], value[keep]
                for left, op, right in filters:
                    keep = np.flatnonzero(_OPS[op](*(value if a == attr else cols[a][row] for a in (left, right))))
                    row, value = row[keep], value[keep]
                for j, (other, by) in enumerate(uses):
                    if j != i:
                        keep = self.lists[other].holds(cols[by][row], value)
                        row, value = row[keep], value[keep]
                if len(row):
                    pieces.append((row, value))
            if pieces:
                row, value = (np.concatenate(p) for p in zip(*pieces))
                more = {}
                if levels and attr in levels:
                    keep, more[_RANK] = levels[attr].find(cols[_RANK][row], value)
                    row, value = row[keep], value[keep]
                yield from self._grow({**{a: c[row] for a, c in cols.items()}, attr: value, **more}, stages[1:], levels)


class _Mapped(_Range):
    """Seeds or prefixes by numbers, over the stored lists."""

    def __init__(self, cols: list[np.ndarray], indices: tuple, spec: dict) -> None:
        self.spec, (self.lists, self.values) = spec, indices
        self.seeds = dict(zip((*spec["head"], *(["w"] if spec["signed"] else [])), cols))
        self.allowed = {}

    def _output(self, attr: str, numbers: np.ndarray) -> np.ndarray:
        return numbers if attr == "w" and self.spec["signed"] else self.values[numbers]


class _Cliques(_Mapped):
    """Cliques of the first vertices' neighbourhoods: members and the tail of those that go on, which one of the tail cuts by its own row."""

    def matches(self) -> Iterator[pa.RecordBatch]:
        x, y = (self.seeds[a] for a in self.spec["head"])
        found = list(self._grow({**self.seeds, _RANK: np.arange(len(x))}, self.spec["stages"]))
        if not found:
            return
        n = len(self.values)
        self.codes = np.sort(np.concatenate([f[_RANK] for f in found]) * n + np.concatenate([f[self.spec["stages"][0][0]] for f in found]))
        row, self.flat = np.divmod(self.codes, n)
        self.pair, self.count = x * n + y, np.bincount(row, minlength=len(x))
        self.start = np.cumsum(self.count) - self.count
        some = np.flatnonzero(self.count)
        yield from self._cut([x[some], y[some]], self.count[some], self.flat)

    def _cut(self, members: list[np.ndarray], count: np.ndarray, tail: np.ndarray) -> Iterator[pa.RecordBatch]:
        k, compact = self.spec["cliques"]
        if len(members) == k - 1:
            cols = [pa.array(self.values[m if compact else np.repeat(m, count)]) for m in members]
            last = pa.array(self.values[tail])
            if compact:
                last = pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(count)), pa.int32()), last)
            yield pa.RecordBatch.from_arrays([*cols, last], [*self.spec["out"][: k - 1], "tail" if compact else self.spec["out"][k - 1]])
            return
        n, prefix = len(self.values), np.repeat(np.arange(len(count)), count)
        start, codes = np.cumsum(count) - count, prefix * n + tail
        row = np.searchsorted(self.pair, members[0][prefix] * n + tail)
        mine, theirs = count[prefix], self.count[row]
        ends = np.cumsum(np.minimum(mine, theirs))
        cuts = np.searchsorted(ends, np.arange(CHUNK, ends[-1] if len(ends) else 0, CHUNK))
        for lo, hi in zip([0, *cuts], [*cuts, len(tail)]):
            at, own = np.arange(lo, hi), theirs[lo:hi] <= mine[lo:hi]
            entries, values = [], []
            for some, size, first, flat, other, by in ((at[own], theirs, self.start[row], self.flat, codes, prefix), (at[~own], mine, start[prefix], tail, self.codes, row)):
                m = size[some]
                entry = np.repeat(some, m)
                if len(entry):
                    value = flat[np.arange(len(entry)) + np.repeat(first[some] - (np.cumsum(m) - m), m)]
                    code = by[entry] * n + value
                    there = other[np.minimum(np.searchsorted(other, code), len(other) - 1)] == code
                    entries.append(entry[there])
                    values.append(value[there])
            if entries:
                entry, value = np.concatenate(entries), np.concatenate(values)
                order = np.argsort(entry, kind="stable")
                each = np.bincount(entry - lo, minlength=hi - lo)
                some = np.flatnonzero(each)
                if len(some):
                    yield from self._cut([*(m[prefix[some + lo]] for m in members), tail[some + lo]], each[some], value[order])


def _changed(lo: int, hi: int, indices: tuple, spec: dict) -> Iterator[pa.RecordBatch]:
    """Matches of the first values ``lo`` to ``hi`` that one of two versions has; some seeds of both at a time."""
    lists = [indices[0][seed] for _, seed in spec["versions"]]
    rows = sum(v.end[lo:hi] - v.start[lo:hi] for v in lists)
    ends = np.cumsum(rows)
    step = max(1, RANGE_ROWS // 8)
    cuts = np.unique(np.searchsorted(ends, np.arange(step, ends[-1] if len(ends) else 0, step))).tolist()
    for i, j in zip([0, *cuts], [*cuts, hi - lo]):
        sides = []
        for (stages, _), own in zip(spec["versions"], lists):
            part = _Mapped(_seeds_of(own, lo + i, lo + j), indices, spec)
            cols = part.seeds
            for left, op, right in spec["filters"]:
                keep = np.flatnonzero(_OPS[op](cols[left], cols[right]))
                cols = {a: c[keep] for a, c in cols.items()}
            found = list(part._grow(cols, stages))
            sides.append([np.concatenate([f[a] for f in found]) if found else np.zeros(0, np.int64) for a in spec["out"]])
        w = np.repeat(np.array([-1, 1], np.int32), [len(s[0]) for s in sides])
        cols = [np.concatenate(c) for c in zip(*sides)]
        order = np.lexsort(cols[::-1])
        cols, w = [c[order] for c in cols], w[order]
        same = np.logical_and.reduce([c[1:] == c[:-1] for c in cols])
        keep = np.flatnonzero(~(np.append(same, False) | np.append(False, same))) if len(w) else []
        if len(keep):
            yield pa.RecordBatch.from_arrays([*(pa.array(indices[1][c[keep]]) for c in cols), pa.array(w[keep])], [*spec["out"], "w"])
