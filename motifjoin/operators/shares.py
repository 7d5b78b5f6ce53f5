"""Balanced rounds over large relations: equal shares of proposals, whose lists are gathered once per share.

A round of ``balanced`` with three changes: proposals are numbered over all prefixes, in
order of their first lookup, so that a share is a contiguous range of numbers and asks for few lists;
lookups travel once per share and are answered by whole lists, not by a row per
candidate; a share is a task, which proposes and filters ``batch`` candidates at a time.
What moves is the prefixes and the lists. No table is sent to all tasks.

For binary relations of long values, as in ``gathered``.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window

from motifjoin.operators import gathered
from motifjoin.operators.extend import MIN_C, MIN_I, init_triples
from motifjoin.operators.gathered import _bounds, _OPS, _packed, _Range, _range_of, _run
from motifjoin.operators.index import IndexCatalog
from motifjoin.plans.stages import Stage
from motifjoin.workspace import drop_stored, materialize

#: Proposals of a share beyond which every worker gets one more.
SHARE = 8_000_000
START, END, _SHARE = "__start", "__end", "__share"


def can_share(prefixes: DataFrame, stages: Sequence[Stage], catalog: IndexCatalog) -> bool:
    """Whether prefixes are longs (and a sign ``w``) and all lookups are by one value of large binary relations."""
    plain = all(f.name == "w" or f.dataType == T.LongType() and f.name in stages[0].bound for f in prefixes.schema.fields) if stages else False
    return plain and gathered.can_gather(stages, catalog)


def dealt(prefixes: DataFrame, stage: Stage, catalog: IndexCatalog, workers: int) -> tuple[DataFrame, int]:
    """``(items, shares)``: prefixes with their proposer, the numbers of its candidates and the share that makes those.

    Shares differ by one proposal at most; a prefix at the border of shares is in both, with other numbers.
    """
    rows = init_triples(prefixes)
    for i, use in enumerate(stage.uses):
        counts = _packed(catalog, use.index_id).rows.select(F.col("k").alias(use.key_attrs[0]), F.size("xs").cast("long").alias("__cnt"))
        smaller = F.col("__cnt") < F.col(MIN_C)
        rows = rows.join(counts.hint("merge"), use.key_attrs[0]).withColumn(MIN_I, F.when(smaller, F.lit(i)).otherwise(F.col(MIN_I))).withColumn(MIN_C, F.least(MIN_C, "__cnt")).drop("__cnt")
    lead = stage.uses[0].key_attrs[0]
    counted = materialize(rows, "counted")
    bounds = _bounds(counted, lead)
    ranged = counted.withColumn("__range", _range_of(F.col(lead), bounds))
    sums = {r["__range"]: r for r in ranged.groupBy("__range").agg(F.sum(MIN_C).alias("all"), F.count(F.lit(1)).alias("n")).collect()}  # a row per range
    total, n = sum(r["all"] for r in sums.values()), sum(r["n"] for r in sums.values())
    if not total:
        return counted.withColumn(START, F.col(MIN_C)).withColumn(END, F.col(MIN_C)).withColumn(_SHARE, F.lit(0)).drop(MIN_C), 0
    shares = workers * max(1, -(-total // (workers * SHARE)), -(-n // (workers * gathered.RANGE_ROWS)))
    base = np.cumsum([0, *(sums[b]["all"] if b in sums else 0 for b in range(len(bounds)))]).tolist()
    order = Window.partitionBy("__range").orderBy(lead, *(c for c in counted.columns if c not in (lead, MIN_C, MIN_I))).rowsBetween(Window.unboundedPreceding, -1)
    at = F.coalesce(F.sum(MIN_C).over(order), F.lit(0)) + F.element_at(F.array(*(F.lit(x).cast("long") for x in base)), F.col("__range") + 1)
    placed = ranged.withColumn("__at", at)
    cut = placed.withColumn(_SHARE, F.explode(F.sequence(F.expr(f"((__at + 1) * {shares} - 1) div {total}"), F.expr(f"((__at + {MIN_C}) * {shares} - 1) div {total}"))))
    bound = lambda share: F.expr(f"({share} * {total}) div {shares}")
    low, high = F.greatest(bound(_SHARE), F.col("__at")), F.least(bound(f"({_SHARE} + 1)"), F.col("__at") + F.col(MIN_C))
    items = cut.withColumn(START, low - F.col("__at") + 1).withColumn(END, high - F.col("__at")).filter(F.col(END) >= F.col(START)).withColumn(_SHARE, F.col(_SHARE).cast("int"))
    stored = materialize(items.drop("__at", "__range", MIN_C), "items")
    drop_stored(counted)
    return stored, shares


def share_stage(prefixes: DataFrame, stage: Stage, catalog: IndexCatalog, workers: int, batch: int | None = None) -> DataFrame:
    """One more attribute for all prefixes; stored, as every round is. ``batch`` bounds the live proposals of a task."""
    items, shares = dealt(prefixes, stage, catalog, workers)
    if not shares:
        return prefixes.withColumn(stage.attr, F.lit(None).cast("long")).filter("false")
    ids = list(dict.fromkeys(u.index_id for u in stage.uses))
    parts = []
    for kind, index_id in enumerate(ids):
        asked = reduce(DataFrame.union, [items.select(F.col(_SHARE).alias("b"), F.col(u.key_attrs[0]).alias("k")) for u in stage.uses if u.index_id == index_id]).distinct()
        parts.append(asked.join(_packed(catalog, index_id).rows.hint("merge"), "k").select("b", F.lit(kind).alias("kind"), "k", F.lit(False).alias("own"), "xs"))
    lead = stage.uses[0].key_attrs[0]
    more = [c for c in prefixes.columns if c != lead] + [MIN_I, START, END]
    parts.append(items.select(F.col(_SHARE).alias("b"), F.lit(-1).alias("kind"), F.col(lead).alias("k"), F.lit(False).alias("own"), F.array(*(F.col(c).cast("long") for c in more)).alias("xs")))
    spec = {
        "head": (lead, *more), "seed": None, "filters": (), "count": False, "first": False, "groups": [], "kinds": len(ids), "batch": batch or gathered.CHUNK,
        "out": tuple(c for c in prefixes.columns if c != "w") + (stage.attr,) + (("w",) if "w" in prefixes.columns else ()),
        "stages": [(stage.attr, [(ids.index(u.index_id), u.key_attrs[0]) for u in stage.uses], stage.filters)],
    }
    sent = reduce(DataFrame.unionByName, parts).repartitionById(shares, F.col("b"))
    found = sent.mapInArrow(lambda it: _run(it, spec, _Share), ", ".join(f"`{a}` {'int' if a == 'w' else 'long'}" for a in spec["out"]))
    stored = materialize(found, "prefixes")
    drop_stored(items)
    prefixes.sparkSession.sparkContext._jvm.System.gc()  # so that Spark lets go of the round's shuffles
    return stored


class _Share(_Range):
    """The items and lists of one share."""

    def _found(self, cols: dict[str, np.ndarray]) -> Iterator[dict[str, np.ndarray]]:
        ((attr, uses, filters),) = self.spec["stages"]
        best, start, end = (self.values[cols.pop(c)] for c in (MIN_I, START, END))
        size, ends = end - start + 1, np.cumsum(end - start + 1)
        for lo in range(0, int(ends[-1]) if len(ends) else 0, self.spec["batch"]):
            hi = min(lo + self.spec["batch"], int(ends[-1]))
            i, j = np.searchsorted(ends, lo, "right"), np.searchsorted(ends, hi, "left") + 1
            before = ends[i:j] - size[i:j]
            n = np.minimum(ends[i:j], hi) - np.maximum(before, lo)
            each = np.repeat(np.arange(i, j), n)
            no = np.arange(len(each)) + np.repeat(np.maximum(lo - before, 0) + start[i:j] - 1 - (np.cumsum(n) - n), n)
            for k, (kind, key) in enumerate(uses):
                mine = np.flatnonzero(best[each] == k)
                row = each[mine]
                value = self.lists[kind].flat[self.lists[kind].start[cols[key][row]] + no[mine]]
                for left, op, right in filters:
                    keep = np.flatnonzero(_OPS[op](*(value if a == attr else cols[a][row] for a in (left, right))))
                    row, value = row[keep], value[keep]
                for other, (index, by) in enumerate(uses):
                    if other != k:
                        keep = self.lists[index].holds(cols[by][row], value)
                        row, value = row[keep], value[keep]
                if len(row):
                    yield {**{a: c[row] for a, c in cols.items()}, attr: value}
