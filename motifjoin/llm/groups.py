"""Groups of candidates to components of similar members: exact, whatever the size of a group.

A group's members are compared as sets by a breadth-first walk that never compares two
members that are connected already. Groups beyond ``2 * GROUP_ROWS`` members are dealt in
parts; every part is walked together with the same few pivots of its group. A group of
copies, whose members are all like the pivots, is one class after that, and its work
grows with its members and not with their pairs. What is left are the classes of a group
that no link joins yet: their parts meet in pairs, as rows of part numbers that Spark
joins with the members, so that no task holds more than two parts. Union-find joins all
links.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifjoin.components import connected_components
from motifjoin.workspace import materialize

#: Members of a part of a large group; pivots of a large group; members that are compared set by set.
GROUP_ROWS, PIVOTS, FEW_ROWS = 1024, 16, 24
#: Columns of dealt groups: a sorted blob of members; a large group's number, null for whole groups.
DEALT = "members binary, gid long"
#: Bits of a map of keys, and of one of its pages as ``bitmap_construct_agg`` makes them.
MAP_BITS, PAGE_BITS = 1 << 26, 1 << 15

Cut = Callable[[str, int], set]


def parts_of(members: np.ndarray) -> Iterator[tuple[bytes, int | None]]:
    """A group's sorted distinct members as rows of ``DEALT``; equal groups get one number."""
    if len(members) <= 2 * GROUP_ROWS:
        if len(members) > 1:
            yield members.tobytes(), None
        return
    pivots, gid = members[:PIVOTS], int(np.uint64(xxhash.xxh64_intdigest(members.tobytes(), 9)).view(np.int64))
    for k in range(PIVOTS, len(members), GROUP_ROWS):
        yield np.concatenate([pivots, members[k : k + GROUP_ROWS]]).tobytes(), gid


def members_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Groups to rows; ``lead`` is what a group is dealt by: its first line, or a large group's own number."""
    for batch in batches:
        arrays = [np.frombuffer(x.as_py(), np.int64) for x in batch.column(0)]
        sizes = [len(a) for a in arrays]
        ids = np.array([xxhash.xxh64_intdigest(a.tobytes(), 5) for a in arrays], np.uint64).view(np.int64)
        leads = np.array([a[0] if len(a) <= FEW_ROWS else g for a, g in zip(arrays, ids)], np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(leads, sizes)), pa.array(np.repeat(ids, sizes)), pa.array(np.concatenate(arrays) if arrays else np.zeros(0, np.int64))], ["lead", "grp", "h"])


def similar_links(lines: list[str], width: int, similarity: float, cut: Cut) -> list[tuple[int, int]]:
    """A spanning forest of the pairs of lines whose shingle sets have that Jaccard similarity.

    Breadth-first over links; every line is compared with those not reached so far, so
    connected lines are never compared again: set against set in a few lines, through an
    index from shingles to lines in many.
    """
    if len(lines) <= FEW_ROWS:
        sets, open_, out = [cut(x, width) for x in lines], list(range(len(lines))), []
        while open_:
            queue = [open_.pop(0)]
            while queue and open_:
                x = queue.pop()
                hit = []
                for y in open_:
                    n, m = len(sets[x]), len(sets[y])
                    if min(n, m) >= similarity * max(n, m) - 1e-9 and (both := len(sets[x] & sets[y])) >= similarity * (n + m - both) - 1e-9:
                        hit.append(y)
                open_ = [y for y in open_ if y not in hit]
                out += [(x, y) for y in hit]
                queue += hit
        return out
    number: dict = {}
    rows = [np.array([number.setdefault(g, len(number)) for g in cut(x, width)], np.int32) for x in lines]
    size = np.array([len(r) for r in rows])
    code, owner = np.concatenate(rows), np.repeat(np.arange(len(lines), dtype=np.int32), size)
    n_codes = len(number)
    del number

    def index(open_: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        keep = open_[owner]
        order = np.argsort(code[keep], kind="stable")
        return owner[keep][order], np.searchsorted(code[keep][order], np.arange(n_codes + 1))

    open_ = np.ones(len(lines), bool)
    by, cuts = index(open_)
    indexed, out = len(lines), []
    for root in range(len(lines)):
        if not open_[root]:
            continue
        open_[root] = False
        queue = [root]
        while queue and open_.any():
            x = queue.pop()
            if open_.sum() < indexed // 2:
                by, cuts = index(open_)
                indexed = int(open_.sum())
            shared = np.bincount(np.concatenate([by[cuts[c] : cuts[c + 1]] for c in rows[x]]), minlength=len(lines))
            hit = np.flatnonzero(open_ & (shared > 0) & (shared >= similarity * (size + size[x] - shared) - 1e-9))
            open_[hit] = False
            out += [(x, int(y)) for y in hit]
            queue += hit.tolist()
    return out


def verify(batches: Iterator[pa.RecordBatch], width: int, similarity: float, cut: Cut) -> Iterator[pa.RecordBatch]:
    """Links of every group; the rows of a group follow each other, those of small groups with one first line too.

    A line is in one group per band, so small groups with one first line are few: their
    shingle sets are kept and pairs that are connected already are not compared.
    """
    lead_now, group, members = None, None, []
    sets: dict[int, set] = {}
    parent: dict[int, int] = {}
    u, v = [], []

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = x = parent[parent[x]]
        return x

    def settle() -> None:
        if 1 < len(members) <= FEW_ROWS:
            for i, (x, line) in enumerate(members):
                for y, other in members[:i]:
                    if (p := root(x)) == (q := root(y)):
                        continue
                    a = sets.get(x) or sets.setdefault(x, cut(line, width))
                    b = sets.get(y) or sets.setdefault(y, cut(other, width))
                    if min(len(a), len(b)) >= similarity * max(len(a), len(b)) - 1e-9 and (both := len(a & b)) >= similarity * (len(a) + len(b) - both) - 1e-9:
                        parent[p] = q
                        u.append(x)
                        v.append(y)
        elif members:
            members.sort()
            for x, y in similar_links([line for _, line in members], width, similarity, cut):
                u.append(members[x][0])
                v.append(members[y][0])
        members.clear()

    for batch in batches:
        for lead, grp, h, line in zip(*(c.to_pylist() for c in batch.columns)):
            if grp != group or lead != lead_now:
                settle()
                group = grp
                if lead != lead_now:
                    lead_now = lead
                    sets.clear()
                    parent.clear()
            members.append((h, line))
        yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])
        u.clear()
        v.clear()
    settle()
    yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])


def links_of(members: DataFrame, texts: DataFrame, width: int, similarity: float, cut: Cut) -> DataFrame:
    """``members(lead, grp, h)`` and ``texts(h, text)`` to links ``(u, v)`` that span every group's components."""
    rows = members.join(texts, "h").select("lead", "grp", "h", "text").repartition(F.col("lead")).sortWithinPartitions("lead", "grp")
    return rows.mapInArrow(lambda it: verify(it, width, similarity, cut), "u long, v long")


def left_to_compare(dealt: DataFrame, roots: DataFrame) -> DataFrame:
    """``(lead, grp, h)``: pairs of parts of the large groups in which more than one class is left.

    A class beyond ``GROUP_ROWS`` members is dealt in parts of its own, smaller ones share parts.
    """
    lines = dealt.filter("gid is not null").mapInArrow(_of_large, "gid long, h long").distinct()
    classed = lines.join(roots.withColumnRenamed("node", "h"), "h", "left").select("gid", "h", F.coalesce("root", "h").alias("c"))
    sizes = classed.groupBy("gid", "c").agg(F.count(F.lit(1)).alias("n"))
    small = F.col("n") <= GROUP_ROWS
    totals = sizes.groupBy("gid").agg(F.count(F.lit(1)).alias("classes"), F.sum(F.when(small, F.col("n")).otherwise(0)).alias("few")).filter("classes > 1")
    many = sizes.join(totals, "gid").select("gid", "c", F.when(~small, F.col("c")).alias("own"), F.ceil(F.when(small, F.col("few")).otherwise(F.col("n")) / GROUP_ROWS).alias("parts"))
    spread = F.pmod(F.xxhash64(F.when(F.col("own").isNull(), F.col("c")).otherwise(F.col("h"))), F.col("parts"))
    placed = materialize(classed.join(many, ["gid", "c"]).select("gid", "h", "own", spread.alias("part")), "left")
    parts = placed.select("gid", "own", "part").distinct()
    a, b = (parts.select("gid", F.col("own").alias(f"own_{x}"), F.col("part").alias(f"part_{x}")) for x in "ab")
    order = lambda x: F.struct(F.coalesce(f"own_{x}", F.lit(0)), F.col(f"own_{x}").isNull(), F.col(f"part_{x}"))
    apart = F.col("own_a").isNull() | F.col("own_b").isNull() | (F.col("own_a") != F.col("own_b"))  # a class of its own is connected
    pairs = a.join(b, "gid").filter((order("a") <= order("b")) & apart)
    pairs = pairs.withColumn("grp", F.xxhash64("gid", "own_a", "part_a", "own_b", "part_b"))
    sides = pairs.select("gid", "grp", F.explode(F.array(*(F.struct(F.col(f"own_{x}").alias("own"), F.col(f"part_{x}").alias("part")) for x in "ab"))).alias("side")).select("gid", "grp", "side.*").distinct()
    met = placed.join(sides, (placed["gid"] == sides["gid"]) & placed["own"].eqNullSafe(sides["own"]) & (placed["part"] == sides["part"]))
    return met.select(F.col("grp").alias("lead"), "grp", "h")


def _of_large(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        arrays = [np.frombuffer(x.as_py(), np.int64) for x in batch.column("members")]
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(batch.column("gid").to_numpy(zero_copy_only=False).astype(np.int64), [len(a) for a in arrays])), pa.array(np.concatenate(arrays) if arrays else np.zeros(0, np.int64))], ["gid", "h"])


def similar_roots(dealt: DataFrame, texts: Callable[[DataFrame], DataFrame], width: int, similarity: float, cut: Cut) -> DataFrame:
    """``dealt`` groups to ``(node, root)`` of members with a link; ``texts`` gives ``(h, text)`` of members ``(lead, grp, h)``."""
    dealt = materialize(dealt.distinct(), "groups")
    members = dealt.select("members").mapInArrow(members_of, "lead long, grp long, h long")
    known = texts(members)
    links = links_of(members, known, width, similarity, cut)
    if dealt.filter("gid is not null").limit(1).count() == 0:
        return connected_components(links)
    links = materialize(links, "links")
    rest = materialize(left_to_compare(dealt, materialize(connected_components(links), "roots")), "rest")
    return connected_components(links.unionByName(links_of(rest, known, width, similarity, cut)))


def deal_rows(rows: DataFrame, part_size: int) -> DataFrame:
    """``rows(g, h, size)``, each ``h`` in one group ``g``, to ``DEALT``; a part holds about ``part_size`` in sizes at most.

    Members are dealt to parts by hash, so that no group is gathered anywhere.
    """
    totals = rows.groupBy("g").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("all")).filter("n > 1")
    fits = (F.col("n") <= 2 * GROUP_ROWS) & (F.col("all") <= part_size)
    parts = F.when(fits, 1).otherwise(F.greatest(F.ceil(F.col("n") / GROUP_ROWS), F.least("n", F.ceil(F.col("all") / part_size))))
    dealt = rows.join(totals.select("g", parts.alias("parts")), "g").withColumn("part", F.pmod(F.xxhash64("h"), F.col("parts")))
    held = dealt.groupBy("g", "part", "parts").agg(F.array_sort(F.collect_list("h")).alias("hs"), F.min("h").alias("least"))
    first = F.slice(F.array_sort(F.collect_list("least")), 1, PIVOTS).alias("pivots")
    pivots = held.filter("parts > 1").groupBy("g").agg(first)
    whole = held.join(pivots, "g", "left").select(F.array_sort(F.array_union("hs", F.coalesce("pivots", F.expr("array()").cast("array<bigint>")))).alias("hs"), F.when(F.col("parts") > 1, F.col("g")).alias("gid"))
    return whole.mapInArrow(_blobs, DEALT)


def _blobs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        yield pa.RecordBatch.from_arrays([pa.array([np.array(x.as_py(), np.int64).tobytes() for x in batch.column("hs")], pa.binary()), batch.column("gid")], ["members", "gid"])


def marked(rows: DataFrame, keys: DataFrame, column: str, name: str) -> DataFrame:
    """``rows`` with a boolean ``name``: false where ``column`` is surely none of ``keys``' values.

    What goes to the tasks is a map of ``MAP_BITS`` bits (8 MB), however many keys there are; where it
    fills up, more rows are marked that need not be, and none is missed.
    """
    at = F.pmod(F.xxhash64(column), F.lit(MAP_BITS))
    page, bit = F.floor(at / PAGE_BITS), at % PAGE_BITS
    held = keys.select(page.alias("__page"), bit.alias("__bit")).groupBy("__page").agg(F.expr("bitmap_construct_agg(__bit)").alias("__bits"))
    byte = F.conv(F.hex(F.substring(F.col("__bits"), (F.floor(bit / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    on = F.col(name) % 2 == 1
    told = rows.join(F.broadcast(held), page == F.col("__page"), "left").withColumn(name, F.floor(byte / F.pow(F.lit(2), bit % 8)))
    return told.withColumn(name, F.coalesce(on, F.lit(False))).drop("__page", "__bits")
