"""SimHash near-duplicates: tiled exact comparison of fingerprints.

Every distinct fingerprint is compared with every other one by numpy
exclusive-or and bit counts, tile against tile. Fingerprints are ordered by
their population count and the counts of their four 16-bit words, so a tile is
a small box in that space; two fingerprints within the radius cannot differ by
more than the radius in the sum of word counts, so tile pairs whose boxes lie
farther apart are skipped, and inside a pair the same holds for sub-tiles.
A pair of tiles returns a spanning forest of its links, never all pairs, and
distributed union-find joins the forests.

Equal fingerprints are one node from the start: a group of copies is one row
after a partial minimum in every task.

Defined results: null text has no words, as an empty one; texts without words
share the fingerprint zero and link as any others do; null ``doc_id`` rows get
fingerprints and components but never name one, and a component of nulls only
is named null; repeated rows are documents of the same component.

``similar_documents`` and ``one_of_each`` link documents by the Jaccard similarity of
their sets of shingles: the same tiled comparison, of 192-bit fingerprints and with a
radius wide enough for that similarity, proposes candidates, and an exact comparison of
the sets decides (``groups``). Two sets of similarity s differ in a bit with probability
acos(2s / (1 + s)) / pi, so pairs of 0.8 differ in 29 of 192 bits on average, and in more
than 54 with probability below 10^-6 (10^-3 for sets of four or five shingles); random
sets are that near with probability 10^-9. Tile pairs whose sets differ too much
in size or whose population counts differ beyond the radius are skipped. Texts without
words are one document there, which is like no other; equal sets are one node.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifjoin.components import connected_components
from motifjoin.llm import groups
from motifjoin.llm.substring import _mixed
from motifjoin.workspace import materialize

#: What separates words, the hash seed.
SPACES, SEED = b" \t\n\x0b\x0c\r", 42
#: Fingerprints in a tile and in a sub-tile; hashes expanded to bits at a time.
TILE_ROWS, SUB_ROWS, BIT_ROWS = 16384, 128, 1 << 16
#: Words of a shingle and the similarity of near-duplicate documents; 64-bit words of their fingerprints and bits that candidates may differ in; shingles of a part of a group.
SET_WIDTH, SIMILARITY, SET_WORDS, SET_RADIUS, PART_SHINGLES = 5, 0.8, 3, 54, 1 << 21
_UPPER = bytes(range(65, 91))
_LOWER_TABLE = bytes.maketrans(_UPPER, _UPPER.lower())
_SPLIT = re.compile(rb"[^\x20\x09-\x0D]+")


def shingle_hashes(text: str | None, width: int) -> np.ndarray:
    """XXH64 of every word shingle of a lower-cased (A-Z) text."""
    words = _SPLIT.findall((text or "").encode("utf-8", "surrogatepass").translate(_LOWER_TABLE))
    if not words:
        return np.zeros(0, np.uint64)
    h = xxhash.xxh64_intdigest
    if len(words) <= width:
        return np.array([h(b" ".join(words), SEED)], np.uint64)
    joined, ends = b" ".join(words), np.cumsum([len(w) + 1 for w in words]).tolist()
    return np.fromiter((h(joined[a : b - 1], SEED) for a, b in zip([0, *ends], ends[width - 1 :])), np.uint64, len(words) - width + 1)


def fingerprint(hashes: np.ndarray) -> int:
    """Bits set in more than half of the hashes."""
    if not len(hashes):
        return 0
    ones = np.zeros(64, np.int64)
    for k in range(0, len(hashes), BIT_ROWS):
        bits = np.unpackbits(hashes[k : k + BIT_ROWS].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
        for j in range(0, len(bits), 255):  # sums of up to 255 bits fit in a byte
            ones += np.add.reduce(bits[j : j + 255], axis=0, dtype=np.uint8)
    return int.from_bytes(np.packbits(2 * ones > len(hashes)).tobytes(), "big")


def _fingerprints(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        fps = np.fromiter((fingerprint(shingle_hashes(t.as_py(), width)) for t in batch.column("text")), np.uint64, batch.num_rows)
        yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(batch.num_columns - 1)), pa.array(fps.view(np.int64))], [*batch.schema.names[:-1], "fp"])


def fingerprints(docs: DataFrame, width: int = 3, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns and ``fp``, a 64-bit fingerprint as a signed long."""
    rows = docs.select(*keep, "text")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])
    return rows.mapInArrow(lambda it: _fingerprints(it, width), f"{schema}, fp long")


def word_counts(fps: np.ndarray) -> np.ndarray:
    """Population counts of the four 16-bit words of each fingerprint."""
    return np.bitwise_count(np.ascontiguousarray(fps).view(np.uint16).reshape(-1, 4)).astype(np.int16)


def _boxes(counts: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return np.minimum.reduceat(counts, starts), np.maximum.reduceat(counts, starts)


def _tiles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    got = [b.column(0).to_numpy() for b in batches]
    fps = np.concatenate(got).view(np.uint64) if got else np.zeros(0, np.uint64)
    if len(fps):
        counts = word_counts(fps)
        order = np.lexsort((*counts.T[::-1], counts.sum(1)))
        fps, counts = fps[order], counts[order]
        low, high = counts.min(0).tolist(), counts.max(0).tolist()
        total = counts.sum(1)
        tile = TaskContext.get().partitionId()
        yield pa.RecordBatch.from_arrays([pa.array([x]) for x in (tile, int(total.min()), int(total.max()))] + [pa.array([low], pa.list_(pa.int64())), pa.array([high], pa.list_(pa.int64())), pa.array([fps.tobytes()], pa.binary())], ["tile", "p_low", "p_high", "low", "high", "fps"])


def merge_labels(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Union-find on arrays: join the classes of a[i] and b[i], labels fall to the smallest."""
    while True:
        x, y = label[a], label[b]
        while True:  # follow labels to their roots
            x2, y2 = label[x], label[y]
            if (x2 == x).all() and (y2 == y).all():
                break
            x, y = x2, y2
        apart = x != y
        if not apart.any():
            return
        np.minimum.at(label, np.maximum(x, y)[apart], np.minimum(x, y)[apart])
        a, b = a[apart], b[apart]


def links_between(a: np.ndarray, b: np.ndarray, radius: int, same: bool) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the links between two tiles, as pairs of fingerprints."""
    both = a if same else np.concatenate([a, b])
    label, shift = np.arange(len(both)), 0 if same else len(a)
    ca, cb = word_counts(a), word_counts(b)
    sa, sb = np.arange(0, len(a), SUB_ROWS), np.arange(0, len(b), SUB_ROWS)
    (la, ha), (lb, hb) = _boxes(ca, sa), _boxes(cb, sb)
    gap = np.maximum(0, np.maximum(la[:, None] - hb[None], lb[None] - ha[:, None])).sum(2)
    near = gap <= radius
    if same:
        near &= np.arange(len(sa))[:, None] <= np.arange(len(sb))[None]
    for i in np.flatnonzero(near.any(1)):
        rows = a[sa[i] : sa[i] + SUB_ROWS]
        cols = np.concatenate([np.arange(sb[j], min(sb[j] + SUB_ROWS, len(b))) for j in np.flatnonzero(near[i])])
        x, y = np.nonzero(np.bitwise_count(rows[:, None] ^ b[cols][None]) <= radius)
        x, y = x + sa[i], cols[y] + shift
        keep = x != y
        if keep.any():
            merge_labels(label, x[keep], y[keep])
    while (label[label] != label).any():
        label = label[label]
    leaf = np.flatnonzero(label != np.arange(len(label)))
    return both[leaf], both[label[leaf]]


def _compare(batches: Iterator[pa.RecordBatch], radius: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for k in range(batch.num_rows):
            a, b = (np.frombuffer(batch.column(c)[k].as_py(), np.uint64) for c in ("fps_a", "fps_b"))
            u, v = links_between(a, b, radius, batch.column("a")[k].as_py() == batch.column("b")[k].as_py())
            yield pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(v.view(np.int64))], ["u", "v"])


def fingerprint_links(fps: DataFrame, radius: int = 2, tile_rows: int = TILE_ROWS) -> DataFrame:
    """Distinct ``fp`` rows to ``(u, v)``: links that span every group within the radius."""
    word = [F.bit_count(F.shiftrightunsigned("fp", 16 * k).bitwiseAND(F.lit(65535))).cast("int") for k in range(4)]
    n = fps.count()
    dealt = fps.repartitionByRange(max(1, -(-n // tile_rows)), sum(word[1:], word[0]), *word, F.col("fp"))
    tiles = materialize(dealt.mapInArrow(_tiles, "tile long, p_low long, p_high long, low array<long>, high array<long>, fps binary"), "tiles")
    box = tiles.drop("fps")
    left = box.select(F.col("tile").alias("a"), F.col("low").alias("la"), F.col("high").alias("ha"), F.explode(F.sequence(F.col("p_low") - radius, F.col("p_high") + radius)).alias("p"))
    right = box.select(F.col("tile").alias("b"), F.col("low").alias("lb"), F.col("high").alias("hb"), F.explode(F.sequence("p_low", "p_high")).alias("p"))
    gap = F.aggregate(F.zip_with(F.arrays_zip(F.col("la").alias("l"), F.col("ha").alias("h")), F.arrays_zip(F.col("lb").alias("l"), F.col("hb").alias("h")), lambda x, y: F.greatest(F.lit(0).cast("long"), x["l"] - y["h"], y["l"] - x["h"])), F.lit(0).cast("long"), lambda s, x: s + x)
    met = left.join(right, "p").filter((F.col("a") <= F.col("b")) & (gap <= radius)).select("a", "b").distinct()
    sides = [tiles.select(F.col("tile").alias(s), F.col("fps").alias(f"fps_{s}")) for s in "ab"]
    return met.join(sides[0], "a").join(sides[1], "b").mapInArrow(lambda it: _compare(it, radius), "u long, v long")


def near_duplicates(docs: DataFrame, width: int = 3, radius: int = 2) -> DataFrame:
    """``(doc_id, fp, component_id)``; component_id is the smallest doc_id that links reach."""
    prints = materialize(fingerprints(docs, width), "fps")
    nodes = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), "nodes")
    roots = connected_components(fingerprint_links(nodes.select("fp"), radius)).withColumnRenamed("node", "fp")
    named = nodes.join(roots, "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), "least")
    least = named.groupBy("root").agg(F.min("least").alias("component_id"))
    by_fp = named.select("fp", "root").join(least, "root").select("fp", "component_id")
    return prints.join(by_fp, "fp").select("doc_id", "fp", "component_id")


def fp_hex(fp: str):
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def shingle_set(text: str | None, width: int) -> np.ndarray:
    """Distinct shingle hashes, ascending."""
    return np.unique(shingle_hashes(text, width))


def wide_fingerprint(hashes: np.ndarray) -> tuple[int, ...]:
    """The fingerprints of the hashes and of the hashes mixed once more and again."""
    return fingerprint(hashes), *(fingerprint(_mixed(hashes ^ np.uint64(k * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF))) for k in range(1, SET_WORDS))


_WORDS = [f"w{k}" for k in range(SET_WORDS)]
_NODE = [("node", pa.int64()), ("size", pa.int32()), *((w, pa.int64()) for w in _WORDS)]


def _set_nodes(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    """Beside the first column, of documents: a name of the text's set, its size, its fingerprint."""
    for batch in batches:
        made, doc = [], batch.column(0)
        for text in doc.field(doc.type.get_field_index("text")):
            hashes = shingle_set(text.as_py(), width)
            made.append((xxhash.xxh64_intdigest(hashes.tobytes(), 7), len(hashes), *wide_fingerprint(hashes)))
        cols = [pa.array(np.array([m[k] for m in made], np.uint64).astype(t.to_pandas_dtype()), t) for k, (_, t) in enumerate(_NODE)]
        yield pa.RecordBatch.from_arrays([*batch.columns, *cols], [*batch.schema.names, *(n for n, _ in _NODE)])


def _set_tiles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    got = [[c.to_numpy() for c in b.columns] for b in batches]
    if got:
        node, size, *words = (np.concatenate(c) for c in zip(*got))
        order = np.lexsort((node, size))
        node, size, words = node[order], size[order], np.column_stack(words)[order]
        total = word_counts(words.view(np.uint64)).reshape(len(node), -1).sum(1)
        row = [TaskContext.get().partitionId(), int(size[0]), int(size[-1]), int(total.min()), int(total.max())]
        blobs = [x.tobytes() for x in (node, size.astype("<i4"), words)]
        yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in row] + [pa.array([b], pa.binary()) for b in blobs], ["tile", "s_low", "s_high", "p_low", "p_high", "nodes", "sizes", "words"])


_SET_TILE = "tile long, s_low long, s_high long, p_low long, p_high long, nodes binary, sizes binary, words binary"


def set_links_between(a: tuple, b: tuple, radius: int, similarity: float, same: bool) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the candidates between two tiles of ``(nodes, sizes, words)`` in order of size, as pairs of nodes."""
    (na, za, wa), (nb, zb, wb) = a, b
    both, shift = (na, 0) if same else (np.concatenate([na, nb]), len(na))
    label = np.arange(len(both))
    for at in range(0, len(na), SUB_ROWS):
        rows, sizes = wa[at : at + SUB_ROWS], za[at : at + SUB_ROWS]
        low, high = np.searchsorted(zb, sizes[0] * similarity - 1e-6), np.searchsorted(zb, sizes[-1] / similarity + 1e-6, "right")
        low = max(low, at) if same else low
        if low < high:
            apart = sum(np.bitwise_count(rows[:, None, k] ^ wb[None, low:high, k]) for k in range(wb.shape[1]))
            x, y = np.nonzero(apart <= radius)
            x, y = x + at, y + low + shift
            other = x != y
            if other.any():
                merge_labels(label, x[other], y[other])
    while (label[label] != label).any():
        label = label[label]
    leaf = np.flatnonzero(label != np.arange(len(label)))
    return both[leaf], both[label[leaf]]


def _compare_sets(batches: Iterator[pa.RecordBatch], radius: int, similarity: float) -> Iterator[pa.RecordBatch]:
    kinds = {"nodes": np.int64, "sizes": np.int32, "words": np.uint64}
    for batch in batches:
        for k in range(batch.num_rows):
            sides = [tuple(np.frombuffer(batch.column(f"{c}_{s}")[k].as_py(), t) for c, t in kinds.items()) for s in "ab"]
            sides = [(n, z, w.reshape(-1, SET_WORDS)) for n, z, w in sides]
            u, v = set_links_between(*sides, radius, similarity, batch.column("a")[k].as_py() == batch.column("b")[k].as_py())
            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], ["u", "v"])


def set_candidates(nodes: DataFrame, radius: int = SET_RADIUS, similarity: float = SIMILARITY, tile_rows: int = TILE_ROWS) -> DataFrame:
    """``nodes(node, size, w0, w1, ..)`` to ``(u, v)``: links that span every group of candidates.

    Sets of fewer than s / (1 - s) shingles are like none but their equals and stay out.
    """
    able = nodes.filter(F.col("size") >= similarity / (1 - similarity) - 1e-9).select("node", "size", *_WORDS)
    n = able.count()
    dealt = able.repartitionByRange(max(1, -(-n // tile_rows)), "size", sum((F.bit_count(w) for w in _WORDS[1:]), F.bit_count(_WORDS[0])), "node")
    tiles = materialize(dealt.mapInArrow(_set_tiles, _SET_TILE), "tiles")
    # sizes by powers of 1 / s: similar sets are in one class or in neighbouring ones
    level = lambda size: F.floor(F.log(F.col(size).cast("double")) / F.log(F.lit(1 / similarity))).cast("long")
    box = tiles.select("tile", "s_low", "s_high", "p_low", "p_high")
    left = box.select(*(F.col(c).alias(f"{c}_a") for c in box.columns), F.explode(F.sequence(level("s_low"), level("s_high") + 1)).alias("level"))
    right = box.select(*(F.col(c).alias(f"{c}_b") for c in box.columns), F.explode(F.sequence(level("s_low"), level("s_high"))).alias("level"))
    near = (F.col("s_high_a") >= F.col("s_low_b") * similarity - 1e-6) & (F.col("p_low_b") - F.col("p_high_a") <= radius) & (F.col("p_low_a") - F.col("p_high_b") <= radius)
    met = left.join(right, "level").filter((F.col("tile_a") <= F.col("tile_b")) & near).select(F.col("tile_a").alias("a"), F.col("tile_b").alias("b")).distinct()
    sides = [tiles.select(F.col("tile").alias(s), *(F.col(c).alias(f"{c}_{s}") for c in ("nodes", "sizes", "words"))) for s in "ab"]
    pairs = met.join(sides[0], "a").join(sides[1], "b").repartition(F.col("a"), F.col("b"))
    return pairs.mapInArrow(lambda it: _compare_sets(it, radius, similarity), "u long, v long")


def _cut(text: str, width: int) -> set[int]:
    return set(shingle_hashes(text, width).tolist())


def _set_components(docs: DataFrame, width: int, similarity: float, radius: int) -> tuple[DataFrame, DataFrame]:
    """``(rows(doc, node, row), nodes(node, root, first))``; ``doc`` is a document's whole row, ``first`` the least of a node's rows."""
    whole = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("doc"))
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in whole.schema.fields)
    made = whole.mapInArrow(lambda it: _set_nodes(it, width), f"{schema}, node long, size int, " + ", ".join(f"{w} long" for w in _WORDS))
    rows = materialize(made.withColumn("row", F.monotonically_increasing_id()), "rows")
    order = F.struct(F.col("doc.doc_id").isNull().alias("none"), F.col("doc.doc_id").alias("doc_id"), F.xxhash64("doc.text").alias("h"), F.col("row"))
    same = lambda c: F.max(c).alias(c)  # equal in all rows of a node
    nodes = materialize(rows.groupBy("node").agg(F.min(order).alias("first"), same("size"), *map(same, _WORDS)), "nodes")
    found = materialize(connected_components(set_candidates(nodes, radius, similarity)), "candidates")
    dealt = groups.deal_rows(found.join(nodes.select("node", "size"), "node").select(F.col("root").alias("g"), F.col("node").alias("h"), "size"), PART_SHINGLES)

    def texts(members: DataFrame) -> DataFrame:
        chosen = materialize(nodes.join(members.select(F.col("h").alias("node")).distinct(), "node").select(F.col("node").alias("h"), F.col("first.row").alias("row")), "chosen")
        near = groups.marked(rows.select("row", F.col("doc.text").alias("text")), chosen, "row", "hit").filter("hit")
        return chosen.join(near, "row").select("h", "text")

    roots = groups.similar_roots(dealt, texts, width, similarity, _cut)
    return rows, nodes.join(roots, "node", "left").select("node", F.coalesce("root", "node").alias("root"), "first")


def similar_documents(docs: DataFrame, width: int = SET_WIDTH, similarity: float = SIMILARITY, radius: int = SET_RADIUS) -> DataFrame:
    """``(doc_id, component_id)``; component_id is the smallest doc_id that links of the similarity reach."""
    rows, nodes = _set_components(docs.select("doc_id", "text"), width, similarity, radius)
    least = nodes.groupBy("root").agg(F.min("first.doc_id").alias("component_id"))
    by_node = nodes.select("node", "root").join(least, "root").select("node", "component_id")
    return rows.select("doc.doc_id", "node").join(by_node, "node").select("doc_id", "component_id")


def one_of_each(docs: DataFrame, width: int = SET_WIDTH, similarity: float = SIMILARITY, radius: int = SET_RADIUS) -> DataFrame:
    """``docs`` with one row of every component: that of the smallest doc_id; null ids come last, ties by text."""
    rows, nodes = _set_components(docs, width, similarity, radius)
    first = materialize(nodes.groupBy("root").agg(F.min("first").alias("first")).select("first.row"), "first")
    lost = rows.select("row").join(first, "row", "left_anti")
    told = groups.marked(rows, lost, "row", "hit")  # only what may be lost has to move
    return told.filter("not hit").select("doc.*").unionByName(told.filter("hit").join(first, "row", "left_semi").select("doc.*"))
