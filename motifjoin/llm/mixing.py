"""Mixing sources to target weights.

Documents of a source, in the order of a keyed hash, form one stream of words,
cut into fixed-length blocks numbered from 0. The mix is a row of slots of one
block each, dealt to output shards; ``packed_blocks`` returns them with their words. Every shard draws multinomial source counts
for its slots; what a source has left over or lacks against its total is settled
in the last draws, so that every source gives exactly its number of slots. The
i-th slot of a source takes block ``perm(i mod n)``, with a keyed permutation of
``0..n-1`` that differs per round ``i div n``, so no block is taken r + 2 times
before all are taken r + 1 times. Slots and blocks are joined by index.

Stream offsets are sums in two levels: within buckets of documents, then over
buckets, so a source that holds most rows is spread over many tasks. All draws
and orders come from keyed hashes: a rerun agrees.

Targets: a source's weight share of all words, at most ``cap`` times what it
has; the excess goes to the others by weight until none is above. Only one row
per source goes to the driver; the number of sources is checked against
``max_sources``.

Defined results: null or wordless text has size 0 and is taken 0 words; null
source is a source, ordered last; null ``doc_id`` is a document; repeated rows
are separate documents; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from motifjoin.workspace import materialize

#: Words of a block, documents of a bucket, slots of an output shard.
BLOCK_WORDS, BUCKET_DOCS, SHARD_SLOTS = 32, 4_000, 65_536
#: Groups of shards that the driver draws for.
MAX_GROUPS = 4096
_ROUNDS = 16


def word_count(text: F.Column) -> F.Column:
    """Number of runs of characters other than space and \\t..\\r."""
    spaced = F.translate(text, "\t\n\x0b\x0c\r", "     ")
    inside = F.regexp_replace(F.trim(spaced), "[^ ]+", "x")
    return F.coalesce(F.length(F.replace(inside, F.lit(" "))), F.lit(0)).cast("long")


def targets(sizes: Sequence[int], weights: Sequence[float], total: float, cap: float) -> list[float]:
    """Shares of ``total`` by weight, none above ``cap`` times its size, excess reshared."""
    got, open_ = [0.0] * len(sizes), [k for k, s in enumerate(sizes) if s > 0 and weights[k] > 0]
    while open_:
        room = total - sum(got)
        by = sum(weights[k] for k in open_)
        over = [k for k in open_ if room * weights[k] / by >= cap * sizes[k]]
        if not over:
            for k in open_:
                got[k] = room * weights[k] / by
            break
        for k in over:
            got[k] = float(cap * sizes[k])
        open_ = [k for k in open_ if k not in over]
    return got


def slot_counts(slots: Sequence[int], shard_slots: int, seed: int) -> list[tuple[int, int, int, int]]:
    """``(shard, source, first slot of the source, slots)``: a multinomial draw per shard.

    Each draw has the shares of what the sources still owe, so the totals come out exactly.
    """
    owed, out = np.array(slots, np.int64), []
    given = np.zeros_like(owed)
    for shard in range(int(-(-owed.sum() // shard_slots))):
        left = int(owed.sum())
        n = min(shard_slots, left)
        rng = np.random.Generator(np.random.Philox(key=[seed, shard]))
        draw = np.minimum(rng.multinomial(n, owed / left), owed)
        while (short := n - int(draw.sum())) > 0:  # a source gave out: draw the rest from the others
            room = owed - draw
            draw = np.minimum(draw + rng.multinomial(short, room / room.sum()), owed)
        out += [(shard, int(k), int(given[k]), int(draw[k])) for k in np.flatnonzero(draw)]
        given, owed = given + draw, owed - draw
    return out


def _spread(x: np.ndarray) -> np.ndarray:
    """A keyed-hash step on 64-bit numbers."""
    for mul in (0xBF58476D1CE4E5B9, 0x94D049BB133111EB):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(mul)
    return x ^ (x >> np.uint64(31))


def permuted(index: np.ndarray, n: int, key: np.ndarray) -> np.ndarray:
    """A keyed permutation of 0..n-1, per element: swap-or-not, exact for every n."""
    i, size = index.astype(np.uint64), np.uint64(n)
    for r in range(1, _ROUNDS + 1):
        round_key = _spread(key + np.uint64(r * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF))
        other = (round_key % size + size - i) % size
        swap = _spread(round_key ^ _spread(np.maximum(i, other) + np.uint64(r))) & np.uint64(1) == 1
        i = np.where(swap, other, i)
    return i.astype(np.int64)


def _draw_shards(batches: Iterator[pa.RecordBatch], shard_slots: int, per_group: int, seed: int, blocks: list[int]) -> Iterator[pa.RecordBatch]:
    """The slots of the shards of a group, with the block that each holds."""
    for batch in batches:
        for row in batch.to_pylist():
            has = row["has"]
            for shard, k, first, n in slot_counts([x["n"] for x in has], shard_slots, seed + 1 + row["grp"]):
                source, slot = has[k]["source_no"], has[k]["first"] + first + np.arange(n)
                size = blocks[source]
                key = _spread(np.uint64(seed) + (slot // size).astype(np.uint64) * np.uint64(0x632BE59BD9B4E019) + np.uint64(source) * np.uint64(0x9FB21C651E98DF25))
                cols = [np.full(n, row["grp"] * per_group + shard), np.full(n, source), slot, permuted(slot % size, size, key)]
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["shard", "source_no", "slot", "block"])


#: What makes rows of documents interchangeable: they are placed together and told apart only by number.
_ALIKE = ("doc_id", "source", "tag")


def document_sizes(docs: DataFrame) -> DataFrame:
    """``(doc_id, source, tag, size, copies)``: one row for all rows of one id, source and text; ``tag`` is the text's hash."""
    rows = docs.select("doc_id", "source", F.xxhash64("text").alias("tag"), word_count(F.col("text")).alias("size"))
    return rows.groupBy(*_ALIKE, "size").agg(F.count(F.lit(1)).alias("copies"))


def source_streams(sizes: DataFrame, seed: int) -> DataFrame:
    """Each document's place in its source's stream of words: ``at`` .. ``at + size``, copies one after another.

    Buckets go by id and text, so that neither null ids nor one repeated id make a large one.
    """
    buckets = max(1, -(-sizes.count() // BUCKET_DOCS))
    dealt = sizes.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "tag", F.lit(seed)), F.lit(buckets))).withColumn("words", F.col("size") * F.col("copies"))
    order = Window.partitionBy("source", "bucket").orderBy(F.xxhash64("doc_id", "tag", F.lit(seed + 1)), "doc_id", "tag", "size")
    placed = dealt.withColumn("at", F.coalesce(F.sum("words").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    tops = dealt.groupBy("source", "bucket").agg(F.sum("words").alias("words"))
    before = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    tops = tops.select(F.col("source").alias("s"), F.col("bucket").alias("b"), F.coalesce(F.sum("words").over(before), F.lit(0)).alias("base"))
    joined = placed.join(tops, F.col("source").eqNullSafe(F.col("s")) & (F.col("bucket") == F.col("b")))
    return joined.select(*_ALIKE, "size", "copies", (F.col("at") + F.col("base")).alias("at"))


def mix(docs: DataFrame, weights: Sequence[float] = (5, 2, 1), cap: float = 3.0, block_words: int = BLOCK_WORDS, shard_slots: int = SHARD_SLOTS, seed: int = 17, max_sources: int = 100_000) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The mix: ``(placed documents, sources, slots)``.

    ``placed``: ``doc_id, source, tag, source_no, size, copies, at`` per document (``copies`` alike rows from ``at`` on); ``sources``:
    ``source, source_no, source_size, target, n_blocks, n_slots``; ``slots``:
    ``shard, source_no, slot, block``, the block that every slot holds.
    """
    spark = docs.sparkSession
    placed = materialize(source_streams(materialize(document_sizes(docs), "sizes"), seed), "placed")
    per = placed.groupBy("source").agg(F.sum(F.col("size") * F.col("copies")).alias("source_size")).limit(max_sources + 1).collect()
    if len(per) > max_sources:
        raise ValueError(f"more than {max_sources} sources")
    per = sorted(per, key=lambda r: (r["source"] is None, r["source"] or ""))
    sizes = [int(r["source_size"]) for r in per]
    by_weight = [float(weights[k % len(weights)]) for k in range(len(per))]
    goal = targets(sizes, by_weight, float(sum(sizes)), cap)
    blocks = [-(-s // block_words) for s in sizes]
    slots = [min(int(cap * b), round(g / s * b)) if s else 0 for s, b, g in zip(sizes, blocks, goal)]
    rows = [(r["source"], k, sizes[k], goal[k], blocks[k], slots[k]) for k, r in enumerate(per)]
    sources = spark.createDataFrame(rows, "source string, source_no long, source_size long, target double, n_blocks long, n_slots long")
    # the driver draws for groups of shards, tasks for the shards of their groups
    per_group = max(1, -(-sum(slots) // (shard_slots * MAX_GROUPS)))
    groups = spark.createDataFrame(slot_counts(slots, per_group * shard_slots, seed), "grp long, source_no long, first long, n long")
    rows = groups.groupBy("grp").agg(F.sort_array(F.collect_list(F.struct("source_no", "first", "n"))).alias("has"))
    # a group is a task's worth of slots: a number of partitions of our own, which are not merged for being small
    n_groups = -(-sum(slots) // (per_group * shard_slots))
    slot_rows = rows.repartition(max(1, min(n_groups, MAX_GROUPS)), "grp").mapInArrow(lambda it: _draw_shards(it, shard_slots, per_group, seed, blocks), "shard long, source_no long, slot long, block long")
    return placed.join(F.broadcast(sources.select(F.col("source").alias("s"), "source_no")), F.col("source").eqNullSafe(F.col("s"))).drop("s"), sources, slot_rows


def each_copy(placed: DataFrame) -> DataFrame:
    """``placed`` with a row per document, copies at places of their own."""
    copy = F.explode(F.sequence(F.lit(0).cast("long"), F.col("copies") - 1))
    return placed.withColumn("copy", copy).withColumn("at", F.col("at") + F.col("copy") * F.col("size")).drop("copy", "copies")


def document_pieces(placed: DataFrame, block_words: int = BLOCK_WORDS) -> DataFrame:
    """Documents with a row per block that they reach into: ``block``, words ``start`` .. ``end`` of the document."""
    some = placed.filter("size > 0")
    first, last = F.floor(F.col("at") / block_words), F.floor((F.col("at") + F.col("size") - 1) / block_words)
    cut = some.withColumn("block", F.explode(F.sequence(first, last)))
    return cut.withColumn("start", F.greatest(F.lit(0).cast("long"), F.col("block") * block_words - F.col("at"))).withColumn("end", F.least("size", (F.col("block") + 1) * block_words - F.col("at")))


def taken_words(docs: DataFrame, block_words: int = BLOCK_WORDS, **options) -> DataFrame:
    """``(doc_id, size, source_size, target, taken)`` for every document."""
    placed, sources, slots = mix(docs, block_words=block_words, **options)
    placed = materialize(each_copy(placed).withColumn("row", F.monotonically_increasing_id()), "rows")
    times = slots.groupBy("source_no", "block").agg(F.count(F.lit(1)).alias("times")).hint("merge")
    pieces = document_pieces(placed.select("row", "source_no", "size", "at"), block_words).select("row", "source_no", "block", (F.col("end") - F.col("start")).alias("words"))
    got = pieces.join(times, ["source_no", "block"]).groupBy("row").agg(F.sum(F.col("words") * F.col("times")).alias("got"))
    out = placed.join(got, "row", "left").join(F.broadcast(sources.select("source_no", "source_size", "target")), "source_no")
    return out.select("doc_id", "size", "source_size", "target", F.coalesce("got", F.lit(0)).cast("long").alias("taken"))


_WORD = re.compile(r"[^\x20\x09-\x0D]+")
_PIECE = [("source_no", pa.int64()), ("block", pa.int64()), ("at", pa.int64()), ("words", pa.string())]


def _pack(batches: Iterator[pa.RecordBatch], block_words: int) -> Iterator[pa.RecordBatch]:
    """Documents (id, text, source number, copies, place) cut at the block boundaries of their source's stream."""
    for batch in batches:
        for i in range(0, batch.num_rows, 500):
            part = batch.slice(i, 500)
            row, made = [], []
            for k, (text, source, copies, at) in enumerate(zip(*(part.column(n).to_pylist() for n in ("text", "source_no", "copies", "at")))):
                words = _WORD.findall(text or "")
                for copy in range(copies if words else 0):
                    place = at + copy * len(words)
                    cuts = [0, *range(block_words - place % block_words, len(words), block_words), len(words)]
                    made += [(source, (place + a) // block_words, place + a, " ".join(words[a:b])) for a, b in zip(cuts, cuts[1:])]
                    row += [k] * (len(cuts) - 1)
            cols = [pa.array([m[c] for m in made], t) for c, (_, t) in enumerate(_PIECE)]
            yield pa.RecordBatch.from_arrays([part.column("doc_id").take(pa.array(row, pa.int64())), *cols], ["doc_id", *(n for n, _ in _PIECE)])


def packed_blocks(docs: DataFrame, block_words: int = BLOCK_WORDS, **options) -> DataFrame:
    """The mixed corpus: ``(shard, slot, source, block, doc_ids, n_words, text)``, a row per slot of an output shard.

    ``text`` is the block that the slot holds, its words joined by one space; ``doc_ids`` the documents that they
    are of, in order. A text moves to its place once and in pieces to its blocks once; slots and blocks meet by index.
    """
    placed, sources, slots = mix(docs, block_words=block_words, **options)
    here = placed.select(F.struct(*_ALIKE).alias("key"), "source_no", "copies", "at").hint("merge")  # grows with the corpus: never broadcast
    # one struct as the key, equal with its nulls and of the same type: the aggregation deals texts as the join wants them, so they move once for both
    key = F.struct("doc_id", "source", F.xxhash64("text").alias("tag")).cast(here.schema["key"].dataType).alias("key")
    texts = docs.filter(word_count(F.col("text")) > 0).select(key, "text").groupBy("key").agg(F.first("text").alias("text"))
    whole = texts.join(here, "key").withColumn("doc_id", F.col("key.doc_id"))
    kind = docs.schema["doc_id"].dataType.simpleString()
    pieces = whole.select("doc_id", "text", "source_no", "copies", "at").mapInArrow(lambda it: _pack(it, block_words), f"doc_id {kind}, source_no long, block long, at long, words string")
    held = pieces.groupBy("source_no", "block").agg(F.array_sort(F.collect_list(F.struct("at", "words", "doc_id"))).alias("has"))  # at most block_words pieces
    blocks = held.select("source_no", "block", F.array_distinct("has.doc_id").alias("doc_ids"), F.array_join("has.words", " ").alias("text"))
    named = F.broadcast(sources.select("source_no", "source"))  # one row per source, whose number mix checks
    out = slots.hint("merge").join(blocks, ["source_no", "block"]).join(named, "source_no")
    return out.select("shard", "slot", "source", "block", "doc_ids", (F.size(F.split("text", " "))).cast("long").alias("n_words"), "text")
