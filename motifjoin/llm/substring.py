"""Exact substring dedup: hashes of every fixed-length token window, counted in Spark.

Every window of every document gets a Rabin-Karp hash (prefix sums of 64-bit
word hashes times powers of an odd base, modulo 2^64). Hashes move to their
buckets packed as blobs, without the part that the bucket number implies. A
task first drops the repeats that it can see itself, so a passage that very
many documents share reaches its bucket once per sub-batch of documents, not
once per document. A bucket finds the hashes that occur more than once and
sends the later occurrences back to their sub-batches, where they are merged
into maximal removal intervals per document; these join the texts.

A window is judged on the input: it is removed if its word sequence also starts
earlier, by (doc_id, start). Two different windows of one 64-bit hash would be
taken for equal; at n windows that is expected n^2 / 2^65 times (0.0005 at 10^8).

Defined results: null text has no words; rows with null ``doc_id`` come after
all others; rows that share a ``doc_id`` are at the same place in the order, so
of repeated rows neither removes the other's windows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard as zstd
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Words of a sub-batch, windows of a bucket, buckets at least, words in a task's cache of hashes.
BATCH_WORDS, BUCKET_WINDOWS, LEAST_BUCKETS, CACHE_WORDS = 1 << 20, 1 << 21, 256, 1 << 18
_BASE = 0x9E3779B97F4A7C15
_LAST = np.iinfo(np.int64).max


class _WordHash(dict):
    """XXH64 of words, remembered."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= CACHE_WORDS:
            self.clear()
        self[word] = value = xxhash.xxh64_intdigest(word, 7)
        return value


def _powers(n: int) -> np.ndarray:
    out = np.full(n, _BASE, np.uint64)
    out[:1] = 1
    return np.multiply.accumulate(out)


def _mixed(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads all bits."""
    for mul in (0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53):
        h = (h ^ (h >> np.uint64(33))) * np.uint64(mul)
    return h ^ (h >> np.uint64(33))


def window_hashes(words: np.ndarray, width: int, powers: np.ndarray) -> np.ndarray:
    """The hash of ``words[s : s + width]`` for every s of one stream of word hashes.

    Prefix sums S_k of w_i * B^i give a window as (S_{s+width} - S_s) * B^(n - s),
    which does not depend on where it stands once the power is fixed.
    """
    n = len(words)
    if n < width:
        return np.zeros(0, np.uint64)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(words * powers[:n][::-1])])
    # w_i weighs B^(n-1-i): bring every window to the weights B^(width-1) .. 1
    inverse = np.uint64(pow(_BASE, -1, 1 << 64))
    back = np.full(n - width + 1, inverse, np.uint64)
    back[:1] = np.uint64(pow(int(inverse), n - width, 1 << 64))
    back[1:] = np.uint64(_BASE)
    return _mixed((sums[width:] - sums[:-width]) * np.multiply.accumulate(back))


def _squeeze(*arrays: np.ndarray) -> bytes:
    """Sorted integer arrays as compressed differences."""
    parts = [np.diff(a.astype(np.int64), prepend=np.int64(0)) for a in arrays]
    head = np.array([len(p) for p in parts], "<i8").tobytes()
    small = [p.astype("<i8").view(np.uint8).reshape(-1, 8).T.tobytes() for p in parts]  # equal bytes together
    return zstd.ZstdCompressor(level=1).compress(head + b"".join(small))


def _spread(blob: bytes, n: int) -> list[np.ndarray]:
    data = zstd.ZstdDecompressor().decompress(blob)
    sizes, at, out = np.frombuffer(data, "<i8", n), 8 * n, []
    for size in sizes:
        raw = np.frombuffer(data, np.uint8, 8 * size, at).reshape(8, size).T
        out.append(np.cumsum(np.ascontiguousarray(raw).view("<i8").reshape(-1)))
        at += 8 * int(size)
    return out


def _cut(h: np.ndarray, buckets: int) -> tuple[np.ndarray, bytes]:
    """What the bucket number does not say of the hashes, in as few bytes as hold it."""
    width = max(1, -(-(((1 << 64) // buckets).bit_length()) // 8))
    return np.ascontiguousarray((h // np.uint64(buckets)).astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width]).tobytes()


def _uncut(raw: bytes, n: int) -> np.ndarray:
    width = len(raw) // n
    out = np.zeros((n, 8), np.uint8)
    out[:, :width] = np.frombuffer(raw, np.uint8).reshape(n, width)
    return out.view("<u8").reshape(-1)


#: Kinds of rows between tasks: a bucket's hashes, a sub-batch's own table, positions to remove.
_HASHES, _TABLE, _LATER = 0, 1, 2
_ROW = "key long, batch long, kind int, sizes binary, body binary"
_ARROW = pa.schema([("key", pa.int64()), ("batch", pa.int64()), ("kind", pa.int32()), ("sizes", pa.binary()), ("body", pa.binary())])


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*rows) if rows else [[]] * 5, _ARROW)], schema=_ARROW)


def _hash_documents(batches: Iterator[pa.RecordBatch], width: int, buckets: int) -> Iterator[pa.RecordBatch]:
    cache, seq = _WordHash(), 0
    held: list[tuple[int, int, list[int]]] = []
    held_words = 0

    def flush() -> pa.RecordBatch:
        nonlocal seq, held, held_words
        batch = (TaskContext.get().partitionId() << 32) | seq
        seq += 1
        powers = _powers(max(len(w) for _, _, w in held))
        hashes, docs, starts = [], [], []
        for k, (_, _, words) in enumerate(held):
            h = window_hashes(np.array(words, np.uint64), width, powers)
            hashes.append(h)
            docs.append(np.full(len(h), k, np.int32))
            starts.append(np.arange(len(h), dtype=np.int32))
        h, doc, start = np.concatenate(hashes), np.concatenate(docs), np.concatenate(starts)
        ids = np.array([d for d, _, _ in held], np.int64)
        first = np.zeros(len(held) + 1, np.int64)
        np.cumsum([len(x) for x in hashes], out=first[1:])
        # repeats inside the sub-batch: the earliest place goes on, later ones are settled here
        order = np.argsort(h, kind="stable")
        run = np.concatenate([[True], h[order][1:] != h[order][:-1]]) if len(h) else np.zeros(0, bool)
        later = np.zeros(len(h), bool)
        if len(h) and not run.all():
            group = np.cumsum(run) - 1
            many = np.flatnonzero(np.bincount(group)[group] > 1)
            rows, g = order[many], group[many]
            rank = np.lexsort((start[rows], ids[doc[rows]], g))
            rows, g = rows[rank], g[rank]
            lead = np.concatenate([[True], g[1:] != g[:-1]])
            lead_of = np.maximum.accumulate(np.where(lead, np.arange(len(g)), 0))
            same = (ids[doc[rows]] == ids[doc[rows[lead_of]]]) & (start[rows] == start[rows[lead_of]])  # at the same place: not later
            later[rows[~same]] = True
        out = [(batch % buckets, batch, _TABLE, _squeeze(ids, np.array([t for _, t, _ in held], np.int64), first), _squeeze(np.flatnonzero(later)))]
        stay = np.flatnonzero(~later)
        bucket = (h[stay] % np.uint64(buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        bounds = np.searchsorted(bucket[order], np.arange(buckets + 1))
        for b in np.flatnonzero(np.diff(bounds)):
            mine = stay[order[bounds[b] : bounds[b + 1]]]
            who, at = np.unique(doc[mine], return_index=True)
            out.append((int(b), batch, _HASHES, _squeeze(mine, ids[who], at, first[who]), _cut(h[mine], buckets)))
        held, held_words = [], 0
        return _rows(out)

    for batch in batches:
        ids, tags, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)
        for k in range(batch.num_rows):
            text = texts[k].as_py()
            words = list(map(cache.__getitem__, text.encode("utf-8", "surrogatepass").split())) if text else []
            held.append((ids[k], tags[k], words))
            held_words += len(words) + 16
            if held_words >= BATCH_WORDS:
                yield flush()
    if held:
        yield flush()


def _count_bucket(group: pa.Table) -> pa.Table:
    """Which windows of a bucket start later than an equal one: rows for their sub-batches."""
    kind = group.column("kind").to_numpy()
    rows = [r for r in group.filter(pa.array(kind != _HASHES)).to_pylist()]
    out = [(r["batch"], r["batch"], r["kind"], r["sizes"], r["body"]) for r in rows]
    q, place, doc, start, owner, batches = [], [], [], [], [], []
    for k, row in enumerate(np.flatnonzero(kind == _HASHES)):
        mine, ids, at, first = _spread(group.column("sizes")[row].as_py(), 4)
        n = len(mine)
        each = np.repeat(np.arange(len(ids)), np.diff(np.append(at, n)))
        q.append(_uncut(group.column("body")[row].as_py(), n))
        place.append(mine)
        doc.append(ids[each])
        start.append((mine - first[each]).astype(np.int32))
        owner.append(np.full(n, k, np.int32))
        batches.append(group.column("batch")[row].as_py())
    if q:
        h = np.concatenate(q)
        order = np.argsort(h)
        new = np.concatenate([[True], h[order][1:] != h[order][:-1]])
        if not new.all():
            group_no = np.cumsum(new) - 1
            many = np.bincount(group_no)[group_no] > 1
            rows_, g = order[many], group_no[many]
            doc, start, owner, place = map(np.concatenate, (doc, start, owner, place))
            rank = np.lexsort((start[rows_], doc[rows_], g))
            rows_, g = rows_[rank], g[rank]
            lead = np.concatenate([[True], g[1:] != g[:-1]])
            lead_of = np.maximum.accumulate(np.where(lead, np.arange(len(g)), 0))
            same = (doc[rows_] == doc[rows_[lead_of]]) & (start[rows_] == start[rows_[lead_of]])
            late = rows_[~same]
            late = late[np.lexsort((place[late], owner[late]))]
            bounds = np.searchsorted(owner[late], np.arange(len(batches) + 1))
            for k in np.flatnonzero(np.diff(bounds)):
                out.append((batches[k], batches[k], _LATER, None, _squeeze(place[late[bounds[k] : bounds[k + 1]]])))
    return pa.Table.from_batches([_rows(out)])


def _merge_batch(group: pa.Table, width: int) -> pa.Table:
    """Removal intervals, in words, of every document of a sub-batch that loses any."""
    at, first, ids, tags = [], None, None, None
    for row in group.to_pylist():
        at.append(_spread(row["body"], 1)[0])
        if row["kind"] == _TABLE:
            ids, tags, first = _spread(row["sizes"], 3)
    window = np.sort(np.concatenate(at))
    doc = np.searchsorted(first, window, side="right") - 1
    start = window - first[doc]
    new = np.concatenate([[True], (doc[1:] != doc[:-1]) | (start[1:] > start[:-1] + width)]) if len(window) else np.zeros(0, bool)
    heads = np.flatnonzero(new)
    tails = np.append(heads[1:] - 1, len(window) - 1) if len(heads) else heads
    who, low, high = doc[heads], start[heads], start[tails] + width
    found, cuts = np.unique(who, return_index=True)
    cuts = np.append(cuts, len(who))
    spans = [np.stack([low[a:b], high[a:b]], 1).astype("<i4").tobytes() for a, b in zip(cuts[:-1], cuts[1:])]
    return pa.table({"d": pa.array(ids[found], pa.int64()), "tag": pa.array(tags[found], pa.int64()), "spans": pa.array(spans, pa.binary())})


def _keys(docs: DataFrame) -> tuple[Column, Column]:
    """A document's number and a tag that tells rows of one number apart where there are such."""
    repeated = docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).filter("n > 1 or doc_id is null").limit(1).count()
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(int(_LAST))), F.xxhash64("text") if repeated else F.lit(0).cast("long")


def repeated_spans(docs: DataFrame, width: int = 20) -> DataFrame:
    """``docs(doc_id, text)`` to ``(d, tag, spans)`` of the documents that lose words; see ``_keys``."""
    number, tag = _keys(docs)
    characters = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    spark = docs.sparkSession
    buckets = max(LEAST_BUCKETS, -(-characters // (6 * BUCKET_WINDOWS)))
    rows = docs.select(number.alias("d"), tag.alias("tag"), "text")
    hashed = rows.mapInArrow(lambda it: _hash_documents(it, width, buckets), _ROW)
    later = hashed.groupBy("key").applyInArrow(_count_bucket, _ROW)
    return later.groupBy("batch").applyInArrow(lambda t: _merge_batch(t, width), "d long, tag long, spans binary").distinct()


def _apply(batches: Iterator[pa.RecordBatch], texts: bool) -> Iterator[pa.RecordBatch]:
    names = ["n_words", "n_removed", "kept_sha256", "spans"] + ["kept"] * texts
    for batch in batches:
        for at in range(0, batch.num_rows, 500):
            part = batch.slice(at, 500)
            cols: list[list] = [[] for _ in names]
            for text, raw in zip(part.column("text"), part.column("spans")):
                words = (text.as_py() or "").encode("utf-8", "surrogatepass").split()
                spans = np.frombuffer(raw.as_py() or b"", "<i4").reshape(-1, 2).tolist()
                left, done = [], 0
                for a, b in spans:
                    left += words[done:a]
                    done = b
                kept = b" ".join(left + words[done:]) if spans else b" ".join(words)
                n_kept = len(left) + len(words) - done if spans else len(words)
                for col, value in zip(cols, (len(words), len(words) - n_kept, hashlib.sha256(kept).hexdigest(), [{"start": a, "end": b} for a, b in spans], kept.decode("utf-8", "surrogatepass"))):
                    col.append(value)
            types = [pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])), pa.string()]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), *(pa.array(c, t) for c, t in zip(cols, types))], ["doc_id", *names])


def dedup_substrings(docs: DataFrame, width: int = 20, texts: bool = True) -> DataFrame:
    """``doc_id, n_words, n_removed, kept_sha256, spans[, kept]`` of every document; spans are word intervals."""
    number, tag = _keys(docs)
    spans = repeated_spans(docs.select("doc_id", "text"), width)
    keyed = docs.select("doc_id", "text", number.alias("d"), tag.alias("tag"))
    joined = keyed.join(spans, ["d", "tag"], "left").select("doc_id", "text", "spans")
    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, n_words long, n_removed long, kept_sha256 string, spans array<struct<start: int, end: int>>" + ", kept string" * texts
    return joined.mapInArrow(lambda it: _apply(it, texts), schema)
