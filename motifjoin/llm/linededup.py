"""Fuzzy line dedup: MinHash candidates, exact Jaccard, distributed union-find.

Lines are compared as sets of character shingles. One hash per shingle falls
into one of ``bands * rows`` bins; the bins' minima are the signature (empty
bins borrow from the next full one), cut into bands. Lines that share a band are
candidates. Candidate groups are verified on exact shingle sets by a
breadth-first walk that never compares two lines that are already connected;
what it walks over are the links, and union-find joins them. One line of every
component stays: the one that comes first by (doc_id, line number).

Equal lines are one node. Blank lines are left alone. Band hashes travel as
packed blobs by bucket, each distinct line of a sub-batch once; large candidate
groups are dealt in parts with common pivots, and what the pivots leave apart is
compared part by part (``groups``). Only texts that a bitmap of fixed size does
not rule out are moved for verification.

Defined results: null text stays null and has no lines; rows with null
``doc_id`` come last in the order; repeated rows are one document, each keeps
and loses the same lines; ties cannot occur otherwise; other columns stay as
they are, but for those named like the results, which these replace.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifjoin.llm import groups
from motifjoin.llm.substring import _keys, _mixed
from motifjoin.workspace import materialize

#: Shingle length in characters; bands and rows of the signature; the similarity of a link.
SHINGLE, BANDS, ROWS, SIMILARITY = 8, 14, 4, 0.8
#: Characters of a sub-batch at least; band hashes of a bucket; buckets at least; bits of the map of candidates.
BATCH_CHARS, BUCKET_KEYS, LEAST_BUCKETS, MAP_BITS = 1 << 20, 1 << 20, 64, 1 << 26
#: With more buckets a sub-batch has this many characters per bucket, so that its blobs stay as long, up to a limit of memory.
BUCKET_SHARE, MOST_BATCH_CHARS = 1 << 12, 1 << 24
_EMPTY, _POLY = np.uint32(0xFFFFFFFF), np.uint32(0x01000193)


def lines_of(text: str | None) -> list[str]:
    return text.split("\n") if text else []


def line_hash(line: str) -> int:
    return xxhash.xxh64_intdigest(line.encode("utf-8", "surrogatepass"), 3)


def signatures(lines: list[str], width: int, bins: int) -> np.ndarray:
    """One minimum per line and bin, as uint32.

    A shingle's hash is a polynomial of its characters, built by doubling (two neighbours of
    2^k characters make one of 2^(k+1)) and then mixed. Windows that run over a line's end
    count for a row that is thrown away; a line shorter than a shingle is one itself.
    """
    n = len(lines)
    size = np.array([len(x) for x in lines], np.int64)
    code = np.frombuffer("".join(lines).encode("utf-32-le", "surrogatepass"), "<u4")
    part, h, done, span = code * np.uint32(0x9E3779B1), np.zeros(len(code), np.uint32), 0, 1
    base = _POLY
    while True:
        if width & span:  # the block of this length comes next
            h *= base
            h[: len(h) - done] += part[done:]
            done += span
        if span * 2 > width:
            break
        following = part[span:].copy()
        part *= base
        part[: len(part) - span] += following
        span, base = span * 2, np.uint32(int(base) * int(base) & 0xFFFFFFFF)
    h ^= h >> np.uint32(15)
    h *= np.uint32(0x2C1B3C6D)
    h ^= h >> np.uint32(12)
    h *= np.uint32(0x297A2D39)
    h ^= h >> np.uint32(15)
    cell = h >> np.uint32(16)
    cell *= np.uint32(bins)
    cell >>= np.uint32(16)
    at = np.repeat(np.arange(n, dtype=np.int64) * bins, size)
    ends = np.cumsum(size)
    long = np.flatnonzero(size >= width)
    at[(ends[long][:, None] - np.arange(1, width)).ravel()] = n * bins
    short = np.flatnonzero(size < width)
    if len(short):
        at[np.concatenate([np.arange(ends[k] - size[k], ends[k]) for k in short])] = n * bins
    at += cell
    sig = np.full((n + 1) * bins, _EMPTY, np.uint32)
    np.minimum.at(sig, at, h)
    sig = sig.reshape(n + 1, bins)[:n]
    for k in short:
        if size[k]:
            sig[k, 0] = line_hash(lines[k]) & 0x7FFFFFFF
    empty = sig == _EMPTY
    row = np.flatnonzero(empty.any(1) & ~empty.all(1))  # borrow from the next full bin
    place = np.where(empty[row], 4 * bins, np.arange(bins))
    following = np.minimum.accumulate(np.concatenate([place, place + bins], 1)[:, ::-1], 1)[:, ::-1][:, :bins]
    step = (following - np.arange(bins)).astype(np.uint32)
    sig[row] = sig[row[:, None], following % bins] ^ step * np.uint32(0x85EBCA6B)
    return sig


def band_keys(sig: np.ndarray, rows: int) -> np.ndarray:
    """A 64-bit key per line and band."""
    n, bins = sig.shape
    bands = bins // rows
    sig = sig.astype(np.uint64)
    key = np.tile(np.arange(1, bands + 1, dtype=np.uint64) * np.uint64(0x8CB92BA72F3D8DD7), (n, 1))
    for r in range(rows):
        key = _mixed(key * np.uint64(0x9E3779B97F4A7C15) + sig.reshape(n, bands, rows)[:, :, r])
    return key


_PACKED = "key long, keys binary, lines binary"


def _sketch(batches: Iterator[pa.RecordBatch], width: int, bands: int, rows: int, buckets: int, batch_chars: int) -> Iterator[pa.RecordBatch]:
    held: dict[int, str] = {}
    chars = 0

    def flush() -> pa.RecordBatch:
        nonlocal held, chars
        h = np.fromiter(held.keys(), np.uint64, len(held))
        keys = band_keys(signatures(list(held.values()), width, bands * rows), rows)
        who, key = np.repeat(h, bands), keys.reshape(-1)
        bucket = (key % np.uint64(buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        bounds = np.searchsorted(bucket[order], np.arange(buckets + 1))
        full = np.flatnonzero(np.diff(bounds))
        cut = [order[bounds[b] : bounds[b + 1]] for b in full]
        held, chars = {}, 0
        return pa.RecordBatch.from_arrays([pa.array(full, pa.int64()), pa.array([key[c].tobytes() for c in cut], pa.binary()), pa.array([who[c].tobytes() for c in cut], pa.binary())], ["key", "keys", "lines"])

    for batch in batches:
        for text in batch.column(0):
            for line in lines_of(text.as_py()):
                if line and not line.isspace() and (h := line_hash(line)) not in held:
                    held[h] = line
                    chars += len(line) + 8
                    if chars >= batch_chars:
                        yield flush()
    if held:
        yield flush()


def _group(bucket: pa.Table) -> pa.Table:
    """Lines that share a band, as groups of line hashes dealt in parts where they are large."""
    key = np.concatenate([np.frombuffer(x.as_py(), np.uint64) for x in bucket.column("keys")])
    line = np.concatenate([np.frombuffer(x.as_py(), np.uint64) for x in bucket.column("lines")])
    order = np.argsort(key)
    key, line = key[order], line[order]
    new = np.concatenate([[True], key[1:] != key[:-1]])
    no = np.cumsum(new) - 1
    many = np.bincount(no)[no] > 1
    no, line = no[many], line[many]
    order = np.lexsort((line, no))
    no, line = no[order], line[order]
    keep = np.concatenate([[True], (no[1:] != no[:-1]) | (line[1:] != line[:-1])]) if len(no) else np.zeros(0, bool)
    no, line = no[keep], line[keep]
    starts = np.flatnonzero(np.concatenate([[True], no[1:] != no[:-1]])) if len(no) else np.zeros(0, int)
    out = [row for a, b in zip(starts, np.append(starts[1:], len(no))) for row in groups.parts_of(line[a:b])]
    return pa.table({"members": pa.array([m for m, _ in out], pa.binary()), "gid": pa.array([g for _, g in out], pa.int64())})


def _wanted(batches: Iterator[pa.RecordBatch], bits: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Distinct lines whose hash the map of candidates knows."""
    size = np.uint64(len(bits) * 8)
    for batch in batches:
        found: dict[int, str] = {}
        for text in batch.column(0):
            lines = [x for x in lines_of(text.as_py()) if x]
            h = np.array([line_hash(x) for x in lines], np.uint64)
            at = (h % size).astype(np.int64)
            for k in np.flatnonzero(bits[at >> 3] >> (at & 7).astype(np.uint8) & 1):
                found[int(h[k])] = lines[k]
        yield pa.RecordBatch.from_arrays([pa.array(np.fromiter(found.keys(), np.uint64, len(found)).view(np.int64)), pa.array(list(found.values()), pa.string())], ["h", "text"])


def shingles(line: str, width: int) -> set[str]:
    return {line[i : i + width] for i in range(max(1, len(line) - width + 1))}


def line_roots(docs: DataFrame, width: int = SHINGLE, bands: int = BANDS, rows: int = ROWS, similarity: float = SIMILARITY) -> DataFrame:
    """``(node, root)``: hashes of lines that are like another one, and their component."""
    texts = docs.select("text")
    characters = texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = int(max(LEAST_BUCKETS, -(-characters * bands // (100 * BUCKET_KEYS))))
    batch_chars = max(BATCH_CHARS, min(MOST_BATCH_CHARS, buckets * BUCKET_SHARE))
    packed = texts.mapInArrow(lambda it: _sketch(it, width, bands, rows, buckets, batch_chars), _PACKED)

    def wanted(members: DataFrame) -> DataFrame:
        at = F.pmod(F.col("h"), F.lit(MAP_BITS))  # as unsigned: the map's size is a power of two
        marked = members.select(at.alias("at")).groupBy(F.shiftright("at", 15).alias("page")).agg(F.expr("bitmap_construct_agg(at & 32767)").alias("bits"))
        bits = np.zeros(MAP_BITS // 8, np.uint8)
        for page in marked.collect():  # of a fixed size, whatever the corpus
            bits[page["page"] * 4096 : page["page"] * 4096 + 4096] = np.frombuffer(bytes(page["bits"]), np.uint8)
        return texts.mapInArrow(lambda it: _wanted(it, bits), "h long, text string").groupBy("h").agg(F.min("text").alias("text"))

    return groups.similar_roots(packed.groupBy("key").applyInArrow(_group, groups.DEALT), wanted, width, similarity, shingles)


def _occurrences(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for k in range(0, batch.num_rows, 2000):
            part = batch.slice(k, 2000)
            h, no, row = [], [], []
            for i, text in enumerate(part.column("text")):
                for j, line in enumerate(lines_of(text.as_py())):
                    if line and not line.isspace():
                        h.append(line_hash(line))
                        no.append(j)
                        row.append(i)
            take = pa.array(row, pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(np.array(h, np.uint64).view(np.int64)), part.column("d").take(take), part.column("tag").take(take), pa.array(no, pa.int32())], ["h", "d", "tag", "no"])


def removed_lines(docs: DataFrame, **options) -> DataFrame:
    """``(d, tag, gone)``: line numbers that documents lose; ``d`` and ``tag`` as ``_keys`` gives them."""
    number, tag = _keys(docs)
    rows = docs.select(number.alias("d"), tag.alias("tag"), "text")
    where = materialize(rows.mapInArrow(_occurrences, "h long, d long, tag long, no int"), "lines")
    roots = line_roots(docs, **options).select(F.col("node").alias("h"), "root")
    place = F.struct("d", "tag", "no")
    first = where.groupBy("h").agg(F.min(place).alias("first"), F.max(place).alias("last"))
    # lines with a twin of any kind: several places, or a component
    twins = first.join(roots, "h", "left").filter("root is not null or first <> last").select("h", F.coalesce("root", "h").alias("root"), "first")
    kept = twins.groupBy("root").agg(F.min("first").alias("kept"))
    keep = twins.select("h", "root").join(kept, "root").select("h", "kept")
    gone = where.join(keep, "h").filter(place != F.col("kept"))
    return gone.groupBy("d", "tag").agg(F.array_sort(F.collect_set("no")).alias("gone"))


def _rewrite(batches: Iterator[pa.RecordBatch], gone_name: str) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for k in range(0, batch.num_rows, 1000):
            part = batch.slice(k, 1000)
            total, lost, texts, hashes = [], [], [], []
            for text, gone in zip(part.column("text").to_pylist(), part.column(gone_name).to_pylist()):
                lines = lines_of(text)
                drop = set(gone or ())
                kept = text if not drop else "\n".join(x for j, x in enumerate(lines) if j not in drop)
                total.append(len(lines))
                lost.append(len(drop))
                texts.append(kept)
                hashes.append(hashlib.sha256((kept or "").encode("utf-8", "surrogatepass")).hexdigest())
            cols = [part.column(n) for n in part.schema.names if n not in ("text", gone_name)]
            made = [pa.array(texts, pa.string()), pa.array(total, pa.int64()), pa.array(lost, pa.int64()), pa.array(hashes, pa.string())]
            yield pa.RecordBatch.from_arrays([*cols, *made], [*(n for n in part.schema.names if n not in ("text", gone_name)), "text", "n_lines", "n_removed", "kept_sha256"])


RESULTS = ("n_lines", "n_removed", "kept_sha256")


def dedup_lines(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with the lines that stay in ``text``, and ``n_lines, n_removed, kept_sha256`` (in place of columns so named)."""
    number, tag = _keys(docs)
    d, t, gone = (free_name(x, docs.columns) for x in ("d", "tag", "gone"))
    lost = removed_lines(docs.select("doc_id", "text"), **options).select(F.col("d").alias(d), F.col("tag").alias(t), F.col("gone").alias(gone))
    others = [c for c in docs.columns if c not in ("text", *RESULTS)]
    keyed = docs.select(*(F.col(f"`{c}`") for c in others), "text", number.alias(d), tag.alias(t))
    joined = keyed.join(lost, [d, t], "left").drop(d, t)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in joined.schema.fields if f.name not in ("text", gone))
    return joined.mapInArrow(lambda it: _rewrite(it, gone), f"{schema}, text string, n_lines long, n_removed long, kept_sha256 string")


def free_name(name: str, taken: list[str]) -> str:
    """A column name like ``name`` that is not taken, whatever its case."""
    while name.lower() in {c.lower() for c in taken}:
        name = f"_{name}"
    return name
