"""Exact top-k by integer inner product: MaxScore over blocks of queries and shards of vectors.

The components of a query are its terms; a term's postings are the vectors with a
component other than zero there. Within a shard every term has a score bound, the most
that it can add to any vector, and every block of ``BLOCK_VECTORS`` similar vectors has
its own. The threshold is the k-th best full score that a query has met so far, in the
best blocks first and then in all shards of its task. Blocks whose bounds do not reach
it are skipped. Terms are split by their bounds: trailing ones that together cannot lift
a vector from nothing to the threshold are non-essential. The postings of the essential
terms are traversed (as one product where they are dense); vectors that none of them
lists, or that the rest cannot lift over the threshold any more, are out. The other
terms are probed in order of their bounds while a vector is competitive: after each
step its sum and the bound on what is left, by the block's ranges and by the norms of
the two rests, must reach the threshold. Every shard returns its k best per query;
shards are merged by a ranked window.

Queries and vectors meet by an equi-join on block numbers, never row by row.

Defined results: vectors that are null, empty or hold null or non-finite components take
no part, as query or as candidate; shorter vectors are padded with zeros; a query's own
row is every row with its ``vec_id`` and is left out; repeated rows are candidates each;
null ids take no part. Equal query rows are one query; different vectors of one id are a
query each, so that id has a ranking for each of them. Sums are exact: in doubles where
they stay below 2^52, else in integers of any size. A component or a score beyond 64 bits
is an error.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from motifjoin.workspace import materialize

#: Vectors in a shard, queries in a block, vectors in a block that has bounds of its own, terms of a probing step.
SHARD_ROWS, BLOCK_ROWS, BLOCK_VECTORS, STEP_TERMS = 8192, 512, 64, 8
#: Share of the threshold that the non-essential terms' bounds stay below: the less, the fewer vectors are left to probe.
REACH = 0.45
#: Share of components other than zero below which postings are traversed as lists.
SPARSE = 0.2


def quantise(vectors: DataFrame, scale: float, id_col: str, vec_col: str) -> DataFrame:
    """``(vec_id, q array<long>)`` with components floor(scale * x)."""
    x = F.col(vec_col)
    usable = x.isNotNull() & (F.size(x) > 0) & F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf")))
    scaled = lambda c: c.cast("double") * scale
    whole = lambda c: F.when(F.abs(scaled(c)) < 2.0**63, F.floor(scaled(c))).otherwise(F.raise_error(F.lit("a component is beyond 64 bits")).cast("long"))
    return vectors.filter(F.col(id_col).isNotNull() & usable).select(F.col(id_col).alias("vec_id"), F.transform(x, whole).alias("q"))


def grouped(m: np.ndarray, rows: int) -> np.ndarray:
    """An order of vectors in which runs of ``rows`` are alike: halves along the widest column, down to such runs."""
    order, parts = np.arange(len(m)), [(0, len(m))]
    while parts:
        a, b = parts.pop()
        if b - a > rows:
            mine = order[a:b]
            column = m[mine][:, (m[mine].max(0) - m[mine].min(0)).argmax()]
            half = -(-(b - a) // rows) // 2 * rows
            order[a:b] = mine[np.argpartition(column, half)]
            parts += [(a, a + half), (a + half, b)]
    return order


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The rows of a partition to one row: their ids and one matrix, alike vectors together."""
    ids: list[np.ndarray] = []
    vecs: list[np.ndarray] = []
    for batch in batches:
        ids.append(batch.column(0).to_numpy(zero_copy_only=False))
        q = batch.column(1)
        flat, offsets = q.flatten().to_numpy(zero_copy_only=False), q.offsets.to_numpy()
        vecs.extend(np.split(flat, (offsets - offsets[0])[1:-1]) if len(q) else [])
    if vecs:
        m = np.zeros((len(vecs), max(map(len, vecs))), "<i8")
        for k, v in enumerate(vecs):
            m[k, : len(v)] = v
        order = grouped(m.astype(float), BLOCK_VECTORS)
        m = m[order]
        m = m.astype(next((t for t in ("<i2", "<i4") if np.iinfo(t).min <= m.min() and m.max() <= np.iinfo(t).max), "<i8"))
        ids = np.concatenate(ids).astype("<i8")[order]
        yield pa.RecordBatch.from_arrays([pa.array([m.shape[0]], pa.int32()), pa.array([m.shape[1]], pa.int32()), pa.array([ids.tobytes()], pa.binary()), pa.array([m.tobytes()], pa.binary())], ["n", "width", "ids", "vecs"])


def _unpack(n: int, width: int, ids: bytes, vecs: bytes) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(ids, "<i8"), np.frombuffer(vecs, f"<i{len(vecs) // (n * width)}").astype(np.int64).reshape(n, width)


def _blocks(vectors: DataFrame, parts: int, name: str) -> DataFrame:
    """One row per partition, numbered by it."""
    packed = vectors.repartition(parts).mapInArrow(_pack, "n int, width int, ids binary, vecs binary")
    return packed.withColumn(name, F.spark_partition_id().cast("long"))


class Shard:
    """Vectors of a shard with their postings, ranges by block and by column, and squares."""

    def __init__(self, ids: np.ndarray, m: np.ndarray, width: int, kind: type) -> None:
        self.ids, self.kind = ids, kind
        self.c = np.pad(m, ((0, 0), (0, width - m.shape[1]))).astype(kind)
        cut = np.arange(0, len(m), BLOCK_VECTORS)
        self.low, self.high = (f.reduceat(self.c, cut, axis=0) for f in (np.minimum, np.maximum))
        self.least, self.most = self.low.min(0), self.high.max(0)
        self.block = np.repeat(np.arange(len(cut)), np.diff(np.append(cut, len(m))))
        self.squares = self.c.astype(float) ** 2
        self.norms = self.squares.sum(1)
        self.lists = [np.flatnonzero(col) for col in self.c.T] if np.count_nonzero(self.c) < SPARSE * self.c.size else None

    def rows_of(self, blocks: np.ndarray) -> np.ndarray:
        return (blocks[:, None] * BLOCK_VECTORS + np.arange(BLOCK_VECTORS)).ravel()[: len(self.ids)]

    def block_bounds(self, q: np.ndarray) -> np.ndarray:
        """The most that the vectors of each block (columns) can score with each query (rows)."""
        return np.maximum(q, 0) @ self.high.T + np.minimum(q, 0) @ self.low.T


class Counts:
    """What was pruned: queries times vectors, those not in a skipped block, competitive after the essential terms, and completed."""

    def __init__(self) -> None:
        self.pairs = self.near = self.competitive = self.completed = 0


def _split(q: np.ndarray, shard: Shard, threshold: float) -> tuple[np.ndarray, int]:
    """Terms by score bound, and how many are essential."""
    bound = np.maximum(np.maximum(q * shard.most, q * shard.least), 0)  # a vector without the term adds nothing
    order = np.argsort(-np.abs(q * np.maximum(np.abs(shard.most), np.abs(shard.least))).astype(float), kind="stable")
    rest = np.append(np.cumsum(bound[order][::-1])[::-1], 0)
    by_norm = np.sqrt(np.append(np.cumsum((q[order].astype(float) ** 2)[::-1])[::-1], 0) * shard.norms.max()) * (1 + 1e-9)
    out = np.minimum(rest.astype(float), by_norm) < REACH * threshold - 1e-9 * abs(threshold)
    return order, int(out.argmax()) if out.any() else len(order)


def max_score(q: np.ndarray, own: np.ndarray, shard: Shard, k: int, floors: np.ndarray, counts: Counts | None = None) -> list[tuple[np.ndarray, np.ndarray]]:
    """Per query (row of ``q``) its k best ``(vec_id, score)`` in the shard that can be among the k best of all; ties to smaller id.

    ``floors`` holds the k-th best score that each query is known to reach (-inf: none) and is raised.
    """
    counts = counts or Counts()
    q = q.astype(shard.kind)
    n, d = shard.c.shape
    bounds = shard.block_bounds(q)
    n_first = min(len(shard.low), -(-2 * k // BLOCK_VECTORS) + 1)
    best_blocks = np.argpartition(-bounds.astype(float), n_first - 1, axis=1)[:, :n_first]
    for i in range(len(q)):  # full scores of the best blocks give a first threshold
        at = shard.rows_of(np.sort(best_blocks[i]))
        at = at[at < n]
        full = shard.c[at[shard.ids[at] != own[i]]] @ q[i]
        if len(full) >= k:
            floors[i] = max(floors[i], float(np.sort(full.astype(object) if shard.kind is object else full)[-k]))
    safe = floors - 1e-9 * np.abs(np.where(np.isfinite(floors), floors, 0))  # bounds in doubles; scores at the threshold stay
    near = bounds.astype(float) >= safe[:, None]
    essential, orders = np.zeros(q.shape, bool), []
    for i in range(len(q)):
        order, split = _split(q[i], shard, floors[i])
        essential[i, order[:split]] = True
        orders.append((order, split))
    if shard.lists is None:
        scores = np.where(essential, q, 0) @ shard.c.T
        left = shard.norms - essential.astype(float) @ shard.squares.T
    out = []
    rest_q = np.sqrt((np.where(essential, 0, q).astype(float) ** 2).sum(1))
    rest_block = shard.block_bounds(np.where(essential, 0, q))
    for i in range(len(q)):
        order, split = orders[i]
        if shard.lists is None:
            score, rest, met = scores[i], left[i], near[i][shard.block]
        else:
            score, rest, met = np.zeros(n, shard.kind), shard.norms.copy(), np.zeros(n, bool)
            for j in order[:split]:
                rows = shard.lists[j]
                met[rows] = True
                score[rows] += q[i, j] * shard.c[rows, j]
                rest[rows] -= shard.squares[rows, j]
            if not np.isfinite(floors[i]) or floors[i] <= 0:
                met[:] = True  # what no posting lists scores 0
            met &= near[i][shard.block]
        met &= shard.ids != own[i]
        counts.pairs += n
        counts.near += int(met.sum())
        at = np.flatnonzero(met)
        score, rest = score[at], rest[at]
        most = np.minimum(rest_block[i][shard.block[at]].astype(float), rest_q[i] * np.sqrt(np.maximum(rest, 0)) * (1 + 1e-9) + 1e-6)
        keep = score.astype(float) + most >= safe[i]
        at, score, rest = at[keep], score[keep], rest[keep]
        counts.competitive += len(at)
        for a in range(split, d, STEP_TERMS):
            terms, later = order[a : a + STEP_TERMS], order[a + STEP_TERMS :]
            part = shard.c[np.ix_(at, terms)]
            score = score + part @ q[i, terms]
            if len(later) and len(at) > k:
                rest = rest - (part.astype(float) ** 2).sum(1)
                left_q = q[i, later]
                by_block = np.maximum(left_q, 0) @ shard.high[:, later].T + np.minimum(left_q, 0) @ shard.low[:, later].T
                most = np.minimum(by_block[shard.block[at]].astype(float), np.sqrt((left_q.astype(float) ** 2).sum() * np.maximum(rest, 0)) * (1 + 1e-9) + 1e-6)
                keep = score.astype(float) + most >= safe[i]
                at, score, rest = at[keep], score[keep], rest[keep]
        counts.completed += len(at)
        best = np.lexsort((shard.ids[at], -score))[:k] if shard.kind is not object else np.array(sorted(range(len(at)), key=lambda x: (-score[x], shard.ids[at[x]]))[:k], int)
        out.append((shard.ids[at][best], score[best]))
        if len(best) == k:
            floors[i] = max(floors[i], float(score[best[-1]]))
    return out


def exact_kind(q: np.ndarray, m: np.ndarray) -> type:
    """Doubles where every sum stays exact in them, else Python integers."""
    most = [max(abs(int(x.min(initial=0))), abs(int(x.max(initial=0)))) for x in (q, m)]
    return np.float64 if most[0] * most[1] * max(q.shape[1], m.shape[1]) < 1 << 52 else object


def _compare(batches: Iterator[pa.RecordBatch], k: int) -> Iterator[pa.RecordBatch]:
    known: tuple = ()
    floors: dict[int, np.ndarray] = {}
    for batch in batches:
        for row in (batch.slice(i, 1).to_pylist()[0] for i in range(batch.num_rows)):
            ids, m = _unpack(row["n"], row["width"], row["ids"], row["vecs"])
            q_ids, q = _unpack(row["q_n"], row["q_width"], row["q_ids"], row["q_vecs"])
            width, kind = max(q.shape[1], m.shape[1]), exact_kind(q, m)
            if known[:3] != (row["shard"], width, kind):
                known = (row["shard"], width, kind, Shard(ids, m, width, kind))
            q = np.pad(q, ((0, 0), (0, width - q.shape[1])))
            floor = floors.setdefault(row["block"], np.full(len(q), -np.inf))
            found = max_score(q, q_ids, known[3], k, floor)
            who = np.repeat(q_ids, [len(v) for v, _ in found])
            no = np.repeat(np.arange(len(q)), [len(v) for v, _ in found])
            scores = [int(s) for _, part in found for s in part]
            cols = [who, np.full(len(who), row["block"]), no, np.concatenate([v for v, _ in found]), scores]
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in cols], ["query_id", "block", "no", "vec_id", "score"])


def top_k(queries: DataFrame, vectors: DataFrame, k: int = 5, scale: float = 256.0, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """``(query_id, rank, vec_id, score)``: each query's k best other vectors, exactly."""
    c, q = quantise(vectors, scale, id_col, vec_col), quantise(queries, scale, id_col, vec_col).distinct()
    n_shards, n_blocks = (max(1, -(-df.count() // n)) for df, n in ((vectors, SHARD_ROWS), (queries, BLOCK_ROWS)))
    shards = materialize(_blocks(c, n_shards, "shard"), "shards")
    # stored, so that a query's number in its block is the same in every shard, whatever is computed again
    blocks = materialize(_blocks(q, n_blocks, "block"), "queries").select("block", *(F.col(x).alias(f"q_{x}") for x in ("n", "width", "ids", "vecs")))
    # every block of queries goes to every shard; a shard's matrix moves once. By shuffle: Spark takes the copies of
    # the blocks for no larger than the blocks, and would gather them on the driver for a broadcast
    met = blocks.withColumn("shard", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n_shards - 1).cast("long")))).hint("merge").join(shards, "shard")
    found = met.mapInArrow(lambda it: _compare(it, k), "query_id long, block long, no long, vec_id long, score long")
    w = Window.partitionBy("query_id", "block", "no").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
