"""Benchmark decontamination by pigeonhole edit matching.

An item of m words may differ from a passage of a document by up to
``k = floor(rate * m)`` word edits. Cut into k + 1 pieces, at least one piece
of it stands unchanged in any such passage. Exact piece hits are looked up by
the hash of their words; around every hit the distance is verified with Myers'
bit-parallel algorithm over words, the item's bits in one integer of m bits.

Words are runs of letters and digits, lower-cased, so punctuation, case and
spacing do not count; in scripts written without spaces every letter is a word.
Every item of one word or more is searched for; ``min_words`` can leave out
those of fewer words, which few budgets and common words make meaningless.

The items are dealt by hash into blocks of about ``block_items`` items and
``block_chars`` characters. The driver holds one block at a time: with several,
each block's pass over the documents is written before the next one is fetched.

Defined results: null or wordless texts and items match nothing; items of equal
words are each reported; null ``doc_id`` is reported as null; repeated rows are
reported each; other columns are ignored. ``doc_id`` and ``item_id`` keep their types.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from motifjoin.workspace import materialize, new_path

Items = list[tuple[object, str]]
#: Letters of scripts without spaces between words: Thai, Lao, Myanmar, Khmer, kana, Han.
_DENSE = r"\u0e01-\u0eff\u1000-\u109f\u1780-\u17ff\u3005-\u3007\u3040-\u30ff\u31f0-\u31ff\u3400-\u4dbf\u4e00-\u9fff\uf900-\ufaff\uff66-\uff9f\U00020000-\U0003ffff"
WORD, DENSE = re.compile(r"\w+"), re.compile(f"[{_DENSE}]")
_DENSE_WORD = re.compile(rf"(?![{_DENSE}])\w(?:(?![{_DENSE}])\w)*|(?=\w)[{_DENSE}]")


def words_of(text: str | None) -> list[str]:
    if not text:
        return []
    return (WORD if text.isascii() or not DENSE.search(text) else _DENSE_WORD).findall(text.lower())


def pieces(n: int, budget: int) -> list[tuple[int, int]]:
    """``budget + 1`` spans that cover 0..n, of equal length but for one."""
    k = min(budget + 1, n)
    cuts = [n * i // k for i in range(k + 1)]
    return list(zip(cuts, cuts[1:]))


def best_ending(pattern: dict[str, int], m: int, text: list[str]) -> tuple[int, int]:
    """Myers: the least edit distance of the pattern to any substring, and the first end of one."""
    ones, high = (1 << m) - 1, 1 << (m - 1)
    pv, mv, score = ones, 0, m
    best, end = m, 0
    for j, word in enumerate(text):
        eq = pattern.get(word, 0)
        xv = eq | mv
        xh = (((eq & pv) + pv) ^ pv) | eq
        ph, mh = mv | ~(xh | pv) & ones, pv & xh
        if ph & high:
            score += 1
        elif mh & high:
            score -= 1
        ph, mh = (ph << 1) & ones, (mh << 1) & ones  # a match may begin anywhere: no cost for the text before it
        pv, mv = mh | ~(xv | ph) & ones, ph & xv
        if score < best:
            best, end = score, j + 1
    return best, end


def bits_of(words: list[str]) -> dict[str, int]:
    out: dict[str, int] = defaultdict(int)
    for i, w in enumerate(words):
        out[w] |= 1 << i
    return dict(out)


def merged(windows: Iterable[tuple[int, int]]) -> list[tuple[int, int]]:
    """Windows in order, those that overlap as one."""
    out: list[tuple[int, int]] = []
    for low, high in sorted(windows):
        if out and low < out[-1][1]:
            out[-1] = (out[-1][0], max(high, out[-1][1]))
        else:
            out.append((low, high))
    return out


class PieceIndex:
    """Pieces of the items by first word, then by all words; and the items' bits."""

    def __init__(self, items: Items, rate: float, min_words: int) -> None:
        self.items: list[tuple[object, list[str], int, dict[str, int], dict[str, int]]] = []
        self.by_first: dict[str, dict[int, dict[tuple[str, ...], list[tuple[int, int]]]]] = {}
        for item_id, text in items:
            words = words_of(text)
            if len(words) < max(1, min_words):
                continue
            budget = int(rate * len(words))
            no = len(self.items)
            self.items.append((item_id, words, budget, bits_of(words), bits_of(words[::-1])))
            for a, b in pieces(len(words), budget):
                self.by_first.setdefault(words[a], {}).setdefault(b - a, {}).setdefault(tuple(words[a:b]), []).append((no, a))

    def search(self, words: list[str]) -> dict[int, tuple[int, int, int]]:
        """Item number to ``(distance, start, end)`` of its best passage within the budget."""
        near: dict[int, list[int]] = defaultdict(list)
        get = self.by_first.get
        for at, lengths in ((i, x) for i, x in enumerate(map(get, words)) if x is not None):
            for n, known in lengths.items():
                for no, offset in known.get(tuple(words[at : at + n]), ()):
                    near[no].append(at - offset)
        found = {}
        for no, begins in near.items():
            _, item, budget, bits, mirrored = self.items[no]
            m = len(item)
            for low, high in merged((max(0, begin - budget), min(len(words), begin + m + 2 * budget)) for begin in begins):
                best, end = best_ending(bits, m, words[low:high])
                if best <= budget and (no not in found or best < found[no][0]):
                    # the same from the end backwards gives the longest-known start of that passage
                    _, back = best_ending(mirrored, m, words[low : low + end][::-1])
                    found[no] = (best, low + end - back, low + end)
                    if best == 0:
                        break
        return found


_ARROW = [("distance", pa.int32()), ("budget", pa.int32()), ("start", pa.int32()), ("end", pa.int32())]


def _search(batches: Iterator[pa.RecordBatch], items: Items, item_type: pa.DataType, rate: float, min_words: int) -> Iterator[pa.RecordBatch]:
    index = PieceIndex(items, rate, min_words)
    for batch in batches:
        at, rows = [], []
        for i, text in enumerate(batch.column(1)):
            for no, (distance, start, end) in sorted(index.search(words_of(text.as_py())).items()):
                at.append(i)
                rows.append((index.items[no][0], distance, index.items[no][2], start, end))
        cols = [pa.array([r[k] for r in rows], t) for k, (_, t) in enumerate([("item_id", item_type), *_ARROW])]
        yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(at, pa.int64())), *cols], ["doc_id", "item_id", *(n for n, _ in _ARROW)])


def _clean(batches: Iterator[pa.RecordBatch], items: Items, rate: float, min_words: int) -> Iterator[pa.RecordBatch]:
    index = PieceIndex(items, rate, min_words)
    for batch in batches:
        yield batch.filter(pa.array([not index.search(words_of(t.as_py())) for t in batch.column("text")], pa.bool_()))


def item_blocks(benchmark: DataFrame, block_items: int, block_chars: int) -> tuple[int, Callable[[int], Items]]:
    """How many blocks the items are dealt into, and a function that fetches one."""
    rows = benchmark.select("item_id", "text").filter("text is not null")
    n, chars = rows.agg(F.count(F.lit(1)), F.sum(F.length("text"))).first()
    blocks = max(1, -(-n // block_items), -(-(chars or 0) // block_chars))
    dealt = rows.withColumn("block", F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)))

    def fetch(k: int) -> Items:
        return [(r["item_id"], r["text"]) for r in dealt.filter(F.col("block") == k).orderBy("item_id", "text").collect()]

    return blocks, fetch


def contaminated(docs: DataFrame, benchmark: DataFrame, rate: float = 0.2, min_words: int = 1, block_items: int = 20_000, block_chars: int = 8_000_000) -> DataFrame:
    """``doc_id, item_id, distance, budget, start, end`` (words) for every item that a document holds within its budget."""
    rows = docs.select("doc_id", "text")
    kinds = {"doc_id": rows.schema["doc_id"].dataType, "item_id": benchmark.schema["item_id"].dataType}
    schema = ", ".join(f"{n} {t.simpleString()}" for n, t in kinds.items()) + ", distance int, budget int, start int, end int"
    item_type = to_arrow_type(kinds["item_id"])
    blocks, fetch = item_blocks(benchmark, block_items, block_chars)
    one = lambda items: rows.mapInArrow(lambda it: _search(it, items, item_type, rate, min_words), schema)
    if blocks == 1:
        return one(fetch(0))
    path = new_path(docs.sparkSession, "hits")
    for k in range(blocks):
        one(fetch(k)).write.parquet(f"{path}/block={k}")
    return docs.sparkSession.read.schema(schema).parquet(*(f"{path}/block={k}" for k in range(blocks)))


def clean_documents(docs: DataFrame, benchmark: DataFrame, rate: float = 0.2, min_words: int = 1, block_items: int = 20_000, block_chars: int = 8_000_000) -> DataFrame:
    """``docs`` without the rows that hold an item; no row moves. With several blocks the rows left after each are written."""
    blocks, fetch = item_blocks(benchmark, block_items, block_chars)
    schema = docs.schema
    for k in range(blocks):
        docs = docs.mapInArrow(lambda it, items=fetch(k): _clean(it, items, rate, min_words), schema)
        if k + 1 < blocks:
            docs = materialize(docs, "clean")
    return docs
