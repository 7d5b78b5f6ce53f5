import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from motifjoin.llm import mixing, queries

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def check(rows, out, tolerance):
    size = Counter()
    for source, text in rows:
        size[source] += len(WORDS.findall(text or ""))
    taken, target = defaultdict(int), {}
    for r in out:
        assert 0 <= r.taken <= 3 * r.size
        taken[r.source_size, r.target] += r.taken
        target[r.source_size, r.target] = r.target
    assert sum(r.size for r in out) == sum(size.values()) and len(out) == len(rows)
    for k, t in target.items():
        n = sum(1 for s in size.values() if s == k[0])
        assert abs(taken[k] - t) <= max(tolerance * t, 2 * mixing.BLOCK_WORDS) * n
    assert sum(target.values()) == pytest.approx(sum(size.values())) or any(s * 3 <= t for (s, _), t in target.items()) or len(size) > len(target)


def test_query_meets_targets_and_reruns_agree(spark, sf):
    rows = [(r.source, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    one, two = (sorted(map(tuple, queries.op5_mix_sources(spark, sf).collect())) for _ in range(2))
    assert one == two
    check(rows, queries.op5_mix_sources(spark, sf).collect(), 0.05)


def test_targets_share_the_excess():
    assert mixing.targets([10, 1000, 1000], [5, 2, 1], 2010, 3) == pytest.approx([30, 1320, 660])
    assert mixing.targets([0, 0], [5, 2], 0, 3) == [0, 0]
    assert mixing.targets([100], [5], 100, 3) == [100]
    assert mixing.targets([1, 1, 1000], [5, 2, 1], 1002, 3) == pytest.approx([3, 3, 996])


def test_slots_come_out_exactly_and_vary_by_shard():
    drawn = mixing.slot_counts([1000, 500, 0, 7], 100, 3)
    total = Counter()
    for shard, k, first, n in drawn:
        assert first == total[k]
        total[k] += n
    assert total == {0: 1000, 1: 500, 3: 7}
    assert len({n for shard, k, _, n in drawn if k == 0}) > 3


def test_permutation_is_one():
    for n in (1, 2, 3, 64, 101, 5000):
        got = [mixing.permuted(np.arange(n), n, np.full(n, key, np.uint64)) for key in (9, 10)]
        assert all(sorted(g) == list(range(n)) for g in got)
        assert n < 64 or (got[0] != got[1]).mean() > 0.9 and (got[0] != np.arange(n)).mean() > 0.9


def test_odd_rows(spark):
    rows = [(1, "a b c", "x"), (1, "a b c", "x"), (None, "d e", None), (2, None, "y"), (3, "", None), (4, " \t", "y"), (5, "w " * 5000, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").selectExpr("*", "1 as size", "2 as block", "3 as at", "4 as bucket")
    out = mixing.taken_words(df).collect()
    assert len(out) == 7 and sum(r.size for r in out) == 5008
    assert all(r.taken <= 3 * r.size for r in out)
    assert mixing.taken_words(df.limit(0)).count() == 0


def test_slots_hold_every_block_equally_often(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    _, sources, slots = mixing.mix(docs, shard_slots=256)
    per = slots.groupBy("source_no", "block").count().groupBy("source_no").agg(F.min("count").alias("lo"), F.max("count").alias("hi"))
    assert all(r.hi - r.lo <= 1 for r in per.collect())
    assert slots.count() == sum(r.n_slots for r in sources.collect())
    assert slots.groupBy("shard").count().agg(F.max("count")).first()[0] <= 256


def expected_streams(rows, placed):
    """Each source's words in the order of the placed documents."""
    words = {}
    for (doc_id, source, text), at in placed:
        for k, w in enumerate(WORDS.findall(text or "")):
            words.setdefault(source, {})[at + k] = (w, doc_id)
    return words


def blocks_agree(spark, rows, block_words):
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    out = mixing.packed_blocks(df, block_words=block_words, shard_slots=16).collect()
    placed, sources, slots = mixing.mix(df, block_words=block_words, shard_slots=16)
    tags = {r.text: r.tag for r in df.select("text", F.xxhash64("text").alias("tag")).collect()}
    text_of = {t: x for x, t in tags.items()}
    words = expected_streams(rows, [((r.doc_id, r.source, text_of[r.tag]), r.at) for r in mixing.each_copy(placed).collect()])
    assert {s: len(w) for s, w in words.items()} == {r.source: r.source_size for r in sources.collect() if r.source_size}
    for s, w in words.items():
        assert sorted(w) == list(range(len(w)))  # no gap, no overlap
    names = {r.source_no: r.source for r in sources.collect()}
    assert sorted((r.shard, r.slot, r.source or "", r.block) for r in out) == sorted((r.shard, r.slot, names[r.source_no] or "", r.block) for r in slots.collect())
    for r in out:
        mine = [words[r.source][k] for k in range(r.block * block_words, min((r.block + 1) * block_words, len(words[r.source])))]
        assert r.text == " ".join(w for w, _ in mine) and r.n_words == len(mine)
        assert r.doc_ids == list(dict.fromkeys(d for _, d in mine))
    taken = Counter()
    for r in mixing.taken_words(df, block_words=block_words, shard_slots=16).collect():
        taken[r.doc_id] += r.taken
    got = Counter()
    for r in out:
        for k in range(r.block * block_words, min((r.block + 1) * block_words, len(words[r.source]))):
            got[words[r.source][k][1]] += 1
    assert {k: n for k, n in taken.items() if n} == dict(got)


def test_blocks_hold_the_words_of_their_slots(spark, sf):
    rows = [(r.doc_id, r.text, r.source) for r in spark.read.parquet(f"{sf}/documents.parquet").limit(60).collect()]
    blocks_agree(spark, rows, 32)


def test_blocks_of_odd_rows(spark):
    rows = [(1, "a b c", "x"), (1, "a b c", "x"), (1, "other text here", "x"), (None, "d e", None), (None, "f", None), (2, None, "y"), (3, "", None), (4, " \t", "y"), (5, "w " * 500, "x"), (6, "one", "z")]
    blocks_agree(spark, rows, 7)
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    assert mixing.packed_blocks(df.limit(0)).count() == 0


def test_null_and_repeated_ids_are_spread(spark, monkeypatch):
    monkeypatch.setattr(mixing, "BUCKET_DOCS", 10)
    df = spark.range(2000).select(F.when(F.col("id") % 2 == 0, 7).cast("long").alias("doc_id"), F.concat(F.lit("w "), "id").alias("text"), F.lit("s").alias("source"))
    sizes = mixing.document_sizes(df)
    dealt = sizes.groupBy(F.pmod(F.xxhash64("doc_id", "tag", F.lit(17)), F.lit(200)).alias("b")).count().agg(F.max("count")).first()[0]
    assert dealt < 40 and mixing.source_streams(sizes, 17).agg(F.countDistinct("at")).first()[0] == 2000
