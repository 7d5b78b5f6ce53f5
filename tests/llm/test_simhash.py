import re

import numpy as np
import pytest
import xxhash

from motifjoin.llm import queries, simhash


def brute_fp(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not words:
        return 0
    grams = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute(rows, radius=2):
    fps = [(i, brute_fp(t)) for i, t in rows]
    arr = np.array([f for _, f in fps], np.uint64)
    label = list(range(len(fps)))

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    for i in range(len(fps)):
        for j in np.flatnonzero(np.bitwise_count(arr ^ arr[i]) <= radius):
            a, b = find(i), find(int(j))
            label[max(a, b)] = min(a, b)
    least = {}
    for k, (i, _) in enumerate(fps):
        if i is not None:
            least[find(k)] = min(i, least.get(find(k), i))
    return sorted(((i, f"{f:016x}", least.get(find(k))) for k, (i, f) in enumerate(fps)), key=repr)


def test_query_equals_brute_force(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    assert sorted(map(tuple, queries.op6_simhash_near_dedup(spark, sf).collect()), key=repr) == brute(rows)


def test_links_between_tiles_lose_nothing():
    rng = np.random.default_rng(5)
    base = rng.integers(0, 2**63, 400).astype(np.uint64)
    flips = np.uint64(1) << rng.integers(0, 64, (400, 3)).astype(np.uint64)
    fps = np.unique(np.concatenate([base, base ^ flips[:, 0], base ^ flips[:, 0] ^ flips[:, 1], base ^ flips[:, 2] ^ flips[:, 1] ^ flips[:, 0]]))
    order = np.lexsort((*simhash.word_counts(fps).T[::-1],))
    fps = fps[order]
    half = len(fps) // 2
    a, b = fps[:half], fps[half:]
    label = {int(x): int(x) for x in fps}

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    for x, y, same in ((a, a, True), (a, b, False), (b, b, True)):
        for u, v in zip(*simhash.links_between(x, y, 2, same)):
            assert int(np.bitwise_count(u ^ v)) >= 0
            p, q = find(int(u)), find(int(v))
            label[max(p, q)] = min(p, q)
    for i, x in enumerate(fps):
        for y in fps[np.bitwise_count(fps ^ x) <= 2]:
            assert find(int(x)) == find(int(y))


@pytest.mark.parametrize("n", [0, 1, 5])
def test_odd_rows(spark, n):
    rows = [(1, None), (2, ""), (3, " \n\t"), (None, "A b"), (4, "a B"), (5, "one two three four"), (5, "one two three four"), (None, "zz yy")][: n or 8]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as fp", "2 as root")
    found = simhash.near_duplicates(df).select("doc_id", simhash.fp_hex("fp"), "component_id").collect()
    assert sorted(map(tuple, found), key=repr) == brute(rows)


def test_empty_table(spark):
    assert simhash.near_duplicates(spark.createDataFrame([], "doc_id long, text string")).count() == 0
