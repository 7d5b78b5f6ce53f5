import random
from fractions import Fraction

import corpus_pipeline as cp
import numpy as np
import pytest

from motifjoin.llm import groups, simhash


def word_sets(text, width=5):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    for c in "\t\n\x0b\x0c\r":
        low = low.replace(c, " ")
    words = [w for w in low.split(" ") if w]
    return frozenset(" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))) if words else frozenset()


def brute(rows, similarity=Fraction(4, 5)):
    """Smallest doc_id of every component over all pairs of Jaccard similarity, set against set."""
    sets = [word_sets(t) for _, t in rows]
    label = list(range(len(rows)))

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if a == b or len(a & b) >= similarity * len(a | b):
                p, q = find(i), find(j)
                label[max(p, q)] = min(p, q)
    least = {}
    for k, (i, _) in enumerate(rows):
        if i is not None:
            least[find(k)] = min(i, least.get(find(k), i))
    return sorted(((i, least.get(find(k))) for k, (i, _) in enumerate(rows)), key=repr)


def edited(seed, n=40):
    """Texts and copies of them with words replaced, on both sides of the similarity."""
    rng, rows = random.Random(seed), []
    for k in range(n):
        words = ["w%d" % rng.randrange(3000) for _ in range(rng.choice((3, 8, 60, 200, 400)))]
        rows.append((len(rows), " ".join(words)))
        for _ in range(rng.randrange(3)):
            copy = list(words)
            for _ in range(rng.randrange(1, max(2, len(words) // 25))):
                copy[rng.randrange(len(copy))] = "Zz%d" % rng.randrange(99)
            rows.append((len(rows), " ".join(copy)))
    return rows


def test_stage_keeps_one_of_documents_that_differ_in_a_few_words(spark, sf):
    rows = edited(1)
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    kept = {r.doc_id for r in cp.keep_one_of_each_group(spark, docs, sf).collect()}
    assert kept == {c for _, c in brute(rows)} and len(kept) < len(rows)


def test_components_equal_brute_force_over_pairs(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    rows += [(1000 + i, t) for i, t in edited(2, 20)] + [(None, None), (5000, ""), (None, "a B"), (None, "A b"), (5001, " \n"), (5000, "")]
    got = simhash.similar_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(map(tuple, got), key=repr) == brute(rows)


def test_large_groups_are_split_without_loss(spark, monkeypatch):
    monkeypatch.setattr(groups, "GROUP_ROWS", 8)
    monkeypatch.setattr(groups, "PIVOTS", 2)
    base = ["b%d" % k for k in range(300)]
    rows = [(i, " ".join(base[:i] + ["x%d" % i] + base[i + 1 :])) for i in range(60)] + [(60 + i, " ".join(base[:30] + ["y%d_%d" % (i, k) for k in range(300)])) for i in range(20)]
    got = simhash.similar_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(map(tuple, got), key=repr) == brute(rows)


def test_candidates_have_high_recall():
    rng, near, far = random.Random(6), 0, 0
    for _ in range(400):
        n = rng.choice((9, 20, 60, 300))
        a = {rng.getrandbits(64) for _ in range(n)}
        gone = rng.sample(sorted(a), n // 9)  # shared 8/9 of each: similarity 0.8
        b = (a - set(gone)) | {rng.getrandbits(64) for _ in gone}
        c = {rng.getrandbits(64) for _ in range(n)}
        x, y, z = (simhash.wide_fingerprint(np.array(sorted(v), np.uint64)) for v in (a, b, c))
        near += sum((p ^ q).bit_count() for p, q in zip(x, y)) <= simhash.SET_RADIUS
        far += sum((p ^ q).bit_count() for p, q in zip(x, z)) <= simhash.SET_RADIUS
    assert near >= 398 and far == 0


@pytest.mark.parametrize("same", [True, False])
def test_candidates_between_tiles_lose_nothing(same):
    rng = np.random.default_rng(8)
    base = rng.integers(0, 2**63, (60, 2)).astype(np.uint64)
    words = np.concatenate([base, base ^ (np.uint64(1) << rng.integers(0, 63, (60, 2)).astype(np.uint64)), rng.integers(0, 2**63, (300, 2)).astype(np.uint64)])
    sizes = np.concatenate([np.full(60, 100), rng.integers(70, 140, 60), rng.integers(4, 400, 300)]).astype(np.int32)
    order = np.argsort(sizes, kind="stable")
    tile = (order.astype(np.int64), sizes[order], words[order])
    tiles = [(tile, tile)] if same else [(tuple(x[::2] for x in tile), tuple(x[1::2] for x in tile))]
    label = {int(i): int(i) for i in order}

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    for u, v in zip(*simhash.set_links_between(*tiles[0], 2, 0.8, same)):
        label[find(int(u))] = find(int(v))
    left, right = (tiles[0][k][0].tolist() for k in (0, 1))
    for i in left:
        for j in right:
            near = np.bitwise_count(words[i] ^ words[j]).sum() <= 2 and min(sizes[i], sizes[j]) >= 0.8 * max(sizes[i], sizes[j])
            assert not near or find(i) == find(j)
    assert len({find(x) for x in label}) > 300


def test_one_of_each_keeps_whole_rows(spark):
    rows = [(3, "A b", "x", 1), (3, "c d", "y", 2), (1, "a B", "z", 3), (None, "a b", "n", 4), (None, "e", "n", 5), (None, "e", "n", 5), (7, None, "q", 6), (8, " ", "q", 7)]
    df = spark.createDataFrame(rows, "doc_id long, text string, node string, row int")
    assert sorted(r.row for r in simhash.one_of_each(df).collect()) == [2, 3, 5, 6] and simhash.one_of_each(df).columns == df.columns


def test_large_parts_by_size(spark):
    rows = spark.createDataFrame([(g, 100 * g + k, 10) for g, n in ((1, 1), (2, 3), (3, 50)) for k in range(n)], "g long, h long, size int")
    got = [(sorted(np.frombuffer(r.members, np.int64).tolist()), r.gid) for r in groups.deal_rows(rows, 100).collect()]
    assert ([200, 201, 202], None) in got and all(g == 3 for m, g in got if m[0] >= 300) and len(got) > 2
    assert {x for m, g in got if g for x in m} == set(range(300, 350))
    pivots = set.intersection(*(set(m) for m, g in got if g))
    assert pivots


def test_empty_table(spark):
    assert simhash.similar_documents(spark.createDataFrame([], "doc_id long, text string")).count() == 0
