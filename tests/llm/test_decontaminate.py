import random

import numpy as np
import pytest

from motifjoin.llm import decontaminate as d
from motifjoin.llm import queries


def substring_distance(p, t):
    """Sellers' table: least distance of p to any substring of t."""
    row = list(range(len(p) + 1))
    best = row[-1]
    for w in t:
        new = [0]
        for i, x in enumerate(p):
            new.append(min(row[i] + (x != w), row[i + 1] + 1, new[i] + 1))
        row = new
        best = min(best, row[-1])
    return best


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a):
        new = [i + 1]
        for j, y in enumerate(b):
            new.append(min(row[j] + (x != y), row[j + 1] + 1, new[j] + 1))
        row = new
    return row[-1]


def all_distances(p, t, codes):
    """The same table by columns of numpy: running minima over the pattern stand in for the inner loop."""
    p, t = (np.array([codes.setdefault(w, len(codes)) for w in x]) for x in (p, t))
    steps = np.arange(len(t) + 1)
    row = np.zeros(len(t) + 1, int)
    for i, x in enumerate(p):
        new = np.append(i + 1, np.minimum(row[1:] + 1, row[:-1] + (t != x)))
        row = np.minimum.accumulate(new - steps) + steps
    return int(row.min())


def brute(docs, items, rate, min_words):
    """Every document against every item, whole."""
    out, codes = set(), {}
    items = [(j, d.words_of(p)) for j, p in items]
    for i, t in docs:
        tw = d.words_of(t)
        for j, pw in items:
            if pw and len(pw) >= min_words and (s := all_distances(pw, tw, codes)) <= int(rate * len(pw)):
                out.add((i, j, s))
    return out


def test_two_tables_agree():
    rng = random.Random(5)
    for _ in range(300):
        p, t = (["ab"[rng.randrange(2)] for _ in range(rng.randrange(1, 12))] for _ in range(2))
        assert all_distances(p, t, {}) == substring_distance(p, t)


def test_query_equals_brute_force(spark, sf):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    got = queries.op9_benchmark_decontamination(spark, sf).collect()
    assert {(r.doc_id, r.item_id, r.distance) for r in got} == brute(docs, items, 0.2, 1)


@pytest.mark.parametrize("seed", range(4))
def test_edited_passages(seed):
    rng = random.Random(seed)
    items = [(k, " ".join(rng.choice("abcdefgh") * 2 + str(rng.randrange(9)) for _ in range(rng.randrange(3, 90)))) for k in range(12)]
    docs = []
    for k in range(40):
        words = d.words_of(rng.choice(items)[1])
        for _ in range(rng.randrange(0, 14)):
            at = rng.randrange(len(words) + 1)
            words[at : at + rng.randrange(2)] = ["zz"] * rng.randrange(2)
        pad = lambda: ["p%d" % rng.randrange(50) for _ in range(rng.randrange(30))]
        docs.append((k, " ".join(pad() + words + pad())))
    index = d.PieceIndex(items, 0.2, 3)
    got = set()
    for i, t in docs:
        for no, (dist, a, b) in index.search(d.words_of(t)).items():
            got.add((i, index.items[no][0], dist))
            assert distance(index.items[no][1], d.words_of(t)[a:b]) == dist
    assert got == brute(docs, items, 0.2, 3)


def test_odd_rows(spark):
    item = "one two three four five six seven eight nine ten"
    docs = [(1, f"x {item} y"), (None, item.upper().replace(" ", ", ")), (2, None), (3, ""), (1, f"x {item} y"), (4, item.replace("five", "5")), (5, "w " * 3000 + item), (6, "one two three")]
    df = spark.createDataFrame(docs, "doc_id long, text string").selectExpr("*", "1 as item_id", "2 as start")
    bench = spark.createDataFrame([(7, item), (8, item), (9, None), (10, "")], "item_id long, text string").selectExpr("*", "3 as doc_id")
    got = d.contaminated(df, bench, block_items=1).collect()
    assert sorted((r.doc_id or 0, r.item_id, r.distance) for r in got) == sorted((i, j, x) for i, x in ((1, 0), (1, 0), (0, 0), (4, 1), (5, 0)) for j in (7, 8))
    assert sorted(r.doc_id for r in d.clean_documents(df, bench).collect()) == [2, 3, 6]
    assert d.contaminated(df, bench.limit(0)).count() == 0 and d.contaminated(df.limit(0), bench).count() == 0


def test_items_whose_pieces_repeat():
    item = "a b c P Q R S d e f g P Q R S"
    for before, after in ((30, 30), (30, 0), (0, 30), (0, 0)):
        words = ["x%d" % k for k in range(before)] + d.words_of("a x c P y R S d z f g P Q R S") + ["y%d" % k for k in range(after)]
        found = d.PieceIndex([(1, item)], 0.2, 8).search(words)
        assert found == {0: (3, before, before + 15)}


@pytest.mark.parametrize("seed", range(4))
def test_few_words_repeated_lose_no_item(seed):
    """Small vocabularies, so that pieces repeat and passages overlap, touch the text's ends or run over them."""
    rng = random.Random(seed)
    for _ in range(1500):
        vocabulary = ["aa", "bb", "cc"][: rng.randrange(2, 4)]
        item = [rng.choice(vocabulary) for _ in range(rng.randrange(1, 25))]
        text = [rng.choice(vocabulary) for _ in range(rng.randrange(0, 12))]
        for _ in range(rng.randrange(1, 3)):
            part = list(item)
            for _ in range(rng.randrange(0, 5)):
                at = rng.randrange(len(part) + 1)
                part[at : at + rng.randrange(2)] = [rng.choice(vocabulary)] * rng.randrange(2)
            text += part + [rng.choice(vocabulary) for _ in range(rng.randrange(0, 6))]
        found = d.PieceIndex([(0, " ".join(item))], 0.2, 1).search(text)
        least = substring_distance(item, text)
        assert (found[0][0] if found else None) == (least if least <= int(0.2 * len(item)) else None)


def test_short_items_are_found(spark):
    bench = spark.createDataFrame([(1, "Who wrote Hamlet?"), (2, "中国的首都在哪里呢"), (3, "one two"), (4, "a b c d e")], "item_id long, text string")
    docs = [(1, "x who wrote HAMLET y"), (2, "who wrote the Hamlet"), (3, "请问中国的首都在哪里呢？谢谢"), (4, "请问中国的首府在哪里呢"), (5, "one two"), (6, "x a b d e")]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = {(r.doc_id, r.item_id, r.distance, r.budget) for r in d.contaminated(df, bench).collect()}
    assert got == {(1, 1, 0, 0), (3, 2, 0, 1), (4, 2, 1, 1), (5, 3, 0, 0), (6, 4, 1, 1)}
    assert sorted(r.doc_id for r in d.clean_documents(df, bench).collect()) == [2]
    assert {(r.doc_id, r.item_id) for r in d.contaminated(df, bench, min_words=3).collect()} == {(1, 1), (3, 2), (4, 2), (6, 4)}


def test_blocks_agree_and_ids_keep_their_types(spark, sf):
    docs, bench = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "benchmark"))
    named = bench.selectExpr("concat('i', item_id) as item_id", "text")
    one, several = d.contaminated(docs, bench), d.contaminated(docs.selectExpr("string(doc_id) as doc_id", "text"), named, block_items=7)
    assert [f.dataType.simpleString() for f in several.schema][:2] == ["string", "string"]
    assert sorted((str(r.doc_id), f"i{r.item_id}", r.distance) for r in one.collect()) == sorted((r.doc_id, r.item_id, r.distance) for r in several.collect())
    left = d.clean_documents(docs, bench, block_chars=500)
    assert sorted(r.doc_id for r in left.collect()) == sorted(r.doc_id for r in d.clean_documents(docs, bench).collect())


def test_words_of_mixed_scripts():
    assert d.words_of("ab中国c1 été, ！テ") == ["ab", "中", "国", "c1", "été", "テ"]
