import hashlib
import random
import re
from collections import defaultdict

import numpy as np
import pytest

from motifjoin.llm import queries, substring

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def brute(rows, width=20):
    where, docs = {}, [(i, WORDS.findall(t or "")) for i, t in rows]
    place = lambda i, s: (i is None, i or 0, s)
    for i, words in docs:
        for s in range(len(words) - width + 1):
            w = tuple(words[s : s + width])
            where[w] = min(place(i, s), where.get(w, place(i, s)))
    out = []
    for i, words in docs:
        gone = set()
        for s in range(len(words) - width + 1):
            if where[tuple(words[s : s + width])] < place(i, s):
                gone.update(range(s, s + width))
        kept = " ".join(w for k, w in enumerate(words) if k not in gone)
        out.append((i, len(words), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out, key=repr)


def got(df):
    return sorted(((r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in df.collect()), key=repr)


def test_query_equals_brute_force(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    assert got(queries.op4_substring_dedup(spark, sf)) == brute(rows)


@pytest.mark.parametrize("batch_words", [40, 1 << 20])
def test_small_windows_over_many_sub_batches(spark, monkeypatch, batch_words):
    monkeypatch.setattr(substring, "BATCH_WORDS", batch_words)
    rng = random.Random(2)
    rows = [(rng.randrange(-5, 10**9), " ".join(rng.choice("abc") for _ in range(rng.randrange(0, 30)))) for _ in range(80)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert got(substring.dedup_substrings(df, 4)) == brute(rows, 4)


def test_odd_rows(spark):
    long = " ".join(f"w{k % 4000}" for k in range(9000))
    rows = [(1, None), (2, ""), (3, "a b c d e"), (3, "a b c d e"), (None, "a b c d e"), (None, "q r s t a b c"), (4, "a\tb\x0bc d e"), (5, long), (6, "x " + long), (3, "zz a b c d")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as d", "2 as tag", "3 as spans")
    assert got(substring.dedup_substrings(df, 3)) == brute(rows, 3)
    assert substring.dedup_substrings(df.limit(0), 3).count() == 0


def test_kept_text_and_spans(spark):
    df = spark.createDataFrame([(1, "a b c d"), (2, "x a b c y")], "doc_id long, text string")
    two = substring.dedup_substrings(df, 3).filter("doc_id = 2").first()
    assert two.kept == "x y" and [tuple(s) for s in two.spans] == [(1, 4)]


def test_window_hashes_do_not_depend_on_place():
    w = np.random.default_rng(1).integers(0, 2**63, 50).astype(np.uint64)
    powers = substring._powers(60)
    whole, part = substring.window_hashes(w, 5, powers), substring.window_hashes(w[7:30], 5, powers)
    assert (whole[7 : 7 + len(part)] == part).all() and len(set(whole.tolist())) == len(whole)


def test_packing_is_lossless():
    h = np.random.default_rng(1).integers(0, 2**64, 500, dtype=np.uint64)
    for b in (256, 1000, 70_000):
        assert (substring._uncut(substring._cut(h, b), 500) == h // np.uint64(b)).all()
    a = np.sort(np.random.default_rng(2).integers(-(2**62), 2**62, 300))
    assert all((x == y).all() for x, y in zip(substring._spread(substring._squeeze(a, a[:0], a[::-1]), 3), (a, a[:0], a[::-1])))
