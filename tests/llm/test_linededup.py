import hashlib
import random
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from motifjoin.llm import groups, queries
from motifjoin.llm import linededup as ld


def grams(line, width=ld.SHINGLE):
    return {line[i : i + width] for i in range(max(1, len(line) - width + 1))}


def components(lines, similar):
    root = {x: x for x in lines}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    sets = {x: grams(x) for x in lines}
    where = defaultdict(list)
    for x in lines:
        for g in sets[x]:
            where[g].append(x)
    for x in lines:
        for y in {y for g in sets[x] for y in where[g]}:
            if len(sets[x] & sets[y]) >= similar * len(sets[x] | sets[y]) - 1e-9:
                a, b = find(x), find(y)
                root[max(a, b)] = min(a, b)
    return {x: find(x) for x in lines}


def brute(rows):
    """(doc_id, n_lines, n_removed, hash of what stays) with all pairs of lines compared."""
    docs = [(i, ld.lines_of(t), t) for i, t in rows]
    of = components({x for _, lines, _ in docs for x in lines if x and not x.isspace()}, ld.SIMILARITY)
    first = {}
    place = lambda i, t, j: (i is None, i or 0, t, j)
    for i, lines, t in docs:
        for j, x in enumerate(lines):
            if x in of:
                first[of[x]] = min(place(i, t, j), first.get(of[x], place(i, t, j)))
    out = []
    for i, lines, t in docs:
        kept = [x for j, x in enumerate(lines) if x not in of or first[of[x]] == place(i, t, j)]
        out.append((i, len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return sorted(out, key=repr)


def got(df):
    return sorted(((r.doc_id, r.n_lines, r.n_removed, r.kept_sha256) for r in df.collect()), key=repr)


def test_query_equals_all_pairs(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    want, have = brute(rows), got(queries.op3_fuzzy_line_dedup(spark, sf))
    assert len(want) == len(have) and sum(a == b for a, b in zip(want, have)) >= 0.98 * len(want)
    assert sum(x[2] for x in have) == pytest.approx(sum(x[2] for x in want), rel=0.02)


@pytest.mark.parametrize("few", [0, 10**6])
def test_links_are_exact(monkeypatch, few):
    monkeypatch.setattr(groups, "FEW_ROWS", few)
    rng = random.Random(7)
    base = ["".join(rng.choice("abcdef ") for _ in range(rng.randrange(5, 120))) for _ in range(40)]
    lines = sorted({"".join(c if rng.random() > p else "z" for c in x) for x in base for p in (0, 0, 0.005, 0.02, 0.1)})
    want = components(lines, 0.8)
    root = {x: x for x in lines}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in groups.similar_links(lines, ld.SHINGLE, 0.8, ld.shingles):
        assert find(lines[a]) != find(lines[b])
        p, q = find(lines[a]), find(lines[b])
        root[max(p, q)] = min(p, q)
    assert {x: find(x) for x in lines} == want


def test_candidates_have_high_recall():
    rng = random.Random(3)
    pairs = []
    while len(pairs) < 300:
        x = "".join(rng.choice("abcdefghijklmnop ") for _ in range(rng.randrange(30, 600)))
        y = list(x)
        for _ in range(rng.randrange(1, 6)):
            y[rng.randrange(len(y))] = "z"
        a, b = grams(x), grams("".join(y))
        if len(a & b) >= 0.8 * len(a | b):
            pairs.append((x, "".join(y)))
    keys = [ld.band_keys(ld.signatures([p[k] for p in pairs], ld.SHINGLE, ld.BANDS * ld.ROWS), ld.ROWS) for k in (0, 1)]
    assert np.mean((keys[0] == keys[1]).any(1)) >= 0.99


@pytest.mark.parametrize("parts", [2, 4096])
def test_odd_rows_and_large_groups(spark, monkeypatch, parts):
    monkeypatch.setattr(groups, "GROUP_ROWS", parts)
    monkeypatch.setattr(groups, "PIVOTS", 3)
    long = "the one long line that many documents hold with some words of their own "
    rows = [(i, f"{long}{i}\nown {i} {'xyz' * i}\n\n  \nshort") for i in range(30)]
    rows += [(50, None), (51, ""), (None, f"{long}7\nnull line here"), (52, "a\nb\na"), (53, "a\nq"), (53, "a\nq"), (54, "w" * 150_000 + "\nshort"), (55, "\n\n")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'c' as gone", "1 as h", "2 as d")
    out = ld.dedup_lines(df)
    assert got(out) == brute(rows) and {"h", "d"} <= set(out.columns)
    assert [r.text for r in out.filter("doc_id = 50").collect()] == [None]
    assert ld.dedup_lines(df.limit(0)).count() == 0


def test_a_key_of_a_million_lines_is_dealt_in_linear_space():
    n = 1_000_000
    lines = np.random.default_rng(1).permutation(n).astype(np.uint64)
    bucket = pa.table({"keys": pa.array([np.full(n, 5, np.uint64).tobytes()], pa.binary()), "lines": pa.array([lines.tobytes()], pa.binary())})
    before = pa.total_allocated_bytes()
    out = ld._group(bucket)
    assert out.nbytes < 2 * lines.nbytes and pa.total_allocated_bytes() - before < 4 * lines.nbytes
    parts = [np.frombuffer(x.as_py(), np.int64) for x in out.column("members")]
    assert max(map(len, parts)) <= groups.GROUP_ROWS + groups.PIVOTS and len(set(out.column("gid").to_pylist())) == 1
    assert len(np.unique(np.concatenate(parts))) == n


def test_unlike_lines_of_one_key_are_all_compared(spark, monkeypatch):
    """Three kinds of line in one group: the pivots know one, pairs of parts find the links inside and between the rest."""
    monkeypatch.setattr(groups, "GROUP_ROWS", 4)
    monkeypatch.setattr(groups, "PIVOTS", 2)
    rng = random.Random(9)
    bases = ["".join(rng.choice("abcdefgh ") for _ in range(150)) for _ in range(12)]
    lines = sorted({b[:k] + "#" + b[k + 1 :] for b in bases for k in range(0, 150, 11)} | set(bases))
    h = {np.int64(np.uint64(ld.line_hash(x)).view(np.int64)).item(): x for x in lines}
    dealt = spark.createDataFrame([(bytearray(m), g) for m, g in groups.parts_of(np.array(sorted(h), np.int64))], groups.DEALT)
    texts = spark.createDataFrame(list(h.items()), "h long, text string")
    got_ = {r.node: r.root for r in groups.similar_roots(dealt, lambda m: texts, ld.SHINGLE, 0.8, ld.shingles).collect()}
    want = components(lines, 0.8)
    of = {x: got_.get(k, k) for k, x in h.items()}
    assert len({(of[x], want[x]) for x in lines}) == len(set(of.values())) == len(set(want.values())) == 12


def test_columns_named_like_results_are_replaced(spark):
    df = spark.createDataFrame([(1, "a\na", 5, "g", "t"), (2, "b", 6, "h", "u")], "doc_id long, text string, n_lines int, gone string, tag string").withColumn("d", F.lit(3)).withColumn("__d", F.lit(4))
    out = {r.doc_id: r for r in ld.dedup_lines(df).collect()}
    assert out[1].text == "a" and out[1].n_lines == 2 and (out[1].gone, out[1].tag, out[1].d, out[1]["__d"]) == ("g", "t", 3, 4) and out[2].n_lines == 1
