from collections import Counter

import corpus_pipeline as cp
from test_decontaminate import brute as brute_leaks
from test_linededup import brute as brute_lines
from test_mixing import WORDS
from test_similar import brute as brute_copies

from motifjoin.llm import linededup, mixing, quality
from motifjoin.workspace import materialize


def test_every_stage_equals_brute_force_on_its_input(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    benchmark = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    columns = docs.columns
    seen = {}
    for name, stage in cp.STAGES:
        before = {r.doc_id: r for r in docs.collect()}
        docs = materialize(stage(spark, docs, sf))
        seen[name] = (before, docs.collect())
        assert docs.columns == columns or name == cp.STAGES[-1][0]
    (b1, a1), (b2, a2), (b3, a3), (b4, a4), (b5, a5) = (seen[n] for n, _ in cp.STAGES)
    model = quality.train(spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet"))
    ids = sorted(b1)
    good = {i for i, s in zip(ids, model.scores([b1[i].text for i in ids])) if s >= 0.3}
    assert {r.doc_id for r in a1} == good and all(b1[r.doc_id] == r for r in a1)
    lost = {i: n for i, _, n, _ in brute_lines([(i, r.text) for i, r in b2.items()])}
    assert {r.doc_id for r in a2} == set(b2)
    assert sum(len(linededup.lines_of(b2[r.doc_id].text)) - lost[r.doc_id] == len(linededup.lines_of(r.text)) for r in a2) >= 0.98 * len(a2)
    assert all(r.n_chars == len(r.text) for r in a2)
    assert {r.doc_id for r in a3} == {c for _, c in brute_copies([(i, r.text) for i, r in b3.items()])}
    gone = set(b4) - {r.doc_id for r in a4}
    small = [(i, r.text) for i, r in b4.items() if len(r.text) < 2000 or i in gone][:80]
    assert {i for i, _, _ in brute_leaks(small, benchmark, 0.2, 1)} == gone & {i for i, _ in small}
    assert all(b4[r.doc_id] == r for r in a4)
    size, taken = Counter(), Counter()
    for r in b5.values():
        size[r.source] += len(WORDS.findall(r.text))
    for r in a5:
        taken[r.source] += r.n_words
    order = sorted(size, key=lambda s: (s is None, s or ""))
    goal = mixing.targets([size[s] for s in order], [(5, 2, 1)[k % 3] for k in range(len(order))], sum(size.values()), 3)
    assert all(abs(taken[s] - t) <= max(0.05 * t, 2 * mixing.BLOCK_WORDS) for s, t in zip(order, goal))
    texts = {i: " ".join(WORDS.findall(r.text)) for i, r in b5.items()}
    assert all(r.text in texts[r.doc_ids[0]] for r in a5 if len(r.doc_ids) == 1)


def test_odd_rows_go_through_every_stage(spark, sf):
    rows = [(1, None, None, None, None), (2, "", "en", None, 0), (None, "lost words here", "en", "s", 15), (None, "lost words here", "en", "s", 15), (3, "a\nb\na " + "word " * 40_000, "en", "s", 5), (3, "a\nb\na " + "word " * 40_000, "en", "s", 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in cp.STAGES:
        out = materialize(stage(spark, docs, sf))
        assert out.count() <= len(rows) or name == cp.STAGES[-1][0]
        empty = stage(spark, docs.limit(0), sf)
        assert empty.count() == 0 and empty.columns == out.columns


def test_run_gives_the_mix(spark, sf):
    assert cp.run(spark, sf).columns == ["shard", "slot", "source", "block", "doc_ids", "n_words", "text"]
