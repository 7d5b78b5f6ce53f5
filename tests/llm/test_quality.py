import itertools
import zlib

import numpy as np
import pytest

from motifjoin.llm import quality, queries


def test_forward_backward_equals_enumeration():
    rng = np.random.default_rng(4)
    n_lines = np.array([3, 1, 4, 2])
    emit, trans = rng.normal(size=n_lines.sum()), rng.normal(size=(2, 2))
    z, good, expected = quality.forward_backward(emit, n_lines, trans)
    at, total = 0, np.zeros((2, 2))
    for k, n in enumerate(n_lines):
        e = emit[at : at + n]
        paths = list(itertools.product((0, 1), repeat=int(n)))
        w = np.array([sum(e[i] * p[i] for i in range(n)) + sum(trans[a, b] for a, b in zip(p, p[1:])) for p in paths])
        assert z[k] == pytest.approx(np.log(np.exp(w).sum()))
        prob = np.exp(w - z[k])
        for i in range(n):
            assert good[at + i] == pytest.approx(sum(q for q, p in zip(prob, paths) if p[i]))
        for q, p in zip(prob, paths):
            for a, b in zip(p, p[1:]):
                total[a, b] += q
        at += n
    assert expected == pytest.approx(total)


def test_query_on_held_out_documents(spark):
    sf = "/root/testdata/sf0.01"
    out = queries.op2_line_field_quality(spark, sf).collect()
    docs = {r.doc_id for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    truth = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    assert {r.doc_id for r in out} == docs and len(out) == len(docs)
    for r in out:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3)
    held = [(truth[r.doc_id], r.predicted) for r in out if r.held_out and r.doc_id in truth]
    assert len(held) > 40 and np.mean([a == b for a, b in held]) >= 0.95


def test_labels_of_held_out_rows_do_not_matter(spark, sf):
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    flipped = labels.withColumn("quality", quality.F.when(quality.held_out(labels.doc_id), 1 - labels.quality).otherwise(labels.quality))
    a, b = quality.train(docs, labels), quality.train(docs, flipped)
    assert (a.weights == b.weights).all()


def test_odd_rows(spark):
    docs = spark.createDataFrame([(1, None, "c"), (2, "", "c"), (None, "a\nb", "c"), (3, "good words here\n\n!!!###\n" * 3000, "c"), (3, "x", "c")], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(1, 0), (3, 1), (3, None), (None, 1)], "doc_id long, quality int")
    for known in (labels, labels.limit(0), labels.filter("quality = 1")):
        out = quality.score_documents(docs, quality.train(docs, known)).collect()
        assert len(out) == 5 and all(0 <= r["score"] <= 1 for r in out)
    model = quality.train(docs, labels)
    assert quality.score_documents(docs.limit(0), model).count() == 0
    assert quality.train(docs.limit(0), labels).constant == 0.5


def test_bad_lines_lower_the_score(spark):
    sf = "/root/testdata/sf0.01"
    model = quality.train(*(spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels")))
    good = "The hand of the other was in and there.\nOf the one and then to her, an inner rest."
    one, two, three = model.scores([good, good + "\nBUY!! NOW!! AND!! GET!! IT!! ALL!! HERE!!", "BUY!! NOW!! AND!! GET!! IT!! ALL!! HERE!!"])
    assert one > two > three
