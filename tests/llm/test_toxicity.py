import random
import zlib

import numpy as np

from episode_engine.llm.toxicity import INSULTS, Voters, fit_all, fit_linear, label_model, toxicity


def made(n=600, seed=3):
    rng = random.Random(seed)
    vocabulary = [a + b for a in ("lo", "mi", "ta", "ru", "ke") for b in ("nes", "pol", "dar", "vim", "sot")]
    docs, labels = [], []
    for i in range(n):
        w = [rng.choice(vocabulary) for _ in range(rng.randint(30, 120))]
        toxic = rng.random() < 0.15
        if toxic:
            for _ in range(rng.randint(3, 6)):
                w.insert(rng.randrange(len(w)), rng.choice(INSULTS[:10]) if i % 2 else "grumzel" + rng.choice(["", "en", "x"]))
        docs.append((i, " ".join(w)))
        if rng.random() < 0.6:
            labels.append((i, int(toxic), int(not toxic)))
    return docs, labels


def test_held_out_accuracy_and_edges(spark):
    docs, labels = made()
    extra = [(1000, None), (1001, ""), (1002, "STOP IT " * 50000), (5, docs[5][1])]
    d = spark.createDataFrame(docs + extra, "doc_id long, text string").selectExpr("*", "1 as toxic", "2 as votes").repartition(3)
    lab = spark.createDataFrame([*labels, (3, None, None), (4, 7, 1)], "doc_id long, toxic int, quality int")
    got = toxicity(d, lab).collect()
    assert len(got) == len(docs) + 4
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in got)
    truth = {i: y for i, y, _ in labels}
    held = [(truth[r.doc_id], r.predicted) for r in got if r.held_out and r.doc_id in truth]
    assert sum(y == p for y, p in held) / len(held) > 0.97
    assert sum(p for y, p in held if y) / max(1, sum(y for y, _ in held)) > 0.85
    assert {r.predicted for r in got if r.doc_id in (1000, 1001)} == {0}
    # Labels of held-out rows change nothing.
    changed = [(i, 1 - y if zlib.crc32(str(i).encode()) % 3 == 1 else y, q) for i, y, q in labels]
    again = toxicity(d, spark.createDataFrame(changed, "doc_id long, toxic int, quality int")).collect()
    assert sorted((r.doc_id, round(r.score, 9)) for r in again) == sorted((r.doc_id, round(r.score, 9)) for r in got)


def test_empty_tables(spark):
    none = spark.createDataFrame([], "doc_id long, toxic int")
    assert toxicity(spark.createDataFrame([], "doc_id long, text string"), none).count() == 0
    assert toxicity(spark.createDataFrame([(1, "you idiot moron"), (2, "fine")], "doc_id long, text string"), none).count() == 2


def test_words_are_whole():
    v = Voters([("grum", 1)])
    votes, _ = v.look("trashy clowning xgrum")
    assert votes[0] == 0 and votes[2] == 0
    assert v.look("Trash, grummel")[0][:3] == [1, 0, 1]


def test_repeating_voters_count_once():
    patterns = [((1, 1), None, 50), ((0, 0), None, 900), ((1, 0), None, 5)]
    q, _ = label_model(patterns)
    assert q[0] > q[2] > q[1]
    x = np.asarray([[0.0], [1.0], [2.0]])
    assert fit_linear(x, np.asarray([0.0, 0.5, 1.0]), 0.1)[0] > 0


def test_all_rows_without_a_label_are_learned_from(spark):
    docs, _ = made(300, seed=8)
    d, none = spark.createDataFrame(docs, "doc_id long, text string").repartition(3), spark.createDataFrame([], "doc_id long, toxic int")
    few, all_ = ({r.doc_id: r.score for r in toxicity(d, none, sample=n).collect()} for n in (10, 10_000))
    assert few.keys() == all_.keys() and all(abs(few[i] - all_[i]) < 1e-9 for i in few)


def test_distributed_fit_equals_local_fit(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(200, 3)).astype(np.float32)
    votes = [[int(a > 0), int(b > 1)] for a, b in x[:, :2]]
    posterior = {((a, b), t): 0.1 + 0.3 * a + 0.5 * b if t is None else float(t) for a in (0, 1) for b in (0, 1) for t in (None, 0, 1)}
    labels = [None if i % 3 else i % 2 for i in range(200)]
    rows = [(a.tolist(), v, t) for a, v, t in zip(x, votes, labels, strict=True)]
    got = fit_all(spark.createDataFrame(rows, "x array<float>, votes array<int>, toxic int").repartition(5), posterior)
    want = fit_linear(x.astype(float), np.asarray([posterior[tuple(v), t] for v, t in zip(votes, labels, strict=True)]))
    assert np.allclose(got, want, atol=1e-9)
