"""The label model's verdicts against expectation-maximisation over documents, one by one."""

import math
import random

from episode_engine.llm import quality as Q


def texts():
    rng = random.Random(1)
    vocabulary = ["the", "of", "and", "to", "house", "river", "quickly", "seven", "paper", "stone", "la", "de", "der", "und"]
    rows = []
    for i in range(160):
        w = [rng.choice(vocabulary) + rng.choice(["", "s", "ing"]) for _ in range(rng.choice([5, 30, 60, 150, 300]))]
        if i % 4 == 0:
            w = [x + rng.choice(["###", "$$", ""]) for x in w]
        if i % 7 == 0:
            w = w[:10] * 12
        lines = [" ".join(w[k : k + 12]) for k in range(0, len(w), 12)]
        rows.append((i, "\n".join(lines + lines[:1] * (i % 5))))
    return [*rows, (900, None), (901, ""), (902, " \n\t"), (3, rows[3][1])]


def test_verdicts_equal_the_rounds_written_out(spark):
    rows = spark.createDataFrame(texts(), "doc_id long, text string").selectExpr("*", "1 as n_words", "2 as kept").repartition(3)
    rules = Q.votes()
    voted = [(r.doc_id, r.n_words, r.n_repeat_words, [r[f"v_{k}"] for k in rules]) for r in Q.features(rows).select("*", *[v.alias(f"v_{k}") for k, v in rules.items()]).collect()]
    k, prior = len(rules), 0.8
    good, bad = [dict(Q.GOOD) for _ in range(k)], [dict(Q.BAD) for _ in range(k)]
    for _ in range(60):
        q = []
        for *_, v in voted:
            a, b = prior, 1 - prior
            for j in range(k):
                a, b = a * good[j][v[j]], b * bad[j][v[j]]
            q.append(a / (a + b))
        prior = min(0.99, max(0.05, (sum(q) + 0.8 * Q.PRIOR_ROWS) / (len(q) + Q.PRIOR_ROWS)))
        for j in range(k):
            for table, first, share in ((good, Q.GOOD, q), (bad, Q.BAD, [1 - x for x in q])):
                total = {x: Q.PRIOR_ROWS * first[x] + sum(s for s, (*_, v) in zip(share, voted, strict=True) if v[j] == x) for x in (-1, 0, 1)}
                table[j] = {x: y / sum(total.values()) for x, y in total.items()}
    want = []
    for doc, n, repeated, v in voted:
        odds = math.log(prior / (1 - prior))
        for j, x in enumerate(v):
            ratio = math.log(good[j][x] / bad[j][x])
            odds += max(0.0, ratio) if x == 1 else min(0.0, ratio) if x == -1 else 0.0
        failed = n < 50 or 100 * repeated > 50 * n
        want.append((doc, failed, not failed and odds >= 0, round(1 / (1 + math.exp(-odds)), 6)))
    got = [(r.doc_id, r.base_failed, r.kept, round(r.quality, 6)) for r in Q.quality(rows).collect()]
    assert sorted(got) == sorted(want) and {x[2] for x in want} == {True, False}
