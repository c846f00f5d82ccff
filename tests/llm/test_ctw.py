import math
import random
import zlib
from collections import Counter

import numpy as np

from episode_engine.llm import ctw


def rows_made():
    rng = random.Random(2)
    words = ["The", "tion", "éa", "ing,", "of", "x1", "And"]
    rows = [(i, " ".join(rng.choice(words) + rng.choice(["", "er", "ed"]) for _ in range(rng.randint(0, 30)))) for i in range(60)]
    return rows + [(60, None), (61, ""), (62, "  \n"), (63, "zzz unseen q"), (5, rows[5][1]), (64, "ab " * 4000)]


def test_base_and_probabilities(spark):
    rows = rows_made()
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as n", "2 as _row").repartition(4)
    got = ctw.score(df, depth=3).collect()
    held = lambda d: zlib.crc32(str(d).encode()) % 7 == 2
    split = lambda t: (t or "").encode().lower().split()
    counts = Counter(w for d, t in rows if not held(d) for w in [*split(t), b""])
    total, distinct = sum(counts.values()), len(counts)
    expected = sorted(
        (d, held(d), len(split(t)) + 1, sum(counts[w] > 0 for w in [*split(t), b""]), total, round(sum(math.log10((counts[w] + 1) / (total + distinct + 1)) for w in [*split(t), b""]), 6))
        for d, t in rows
    )
    assert sorted((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in got) == expected
    # After any context, the probabilities of all bytes sum to one, and texts score as their bytes do.
    keys, values, use = ctw.learn(spark.createDataFrame([r for r in rows if not held(r[0])], "doc_id long, text string"), 3)
    table = ctw.Table(keys, values, use)
    for context in (b"the", b" of", b"qqq", b"\n\n\n", b"e e"):
        k = np.asarray([int.from_bytes(context[::-1] + bytes([b]), "big") for b in range(256)], np.uint64)
        assert abs(np.exp(table.log_p(k)).sum() - 1) < 1e-3
    by_id = {r.doc_id: r for r in got}
    data = b"\n\n\n" + b"zzz unseen q\n"
    one = [int.from_bytes(data[i - 3 : i][::-1] + data[i : i + 1], "big") for i in range(3, len(data))]
    assert abs(by_id[63].score - table.log_p(np.asarray(one, np.uint64)).sum() / math.log(10)) < 1e-3
    assert abs(by_id[60].score - by_id[61].score) < 1e-9 and by_id[60].n_scored_bytes == 1


def test_weights_equal_the_recursion(spark):
    """One decision's trees against the recursion written out over dictionaries."""
    rng = random.Random(5)
    data = bytes(rng.choice(b"ab") for _ in range(300))
    keys, counts = np.unique(ctw.sequences(np.frombuffer(data, np.uint8), 2), return_counts=True)
    t = ctw.BitTrees(keys, counts, 2, 7, 1)  # the last decision: all else of the byte is shared by a and b
    seen = Counter((data[i - 1], data[i - 2], data[i] >> 1, data[i] & 1) for i in range(2, len(data)))

    def estimate(zeros, ones):
        p = 1.0
        for k in range(zeros):
            p *= (k + 0.5) / (k + 1)
        for k in range(ones):
            p *= (k + 0.5) / (zeros + k + 1)
        return p

    got = {}
    for k, node in zip(keys.tolist(), t.node[1].tolist(), strict=True):
        got[(k >> 16, (k & 255) >> 1)] = t.mixed[1][node]
    for (c1, prefix), value in got.items():
        own = [sum(n for (a, _, p, x), n in seen.items() if (a, p, x) == (c1, prefix, bit)) for bit in (0, 1)]
        below = 1.0
        for c2 in {b for a, b, p, _ in seen if (a, p) == (c1, prefix)}:
            below *= estimate(*[seen[c1, c2, prefix, bit] for bit in (0, 1)])
        assert abs(value - math.log((estimate(*own) + below) / 2)) < 1e-6


def test_distributed_table_gives_the_same(spark, monkeypatch):
    monkeypatch.setattr(ctw, "CHUNK", 500)
    df = spark.createDataFrame(rows_made(), "doc_id long, text string").repartition(3)
    rounded = lambda rows: sorted((r.doc_id, r.held_out, r.n_tokens, r.n_known, round(r.base_score, 6), round(r.score, 3), r.n_scored_bytes) for r in rows)
    assert rounded(ctw.score(df, depth=3, max_entries=0).collect()) == rounded(ctw.score(df, depth=3).collect())
    assert ctw.score(df.limit(0), depth=3, max_entries=-1).count() == 0


def test_empty_and_untrained(spark):
    assert ctw.score(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    alone = next(i for i in range(100) if zlib.crc32(str(i).encode()) % 7 == 2)
    (r,) = ctw.score(spark.createDataFrame([(alone, "a b")], "doc_id long, text string")).collect()
    assert r.held_out and r.n_known == 0 and r.train_tokens == 0 and abs(r.score + 4 * math.log10(256)) < 1e-6


def test_scores_equal_the_tree_written_out(spark):
    """A training text's score by the recursion over all depths and decisions, with dictionaries; every sequence of it is known."""
    from functools import cache

    rng = random.Random(9)
    rows = [(i, " ".join(rng.choice(["ab", "ba", "c", "abc"]) for _ in range(12))) for i in range(30)]
    depth, seen, training = 2, Counter(), [r for r in rows if zlib.crc32(str(r[0]).encode()) % 7 != 2]
    raw = lambda t: b"\n" * depth + b" ".join(t.encode().split()) + b"\n"
    data = {d: ctw.END * depth + ctw.stream(t)[1] for d, t in rows}
    assert all(data[d] == raw(t) for d, t in rows)
    for d, _ in training:
        x = data[d]
        for i in range(depth, len(x)):
            seen[x[i - 1], x[i - 2], x[i]] += 1

    @cache
    def node(context: tuple, prefix: int, bit: int) -> tuple[int, int]:
        """How often a 0 and a 1 followed the first `bit` bits of a byte after these bytes (the latest first)."""
        own = [0, 0]
        for (a, b, byte), n in seen.items():
            if (a, b)[: len(context)] == context and byte >> (8 - bit) == prefix:
                own[byte >> (7 - bit) & 1] += n
        return own[0], own[1]

    def estimate(zeros: int, ones: int) -> float:
        return math.lgamma(zeros + 0.5) + math.lgamma(ones + 0.5) - math.lgamma(zeros + ones + 1) - math.log(math.pi)

    @cache
    def mixed(context: tuple, prefix: int, bit: int) -> float:
        own = estimate(*node(context, prefix, bit))
        if len(context) == depth:
            return own
        children = {(a, b)[: len(context) + 1] for a, b, byte in seen if (a, b)[: len(context)] == context and byte >> (8 - bit) == prefix}
        below = sum(mixed(c, prefix, bit) for c in children)
        top = max(own, below)
        return top + math.log((math.exp(own - top) + math.exp(below - top)) / 2)

    def predicted(context: tuple, full: tuple, prefix: int, bit: int, one: int) -> float:
        counts = node(context, prefix, bit)
        p = (counts[one] + 0.5) / (sum(counts) + 1)
        if len(context) == depth:
            return p
        w = math.exp(math.log(0.5) + estimate(*counts) - mixed(context, prefix, bit))
        return w * p + (1 - w) * predicted(full[: len(context) + 1], full, prefix, bit, one)

    got = {r.doc_id: r.score for r in ctw.score(spark.createDataFrame(rows, "doc_id long, text string"), depth=depth).collect()}
    for d, _ in training[:6]:
        x, total = data[d], 0.0
        for i in range(depth, len(x)):
            full = (x[i - 1], x[i - 2])
            total += sum(math.log10(predicted((), full, x[i] >> (8 - bit), bit, x[i] >> (7 - bit) & 1)) for bit in range(8))
        assert abs(got[d] - total) < 1e-3, (got[d], total)
