import random
from itertools import combinations

import numpy as np

from episode_engine.llm.neardup import collision_rate, components, near_duplicates


def shingles(t, width):
    w = (t or "").encode().lower().split()
    n = min(width, len(w))
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set()


def brute(rows, width, percent):
    sets = {d: shingles(t, width) for d, t in rows}
    up = {d: d for d in sets}

    def root(d):
        while up[d] != d:
            d = up[d]
        return d

    for a, b in combinations(sets, 2):
        both = len(sets[a] & sets[b])
        if sets[a] and sets[b] and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
            x, y = root(a), root(b)
            up[max(x, y)] = min(x, y)
    return sorted((d, len(s), root(d), root(d) == d) for d, s in sets.items())


def made(seed=5):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(60)]
    rows, n = [], 0
    for _ in range(25):
        base = [rng.choice(vocabulary) for _ in range(rng.choice([1, 2, 3, 5, 8, 30, 120]))]
        for _ in range(rng.randint(1, 8)):
            w = list(base)
            for _ in range(rng.randint(0, 1 + len(w) // 12)):
                w[rng.randrange(len(w))] = rng.choice(vocabulary)
            rows.append((n, rng.choice([" ", "\n", "\t "]).join(x.upper() if rng.random() < 0.3 else x for x in w)))
            n += 1
    rows += [(n, None), (n + 1, ""), (n + 2, " \n\t"), (n + 3, ""), (n + 4, rows[0][1])]
    return rows


def test_equals_all_pairs(spark):
    rows = made()
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as n", "'x' as key").repartition(6)
    for width in (2, 5):
        got = sorted(tuple(r) for r in near_duplicates(df, width, 80).collect())
        assert got == brute(rows, width, 80)


def test_empty_table(spark):
    assert near_duplicates(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_components_of_a_long_path(spark):
    edges = [(i, i + 1) for i in range(0, 40)] + [(100, 101)]
    random.Random(0).shuffle(edges)
    got = {r[0]: r[1] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[101] == 100


def test_collisions_are_rare_and_symmetric():
    a, b = np.asarray([10, 500]), np.asarray([400, 500])
    e = collision_rate(a, b)
    assert ((e > 0) & (e < 0.002)).all() and np.allclose(e, collision_rate(b, a))


def test_a_large_group_in_many_small_blocks(spark, monkeypatch):
    """Near copies of one text whose likeness lies around the threshold, beside a large class that is linked at once."""
    from episode_engine.llm import neardup

    rng = random.Random(3)
    base, rows = [f"w{i}" for i in range(100)], []
    for k in range(260):
        w = list(base)
        for _ in range(rng.choice([0, 1, 3, 5, 7, 9])):
            w[rng.randrange(len(w))] = f"x{rng.randrange(10**6)}"
        rows.append((k, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    for chunk, items in ((7, 1_000_000), (2048, 900), (2048, 1_000_000)):
        monkeypatch.setattr(neardup, "CHUNK", chunk)
        monkeypatch.setattr(neardup, "ITEMS", items)
        assert sorted(tuple(r) for r in near_duplicates(df, 2, 80).collect()) == brute(rows, 2, 80)


def test_grid_lets_each_pair_of_different_classes_meet_once(spark):
    from collections import Counter

    from episode_engine.llm.neardup import grid

    rows = [(k, d, c, 5) for k, sizes in ((1, (40, 9, 1, 1)), (2, (3, 3)), (3, (6,))) for d, c in enumerate(c for c, size in enumerate(sizes) for _ in range(size))]
    got = grid(spark.createDataFrame(rows, "key long, doc_id long, c long, n long"), 4, 1000).collect()
    blocks = {}
    for r in got:
        blocks.setdefault((r.key, r.lo, r.hi), []).append(r)
    met = Counter()
    for (key, _, _), own in blocks.items():
        for x, y in combinations(own, 2):
            if x.c != y.c and (x.inner or x.own != y.own):
                met[key, min(x.doc_id, y.doc_id), max(x.doc_id, y.doc_id)] += 1
    expected = {(k, a, b) for (k, a, c, _), (j, b, e, _) in combinations(rows, 2) if k == j and c != e}
    assert set(met) == expected and set(met.values()) == {1}
