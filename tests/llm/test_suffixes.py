import hashlib
import random

import pytest

from episode_engine.llm.suffixes import common_prefixes, front_code, front_decode, merge_runs, remove_repeats


def brute(rows, length):
    seen = {}
    for doc, t in rows:
        b = (t or "").encode()
        for i in range(len(b) - length + 1):
            w = b[i : i + length]
            seen[w] = min(seen.get(w, doc), doc)
    out = []
    for doc, t in rows:
        b = (t or "").encode()
        gone = [False] * len(b)
        for i in range(len(b) - length + 1):
            if seen[b[i : i + length]] < doc:
                gone[i : i + length] = [True] * length
        kept = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        spans = sum(g and not (i and gone[i - 1]) for i, g in enumerate(gone))
        out.append((doc, len(b), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def test_against_every_window(spark):
    rng = random.Random(3)
    words = ["ab", "the", "éa", "tion", "x", " "]
    passages = ["".join(rng.choice(words) for _ in range(rng.randint(20, 60))) for _ in range(6)]
    rows = [(100 - i, "".join(rng.choice(passages)[rng.randint(0, 20) :] + rng.choice(words) * rng.randint(0, 30) for _ in range(rng.randint(0, 5)))) for i in range(60)]
    rows += [(7, None), (8, ""), (9, "a" * 49), (10, "a" * 50), (11, "a" * 300), (5, "b" * 120), (6, "b" * 80), (300, "\0" * 70), (301, "\0" * 70 + "q"), (302, passages[0]), (303, passages[0])]
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as part", "text as block").repartition(5)
    for block in (200, 4_000_000):
        got = sorted(tuple(r) for r in remove_repeats(df, 50, block_bytes=block).collect())
        assert got == brute(rows, 50)
    kept = {r.doc_id: r for r in remove_repeats(df, 50, with_text=True).collect()}
    assert kept[11].kept_text == "" and kept[5].kept_text == "b" * 120


def test_rows_of_one_id_are_copies(spark):
    rows = [(1, "q" * 60), (1, "q" * 60), (2, "q" * 60)]
    got = sorted((r.doc_id, r.n_removed) for r in remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == [(1, 0), (1, 0), (2, 60)]


def test_empty_table_and_bad_length(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert remove_repeats(empty).count() == 0
    with pytest.raises(ValueError):
        remove_repeats(empty, 10)


def test_merge_knows_prefixes():
    rng = random.Random(1)
    for n in (1, 2, 3, 5, 9):
        runs = [sorted(bytes(rng.choice(b"ab") for _ in range(rng.randint(0, 9))) for _ in range(rng.randint(0, 12))) for _ in range(n)]
        coded = [(front_decode(*front_code(r)), common_prefixes(r).tolist()) for r in runs]
        assert [c[0] for c in coded] == runs
        merged = list(merge_runs(coded))
        strings = [runs[r][i] for r, i, _ in merged]
        assert strings == sorted(x for r in runs for x in r)
        assert [p for _, _, p in merged] == common_prefixes(strings).tolist()
