import zlib
from collections import defaultdict

import numpy as np
import pytest

from episode_engine.llm.packing import pack, plan

public_tokenizers = pytest.importorskip("public_tokenizers")


def test_round_trip(spark):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    tok = Tokenizer.from_file(path)
    texts = [None, "", " ", "Hello, World!  it's\tÉté\n42 foo<|endoftext|>bar", "word " * 3000, "x" * 5000, "a b   ć", "tail", "tail"] + [f"some text {i} " * (i % 37) for i in range(120)]
    rows = [(i, t) for i, t in enumerate(texts)] + [(3, texts[3])]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as length", "2 as task").repartition(3)
    got = pack(df, path).collect()
    expected = []
    for d, t in rows:
        ids = np.asarray([*tok.encode(t or "", add_special_tokens=False).ids, 0], "<u4")
        expected += [(d, k, k * 2048, len(p), zlib.crc32(p.tobytes())) for k, p in enumerate(ids[i : i + 2048] for i in range(0, len(ids), 2048))]
    assert sorted((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got) == sorted(expected)
    bins = defaultdict(list)
    for r in got:
        bins[r.sequence_id].append((r.offset, r.length))
    for b in bins.values():
        at = 0
        for o, n in sorted(b):
            assert o == at
            at += n
        assert at <= 2048
    assert len(bins) <= -(-sum(r.length for r in got) // 2048) + 1


def test_plan_uses_every_piece_once_and_two_may_replace_one():
    counts = {7: 1, 5: 3, 4: 2, 3: 5, 2: 1}
    used = defaultdict(int)
    for slots, times in plan(counts, 10):
        assert sum(slots) <= 10
        for n in slots:
            used[n] += times
    assert dict(used) == counts
    assert [sorted(s) for s, _ in plan({6: 1, 3: 1, 2: 2}, 10)][0] == [2, 2, 6]


def test_empty_table(spark):
    assert pack(spark.createDataFrame([], "doc_id long, text string"), public_tokenizers.path("word_bpe_49k.json")).count() == 0


def test_plain_words_have_the_ids_of_the_whole_tokenizer():
    import random

    from tokenizers import Tokenizer

    from episode_engine.llm.packing import ChunkTokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    whole, tok, rng = Tokenizer.from_file(path), ChunkTokenizer(path), random.Random(4)
    assert tok.plain is not None
    letters = [chr(x) for x in range(33, 0x250)] + list("ΑΣσςЖж漢字İıſŉǅﬁ①½²́‍\xa0\x85 \t\r\x0b\x00😀")
    common = "etaoinETAOIN'sntvd0123456789.,-ßéÄñ"
    for _ in range(3000):
        text = "".join(rng.choice(letters if rng.random() < 0.3 else common) for _ in range(rng.randint(0, 25)))
        if rng.random() < 0.1:
            text += rng.choice(["<|endoftext|>", "<|startoftext|>", "<|", "'S 'LL we'Ve"])
        want = np.asarray(whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        assert tok.ids(text) == want, repr(text)
    for x in range(33, 0x180):
        for text in (chr(x), "a" + chr(x), chr(x) + "b", "a" + chr(x) + chr(x) + "Σ"):
            assert tok.ids(text) == np.asarray(whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes(), repr(text)
