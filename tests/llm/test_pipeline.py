"""The pipeline and each of its stages on a small table, against brute force: nulls, empty tables, repeats, clashing columns."""

import re
import zlib

import pytest

import corpus_pipeline as P
from episode_engine.llm.toxicity import INSULTS

public_tokenizers = pytest.importorskip("public_tokenizers")
ITEM = " ".join(f"item{i}" for i in range(30))
PASSAGE = " ".join(f"passage{i}" for i in range(20))


def plain(i):
    return " ".join(f"d{i}w{j}" for j in range(40))


def rows():
    texts = [plain(i) for i in range(12)]
    texts[1] = texts[0]  # a copy
    texts[2] = "x1 " + PASSAGE + " y1 " + texts[2]
    texts[3] = "x2 " + texts[3] + " y2 " + PASSAGE + " z2"
    texts[4] = texts[4] + " " + ITEM.upper()
    texts[5], texts[6], texts[7] = None, "", " "
    made = list(enumerate(texts)) + [(8, texts[8]), (5, None)]  # rows twice
    return made + [(i, " ".join([*plain(i).split()[:20], *INSULTS[:8]])) for i in range(20, 60)] + [(i, plain(i)) for i in range(60, 140)]


COLUMNS = "doc_id long, text string"
CLASHING = ["*", "CAST(length(text) AS BIGINT) AS n_chars", "1 AS _text2", "2 AS kept_text", "3 AS n_removed", "4 AS predicted", "5 AS toxic", "6 AS item_id"]


@pytest.fixture(scope="module")
def sf(spark, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("sf"))
    spark.createDataFrame(rows(), COLUMNS).selectExpr(*CLASHING).write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame([(i, int(i < 60)) for i in range(20, 140)] + [(None, 1)], "doc_id long, toxic int").write.parquet(f"{d}/labels.parquet")
    spark.createDataFrame([(1, ITEM), (2, None)], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    return d


def frame(spark, data):
    return spark.createDataFrame(data, COLUMNS).selectExpr(*CLASHING).repartition(3)


def got(df):
    assert df.columns == ["doc_id", "text", "n_chars", "_text2", "kept_text", "n_removed", "predicted", "toxic", "item_id"]
    return ordered((r.doc_id, r.text) for r in df.collect())


def ordered(data):
    return sorted(data, key=str)


def without_toxic(data):
    return [(d, t) for d, t in data if not set((t or "").split()) & set(INSULTS)]


def without_copies(data):
    least = {}
    for d, t in data:
        if (t or "").split():
            least[t] = min(least.get(t, d), d)
    return [(d, t) for d, t in data if least.get(t, d) == d]


def without_repeats(data, n=P.REPEAT_BYTES):
    seen, out = {}, []
    for d, t in data:
        b = (t or "").encode()
        for i in range(len(b) - n + 1):
            seen[b[i : i + n]] = min(seen.get(b[i : i + n], d), d)
    for d, t in data:
        b = (t or "").encode()
        gone = {j for i in range(len(b) - n + 1) if seen[b[i : i + n]] < d for j in range(i, i + n)}
        left = bytes(x for i, x in enumerate(b) if i not in gone).decode()
        if not gone or left.strip(" "):
            out.append((d, left if gone else t))
    return out


def without_items(data):
    cut = lambda t: {tuple(w[i : i + 5]) for w in [re.findall(r"[^\W_]+", (t or "").lower())] for i in range(len(w) - 4)}
    bad = {d for d, t in data if 10 * len(cut(t) & cut(ITEM)) >= 8 * len(cut(ITEM))}
    return [(d, t) for d, t in data if d not in bad]


BRUTE = [without_toxic, without_copies, without_repeats, without_items]


def test_stages_and_run(spark, sf):
    data = rows()
    for (name, stage), brute in zip(P.STAGES, BRUTE, strict=False):
        assert got(stage(spark, frame(spark, rows()), sf)) == ordered(brute(rows())), name
        data = brute(data)
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    crc = lambda t: zlib.crc32(b"".join(x.to_bytes(4, "little") for x in [*tok.encode(t or "", add_special_tokens=False).ids, 0]))
    assert ordered((r.doc_id, r.ids_crc32) for r in P.run(spark, sf).collect()) == ordered((d, crc(t)) for d, t in data)


def test_texts_that_are_cut_away_go(spark, sf):
    data = [(1, PASSAGE), (2, PASSAGE), (3, PASSAGE + " "), (4, ""), (5, None), (4, "")]
    assert got(P.cut_repeats(spark, frame(spark, data), sf)) == ordered(without_repeats(data)) == ordered([(1, PASSAGE), (4, ""), (4, ""), (5, None)])


def test_empty_table(spark, sf):
    for name, stage in P.STAGES:
        assert stage(spark, frame(spark, []), sf).count() == 0, name
