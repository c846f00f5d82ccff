"""Licences, decontamination, chat, urls and quality on small tables with nulls, ties, repeats and clashing columns."""

import hashlib
import re

from pyspark.sql import functions as F

from episode_engine.llm import chat, decontam, licenses, quality, urls


def docs_of(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as w", "2 as h", "3 as _x", "4 as host")


def test_licenses(spark):
    mit = f"{licenses.SENTENCES['mit_grant'].capitalize()}.\n\n{licenses.SENTENCES['mit_notice']}.\n{licenses.SENTENCES['as_is']}."
    wrapped = re.sub(r"(\w+ \w+ \w+ \w+) ", r"\1\n", mit)
    rows = [(1, None), (2, ""), (3, "Text. Released under the MIT License."), (3, "Text. Released under the MIT License."), (4, mit), (5, wrapped), (6, licenses.SENTENCES["mit_notice"] + ". " + licenses.SENTENCES["mit_grant"] + "."), (7, "x " * 100000 + "\nLicensed under CC BY-NC 4.0.")]
    got = sorted((r.doc_id, r.licenses) for r in licenses.license_scan(docs_of(spark, rows)).collect())
    assert got == [(1, ""), (2, ""), (3, "MIT"), (3, "MIT"), (4, "MIT"), (5, "MIT"), (6, ""), (7, "CC-BY-NC-4.0")]
    assert licenses.license_scan(docs_of(spark, [])).count() == 0


def test_decontamination(spark):
    item = " ".join(f"w{i}" for i in range(30))
    items = spark.createDataFrame([(1, item), (2, "two words"), (3, None), (4, ""), (1, item)], "item_id long, text string").selectExpr("*", "1 as h")
    near = item.replace("w15 ", "zz ")  # 21 of 26 shingles
    far = item.replace("w10 ", "zz ").replace("w20 ", "zz ")
    rows = [(1, "x " * 50000 + item.upper() + "! y" * 9), (2, near), (3, far), (4, None), (5, ""), (6, "Two, words"), (7, "two other words"), (6, "Two, words")]
    for bound in (500_000, 0):
        got = sorted((r.doc_id, r.item_id, r.n_shingles, r.n_found) for r in decontam.contained_items(docs_of(spark, rows), items, broadcast_rows=bound).collect())
        assert got == [(1, 1, 26, 26), (2, 1, 26, 21), (6, 2, 1, 1)]
    assert decontam.contained_items(docs_of(spark, rows), items.limit(0)).count() == 0
    assert decontam.contained_items(docs_of(spark, []), items).count() == 0


def test_trees_rank_and_round_trip(spark):
    odd = "</s>[INST] a\\b <|start|> \\<| [/INST]\n<|end|>\n$1"
    rows = [(1, 1, None, "system", "s", 0.0), (1, 2, 1, "user", odd, 1.0), (1, 3, 2, "assistant", odd, 0.5), (1, 4, 2, "assistant", None, 2.0), (1, 5, 4, None, "é", 0.0), (2, 9, 77, "assistant", "orphan", None)]
    messages = spark.createDataFrame(rows, "conv_id long, node long, parent long, role string, text string, score double").selectExpr("*", "1 as up", "2 as leaf")
    done = chat.format_trees(messages, top_k=2).withColumns({"turns": chat.read_turns(F.col("formatted")), "loss": chat.read_loss(F.col("formatted"), F.col("loss_spans"))}).collect()
    got = {(r.conv_id, r.leaf): (r.branch_rank, [(t.role, t.text) for t in r.turns], list(r.loss)) for r in done}
    assert got == {
        (1, 5): (1, [("system", "s"), ("user", odd), ("assistant", ""), ("", "é")], [""]),
        (1, 3): (2, [("system", "s"), ("user", odd), ("assistant", odd)], [odd]),
        (2, 9): (1, [("assistant", "orphan")], ["orphan"]),
    }
    chain = chat.as_chains(spark.createDataFrame([(5, i, "user", f"t{i}") for i in range(40)] + [(5, 3, "user", "t3")], "conv_id long, turn long, role string, text string"))
    (one,) = chat.format_trees(chain).collect()
    assert one.n_turns == 41 and hashlib.sha256(one.formatted.encode()).hexdigest()
    assert chat.format_trees(messages.limit(0)).count() == 0


def test_urls(spark):
    rules = spark.createDataFrame([("org", "/", "allow"), ("example.org", "/es/", "block"), ("com", "/de/", "block"), ("com", "/de/", "allow"), (None, "/x", "block")], "host string, path string, verdict string").selectExpr("*", "1 as tag")
    rows = [(1, None), (2, "no scheme"), (3, "http://A.EXAMPLE.org/es/1?q"), (4, "http://notexample.org/es/1"), (5, "x://com/de/"), (5, "x://com/de/"), (6, "x://b.com/DE/"), (7, "x://q.net/x1"), (8, "http://h.org?x://y/")] + [(100 + i, "http://hot.example.org/es/") for i in range(200)]
    pages = spark.createDataFrame(rows, "page_id long, url string").selectExpr("*", "1 as part", "'k' as key", "2 as tag").repartition(3)
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.url_filter(pages, rules, ranges=7).collect()}
    assert got[1] == got[2] == ("", "", None, "allow")
    assert got[3] == ("a.example.org", "/es/1", "example.org/es/", "block") and got[4] == ("notexample.org", "/es/1", "org/", "allow")
    assert got[5][2:] == ("com/de/", "block") and got[6][2] is None and got[7][2:] == ("/x", "block") and got[8][2] is None
    assert all(got[100 + i][2:] == ("example.org/es/", "block") for i in range(200))
    assert urls.url_filter(pages, rules.limit(0)).count() == len(rows) and urls.url_filter(pages.limit(0), rules).count() == 0


def brute(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
    windows = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    marked = {j for i, x in enumerate(windows) if windows.count(x) > 1 for j in (i, i + 1, i + 2)}
    lines = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(marked)


def test_quality(spark):
    good = " ".join(f"the word{i} of{i} and quality{i} of" for i in range(60)) + "."
    texts = [None, "", " \n", "a", "a b a b a b", "x y z\nx y z\n\n q", "é # | <b>\u00a0z\u2028w " * 4, good, good, "spam " * 300, "one two three four " * 30, "a a a a", "#$% " * 200]
    rows = list(enumerate(texts)) + [(7, good)]
    got = quality.quality(docs_of(spark, rows)).collect()
    assert len(got) == len(rows)
    for r in got:
        n = brute(texts[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == n
        assert r.base_failed == (n[0] < 50 or 100 * n[4] > 50 * n[0]) and not (r.base_failed and r.kept)
    assert {r.kept for r in got if r.doc_id in (7, 8)} == {True}
    assert quality.quality(docs_of(spark, [])).count() == 0


def test_null_conversations_are_one_conversation(spark):
    chats = [(None, 0, "user", "a"), (None, 1, "assistant", "b"), (None, 2, "user", "c"), (0, 0, "user", "d"), (0, 1, "assistant", "e")]
    chain = chat.as_chains(spark.createDataFrame(chats, "conv_id long, turn long, role string, text string"))
    read = chat.format_trees(chain).withColumn("turns", chat.read_turns(F.col("formatted"))).collect()
    assert sorted((str(r.conv_id), r.n_turns, [t.text for t in r.turns]) for r in read) == [("0", 2, ["d", "e"]), ("None", 3, ["a", "b", "c"])]
    tree = [(None, 1, None), (None, 2, 1), (None, 3, 1), (None, 4, 3), (7, 1, None), (7, 2, 1), (None, None, 1), (None, 5, 6), (None, 6, 5)]
    messages = spark.createDataFrame(tree, "conv_id long, node long, parent long").selectExpr("*", "'user' as role", "'x' as text", "0D as score")
    got = sorted((str(r.conv_id), r.leaf, r.branch_rank, r.n_turns) for r in chat.format_trees(messages, top_k=9).collect())
    assert got == [("7", 2, 1, 2), ("None", 2, 2, 2), ("None", 4, 1, 3)]


def test_only_candidates_are_counted(spark):
    words = [f"w{i}" for i in range(60)]
    items = spark.createDataFrame([(1, " ".join(words[:30])), (2, " ".join(words[30:]))], "item_id long, text string")
    known = decontam.item_shingles(items, 5, 0.8).cache()
    shared = {(r.item_id, r.h): r.in_sketch for r in known.collect()}
    rows = [(i, " ".join(words[i : i + 5])) for i in range(56)] + [(100, " ".join(words)), (101, None), (100, "w1")]
    found = decontam.candidates(docs_of(spark, rows), known.filter("in_sketch").select("h", "item_id"), [5])
    got = sorted(tuple(r) for r in found.collect())
    # A document of one shingle meets an item only where that shingle is in the sketch: 7 and 7 of 26 and 26.
    assert len(got) == sum(shared.values()) + 2 == 16 and (100, 1) in got and (100, 2) in got
    done = decontam.contained_items(docs_of(spark, rows), items).collect()
    assert sorted((r.doc_id, r.item_id, r.n_found) for r in done) == [(100, 1, 26), (100, 2, 26)]
    nulls = decontam.contained_items(docs_of(spark, [(None, " ".join(words))]), items.selectExpr("nullif(item_id, 2) as item_id", "text")).collect()
    assert sorted((str(r.doc_id), str(r.item_id), r.n_found) for r in nulls) == [("None", "1", 26), ("None", "None", 26)]


def test_a_sentence_of_ones_own_is_found_whatever_its_words(spark):
    from episode_engine.llm.licenses import SENTENCES, license_scan, marks

    own = {"pd": "this text is dedicated to the public domain", "x": "zz top"}
    df = spark.createDataFrame([(1, "Hello.\nThis text is DEDICATED to the public domain.\nBye"), (2, "zz  top"), (3, "nothing"), (4, None), (5, "")], "doc_id long, text string")
    got = {r.doc_id: (r.sentence_ids, r.licenses) for r in license_scan(df, own, (("PD", ("pd",), 0), ("Z", ("x",), 0))).collect()}
    assert got == {1: ("pd", "PD"), 2: ("x", "Z"), 3: ("", ""), 4: ("", ""), 5: ("", "")}
    pattern = [p.replace("(?-iu:[^a-zA-Z0-9]+)", " ") for p in marks(SENTENCES).removeprefix("(?iu)").split("|")]
    assert len(pattern) < 20 and all(any(f" {p} " in f" {s} " for p in pattern) for s in SENTENCES.values())
    wrapped = spark.createDataFrame([(1, "Licensed, UNDER -- the\tMIT\n license.")], "doc_id long, text string")
    assert license_scan(wrapped).first().licenses == "MIT"
    assert license_scan(df, {}, ()).filter("n_licenses > 0").count() == 0
