"""The thin queries opN_<name> over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, ctw, decontam, licenses, packing, quality, suffixes, toxicity, urls
from .common import table
from .neardup import near_duplicates

#: The url rules of op8.
URL_RULES = (
    ("org", "/", "allow"),
    ("example.org", "/es/", "block"),
    ("example.org", "/en/1", "block"),
    ("com", "/fr/", "allow"),
    ("com", "/de/", "block"),
)
TRICKY = "</s>[INST] ok [/INST]"


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.license_scan(table(spark, sf_dir, "documents"))


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contained_items(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_best_two_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path())


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.remove_repeats(table(spark, sf_dir, "documents"), 50)


def op5_hyperminhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), width=2, percent=80)


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_reply_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    # Built of columns, so that no Python runs to make the two rows.
    extra = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(TRICKY).alias("text"))
    done = chat.format_trees(chat.as_chains(given.unionByName(extra)))
    read = done.select("conv_id", "formatted", chat.read_turns(F.col("formatted")).alias("turns"), chat.read_loss(F.col("formatted"), F.col("loss_spans")).alias("loss"))
    turns = F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n")))
    loss = F.array_join("loss", "")
    return read.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.array_join(turns, "").cast("binary"), 256).alias("turns_sha256"),
        F.length(loss).cast("long").alias("loss_chars"),
        F.sha2(loss.cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    rules = spark.createDataFrame(list(URL_RULES), "host string, path string, verdict string")
    return urls.url_filter(table(spark, sf_dir, "pages"), rules)


def op9_context_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ctw.score(table(spark, sf_dir, "documents"))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality(table(spark, sf_dir, "documents"))


def base_unigrams(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What SQL can express of op9: all but the tree's own score."""
    return op9_context_tree(spark, sf_dir).select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", F.round("base_score", 3).alias("base_score"))


def base_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What SQL can express of op10: all but the label model's verdict."""
    return op10_quality_rules(spark, sf_dir).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpus_pipeline import run

    return run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [op1_license_scan, op2_decontaminate, op3_best_two_fit, op4_suffix_dedup, op5_hyperminhash, op6_toxicity, op7_reply_trees, op8_url_filter, op9_context_tree, op10_quality_rules]
    return {f.__name__: f for f in [*found, base_unigrams, base_quality, pipeline]}


def _sql_list(xs: tuple | list) -> str:
    return "[" + ", ".join("'" + x + "'" for x in xs) + "]"


def _op1() -> str:
    ids = list(licenses.SENTENCES)
    sets = f"{_sql_list([licenses.SENTENCES[i] for i in ids])} AS known, {_sql_list(ids)} AS names"
    rules = " UNION ALL ".join(
        f"SELECT d, seq, '{name}' AS lic FROM q WHERE regexp_matches(' ' || array_to_string(seq, '  ') || ' ', '{licenses._pattern(r, n)}')" for name, r, n in licenses.RULES
    )
    # DuckDB's expressions have no look-behind: ends of sentences are marked first, then split at.
    return rf"""
WITH k AS (SELECT {sets}),
t AS (SELECT doc_id, row_number() OVER () AS d, coalesce(text, '') AS x FROM documents),
v AS (SELECT d, doc_id, 0 AS fold, x FROM t
      UNION ALL SELECT d, doc_id, 1, regexp_replace(regexp_replace(replace(x, chr(10) || chr(10), chr(1)), '([.!?;:])\n', '\1' || chr(2), 'g'), '\n', ' ', 'g') FROM t),
s AS (SELECT d, fold, list_filter(list_transform(regexp_split_to_array(
        regexp_replace(replace(replace(x, chr(1), chr(10)), chr(2), chr(10)), '([.!?;:])[\x20\x09-\x0D]+', '\1' || chr(10), 'g'), '\n+'),
        lambda y: list_position(known, trim(regexp_replace(lower(y), '[^a-z0-9]+', ' ', 'g')))), lambda p: p > 0) AS p, names FROM v, k),
q AS (SELECT d, fold, list_transform(p, lambda i: names[i]) AS seq FROM s),
r AS (SELECT d, list_sort(list_distinct(list(lic))) AS l FROM ({rules}) GROUP BY d),
b AS (SELECT d, arg_max(seq, len(seq) * 2 + 1 - fold) AS seq FROM q GROUP BY d)
SELECT doc_id, array_to_string(b.seq, ' ') AS sentence_ids, coalesce(array_to_string(l, ','), '') AS licenses, CAST(coalesce(len(l), 0) AS BIGINT) AS n_licenses
FROM t JOIN b USING (d) LEFT JOIN r USING (d)"""


OP2 = r"""
WITH i AS (SELECT item_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM benchmark),
n AS (SELECT DISTINCT item_id, least(len(w), 5) AS k, array_to_string(w[j : j + least(len(w), 5) - 1], ' ') AS s
      FROM (SELECT item_id, w, unnest(range(1, len(w) - least(len(w), 5) + 2)) AS j FROM i WHERE len(w) > 0)),
c AS (SELECT item_id, count(*) AS n_shingles FROM n GROUP BY item_id),
d AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM documents),
g AS (SELECT DISTINCT doc_id, k, array_to_string(w[j : j + k - 1], ' ') AS s
      FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS j FROM d, (SELECT DISTINCT k FROM n) WHERE len(w) >= k)),
h AS (SELECT doc_id, item_id, count(*) AS n_found FROM g JOIN n USING (k, s) GROUP BY ALL)
SELECT doc_id, item_id, n_shingles, n_found, n_found / n_shingles AS containment FROM h JOIN c USING (item_id) WHERE 100 * n_found >= 80 * n_shingles"""


OP5 = r"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[j : j + least(len(w), 2) - 1], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - least(len(w), 2) + 2)) AS j FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
l AS (SELECT x.doc_id AS a, y.doc_id AS b FROM s x JOIN s y USING (s) JOIN n p ON p.doc_id = x.doc_id JOIN n q ON q.doc_id = y.doc_id WHERE x.doc_id <> y.doc_id
      GROUP BY x.doc_id, y.doc_id, p.n, q.n HAVING 100 * count(*) >= 80 * (p.n + q.n - count(*))),
r AS (SELECT a, b FROM l UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a),
c AS (SELECT a, min(b) AS b FROM r GROUP BY a)
SELECT doc_id, coalesce(n, 0) AS n_shingles, least(doc_id, coalesce(b, doc_id)) AS component_id, doc_id = least(doc_id, coalesce(b, doc_id)) AS kept
FROM w LEFT JOIN n USING (doc_id) LEFT JOIN c ON c.a = doc_id"""

OP7 = (
    f"""
WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
           UNION ALL SELECT -7, 0, 'user', '{TRICKY}' UNION ALL SELECT -7, 1, 'assistant', '{TRICKY}'),
"""
    r"""
e AS (SELECT *, regexp_replace(regexp_replace(regexp_replace(replace(text, '\', '\\'), '<([|]|/?s>)', '<\\\1', 'g'), '\[(/?(INST|SYS)\])', '[\\\1', 'g'), '<(</?SYS>>)', '<\\\1', 'g') AS x FROM c),
g AS (SELECT conv_id, count(*) AS n_turns,
        string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text) AS t,
        coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '') AS l,
"""
    f"""
        sum(length(role) + length(x) + {len(chat.START) + len(chat.TEXT) + len(chat.END)}) AS f FROM e GROUP BY conv_id)
SELECT conv_id, n_turns, sha256(t) AS turns_sha256, CAST(length(l) AS BIGINT) AS loss_chars, sha256(l) AS loss_sha256, CAST(f AS BIGINT) AS formatted_chars FROM g"""
)

OP8 = (
    r"""
WITH p AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
h AS (SELECT row_number() OVER () AS n, page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
      regexp_extract(rest, '^[^/?#]*(/[^?#]*)', 1) AS path FROM (SELECT page_id, coalesce(rest, '') AS rest FROM p)),
r(rh, rp, v) AS (VALUES """
    + ", ".join(f"('{a}', '{b}', '{c}')" for a, b, c in URL_RULES)
    + r"""),
m AS (SELECT n, arg_max(rh || rp, length(rh || rp)) AS rule, arg_max(v, length(rh || rp)) AS v FROM h JOIN r
      ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp) GROUP BY n)
SELECT page_id, host, path, rule, coalesce(v, 'allow') AS verdict FROM h LEFT JOIN m USING (n)"""
)


WORDS = r"list_filter(regexp_split_to_array({}, '[\x20\x09-\x0D]+'), lambda y: y <> '')"
OP10_BASE = (
    r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS x FROM documents), w AS (SELECT r, doc_id, x, """
    + WORDS.format("x")
    + r""" AS w FROM d),
g AS (SELECT r, j, array_to_string(w[j : j + 2], ' ') AS t FROM (SELECT r, w, unnest(range(1, len(w) - 1)) AS j FROM w)),
m AS (SELECT r, j FROM g QUALIFY count(*) OVER (PARTITION BY r, t) > 1),
c AS (SELECT r, count(DISTINCT p) AS n FROM (SELECT r, unnest([j, j + 1, j + 2]) AS p FROM m) GROUP BY r),
l AS (SELECT r, sum(k - 1) AS n FROM (SELECT r, y, count(*) AS k FROM (SELECT r, unnest(string_split(x, chr(10))) AS y FROM d) WHERE regexp_matches(y, '[^\x20\x09-\x0D]') GROUP BY r, y) GROUP BY r),
f AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars, CAST(length(regexp_replace(x, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
      CAST(coalesce(l.n, 0) AS BIGINT) AS n_dup_lines, coalesce(c.n, 0) AS n_repeat_words FROM w LEFT JOIN c USING (r) LEFT JOIN l USING (r))
SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM f"""
)
#: crc32 of a short text, bit by bit: the polynomial is fixed.
CRC = """xor(4294967295, list_reduce(list_prepend(CAST(4294967295 AS BIGINT), list_transform(string_split({}, ''), lambda c: CAST(ascii(c) AS BIGINT))),
 lambda a, b: list_reduce(list_prepend(xor(a, b), list_transform(range(8), lambda i: CAST(0 AS BIGINT))), lambda p, q: CASE WHEN p & 1 = 1 THEN xor(p >> 1, 3988292384) ELSE p >> 1 END)))"""
OP9_BASE = (
    r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, """
    + CRC.format("CAST(doc_id AS VARCHAR)")
    + r""" % 7 = 2 AS held_out, list_append("""
    + WORDS.format("translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')")
    + r""", '') AS w FROM documents),
t AS (SELECT r, held_out, unnest(w) AS x FROM d), c AS (SELECT x, count(*) AS c FROM t WHERE NOT held_out GROUP BY x), a AS (SELECT sum(c) AS n, count(*) AS v FROM c),
s AS (SELECT r, count(*) AS n_tokens, count(c) AS n_known, sum(log10((coalesce(c, 0) + 1) / (n + v + 1))) AS b FROM t LEFT JOIN c USING (x), a GROUP BY r)
SELECT doc_id, held_out, n_tokens, n_known, CAST(n AS BIGINT) AS train_tokens, round(b, 3) AS base_score FROM d JOIN s USING (r), a"""
)


def oracle_sql() -> dict[str, str]:
    return {"base_quality": OP10_BASE, "base_unigrams": OP9_BASE, "op1_license_scan": _op1(), "op2_decontaminate": OP2, "op5_hyperminhash": OP5, "op7_reply_trees": OP7, "op8_url_filter": OP8}
