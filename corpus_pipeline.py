"""The corpus pipeline: five stages, each over all that its predecessor kept.

run(spark, sf_dir) applies them to `documents`; between stages the rows are written as Parquet and read again.

Every stage but the last returns the columns it was given, extra ones too, whatever their names. Ids should be unique and not null: a
decision on an id holds for all of its rows, and rows with a null id pass the stages that drop documents. Null texts are empty.
An empty table gives an empty one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from episode_engine.llm.common import table, written
from episode_engine.llm.decontam import contained_items
from episode_engine.llm.neardup import near_duplicates
from episode_engine.llm.packing import pack
from episode_engine.llm.queries import tokenizer_path
from episode_engine.llm.suffixes import remove_repeats
from episode_engine.llm.toxicity import toxicity

#: Bytes from which a passage that repeats is cut from all but the first document.
REPEAT_BYTES = 64


def _without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """docs whose doc_id is not in ids, in docs' columns."""
    return docs.join(ids.select("doc_id").distinct(), "doc_id", "left_anti").select(*docs.columns)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier calls toxic go: a score of 0.7 or more. Without labels the voters alone decide; null and empty texts are scored as such."""
    judged = toxicity(docs, table(spark, sf_dir, "labels"))
    return _without(docs, judged.filter("predicted = 1"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates (five-word shingles, 0.8) the document with the smallest id stays.

    Texts without words are linked with nothing and stay; ties do not arise, as copies and near copies are ordered by their ids.
    """
    return _without(docs, near_duplicates(docs, width=5, percent=80).filter("not kept"))


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that an earlier document has go from texts; documents of which nothing is left go too, unless they were empty.

    Repeats inside one document stay, and so do those among rows of one id, which count as copies of one document; characters that are cut in their middle go.
    """
    cut = remove_repeats(docs.select("doc_id", "text"), REPEAT_BYTES, with_text=True)
    changed = cut.filter("n_removed > 0").select("doc_id", F.col("kept_text").alias("_text"))
    both = docs.join(changed.dropDuplicates(["doc_id"]), "doc_id", "left").filter(F.col("_text").isNull() | (F.trim("_text") != ""))
    text = F.coalesce("_text", "text")
    new = {"text": text} | ({"n_chars": F.when(F.col("_text").isNotNull(), F.length("_text").cast("long")).otherwise(F.col("n_chars"))} if "n_chars" in docs.columns else {})
    return both.select(*[new[c].alias(c) if c in new else F.col(c) for c in docs.columns])


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item (0.8 of its five-word shingles) go. Empty items are in no document, and repeated items count once."""
    return _without(docs, contained_items(docs, table(spark, sf_dir, "benchmark")))


def pack_best_fit(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """What is left, tokenised and packed into sequences of 2048 tokens: a row for each piece. An empty text is one piece, its end; repeated rows are packed as often as they come."""
    return pack(docs, tokenizer_path())


STAGES = [
    ("toxicity", drop_toxic),
    ("minhash near-dedup", drop_near_duplicates),
    ("suffix-array dedup", cut_repeats),
    ("benchmark decontamination", drop_contaminated),
    ("best-fit packing", pack_best_fit),
]
#: No stage but decontamination can be put in SQL, so that there is none for run()'s rows.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
