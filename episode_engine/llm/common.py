"""What the training-data operators share: tables, words, written intermediates."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import uuid
import zlib
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space, as a Java regular expression and as the characters themselves.
BLANKS = r"[\x20\x09-\x0D]+"
BLANK_CHARS = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value evaluated once a row, however often body's lambdas use it."""
    return F.element_at(F.transform(F.array(value), lambda x: body(x)), 1)


def trimmed(text: Column) -> Column:
    return F.btrim(F.coalesce(text, F.lit("")), F.lit(BLANK_CHARS))


def words(text: Column) -> Column:
    """The maximal runs of anything but ASCII white space; a null text has none."""
    t = trimmed(text)
    return F.when(t == "", F.array().cast("array<string>")).otherwise(F.split(t, BLANKS))


def ascii_lower(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)


def crc_mod(doc_id: Column, n: int) -> Column:
    """crc32 of the id's decimal text, modulo n."""
    return F.crc32(doc_id.cast("string").cast("binary")) % n


def py_crc_mod(doc_id: int, n: int) -> int:
    return zlib.crc32(str(doc_id).encode()) % n


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir, or by setCheckpointDir; a temporary one in local mode only."""
    found = spark.conf.get("spark.checkpoint.dir", None) or getattr(spark, "_own_shared_dir", None)
    if not found:
        given, master = spark.sparkContext._jsc.sc().getCheckpointDir(), spark.sparkContext.master
        if given.isDefined():
            found = given.get()
        elif master.startswith("local") and not master.startswith("local-cluster"):
            found = tempfile.mkdtemp(prefix="shared-")
            atexit.register(shutil.rmtree, found, ignore_errors=True)
        else:
            raise RuntimeError("spark.checkpoint.dir has to name a folder that the driver and all executors share")
        spark._own_shared_dir = found
    return found.rstrip("/")


def drawn(df: DataFrame, wanted: int, rows: int) -> DataFrame:
    """Of `rows` rows about `wanted`, by chance: nothing is sorted, and executors send no more than what is wanted in all. For range borders."""
    return df if rows <= wanted else df.filter(F.rand(11) < wanted / rows)


def written(df: DataFrame, name: str) -> DataFrame:
    """df as Parquet in the shared folder, read again: lineage is cut, and a lost executor loses nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_path = path
    return out


def discard(*frames: DataFrame) -> None:
    """Delete written() frames that nothing reads any more."""
    for df in frames:
        if path := getattr(df, "_written_path", None):
            spark = df.sparkSession
            place = spark._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


_kept: dict[str, object] = {}


def kept(name: str, make: Callable[[], object]) -> object:
    """What a Python worker keeps from task to task: one thing at a time."""
    if name not in _kept:
        _kept.clear()
        _kept[name] = make()
    return _kept[name]


def let_go() -> None:
    """Frees what earlier tasks of other operators left in this worker, before a task that needs memory of its own."""
    if _kept:
        _kept.clear()
        gc.collect()
    pa.default_memory_pool().release_unused()
