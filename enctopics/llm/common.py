"""What the operators of this subpackage share: lineage cuts, row keys and fixed sizes."""

from __future__ import annotations

import ctypes
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A table goes to every executor only if it has been counted and has at most so many rows.
BROADCAST_ROWS = 200_000
#: Bytes of rows that a Python worker is handed at once, where the session doesn't say.
BATCH_BYTES = 4 << 20


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster names for checkpoints; a local session, which names none, gets one under its warehouse."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("on a cluster, set spark.checkpoint.dir to a folder that all executors share")
        named = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/checkpoints-{spark.sparkContext.applicationId}"
        spark.sparkContext.setCheckpointDir(named)
    return named


def cut(df: DataFrame) -> DataFrame:
    """df, computed once and kept in the shared folder, so that a lost executor costs nothing of it."""
    spark = df.sparkSession
    folder = shared_folder(spark)
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(folder)
    return df.checkpoint(eager=True)


def give_back() -> None:
    """Gives memory that this process no longer uses back to the machine."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def trimmed(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """run, after which the worker gives memory back: workers go on to other stages."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        give_back()

    return go


def small_batches(spark: SparkSession) -> None:
    """Whole texts go to Python workers a few MB at a time: of each batch worker and JVM hold several copies. A limit that the session sets stays."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    if spark.conf.get(key, None) is None:
        spark.conf.set(key, str(BATCH_BYTES))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def narrow(docs: DataFrame, **columns: str) -> DataFrame:
    """Only the columns an operator works on, under its own names, whatever else docs carries."""
    return docs.select(*[docs[source].alias(name) for name, source in columns.items()])


def small(df: DataFrame, rows: int) -> DataFrame:
    """df with a broadcast hint if its counted rows allow it."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def free_name(df: DataFrame, name: str) -> str:
    """name, or the like of it, that no column of df has."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def without(docs: DataFrame, ids: DataFrame, id_col: str) -> DataFrame:
    """docs less the rows whose id is the one column of ids; rows without an id stay."""
    name = free_name(docs, "id")
    gone = ids.select(F.col(ids.columns[0]).alias(name))
    return docs.join(small(gone, ids.count()), docs[id_col] == F.col(name), "left_anti")


def first_copies(docs: DataFrame, ids: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """The rows of docs whose id is the one column of ids, each id and text once; rows without an id stay."""
    name, copy = free_name(docs, "id"), free_name(docs, "copy")
    least = ids.select(F.col(ids.columns[0]).alias(name)).distinct()
    kept = docs.where(docs[id_col].isNotNull()).join(least, docs[id_col] == F.col(name), "left_semi")
    once = kept.withColumn(copy, F.xxhash64(text_col)).dropDuplicates([id_col, copy]).drop(copy)
    return once.unionByName(docs.where(docs[id_col].isNull()))


def no_null(column: Column) -> Column:
    return F.coalesce(column, F.lit(""))


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body of value, which is computed once: Spark writes a column's expression anew wherever it is used, lambdas included."""
    return F.transform(F.array(value), body)[0]


def save(df: DataFrame, compression: str = "snappy") -> DataFrame:
    """df as a table in the shared folder: like cut(), with columns compressed, for the larger intermediate results."""
    path = f"{shared_folder(df.sparkSession).rstrip('/')}/{uuid.uuid4().hex}"
    df.write.option("compression", compression).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def remainder(n: int, id_col: str = "doc_id") -> Column:
    """crc32 of an id as text, modulo n: what fixes the rows that are held out."""
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(n))


def word_bpe() -> str:
    """The tokenizer of the packing contract, as installed on driver and executors alike."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")
