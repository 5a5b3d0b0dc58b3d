"""Written intermediate tables, row helpers and the Arrow plumbing that the operators share."""

from __future__ import annotations

import threading
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..ship import shared_folder, ship

#: A word of the contracts; every other character of a text separates words.
WORD = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def written(df: DataFrame) -> DataFrame:
    """The same rows, stored once as Parquet in the shared folder and read back: lineage ends here, and a lost executor costs no recomputation."""
    spark = df.sparkSession
    ship(spark)
    path = f"{shared_folder(spark)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _tables(spark).append((threading.get_ident(), path))
    return spark.read.schema(df.schema).parquet(path)


def _tables(spark: SparkSession) -> list[tuple[int, str]]:
    """Threads and paths that `written` made in this application and that were not removed yet."""
    context = spark.sparkContext
    if not hasattr(context, "_topfd_tables"):
        context._topfd_tables = []
    return context._topfd_tables


def marked(spark: SparkSession) -> int:
    """Where the written tables stand now, for `removed`."""
    return len(_tables(spark))


def removed(spark: SparkSession, since: int = 0, keep: DataFrame | None = None) -> None:
    """Deletes the tables that this thread wrote since a mark, but for the one that `keep` reads. For when what they led to is stored itself."""
    kept = [str(f) for f in keep.inputFiles()] if keep is not None else []
    paths = _tables(spark)
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for thread, path in paths[since:]:
        if thread == threading.get_ident() and not any(path.rsplit("/", 1)[1] in f for f in kept):
            at = jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(conf).delete(at, True)
            paths.remove((thread, path))


def word_count(text: Column) -> Column:
    """Words of a text as BIGINT; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def ascii_lower(text: Column) -> Column:
    """A-Z alone, so that no other letter changes."""
    return F.translate(text, UPPER, LOWER)


def arrow_map(df: DataFrame, columns: Iterable[str | Column], schema: str, make: Callable[[], Callable[[pa.RecordBatch], Iterator[pa.RecordBatch]]]) -> DataFrame:
    """mapInArrow over the given columns alone. make() runs once in a task and gives the function of a batch."""

    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        each = make()
        for batch in batches:
            if batch.num_rows:
                yield from each(batch)
        pa.default_memory_pool().release_unused()

    return df.select(*columns).mapInArrow(run, schema)
