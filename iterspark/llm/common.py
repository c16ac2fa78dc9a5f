"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a run of characters other than the six ASCII white-space characters.
WORD = r"[^\x20\x09-\x0D]+"


#: A key that holds more than this part of all rows is joined by broadcast; fewer keys than this can.
MOST_HOT = 1000


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share. Only a local master, whose executors are the driver, may go without."""
    sc = spark.sparkContext
    known = sc._jsc.sc().getCheckpointDir()
    named = spark.conf.get("spark.checkpoint.dir", None) or (known.get() if known.isDefined() else None)
    if named is None:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        named = tempfile.mkdtemp(prefix="iterspark-")
    if not known.isDefined():
        sc.setCheckpointDir(named)
    return named.rstrip("/")


#: Folders written since the innermost `scratch` was opened, a list for each.
_open: list[list[str]] = []


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Removes what `cut`, `parked` and `fresh_path` have written inside, and puts the batch length back.

    Results made inside are lazy, so write what is to stay before the block ends, elsewhere.
    """
    batch = spark.conf.get(_BATCH)
    _open.append([])
    try:
        yield
    finally:
        spark.conf.set(_BATCH, batch)
        for path in _open.pop():
            remove(spark, path)


def remove(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def _note(path: str) -> str:
    if _open:
        _open[-1].append(path)
    return path


def _checkpoint_file(df: DataFrame) -> str | None:
    plan = df._jdf.queryExecution().logical()
    file = plan.rdd().getCheckpointFile() if plan.getClass().getSimpleName() == "LogicalRDD" else None
    return file.get() if file is not None and file.isDefined() else None


def cut(df: DataFrame) -> DataFrame:
    """Write `df` to the shared folder and return it without its lineage."""
    shared_folder(df.sparkSession)
    out = df.checkpoint(eager=True)
    if _open and (file := _checkpoint_file(out)):
        _note(file)
    return out


def discard(*used: DataFrame) -> None:
    """Remove what `cut` wrote for tables that nothing needs any more, and let Spark drop the shuffle files of finished steps.

    Spark drops them when the driver's garbage is collected, which a long run of small jobs may not come to.
    """
    spark = used[0].sparkSession
    for df in used:
        if file := _checkpoint_file(df):
            remove(spark, file)
    release(spark)


def release(spark: SparkSession) -> None:
    gc.collect()
    spark._jvm.System.gc()


def fresh_path(spark: SparkSession, label: str) -> str:
    """A new folder below the shared one."""
    return _note(f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}")


def parked(df: DataFrame, label: str) -> DataFrame:
    """Like `cut`, through compressed Parquet: for tables that hold texts or arrays."""
    path = fresh_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def joined_by_key(rows: DataFrame, facts: DataFrame, key: str, n: str, total: int, heaviest: int | None = None, most: int = MOST_HOT) -> DataFrame:
    """`rows` with the columns of `facts`, which has one row for each key; keys without facts are left out.

    `n` is a column of `facts`, at least the number of `rows` with the key; `total` the sum of `n`. Keys
    with more than a `most`-th of that, of which there are fewer than `most`, go by broadcast, so no task
    holds all rows of a hot key; the others go by shuffle. `heaviest`: the greatest `n`, where it
    is known; if that is not hot, all go by shuffle.
    """
    limit = max(total / most, 64)
    if heaviest is not None and heaviest <= limit:
        return rows.join(facts, key)
    often = F.col(n) > limit
    hot, rare = F.broadcast(facts.filter(often)), facts.filter(~often)
    return rows.join(hot, key).unionByName(rows.join(hot.select(key), key, "left_anti").join(rare, key))


_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


def short_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Send texts to Python in batches of at most so many rows: texts are long, and both sides hold a whole batch.

    Spark reads the setting when a plan runs, so it stays until a `scratch` around the work ends.
    """
    if int(spark.conf.get(_BATCH)) > rows:
        spark.conf.set(_BATCH, str(rows))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    short_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def n_words(text: Column) -> Column:
    """Words of a text; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def fold(doc_id: Column, folds: int = 5) -> Column:
    """crc32 of the id as text, modulo the number of folds; fold 0 is held out."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % folds, F.lit(0)).cast("int")


def collect_bounded(df: DataFrame, most: int, what: str) -> list:
    """Rows of a table whose size has a stated bound; more rows are an error, never dropped."""
    rows = df.limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"{what}: more than {most} rows")
    return rows
