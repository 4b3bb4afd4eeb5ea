"""What the operators for training data share: inputs, word rules, Arrow mapping."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Fixed values of the word rule: words are runs of anything but these six characters.
BLANKS = " \t\n\x0b\x0c\r"
BLANK_RUN = r"[\x20\x09-\x0D]+"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Bytes of an Arrow batch between the JVM and a Python worker.
BATCH_BYTES = 4 << 20


def named(df: DataFrame, name: str) -> Column:
    """A column by its whole name, dots and blanks included."""
    return F.col("`" + name.replace("`", "``") + "`")


def packed(df: DataFrame) -> Column:
    """All columns of ``df`` as one struct; ``select("x.*")`` gives them back whatever their names."""
    return F.struct(*(named(df, c) for c in df.columns))


def free(names: list[str], *new: str) -> list[str]:
    """``names``, to stand beside ``new`` ones: one that is like a new one gets underscores before it until it is like no other."""
    reserved = {n.lower() for n in new}
    taken = {n.lower() for n in names} | reserved
    out = []
    for was in names:
        name = was
        while name.lower() in reserved or name != was and name.lower() in taken:
            name = "_" + name
        taken.add(name.lower())
        out.append(name)
    return out


def beside(df: DataFrame, *new: str) -> list[Column]:
    """All columns of ``df``, to stand beside columns called ``new``."""
    return [named(df, c).alias(n) for c, n in zip(df.columns, free(df.columns, *new), strict=True)]


def extended(df: DataFrame, ddl: str) -> T.StructType:
    """The schema of ``df`` with further columns; names and types of its own may hold any sign."""
    return T.StructType([*df.schema.fields, *T.StructType.fromDDL(ddl).fields])


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """One input table, with only the named columns (all if none are named)."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def lower_ascii(col: Column) -> Column:
    """A-Z to a-z and nothing else, unlike ``lower``, which also folds other letters."""
    return F.translate(col, UPPER, UPPER.lower())


def words(col: Column) -> Column:
    """The words of a text in order (null: none)."""
    return F.array_remove(F.split(F.coalesce(col, F.lit("")), BLANK_RUN), "")


def word_count(col: Column) -> Column:
    return F.size(words(col)).cast("long")


def bounded(df: DataFrame) -> DataFrame:
    """``df``, with Arrow batches of its session bounded in bytes."""
    # a run-time setting: what the JVM and a worker hold of one batch, however long the texts are
    conf, key = df.sparkSession.conf, "spark.sql.execution.arrow.maxBytesPerBatch"
    now = str(conf.get(key, f"{BATCH_BYTES + 1}b")).rstrip("b")
    if not now.isdigit() or not 0 < int(now) <= BATCH_BYTES:
        conf.set(key, str(BATCH_BYTES))
    return df


def map_batches(df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch]], schema: str | T.StructType, rows: int = 256) -> DataFrame:
    """Maps Arrow batches with a function built once per task.

    Batches are cut to ``rows`` rows before they reach the function, so its memory follows
    the longest texts of a slice, not of a whole Arrow batch.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = make()
        for batch in batches:
            for start in range(0, batch.num_rows, rows):
                yield work(batch.slice(start, rows))

    return bounded(df).mapInArrow(run, schema)
