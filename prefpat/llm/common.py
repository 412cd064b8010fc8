"""Shared pieces of the corpus operators: reading, word patterns, checkpoints."""

from __future__ import annotations

import tempfile
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The six ASCII white-space characters that separate words.
SPACE_CHARS = " \t\n\x0b\x0c\r"
#: The same set as a Java regular expression; a word is a run of anything else.
SPACE_RE = "[ \\t-\\r]+"
WORD_CHAR_RE = "[^ \\t-\\r]"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read by Spark alone (any file system it knows)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the cluster's shared checkpoint folder; fall back to a local one only
    where the session names none and the master is local (tests)."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isDefined():
        return
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named is None and not context.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    context.setCheckpointDir(named or tempfile.mkdtemp(prefix="prefpat-checkpoint-"))


def cut(df: DataFrame) -> DataFrame:
    """Materialise ``df`` reliably (a checkpoint, never a local one), so that a
    lost executor costs a reread and not a recomputation of everything above.

    What was shuffled above is of no more use then, but stays on the executors' disks
    until the driver's collector notices; it is asked to.
    """
    ensure_checkpoint_dir(df.sparkSession)
    written = df.checkpoint(eager=True)
    df.sparkSession._jvm.System.gc()
    return written


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with ``value`` evaluated once per row.

    A column used inside a higher-order function is evaluated again for every
    element. Binding it as a lambda variable of a one-element array avoids that.
    """
    return F.element_at(F.transform(F.array(value), body), 1)


def shuffle_parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def own_columns(df: DataFrame, *names: str) -> list[Column]:
    """Just the named input columns; other columns, whatever their names, do not
    take part, so that a column named like an output cannot clash with it."""
    return [F.col(f"`{n}`") for n in names]


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only, whatever the locale."""
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return F.translate(text, upper, upper.lower())


def words_of(text: Column) -> Column:
    """Words ``[^\\x20\\x09-\\x0D]+`` of a text; null and blank texts have none."""
    trimmed = F.btrim(F.coalesce(text, F.lit("")), F.lit(SPACE_CHARS))
    return F.when(F.length(trimmed) == 0, F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACE_RE))
