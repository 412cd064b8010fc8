"""Corpus pipeline: stages applied in turn to ``documents``.

Every stage takes (spark, docs, sf_dir), where docs is what its predecessor kept,
and returns a DataFrame; all but the last return the columns of documents. ``run``
writes each stage's result as Parquet into the shared checkpoint folder and reads
it again, so that a lost executor costs a reread. The folder goes when the session's
process ends.

1. quality rules: documents that the risk-controlled rules reject go; a cutoff is
   used only where the labels prove that it rejects few good documents.
2. language ID: documents without a letter, or told less surely than nearly all
   others, go.
3. line dedup: passages that stand in an earlier document go from the texts.
4. SimHash near-dedup: of each group of near copies (five-word shingles, near
   fingerprints or a Jaccard similarity of 0.8 or more) the document with the
   smallest id stays.
5. best-fit packing: what is left, as pieces of sequences of at most 2048 tokens.
"""

from __future__ import annotations

import atexit
import uuid

from pyspark.sql import DataFrame, SparkSession

from prefpat.llm import langid, linededup, packing, quality, simhash
from prefpat.llm.common import ensure_checkpoint_dir, read_table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs, "doc_id", "text", read_table(spark, sf_dir, "labels"), "quality")


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return langid.keep_known(docs, "doc_id", "text", "lang")


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return linededup.without_repeats(docs, "doc_id", "text")


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_representatives(docs, "doc_id", "text")


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, "doc_id", "text").withColumnRenamed("key", "doc_id")


STAGES = [
    ("quality_rules", quality_rules),
    ("language_id", language_id),
    ("line_dedup", line_dedup),
    ("near_dedup", near_dedup),
    ("best_fit_packing", best_fit_packing),
]

#: SimHash and the tokenizer have no SQL form; tests hold the run against a plain one.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ensure_checkpoint_dir(spark)
    folder = f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/corpus-pipeline-{uuid.uuid4().hex}"
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    files = path.getFileSystem(spark._jsc.hadoopConfiguration())
    atexit.register(_delete, files, path)
    docs = read_table(spark, sf_dir, "documents")
    for number, (name, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{number}-{name}")
        docs = spark.read.parquet(f"{folder}/{number}-{name}")
    return docs


def _delete(files, path) -> None:
    """At the process's end; a session that has ended already has taken its files' connection along."""
    try:
        files.delete(path, True)
    except Exception:  # noqa: BLE001
        pass
