"""A corpus pipeline over ``documents``: quality rules, near-dedup, substring dedup, packing.

Each stage works on what the one before it has kept, read again from Parquet. For all stages: an empty table gives an empty
one; documents of any length are handled whole; columns beyond doc_id, text and n_chars pass through as they are, whatever their names
(the last stage has columns of its own and reads doc_id and text alone); an id may occur more than once.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from devfed.llm import neardup, packing, quality, substring
from devfed.llm.graph import checkpoint_folder


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep. Null, empty and blank texts have fewer than 50 words and go; repeated rows, and rows without an id, are judged one by one."""
    return quality.keep_good(docs)


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: the one with the smallest id, one without an id only where no other is.

    Texts without a word, null ones included, are like nothing and stay. Rows equal in id and text are one document and stay together;
    of rows equal in id alone one stays in each group.
    """
    return neardup.drop_near_copies(docs)


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without the passages that one with a smaller id holds; n_chars follows the text.

    Null and short texts lose nothing and a null id is larger than all others. Rows with equal ids take nothing from each other. A text may end up
    empty and stays as a row.
    """
    return substring.remove(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents in sequences, with their ids. A null or empty text is the closing id alone; repeated rows and rows without an id are packed one by one."""
    import public_tokenizers

    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [("quality_rules", quality_stage), ("near_dedup", near_dedup_stage), ("substring_dedup", substring_stage), ("packing", packing_stage)]

#: Packing needs a tokenizer, which SQL can't express.
ORACLE_SQL = None


def _delete(spark: SparkSession, folder: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows. What a stage returns is written to the shared checkpoint folder and deleted once the next one's is; the rows returned read the last folder, which the caller may delete."""
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    folder = f"{checkpoint_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if before:
            _delete(spark, before)
        before = f"{folder}/{name}"
    return STAGES[-1][1](spark, docs, sf_dir)
