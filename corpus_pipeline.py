"""A corpus pipeline over ``documents``: five stages, each applying one operator of ``sparsegrid.llm``.

Every stage takes (spark, docs, folder of the tables) and returns the documents
that it keeps with all their columns; the last returns the mixed corpus in
pieces (shard, slot, at, doc_id, first_word, n_words, text).  Between stages the
documents are written as Parquet in the shared checkpoint folder; a stage's folder
goes when the next has been written, the last one stays for the lazy result.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsegrid.llm.decontaminate import remove_contaminated
from sparsegrid.llm.line_dedup import dedup_lines
from sparsegrid.llm.mixing import mix_sources, mixed_corpus
from sparsegrid.llm.ngram_join import ngram_components
from sparsegrid.llm.quality import keep_good, train_quality
from sparsegrid.plans.lineage import drop_folder, ensure_checkpoint_dir


def quality_stage(spark: SparkSession, docs: DataFrame, folder: str) -> DataFrame:
    """Documents that the quality classifier scores 0.3 or more; null and empty texts are scored like others."""
    return keep_good(docs, train_quality(docs, spark.read.parquet(f"{folder}/labels.parquet"), fold=(5, 0)), threshold=0.3)


def line_stage(spark: SparkSession, docs: DataFrame, folder: str) -> DataFrame:
    """All documents, without lines that repeat earlier ones; ``n_chars`` follows the text."""
    out = dedup_lines(docs, min_words=8)
    return out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text")).cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, folder: str) -> DataFrame:
    """One document, that with the smallest id, of each group linked by 5-word shingles with a similarity of 0.8 or more.

    Documents without words or id stay; rows that share an id share its fate.
    """
    gone = ngram_components(docs, n=5, num=80, den=100).where("component < doc_id").select(F.col("doc_id").alias("gone_id_")).distinct()
    return docs.join(gone, docs["doc_id"].cast("long") == gone["gone_id_"], "left_anti")


def benchmark_stage(spark: SparkSession, docs: DataFrame, folder: str) -> DataFrame:
    """Documents of which less than one word in twenty lies in a 13-word window of a benchmark item.

    Null and empty texts stay; each of repeated rows is judged on its own, all
    alike; an empty benchmark removes nothing, an empty table stays empty.
    """
    return remove_contaminated(docs, spark.read.parquet(f"{folder}/benchmark.parquet"), window=13, share=20)


def mixing_stage(spark: SparkSession, docs: DataFrame, folder: str) -> DataFrame:
    """The mixed corpus: sources weigh 1, 2, 3 in turn, none more than three times its own size.

    Null and empty texts are in no piece; a null source is one of its own;
    repeated rows are mixed each; ties of order are broken by id and text; an
    empty table gives no pieces.
    """
    return mixed_corpus(docs, mix_sources(docs, weights=(1, 2, 3), cap=3))


STAGES = [
    ("quality classifier", quality_stage),
    ("line dedup", line_stage),
    ("n-gram Jaccard join", near_duplicate_stage),
    ("benchmark decontamination", benchmark_stage),
    ("mixing sources", mixing_stage),
]

#: SQL can express neither the trained classifier nor the hashed permutations.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in order, from ``documents`` to the mixed corpus."""
    shared = f"{ensure_checkpoint_dir(spark)}/corpus-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES[:-1]):
        stage(spark, docs, sf_dir).write.parquet(f"{shared}/{k}")
        docs = spark.read.parquet(f"{shared}/{k}")
        if k:
            drop_folder(spark, f"{shared}/{k - 1}")
    return STAGES[-1][1](spark, docs, sf_dir)
