"""From raw documents to token ids in five stages, each of one operator.

A stage takes (spark, docs, sf_dir) and returns a DataFrame; its caller writes that as Parquet and
passes what it reads back to the next. All but the last return the columns of ``documents``.

Edges, besides those of the operators: documents whose text a stage empties stay, with empty text; with
no labelled document at all nothing is known about languages and every document stays.
"""

from __future__ import annotations

import functools
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codist.llm import bpe, decontaminate, jaccard_join, langid, storage, substring_dedup
from codist.llm.catalog import BYTE_BPE, tokenizer_path

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]

#: Tables behind the result of the stage before, which is written by the time the next stage begins.
_behind: list = []


def _stage(last: bool = False) -> Callable[[Stage], Stage]:
    def wrap(f: Stage) -> Stage:
        @functools.wraps(f)
        def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
            storage.release(_behind)
            _behind.clear()
            with storage.recorded() as tables:
                out = f(spark, docs, sf_dir)
            if not last:
                _behind.extend(tables)
            return out

        return run

    return wrap


@_stage()
def language_identification(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the models accept; a missing language is filled in."""
    models = langid.learn_models(docs)
    if not models.languages:
        return docs
    return langid.keep_identified(docs, models, fill="lang")


@_stage()
def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, the first by id, of each group of near copies."""
    return jaccard_join.keep_first(docs)


@_stage()
def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without the windows of 50 words that an earlier one holds; other texts are unchanged."""
    return substring_dedup.cut_repeats(docs, size_col="n_chars")


@_stage()
def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no window of a benchmark item."""
    return decontaminate.remove_documents(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


@_stage(last=True)
def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids, text): the ids of each document and the text they decode to."""
    path = tokenizer_path(BYTE_BPE)
    ids = bpe.encode(docs, path, decoded_out="text")
    return ids.select("doc_id", F.size("ids").cast("bigint").alias("n_tokens"), "ids", "text")


STAGES: list[tuple[str, Stage]] = [
    ("language identification", language_identification),
    ("near duplicates", near_duplicates),
    ("repeated passages", repeated_passages),
    ("benchmark decontamination", benchmark_decontamination),
    ("tokens", tokens),
]

#: SQL can't express the language models or the tokenizer; the stages are tested against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on the documents of ``sf_dir``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    where = f"{storage.shared_dir(spark)}/pipeline/{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            path = f"{where}/{k}"
            docs.write.parquet(path)
            storage._written.append((spark, "", path))
            docs = spark.read.parquet(path)
    return docs
