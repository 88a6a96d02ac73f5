"""Corpus pipeline: toxicity, quality, near-duplicates, decontamination, mixing.

Every stage works on all that its predecessor kept; classifiers learn from the
labelled documents among its input. All but the last return the columns of
``documents``, whatever their names; the last adds the fitted ``rate`` and whole
``copies`` of each document, in place of columns of these names, and leaves out
documents of rate 0. Null and empty texts are ordinary documents of no words,
documents without id stay unless their text condemns them, rows that repeat an id
and text count once from the third stage on, and an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from modelsort.llm import decontaminate, mixing, quality, simhash, toxicity
from modelsort.llm.catalog import labelled_languages
from modelsort.llm.samples import free_name, quoted
from modelsort.plans.durable import materialize


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose maximum-scoring segments don't make them toxic; texts without words aren't, equal texts are judged alike."""
    return toxicity.keep_clean(docs, toxicity.train(docs, _table(spark, sf_dir, "labels")))


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the attention network scores at its threshold or above, null texts as empty ones; equal texts are judged alike."""
    return quality.keep_good(docs, quality.train(docs, _table(spark, sf_dir, "labels")))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each SimHash group, that of least id; documents without id all stay."""
    return simhash.deduplicate(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without contamination by benchmark windows; an empty benchmark drops none."""
    return decontaminate.decontaminate(docs, _table(spark, sf_dir, "benchmark"))


def mix_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with rates that give every language the same expected tokens.

    Rows that share an id share its rate; documents without id are rated together
    by text and join no rate, so they keep rate 1 and one copy.
    """
    rates, _, _ = mixing.mix(docs, labelled_languages(docs, _table(spark, sf_dir, "labels")))
    key = free_name(docs, "__id")
    rates = rates.where("doc_id is not null").select(F.col("doc_id").alias(key), "rate", "copies")
    kept = docs.select(*(c for c, name in zip(quoted(docs), docs.columns, strict=True) if name.lower() not in ("rate", "copies")))
    rated = kept.join(rates, kept["doc_id"] == rates[key], "left").drop(key)
    filled = rated.withColumns({"rate": F.coalesce("rate", F.lit(1.0)), "copies": F.coalesce("copies", F.lit(1).cast("long"))})
    return filled.where("rate > 0")


STAGES = [
    ("toxicity", drop_toxic),
    ("quality classifier", keep_quality),
    ("SimHash near-dedup", near_dedup),
    ("benchmark decontamination", drop_contaminated),
    ("mixing sources to target weights", mix_languages),
]
#: Learned scores and graph components have no SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents``, each written and read again before the next."""
    docs = _table(spark, sf_dir, "documents")
    for number, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if number < len(STAGES) - 1:
            docs = materialize(docs, "pipeline")
    return docs
