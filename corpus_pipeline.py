"""A corpus pipeline over ``documents``: toxicity, near-duplicates, secrets, source mix, tokens.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coverjoin.llm import minhash, mix, pieces, secrets, toxicity
from coverjoin.llm.common import cut
from coverjoin.llm.queries import MODEL

#: A document with at least this probability of toxicity goes.
TOXIC = 0.7


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents below TOXIC, by a classifier trained on the labelled ones among ``docs``. Empty and null texts are scored
    like any other and stay unless the score says otherwise."""
    model = toxicity.train(toxicity.training_rows(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    out = "toxicity"
    while out in docs.columns:
        out = f"_{out}"
    return toxicity.score(docs, model, out=out).filter(F.col(out) < TOXIC).drop(out)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest id of each group of near-duplicates (five-word shingles, similarity of 0.8 or more). Texts
    without words are in no group and stay."""
    gone = minhash.near_duplicates(docs, shingle=5).filter(~F.col("kept")).select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, secrets in their texts replaced; n_chars follows the new text."""
    out = "secrets"
    while out in docs.columns:
        out = f"_{out}"
    done = secrets.scan(docs, secrets.train(spark), findings=out, redacted="text")
    return done.withColumn("n_chars", F.when(F.size(out) > 0, F.char_length("text").cast("long")).otherwise(F.col("n_chars"))).select(*docs.columns)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix to default weights: a document taken twice stands there twice, one taken in part keeps its first words."""
    return mix.mixed(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, source, n_ids and ids of every document; decoding the ids gives the text back."""
    coded = pieces.encode(docs.select("doc_id", "source", "text"), pieces.load(MODEL), keep_text=False)
    return coded.select("doc_id", "source", F.size("ids").alias("n_ids"), "ids")


STAGES = [("toxicity", drop_toxic), ("minhash", one_of_each_group), ("secrets", redact_secrets), ("mix", mix_sources), ("sentencepiece", tokens)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)


#: Training, hashing of words and the order of merges have no form in SQL: tests/llm holds run() against plain Python.
ORACLE_SQL = None

QUERIES = {"pipeline": run}
ORACLES: dict[str, str] = {}
