"""The corpus pipeline: five stages, each calling one operator of `runstore.llm`.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last
return the columns of `documents`.  `run` writes every stage's result to scratch
space and reads it back for the next.

Documents are passed on whole or not at all: no stage changes a value, and
columns beyond those of `documents` are carried along whatever their names.
Null, empty and letterless texts go at the language stage.  Very long texts are
treated as whole texts everywhere.  Repeated rows (rows of one id) stay together
or go together, except that only the least id of a group of near duplicates
stays; rows with a null id stand for themselves there.  An empty table passes
as an empty table, in every stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from runstore.llm import base, decontaminate, language_id, near_dup, piece_codec, quality

#: A document stays if its predicted language has at least this probability.
LEAST_LANGUAGE_SCORE = 0.5
#: Documents of at least this similarity (in per cent) are near duplicates; the bands follow it (`near_dup.bands_for`).
NEAR_DUP_PERCENT = near_dup.PERCENT


def with_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of a language that can be told; texts without a letter go."""
    base.bounded_batches(spark)
    model = language_id.train(docs.where(language_id.fold("doc_id", 3) != 1))
    own = {c: f"__own_{c}" for c in docs.columns if c in ("lang_pred", "score")}  # the operator would replace them
    got = language_id.identify(docs.withColumnsRenamed(own), model)
    kept = got.where((F.col("lang_pred") != language_id.UNDETERMINED) & (F.col("score") >= LEAST_LANGUAGE_SCORE))
    return kept.select(*[F.col(own.get(c, c)).alias(c) for c in docs.columns])


def of_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts."""
    model = quality.fit_on_tables(docs, base.table(spark, sf_dir, "labels"))
    return quality.score(docs, model, out="__quality").where(F.col("__quality") >= quality.CUT).select(*docs.columns)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates, that of the least id."""
    base.bounded_batches(spark)
    return near_dup.deduplicate(docs, percent=NEAR_DUP_PERCENT)


def uncontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    got = decontaminate.is_clean(docs, base.table(spark, sf_dir, "benchmark"), "__clean")
    return got.where("__clean").select(*docs.columns)


def tokenized(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids (with begin and end), their number, and whether they decode to the text."""
    base.bounded_batches(spark)
    sums = piece_codec.encode_decode(docs.select("doc_id", "text"))
    return sums.select("doc_id", "n_tokens", F.col("ids").cast("array<int>").alias("ids"), F.sha2("decoded", 256).alias("decoded_sha256"))


STAGES = [
    ("language_id", with_language),
    ("quality", of_quality),
    ("near_dup", one_of_each),
    ("decontaminate", uncontaminated),
    ("tokenize", tokenized),
]

#: Trained stages are not SQL; tests compare `run` with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = base.table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = base.stored(stage(spark, docs, sf_dir), f"pipeline_{name}")
    return docs
