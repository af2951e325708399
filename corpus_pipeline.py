"""A corpus pipeline of five stages; each reads what the one before has kept.

Every stage gives its documents' columns as they came, also those whose names an operator uses for its own results.
Null and empty texts have importance weight 1 and no language, so the second stage drops them; repeated rows are
judged alike by the first two stages and meet in the third, which keeps the row of the smallest id of equal texts (one
of them where ids are equal, too). Texts are read whole whatever their length. An empty table stays empty.

``STAGES`` lists (name, function); a function takes (spark, docs, sf_dir) and returns the documents that stay, the
last one the packed pieces. ``run`` applies them to the table ``documents``, each stage written as Parquet to the
shared folder and read again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from patternspark.llm import exact_dedup, langid, packing, resampling, simhash
from patternspark.llm.common import cut
from patternspark.llm.queries import language_model

#: A document goes if its best language has a smaller posterior (a quarter is chance among four).
LEAST_POSTERIOR = 0.3


def _by_place(docs: DataFrame) -> tuple[DataFrame, dict[str, str], list[str]]:
    """``docs`` with columns named by their place, so that no result of an operator clashes; old to new names; the new."""
    inner = [f"in{i}" for i in range(len(docs.columns))]
    return docs.toDF(*inner), dict(zip(docs.columns, inner)), inner


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that importance resampling towards the labelled good ones draws."""
    model = resampling.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    plain, name, inner = _by_place(docs)
    drawn = resampling.resample(plain, model, id_col=name["doc_id"], text_col=name["text"], keep=inner).where("selected")
    return drawn.select(*inner).toDF(*docs.columns)


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which a language is found."""
    plain, name, inner = _by_place(docs)
    found = langid.predict(plain, language_model(docs), text_col=name["text"], keep=inner)
    return found.where((F.col("lang_pred") != langid.UND) & (F.col("score") >= LEAST_POSTERIOR)).select(*inner).toDF(*docs.columns)


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts."""
    return exact_dedup.exact_dedup(docs, keep="smallest")


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies."""
    return simhash.drop_near_copies(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces in sequences of at most 1024 tokens."""
    import public_tokenizers as known

    pieces = packing.token_pieces(docs, known.path("byte_bpe_50k.json"), ranks_path=known.path("byte_bpe_50k.tiktoken"), pattern=known.PATTERN)
    return packing.pack(pieces).withColumnRenamed("id", "doc_id")


STAGES = [("quality", quality), ("language", language), ("exact_dedup", exact), ("near_dedup", near), ("packing", pack)]

#: SQL cannot express the fitted models and the similarity graph.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
