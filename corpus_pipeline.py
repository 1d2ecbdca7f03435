"""The corpus pipeline: language ID, toxicity, near duplicates, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read again for the next one.
All but the last return the columns of ``documents``. Each stage decides about whole texts; exact rules:

* language_id drops documents whose language is ``und`` (null texts and texts without a letter);
* toxicity drops documents with a toxicity score of 0.7 or more;
* near_duplicates keeps, of each group linked by a Jaccard similarity of 0.8 on five-word shingles, the smallest doc_id;
  documents without words are unlinked and stay; rows that repeat a kept doc_id are reduced to one;
* packing returns the pieces of all remaining documents with their sequences.

Rows without doc_id go through every stage like others (they are in no group and pack under a null id); repeated rows stay
repeated until near_duplicates makes one of them; columns beyond those of ``documents`` are dropped; empty tables give empty
results at every stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from semcat.llm.common import fold, materialise
from semcat.llm.language_id import fit as fit_languages
from semcat.llm.language_id import predict
from semcat.llm.ngram_join import jaccard_join
from semcat.llm.packing import pack
from semcat.llm.pu_learning import TOXIC_FEATURES
from semcat.llm.pu_learning import fit as fit_pu
from semcat.llm.pu_learning import score

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a recognised language; prototypes come from the documents' own lang values outside fold 0 of 5."""
    model = fit_languages(docs.where(fold("doc_id", 5) != 0))
    carried = docs.select(*COLUMNS, F.col("text").alias("body"))
    return predict(carried, model, "doc_id", "body", tuple(COLUMNS[1:])).where("lang_pred <> 'und'").select(COLUMNS)


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score below 0.7; labels of fold 1 of 3 are not learned from."""
    model = fit_pu(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), "toxic", fold("doc_id", 3) != 1, **TOXIC_FEATURES)
    carried = docs.select(*COLUMNS, F.col("text").alias("body"))
    return score(carried, model, "doc_id", "body", tuple(COLUMNS[1:])).where("score < 0.7").select(COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group: its smallest doc_id. Rows without doc_id cannot be named in a group and stay."""
    members, _ = jaccard_join(docs, links="components")
    extra = members.where("component_id <> id").select(F.col("id").alias("doc_id")).distinct()
    kept = docs.select(COLUMNS).join(extra, "doc_id", "left_anti")
    repeated = materialise(docs.groupBy("doc_id").count().where("count > 1 and doc_id is not null").select("doc_id"), "repeats")
    once = F.row_number().over(Window.partitionBy("doc_id").orderBy("text", "lang", "source", "n_chars"))
    single = kept.join(repeated, "doc_id", "left_semi").withColumn("nth", once).where("nth = 1").select(COLUMNS)
    return kept.join(repeated, "doc_id", "left_anti").select(COLUMNS).unionByName(single)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 2048 tokens with their sequences."""
    import public_tokenizers

    return pack(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [("language_id", language_id), ("toxicity", toxicity), ("near_duplicates", near_duplicates), ("packing", packing)]

#: The stages learn models and use a tokenizer, so SQL cannot express them; tests compare them with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = materialise(docs, name)
    return docs
