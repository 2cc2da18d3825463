"""From raw documents to packed training sequences, five stages of the training-data operators.

Each stage takes (spark, docs, sf_dir) and works on all rows that its predecessor kept; all but
the last return the columns of `documents`. Extra columns are dropped, empty tables give no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bundlegraph.llm.bpe import vocabulary
from bundlegraph.llm.common import table, written
from bundlegraph.llm.langid import UNKNOWN, fit_languages, fold, predict_languages
from bundlegraph.llm.mixing import mix
from bundlegraph.llm.near_dup import near_duplicates
from bundlegraph.llm.packing import pack
from bundlegraph.llm.toxicity import fit_toxicity, score_toxicity

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def keep_known_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Language ID: documents that it cannot name a language for go, which are those without a letter or
    without text; where no row has a language, those with letters stay. Documents of every learned
    language stay, however sure it is; repeated rows stay or go together."""
    docs = docs.select(*COLUMNS)
    model = fit_languages(docs.where(fold(F.col("doc_id"), 3) != 1))
    return predict_languages(docs, model, "__lang", "__sure", COLUMNS, untaught="any").where(F.col("__lang") != UNKNOWN).select(*COLUMNS)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Toxicity: documents with a score of 0.5 or more go. Null and blank texts score 0 and stay;
    repeated rows score alike; without labels of both classes all stay."""
    docs = docs.select(*COLUMNS)
    labels = table(spark, sf_dir, "labels")
    model = fit_toxicity(docs, labels.where(fold(F.col("doc_id"), 5) != 0))
    return score_toxicity(docs, model, COLUMNS, "__score").where(F.col("__score") < 0.5).select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Near duplicates: of each component the document with the smallest doc_id stays, once.

    Of repeated rows of one kept doc_id and text one stays; rows of one doc_id with different texts
    each stay. Documents without doc_id have no links and stay, as do null and blank texts.
    """
    docs = docs.select(*COLUMNS)
    kept = near_duplicates(docs, words=5, percent=80).where("kept AND doc_id IS NOT NULL").select("doc_id").distinct()
    one = docs.join(kept, "doc_id", "left_semi").dropDuplicates(["doc_id", "text"])
    return one.select(*COLUMNS).unionByName(docs.where("doc_id IS NULL"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Mixing: each document as often as its source's target asks for, up to twice. Texts without words,
    and sources without any, may go; null sources are one source."""
    return mix(docs.select(*COLUMNS))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packing: sequences of at most 4096 ids; a document that the mix took twice is packed twice. A null
    text is one end id."""
    return pack(docs, vocabulary("word_bpe_49k.json"), end_id=1, capacity=4096)


STAGES = [
    ("language_id", keep_known_languages),
    ("toxicity", drop_toxic),
    ("near_dedup", drop_near_duplicates),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: Models, connected components and a tokenizer's merges have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = written(docs, f"pipeline-{name}")
    return docs
