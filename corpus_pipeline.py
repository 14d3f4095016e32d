"""From raw documents to token ids in five stages: quality, repeated lines, near copies, the mix of sources, encoding.

Each stage takes (spark, docs, sf_dir), docs having the columns of the table documents, and works on all that the stage before it
kept. All but the last return these columns again; the last returns each document's ids.

Defined results: the stages' own, see the modules; a document that loses all its lines stays with an empty text until the mix, which takes
nothing of it; the mix repeats documents, so an id may come up to three times at the end.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from modspark.llm import bpe, common, jaccard, line_templates, mixing, quality


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier doesn't reject."""
    model = quality.fit(docs, quality.labels_of(spark, sf_dir))
    return quality.with_score(docs, model, out="_score").where(F.col("_score") >= quality.THRESHOLD).select(*docs.columns)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines of recurring templates, from three documents on.

    Long lines of two documents stay here: most are those of pairs of copies, which the next stage removes whole; cut here, the second
    document of a pair would stay as what is left of it.
    """
    return line_templates.drop_recurring(docs, long_docs=line_templates.MIN_DOCS).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies."""
    return jaccard.one_of_each_class(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them."""
    return mixing.repeat(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, source, n_tokens, ids."""
    coded = bpe.encode(docs.select("doc_id", "source", "text"), decoded=False)
    return coded.select("doc_id", "source", F.size("ids").cast("long").alias("n_tokens"), "ids")


STAGES = [
    ("quality classifier", keep_quality),
    ("line dedup", drop_lines),
    ("n-gram Jaccard join", drop_near_copies),
    ("mixing sources to target weights", mix_sources),
    ("BPE encoding and decoding", encode),
]

#: The classifier's scores, the rounding's draws and the ids can't be stated in SQL; the tests rebuild the stages by brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir)
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = common.keep(docs, f"stage{k}")
    return docs
