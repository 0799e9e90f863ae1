"""A corpus pipeline: each stage takes the documents its predecessor kept, and its decisions take effect.

All stages but the last return the columns of `documents`; the last returns them with the pieces of each text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.llm import decontaminate, langid, pieces, secrets, setjoin
from hamcover.llm.common import Steps, written


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no language can be told go."""
    return langid.identified(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of similar documents the one of the least id stays."""
    return setjoin.one_of_each(docs)


def contamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark text go."""
    tests = spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", "text")
    return decontaminate.decontaminated(docs, tests)


def credentials(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by their kind."""
    return secrets.redacted(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of each text; n_pieces, round_trip and parity tell how they went."""
    mark = "__pieces"
    found = pieces.encode_pieces(docs, pieces.read_model(), output=mark)
    ids = F.col(f"{mark}.ids")
    return found.select(*docs.columns, ids.alias("piece_ids"), F.size(ids).cast("long").alias("n_pieces"), F.col(f"{mark}.round_trip").alias("round_trip"), F.col(f"{mark}.parity").alias("parity"))


STAGES = [
    ("language_id", language),
    ("set_join", near_copies),
    ("decontaminate", contamination),
    ("secret_links", credentials),
    ("pieces", tokens),
]

#: Language scores and the near-copy classes have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each stage's rows are written and read again; what a stage wrote on its way, and the rows before, go when they are."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    with Steps() as steps:
        for name, stage in STAGES[:-1]:
            with Steps() as own:
                docs = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
                own.keep(docs)
        steps.keep(docs)
    return STAGES[-1][1](spark, docs, sf_dir)
