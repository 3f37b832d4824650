"""A corpus made ready for training: language, near copies, secrets, mixing, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; its result is written as Parquet and read again as the next
one's documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronofold.llm import language, mixing, nearcopies, packing, secrets
from chronofold.llm.common import spool

#: A document is rejected if no language can be told or the posterior of the best is below this.
LEAST_POSTERIOR = 0.5
#: Chunks that an encoder remembers: less than on its own, as workers still hold what earlier stages left.
ENCODER_MEMO = 100_000
#: A document stays if its rate rounds to one.
LEAST_RATE = 0.5
#: Weight of the rates' distance from one: more than on its own, so that clean documents are left alone.
RIDGE = 0.01


def tell_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language can be told, learnt from the labelled ones; without any label, all stay.  Columns of any name are
    kept as they are."""
    model = language.train(docs)
    if not model.languages:
        return docs
    names = set(docs.columns)
    pred, score = (next(n for n in (f"{x}{'_' * i}" for i in range(len(names) + 1)) if n not in names) for x in ("lang_pred", "score"))
    found = language.identify(docs, model, pred, score)
    return found.where((F.col(pred) != language.UNDETERMINED) & (F.col(score) >= LEAST_POSTERIOR)).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of copies and near copies."""
    return nearcopies.keep_one_each(docs)


def hide_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with secrets replaced by a mark."""
    return secrets.redact_secrets(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose rate is near one when the domain toxic is to have no tokens and the others all of theirs."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    found = spool(mixing.posteriors(docs, mixing.train(docs, labels)))
    rates = mixing.mixed(found, mixing.solve(found, None, most=1.0, ridge=RIDGE))
    gone = spool(rates.where(F.col("rate") < LEAST_RATE).select("doc_id").distinct())
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places of all documents' pieces in sequences of 2048 tokens."""
    return packing.pack_documents(docs, memo_chunks=ENCODER_MEMO)


STAGES = [("language ID", tell_language), ("SimHash near-dedup", drop_near_copies), ("secret scans", hide_secrets), ("mixing to target weights", mix), ("best-fit packing", pack)]

#: Language posteriors, SimHash and byte-pair encoding can't be told in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the table documents."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = spool(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
