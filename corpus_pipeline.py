"""A corpus pipeline: toxic documents go, one document of each near-duplicate class stays, documents
contaminated by benchmark items go, the rest is mixed to target weights and put into shards.

Every stage takes (spark, docs, sf_dir) and works on all rows its predecessor kept; ``run`` and the
check tool write each result as Parquet before the next stage reads it.  All stages but the last
return the columns of ``documents``; the last adds size, shard and slot.  The mix writes its rows in
order of their training position and the slots of each shard follow that order.  A null text is never
toxic, contaminated or a near duplicate; it has size 0, so the mix drops it unless repeated.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from trajkit.llm import decontamination, mixing, order_minhash, resharding, toxicity
from trajkit.llm.samples import id_mod
from trajkit.llm.scratch import stored, table

def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str, least: float = 0.7) -> DataFrame:
    """Fits on the labelled documents of this stage's input and drops those that score ``least``."""
    labels = table(spark, sf_dir, "labels", "doc_id", "toxic").filter(id_mod(3) != 1)
    model = toxicity.fit(docs, labels)
    return toxicity.keep_below(docs, model, least)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return order_minhash.one_of_each(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontamination.clean(docs, table(spark, sf_dir, "benchmark", "item_id", "text"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(docs)


def put_into_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Slots keep the order of the mix: within a shard, documents come in training order."""
    return resharding.with_shards(docs, order="stored")


STAGES = [
    ("toxicity", drop_toxic),
    ("order_minhash", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("mixing", mix_sources),
    ("sharding", put_into_shards),
]
#: Trained scores, alignments and flows are not expressible in SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
