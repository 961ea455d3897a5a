"""A training corpus from raw documents: toxicity, near-duplicates, contamination, mix, shards."""
from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provgraph.functions.columns import column, packed, unpacked
from provgraph.functions.durable import checkpoint_folder
from provgraph.llm import decontamination, hilbert, near_duplicates, pfair, toxicity
from provgraph.llm.queries import OTHER, TARGETS

#: What the rows of a source are dealt by.
SPREAD = ["doc_id", "n_chars"]


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go."""
    return toxicity.drop_toxic(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays; five words, similarity 0.8."""
    return near_duplicates.keep_one(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark window go."""
    return decontamination.decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, in the order of the mix."""
    return pfair.mixed(docs, TARGETS, other=OTHER, spread=SPREAD)


def cut_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents with their slot of the mix, shard and slot along the curve.

    The place in the mix is a dimension of the curve, and source is none: shards keep the mix's order in
    the large and the targets' proportions, and a reader skips those of other stretches of the mix.  A
    table has no order that a stage could read, so the slots are worked out again; the schedule depends on
    the rows alone.  Columns of the same name as an added one are replaced by it.
    """
    names = docs.columns
    size = F.coalesce(F.octet_length("text"), F.lit(0)) + 8
    slim = packed(docs, **{c: column(c) for c in ("doc_id", "source", "lang", "n_chars")}, size=size.cast("long"))
    slots = pfair.mix(slim, TARGETS, other=OTHER, spread=SPREAD).withColumnRenamed("slot", "mix_slot").drop("block", "pos", "release", "deadline")
    placed = hilbert.shard(slots, ["mix_slot", "lang", "n_chars"], spread=[F.col("doc_id"), F.col("n_chars")], size=F.col("size"))
    return unpacked(placed, names, **{c: F.col(c) for c in ("mix_slot", "curve", "place", "shard", "slot")})


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("mixing", mix_sources),
    ("sharding", cut_shards),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every stage on all that its predecessor kept; an empty table stays empty, nulls are as in the stages' operators."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = f"{checkpoint_folder(spark)}/corpus-{uuid.uuid4().hex}"
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        spark.sparkContext._jvm.System.gc()  # the driver gives the stage's plans, generated classes and heap back
    return STAGES[-1][1](spark, docs, sf_dir)


#: The toxicity stage is a trained classifier, which SQL can't express.
ORACLE_SQL = None
