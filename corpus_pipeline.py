"""Five stages over documents: toxicity, near duplicates, decontamination, mixing, sharding.

Each stage takes (spark, docs, sf_dir), works on all rows its predecessor kept, and returns
the columns of documents; the last returns the shards. Stored order carries the mix from
the fourth stage to the fifth: rows are written in mixed order and sharded in it.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from supplyrisk.llm import decontaminate, mixing, sharding, simhash, toxicity
from supplyrisk.llm.common import delete, shared_dir, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the lexicon, fitted on the labelled rows, does not reject.

    Null and empty texts score by length zero and stay; repeated rows share a score; rows of
    labels without a document, or without a label, are not learned from; without labels
    nothing is rejected. Empty input: no rows. Other columns are not read."""
    docs = docs.select(*COLUMNS)
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    return toxicity.drop_toxic(docs, model)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each near-duplicate group.

    Rows without an id stay; texts without a word are one group; of rows that repeat id and
    text one stays. Ties do not occur: groups are named by their smallest id. Empty input:
    no rows."""
    return simhash.keep_representatives(docs.select(*COLUMNS))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a passage of the benchmark.

    Null and empty texts have none and stay; ids play no part, so repeated rows share a fate;
    a null benchmark text or an empty benchmark removes nothing."""
    return decontaminate.drop_contaminated(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, stored in the order that mixes sources to their target weights.

    A null source is a source of its own; null ids come first in theirs; repeated rows share
    a place. Empty input: no rows."""
    return mixing.mixed_order(docs.select(*COLUMNS))


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot: shards of equal bytes along the stored order.

    A null text has size 1 and checksum 0; rows of equal places do not occur in files. For
    rows that were not read from files the order is that of the ids. Empty input: no rows."""
    got = sharding.shard_documents(docs, 16, order=sharding.stored_order(docs))
    return got.select("doc_id", "size", "text_crc32", "shard", F.col("slot").cast("long").alias("slot"))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", one_of_each_group),
    ("decontamination", drop_contaminated),
    ("mixing", mix),
    ("sharding", shard),
]

#: A fitted lexicon cannot be said in SQL; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what is between two stages is written and read again.

    Each stage's output is deleted once the next one's is written, but for the last, which
    the returned DataFrame reads."""
    docs, held = table(spark, sf_dir, "documents"), None
    base = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for number, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if number < len(STAGES) - 1:
            path = f"{base}/{number}-{name}"
            docs.write.parquet(path)
            docs = spark.read.parquet(path)
            if held:
                delete(spark, held)
            held = path
    return docs
