"""The corpus pipeline: stages over ``documents``, each written as Parquet and read again by the next."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from axisgrove.llm import decontaminate, jaccard_join, kd_sharding, line_rules, mixing
from axisgrove.llm.common import cut, table

#: Columns that every stage but the last returns.
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Near duplicates: shingles of five words, similarity of 0.8 or more.
SHINGLE, SIMILAR = 5, 80
SHARDS = 16


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejected documents go; boilerplate lines go from those that stay."""
    found = line_rules.judged(docs, ["doc_id", "lang", "source", "n_chars"], with_text=True).filter("kept")
    return found.select("doc_id", F.col("clean_text").alias("text"), "lang", "source", F.length("clean_text").cast("bigint").alias("n_chars"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of similar documents stays."""
    return jaccard_join.one_of_each_group(docs, width=SHINGLE, percent=SIMILAR).select(*COLUMNS)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go."""
    found = decontaminate.contaminated_words(docs, table(spark, sf_dir, "benchmark"), ["doc_id", "lang", "source", "n_chars"], with_text=True)
    return found.filter(F.size("hits") == 0).select(*COLUMNS)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix takes it. Texts are counted once, and stay in the JVM."""
    sized = cut(docs.select(*COLUMNS).withColumn("size", mixing.word_count(F.col("text"))))
    taken = mixing.pareto_mix(sized).filter("copies > 0")
    return taken.withColumn("__copy", F.explode(F.sequence(F.lit(1).cast("bigint"), "copies"))).select(*COLUMNS)


def sharded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents with their size and shard."""
    _, tree = kd_sharding.kd_shards(docs, SHARDS)
    return kd_sharding.with_shard(docs, tree)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("without_benchmark", without_benchmark),
    ("mixed", mixed),
    ("sharded", sharded),
]

#: SQL has no practical form of the similarity join and the k-d tree over whole tables; tests/llm compares the first three stages with a brute-force version, and the last two by what they must keep.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, each written to the shared folder and read again."""
    context = spark.sparkContext
    shared = context.getCheckpointDir() or context.getConf().get("spark.checkpoint.dir") or tempfile.mkdtemp(prefix="axisgrove-pipeline-")
    docs, place = table(spark, sf_dir, "documents"), f"{shared}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{place}/{k}")
        docs = spark.read.parquet(f"{place}/{k}")
    return docs
