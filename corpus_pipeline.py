"""The corpus pipeline: toxicity, line dedup, near dedup, mixing of sources, encoding.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes it as Parquet to the shared folder and
gives it to the next stage. All stages but the last return the columns of ``documents``.

1. ``toxicity``: documents that the model of the table ``labels`` scores 0.5 or more go.
2. ``line_dedup``: repeated runs of lines go but for their first occurrence; a document of which nothing is left goes.
3. ``near_dedup``: of each class of near duplicates the document with the smallest id stays.
4. ``mixing``: the sources of what is left are mixed to weights 1, 2, 3 in turn, at most three epochs each; a document
   comes as often as the mix takes it whole (the one that the mix takes in part comes if at least half of it is taken).
5. ``encode``: token ids of each text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rastertopo.llm.common import table, written
from rastertopo.llm.line_dedup import drop_passages
from rastertopo.llm.mixing import mix
from rastertopo.llm.near_dedup import keep_one
from rastertopo.llm.pieces import encode
from rastertopo.llm.toxicity import score, train

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = train(docs, table(spark, sf_dir, "labels"))
    return score(docs.select(*COLUMNS), model, "_toxic").filter("_toxic < 0.5").drop("_toxic")


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    kept = drop_passages(docs.select(*COLUMNS)).filter("removed IS NULL OR length(trim(text)) > 0").drop("removed")
    return kept.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_one(docs.select(*COLUMNS))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    mixed = mix(docs.select("doc_id", "source", "text"))
    times = F.when(F.col("size") > 0, F.expr("(2 * taken + size) div (2 * size)")).otherwise(F.lit(1)).cast("int")
    times = mixed.select(F.col("doc_id").alias("_doc"), times.alias("_times")).filter("_times > 0").groupBy("_doc").agg(F.max("_times").alias("_times"))
    repeated = docs.select(*COLUMNS).join(times, F.col("doc_id").cast("long").eqNullSafe(F.col("_doc")))
    return repeated.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_times")))).select(*COLUMNS)


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return encode(docs.select("doc_id", "text", "lang", "source"), keep_text=False).withColumn("n_tokens", F.size("ids").cast("long"))


STAGES = [("toxicity", toxicity), ("line_dedup", line_dedup), ("near_dedup", near_dedup), ("mixing", mixing), ("encoding", encoding)]

#: The stages are learnt models, keyed hashes of the text and a transducer: SQL can't express them.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
