"""The corpus pipeline: documents pass STAGES in turn, each written as Parquet and read again before the next.

quality   documents that the quality classifier rejects go (score below its threshold)
dedup     of each group of near-duplicates (4-word Jaccard joins at 85 %) one row stays: that with the smallest doc_id, null ids last;
          of rows with one id that with the smallest digest over all columns; of rows equal in all columns one. Rows without words
          are linked with nothing, so all of them stay
repeats   byte strings of 200 bytes that occur again anywhere in the corpus are cut out; a character of which bytes went goes whole;
          documents of which no word is left go, and n_chars follows the text
mix       sources come to their target weights: documents are left out, or repeated up to 3 times
encode    token ids of the byte-level BPE: doc_id, source, ids and n_tokens
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from devicelens.llm.byte_bpe import encode_ids_of
from devicelens.llm.common import WORD, cut, scratch
from devicelens.llm.jaccard import grouped_rows
from devicelens.llm.mixing import mix
from devicelens.llm.quality import fit, quality_scores
from devicelens.llm.queries import tokenizer
from devicelens.llm.repeats import remove_repeats

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality_scores(docs.select(*COLUMNS), model, keep=COLUMNS).filter("predicted = 1").select(*COLUMNS)


def dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    digest = F.sha2(F.to_json(F.struct("doc_id", "lang", "source", "n_chars", F.sha2("text", 256).alias("text"))), 256)  # to_json leaves nulls out
    rows = docs.select(*COLUMNS, F.unhex(digest).alias("row_key"))
    grouped = grouped_rows(rows.select("doc_id", "text", "row_key"), carry=["row_key"]).groupBy("root", "row_key").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies"))
    first = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "row_key", "copies")).alias("first")
    linked = grouped.filter("root IS NOT NULL").groupBy("root").agg(first).select("first.row_key", "first.copies")
    kept = cut(linked.union(grouped.filter("root IS NULL").select("row_key", F.lit(1).cast("long"))))  # one row a key
    left = rows.join(kept, "row_key")
    once, again = left.filter("copies = 1"), left.filter("copies > 1").dropDuplicates(["row_key"])
    return once.union(again).select(*COLUMNS)


def repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    left = remove_repeats(docs.select(*COLUMNS), carry=["lang", "source"], wanted=["kept_text"]).withColumnRenamed("kept_text", "text")
    return left.filter(F.col("text").rlike(WORD)).withColumn("n_chars", F.char_length("text").cast("long")).select(*COLUMNS)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    times = mix(docs.select(*COLUMNS)).filter("taken > 0").withColumn("times", (F.col("taken") / F.col("size")).cast("int"))
    return times.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("times")))).select(*COLUMNS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return encode_ids_of(docs, tokenizer("byte_bpe_50k.json"), ["doc_id", "source"])


STAGES = [("quality", quality), ("dedup", dedup), ("repeats", repeats), ("mix", mixed), ("encode", encode)]

ORACLE_SQL = None  # nearest neighbours, suffix arrays and merges aren't SQL; tests hold the stages against brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder, done = scratch(spark, "pipeline"), None
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if done:  # what the stage read isn't needed any more
            path = spark._jvm.org.apache.hadoop.fs.Path(done)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
        done = f"{folder}/{name}"
    return docs
