"""A training corpus from raw documents: five stages, each one operator of ``rotagrad.llm``.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes each
stage's result as Parquet in the shared folder, rereads it for the next and then deletes what
that one has read.  All but the last return the columns of documents.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rotagrad.llm import bpe, exact_dedup, langid, mixing, simhash
from rotagrad.llm.common import broadcast_if_small, checkpointed, crc_bucket, shared_folder, table, text_or_empty
from rotagrad.llm.queries import tokenizer_path

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language go on; those without letters (``und``) go."""
    model = langid.train(docs.filter(crc_bucket(F.col("doc_id"), 5) != 0), tokenizer_path("piece_bpe_32k.model"))
    return langid.identify(docs.select(*COLUMNS), model, lang_out="__lang", score_out="__score").filter("__lang != 'und'").select(*COLUMNS)


def content(text: Column) -> Column:
    return F.unhex(F.md5(text_or_empty(text)))


def only(docs: DataFrame, decisions: DataFrame, text_hash: Column) -> DataFrame:
    """The documents that ``decisions`` (doc_id, h, kept: a row per document) keeps, once each if (id, hash) repeats.

    A null id is an id like any other.  Only what goes or repeats is joined, as hashes, so that texts stay where they are.
    """
    found = decisions.groupBy(F.col("doc_id").alias("__id"), F.col("h").alias("__of")).agg(F.max("kept").alias("__kept"), F.count(F.lit(1)).alias("n"))
    found = checkpointed(found.filter("n > 1 or not __kept").drop("n"))
    held = docs.select(*COLUMNS).withColumn("__h", text_hash)
    both = held.join(broadcast_if_small(found), F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("__h") == F.col("__of")), "left")
    out = both.filter("__of is null").select(*COLUMNS)
    if found.filter("__kept").isEmpty():
        return out
    once = both.filter("__kept").groupBy("doc_id", "__h").agg(F.min(F.struct(*COLUMNS)).alias("row"))
    return out.union(once.select("row.*"))


def exact_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, the document with the smallest id stays (null after all others); a row that repeats goes on once."""
    groups = exact_dedup.exact_groups(docs)
    return only(docs, groups.select("doc_id", F.unhex("text_sha256").alias("h"), "kept"), F.unhex(F.sha2(exact_dedup.normalised(docs["text"]), 256)))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by a similarity of 0.8 or more over five-word shingles (as SimHash of 256 bits
    estimates it, and exactly where that leaves two apart), the one with the smallest id stays (null after all others; of one id on several texts, the smallest hash)."""
    key = F.struct(F.col("doc_id").isNull().alias("last"), F.col("doc_id"), content(F.col("text")).alias("h"))
    found = simhash.similar(docs.select(key.alias("key"), "text"), id_col="key", shingle=5, similarity=0.8)
    return only(docs, found.select("doc_id.doc_id", "doc_id.h", (F.col("doc_id") == F.col("component_id")).alias("kept")), content(docs["text"]))


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as many times as whole passes of its words were taken, at least once if
    any were, never more than three times.  A document is its id and text; the copies of rows that repeat add up."""
    keyed = docs.select(*COLUMNS, F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.lit(":"), F.hex(content(docs["text"]))).alias("__key"))
    times = F.least(F.lit(3), F.greatest(F.lit(1), F.round(F.col("taken") / F.col("size")))).cast("int")
    taken = mixing.mix(keyed, id_col="__key").groupBy(F.col("doc_id").alias("__key"))
    taken = checkpointed(taken.agg(F.sum(F.when(F.col("taken") > 0, times).otherwise(0)).cast("int").alias("__times"), F.count(F.lit(1)).alias("n")))
    if not taken.filter("n > 1").isEmpty():
        keyed = keyed.groupBy("__key").agg(F.min(F.struct(*COLUMNS)).alias("row")).select("row.*", "__key")
    return keyed.join(taken.filter("__times > 0"), "__key").withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__times")))).select(*COLUMNS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each row; ids decode to the text's bytes."""
    out = bpe.encode(docs, tokenizer_path("byte_bpe_50k.tiktoken"), decode_back=True)
    return out.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"), "ids")


STAGES = [
    ("language_id", language_id),
    ("exact_duplicates", exact_duplicates),
    ("near_duplicates", near_duplicates),
    ("source_mix", source_mix),
    ("encode", encode),
]

#: Fingerprints, model scores and token ids are beyond SQL; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    folder = f"{shared_folder(spark)}/corpus-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        out = f"{folder}/{k}-{name}"
        stage(spark, docs, sf_dir).write.parquet(out)
        if k:
            drop(spark, f"{folder}/{k - 1}-{STAGES[k - 1][0]}")
        docs = spark.read.parquet(out)
    return docs


def drop(spark: SparkSession, folder: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
