"""Exact duplicate removal by a 128-bit content hash with byte comparison.

Texts are equal when they agree after every run of ASCII white space became one
space.  Rows are grouped by a 128-bit hash first, without their texts; only texts whose hash
occurs more than once are read again and grouped by (hash, normalised text), where
Spark's hash aggregate compares the key's bytes before it merges two rows, so a hash
collision can never join two different texts.  Both aggregates combine map-side, so a group that
holds a third of all rows reaches the shuffle as one row per input partition.

Defined results: null text counts as empty; null ids lose to any other id; rows that
repeat an id with the same text share one decision; an empty table gives an empty
table; other columns of the input are ignored, so their names cannot clash.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotagrad.llm.common import broadcast_if_small, checkpointed, text_or_empty

#: A run of white space that is not already a single space.
RUN = r" [ \t-\r]+|[\t-\r][ \t-\r]*"


def normalised(text):
    return F.regexp_replace(text_or_empty(text), RUN, " ")


def exact_groups(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, keep_id, group_size, kept, text_sha256.

    Two scans of the texts.  The repeated hashes are broadcast if they are few enough, so that texts of
    single documents are not shuffled; beyond that the join shuffles.  Ids travel back over a
    join on hashes, which AQE may split when one text is very common.
    """
    rows = df.select(F.col(id_col).alias("doc_id"), normalised(F.col(text_col)).alias("norm"))
    hashed = rows.withColumn("h", F.unhex(F.md5("norm")))
    light = checkpointed(hashed.select("doc_id", "h", F.unhex(F.sha2("norm", 256)).alias("sha")))
    often = checkpointed(light.groupBy("h").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("h"))
    classes = (
        hashed.join(broadcast_if_small(often), "h", "left_semi")
        .groupBy("h", "norm")
        .agg(F.min("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
        .filter("group_size > 1")
        .select("h", F.unhex(F.sha2("norm", 256)).alias("sha"), "keep_id", "group_size")
    )
    out = light.join(classes, ["h", "sha"], "left")
    alone = F.col("group_size").isNull()
    keep = F.when(alone, F.col("doc_id")).otherwise(F.col("keep_id"))
    return out.select(
        "doc_id",
        keep.alias("keep_id"),
        F.when(alone, F.lit(1)).otherwise(F.col("group_size")).cast("long").alias("group_size"),
        F.col("doc_id").eqNullSafe(keep).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"),
    )
