"""Tables as design matrices: (row_id BIGINT, features ARRAY<DOUBLE>, label DOUBLE), row_id dense from 0."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rotagrad.functions import prf


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, kind: str, path: str, schema: str | None = None) -> DataFrame:
    """CSV, JSON, ORC or Parquet with a declared schema (Parquet and ORC carry their own)."""
    reader = spark.read.format(kind)
    if schema:
        reader = reader.schema(schema)
    return reader.load(path, **({"header": True} if kind == "csv" else {}))


def write_blocks(blocks: DataFrame, path: str, buckets: int = 64) -> None:
    """Rotated rows by bucket of blocks, so that a step reads only the blocks that answered."""
    bucketed = blocks.withColumn("block_bucket", F.col("block_id") % buckets)
    bucketed.repartition("block_bucket").sortWithinPartitions("block_id").write.partitionBy("block_bucket").mode("overwrite").parquet(path)


def append_history(rows: DataFrame, path: str) -> None:
    """A run's history, added to those stored under ``path``, a folder per run; a run that is written again is replaced."""
    rows.write.partitionBy("run").option("partitionOverwriteMode", "dynamic").mode("overwrite").parquet(path)


def write_sketch(rotated: DataFrame, own: list[int], scale: float, path: str) -> None:
    """The compressed store: the drawn blocks' rotated rows (block_id, v), scaled, in place of the matrix."""
    rotated.filter(F.col("block_id").isin(own)).select("block_id", F.transform("v", lambda x: x * scale).alias("v")).write.mode("overwrite").parquet(path)


def checkpointed(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in the folder the session names."""
    spark = df.sparkSession
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_folder(spark))
    return df.checkpoint(eager=True)


def shared_folder(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; one of the machine's own only where Spark runs on one machine alone."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named is None and not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return (named or "/tmp/checkpoints").rstrip("/")


def dense_row_ids(df: DataFrame, keys: list[str], name: str = "row_id") -> DataFrame:
    """Dense ids in the order of ``keys`` without a global window.

    Rows are range-partitioned, sorted and checkpointed, since range bounds are sampled anew
    whenever a plan runs again.  A row's place in its partition is known without a shuffle,
    and the counts of the partitions (one row each) give offsets.  ``keys`` must be unique.
    """
    placed = checkpointed(df.repartitionByRange(*keys).sortWithinPartitions(*keys))
    at = F.monotonically_increasing_id()  # partition number in the upper bits, place in the lower 33
    local = placed.withColumn("__at", at)
    part = F.shiftright("__at", 33)
    counts = sorted((r["p"], r["n"]) for r in local.groupBy(part.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect())
    offsets, total = [], 0
    for p, n in counts:
        offsets.append((p, total))
        total += n
    known = df.sparkSession.createDataFrame(offsets, "__part bigint, __off bigint")
    joined = local.withColumn("__part", part).join(F.broadcast(known), "__part")
    return joined.withColumn(name, F.col("__off") + F.col("__at").bitwiseAND(F.lit((1 << 33) - 1))).drop("__part", "__at", "__off")


def assemble(df: DataFrame, row_id: str, features: list[Column], label: Column) -> DataFrame:
    return df.select(F.expr(row_id).cast("bigint").alias("row_id"), F.array(*[f.cast("double") for f in features]).alias("features"), label.cast("double").alias("label"))


def planted(mat: DataFrame, d: int, key: str, sigma: float = 1.0) -> DataFrame:
    """label = features . x0 + sigma z, with x0 and z from hashes."""
    x0 = [prf.uniform(f"{key}:x0", j) * 2 - 1 for j in range(d)]
    signal = sum((F.col("features")[j] * x for j, x in enumerate(x0)), F.lit(0.0))
    z = F.expr(prf.normal(prf.SPARK.uniform(f"{key}:z", "row_id", "1"), prf.SPARK.uniform(f"{key}:z", "row_id", "2")))
    return mat.withColumn("label", signal + sigma * z)


def heavy_tailed(ids: DataFrame, d: int, df: int, key: str) -> DataFrame:
    """t-distributed entries with 1, 2 or 4 degrees of freedom, from hashes of (row, column)."""
    entries = [F.expr(prf.t_quantile(prf.SPARK.uniform(key, "row_id", str(j)), df)) for j in range(d)]
    return planted(assemble(ids, "row_id", entries, F.lit(0.0)), d, key)


def part_heavy(spark: SparkSession, sf_dir: str, df: int = 2, d: int = 40, salt: int = 1) -> DataFrame:
    # A small file is one task, and the hashes of its rows' entries are the work.
    ids = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("row_id")).repartition(spark.sparkContext.defaultParallelism)
    return heavy_tailed(ids, d, df, f"t{df}:{salt}")


PRIORITY = "cast(substr(o_orderpriority, 1, 1) as bigint)"


def orders(spark: SparkSession, sf_dir: str, key: str = "orders") -> DataFrame:
    e = F.expr
    features = [F.lit(1.0), e("year(o_orderdate) - 1995"), e("month(o_orderdate)"), e(PRIORITY), e("int(o_orderstatus = 'F')"), e("int(o_orderstatus = 'O')"), e("o_custkey % 7"), e("o_totalprice / 1e5")]
    return planted(assemble(read(spark, sf_dir, "orders"), "o_orderkey", features, F.lit(0.0)), 8, key)


def orders_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(row_id, v ARRAY<BIGINT>): four integer features and an integer label."""
    v = F.expr(f"array(1L, cast(month(o_orderdate) as bigint), {PRIORITY}, cast(o_custkey % 7 as bigint), cast(round(o_totalprice) as bigint))")
    return read(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("bigint").alias("row_id"), v.alias("v"))


def customers_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(row_id, v ARRAY<BIGINT>): four integer features of every customer."""
    v = F.expr("array(1L, cast(c_nationkey as bigint), cast(floor(c_acctbal) as bigint), cast(c_nationkey % 3 as bigint))")
    return read(spark, sf_dir, "customer").select(F.col("c_custkey").cast("bigint").alias("row_id"), v.alias("v"))


def vectors(spark: SparkSession, sf_dir: str, d: int = 40) -> DataFrame:
    """The embeddings' first d coordinates with a planted response: flat scores, a control."""
    rows = read(spark, sf_dir, "embeddings")
    column = next(f.name for f in rows.schema.fields if f.dataType.simpleString().startswith("array"))
    return planted(assemble(rows, "vec_id", [F.col(column)[j] for j in range(d)], F.lit(0.0)), d, "vectors", 0.1)


STAR_KEYS = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"]


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with its dimensions, all features and the ids' keys; AQE decides about broadcasts."""
    t = {n: read(spark, sf_dir, n) for n in ("lineitem", "orders", "part", "supplier", "customer")}
    joined = t["lineitem"].join(t["orders"], F.expr("l_orderkey = o_orderkey")).join(t["part"], F.expr("l_partkey = p_partkey")).join(t["supplier"], F.expr("l_suppkey = s_suppkey")).join(t["customer"], F.expr("o_custkey = c_custkey"))
    e = F.expr
    features = [F.lit(1.0), e("l_quantity"), e("l_discount * 100"), e("l_tax * 100"), e("l_linenumber"), e("int(l_returnflag = 'A')"), e("int(l_returnflag = 'N')"), e("int(l_linestatus = 'O')"), e("year(l_shipdate) - 1995"), e("month(l_shipdate)"), e("p_size"), e("p_retailprice / 1000"), e("o_totalprice / 1e5"), e("c_acctbal / 1000"), e("s_acctbal / 1000"), e(PRIORITY)]
    return joined.select(*STAR_KEYS, F.array(*[f.cast("double") for f in features]).alias("features"))


def star_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = dense_row_ids(star(spark, sf_dir), STAR_KEYS)
    return planted(rows.select(F.col("row_id").cast("bigint").alias("row_id"), "features", F.lit(0.0).alias("label")), 16, "star")
