"""Examples (row_id, client, x, y) from the given tables, and sinks for results."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from codedreg.functions.hashrand import gauss, with_gauss
from codedreg.functions.vectors import dot, literal
from codedreg.operators.features import scale_columns, scale_unit, text_statistics
from codedreg.operators.partition import global_rank, partition_clients
from codedreg.storage import cut

TEACHER_SEED, NOISE_SEED = 61, 62
CLIENTS = 20

#: Streams need their schema ahead.
EVENTS = T.StructType([
    T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()),
    T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType()),
])


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_stream(spark: SparkSession, sf_dir: str, name: str, schema: T.StructType) -> DataFrame:
    """The table as a stream, be it one file or a folder of files.

    All files come in one trigger: those of a table are in no order of time, so a watermark that moved between them would drop
    rows.  The pattern matches one name; a plain path would have to be a folder.
    """
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/{name}.parque[t]")


def embedding_rows(spark: SparkSession, sf_dir: str, d: int | None = None) -> DataFrame:
    """row_id, label, x (doubles, the first d of them)."""
    x = F.col("embedding") if d is None else F.slice("embedding", 1, d)
    return read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), "label", F.transform(x, lambda v: v.cast("double")).alias("x"))


def teacher(d: int, o: int, seed: int = 0) -> np.ndarray:
    """Planted weights."""
    return gauss(TEACHER_SEED + seed, np.arange(d)[:, None], np.arange(o)[None, :])


def with_teacher(rows: DataFrame, w: np.ndarray, noise: float = 0.1, seed: int = 0) -> DataFrame:
    """Add y = xW plus noise of the row's own."""
    out = rows
    for q in range(w.shape[1]):
        out = with_gauss(out, f"z{q}__", str(q), "row_id", NOISE_SEED + seed)
    parts = [dot("x", literal(w[:, q])) + noise * F.col(f"z{q}__") for q in range(w.shape[1])]
    return out.withColumn("y", F.array(*parts)).drop(*[f"z{q}__" for q in range(w.shape[1])])


def small_examples(spark: SparkSession, sf_dir: str, d: int = 8) -> DataFrame:
    """The first d entries of the embeddings, scaled, in label shards, with one planted output."""
    rows = partition_clients(scale_unit(embedding_rows(spark, sf_dir, d)), CLIENTS)
    return cut(with_teacher(rows, teacher(d, 1)).select("row_id", "client", "x", "y"))


def teacher_examples(spark: SparkSession, sf_dir: str, o: int = 10) -> DataFrame:
    """All embedding entries, scaled, in label shards, with o planted outputs."""
    rows = partition_clients(scale_unit(embedding_rows(spark, sf_dir)), CLIENTS)
    return cut(with_teacher(rows, teacher(64, o)).select("row_id", "client", "label", "x", "y"))


def skewed_examples(spark: SparkSession, sf_dir: str, o: int = 10, iid: bool = False) -> DataFrame:
    """Class = largest planted output, y its one-hot, shards in class order: skew that acts on training."""
    rows = with_teacher(scale_unit(embedding_rows(spark, sf_dir)), teacher(64, o), 0.0)
    rows = rows.withColumn("label", F.array_position("y", F.array_max("y")).cast("int") - 1)
    rows = rows.withColumn("y", F.transform("y", lambda v: F.when(v == F.array_max("y"), 1.0).otherwise(0.0)))
    if iid:
        rows = rows.withColumn("spread", F.pmod(F.col("row_id") * 7919, F.lit(104729)))
        return cut(partition_clients(rows, CLIENTS, label="spread").select("row_id", "client", "label", "x", "y"))
    return cut(partition_clients(rows, CLIENTS).select("row_id", "client", "label", "x", "y"))


def lineitem_examples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """row_id by the total order of all columns, client = the supplier's nation, five scaled features, a planted y."""
    lines, suppliers = read(spark, sf_dir, "lineitem"), read(spark, sf_dir, "supplier")
    rows = lines.join(suppliers.select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").cast("int").alias("client")), "l_suppkey")
    phase = F.dayofyear(F.col("l_shipdate")) / F.lit(366.0)
    rows = rows.withColumn("x", F.array(F.lit(1.0), F.col("l_quantity") / 50.0, F.col("l_discount") / 0.1, F.col("l_tax") / 0.08, phase))
    order = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate"]
    ranked = global_rank(rows.select(*order, "client", "x"), order, "row_id")
    return with_teacher(ranked, teacher(5, 1)).select("row_id", "client", "x", "y")


def document_examples(spark: SparkSession, sf_dir: str, languages: tuple[str, ...] = ("de", "en", "es", "fr")) -> DataFrame:
    """Labelled documents: text statistics against quality and toxicity, client = number of the source."""
    docs = read(spark, sf_dir, "documents").join(read(spark, sf_dir, "labels"), "doc_id")
    rows = text_statistics(docs, list(languages))
    client = F.regexp_extract("source", "([0-9]+)", 1).cast("int")
    y = F.array(F.col("quality").cast("double"), F.col("toxic").cast("double"))
    return scale_columns(rows.select(F.col("doc_id").alias("row_id"), client.alias("client"), "x", y.alias("y")))


def write_examples(ex: DataFrame, path: str) -> None:
    """By client and subset, so that a batch is a set of folders."""
    ex.write.mode("overwrite").partitionBy("client", "subset").parquet(path)


def read_examples(spark: SparkSession, path: str, subset: int | None = None, clients: list[int] | None = None) -> DataFrame:
    """With partition pruning."""
    rows = spark.read.parquet(path)
    if subset is not None:
        rows = rows.where(F.col("subset") == subset)
    return rows if clients is None else rows.where(F.col("client").isin(clients))


def write_table(df: DataFrame, path: str, keys: list[str] | None = None) -> None:
    writer = df.write.mode("overwrite")
    (writer.partitionBy(*keys) if keys else writer).parquet(path)


def read_profiles(spark: SparkSession, path: str, form: str = "csv") -> DataFrame:
    schema = "client int, mac_rate double, up_bps double, down_bps double, p_erase double, l long, b long"
    return spark.read.schema(schema).csv(path, header=True) if form == "csv" else spark.read.schema(schema).json(path)
