"""Disjoint clients, subsets within them, and a global rank that no single task computes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.functions.hashrand import with_uniform
from codedreg.storage import cut


def global_rank(df: DataFrame, cols: list[str], name: str = "rank") -> DataFrame:
    """Place of each row (from 0) in the total order of cols.

    One range shuffle; the sorted layout is materialised, one count for each partition goes to the driver, and a
    row's rank is its place in its partition plus the rows of earlier ones.
    """
    spark = df.sparkSession
    place = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
    width = int(spark.conf.get("spark.sql.shuffle.partitions"))
    laid = cut(df.repartitionByRange(width, *cols).sortWithinPartitions(*cols).withColumn("part__", F.spark_partition_id()).withColumn("place__", place))
    counts = sorted((r["part__"], r["n"]) for r in laid.groupBy("part__").agg(F.count("*").alias("n")).collect())
    before, total = [], 0
    for part, n in counts:
        before.append((part, total))
        total += n
    offsets = spark.createDataFrame(before or [(0, 0)], "part__ int, before__ long")
    ranked = laid.join(F.broadcast(offsets), "part__")
    return ranked.withColumn(name, F.col("before__") + F.col("place__")).drop("part__", "place__", "before__")


def partition_clients(df: DataFrame, n: int, how: str = "label_shards", label: str = "label", ident: str = "row_id", key: str | None = None, seed: int = 11) -> DataFrame:
    """Add client: equal shards in label order, a hash of the id, or a natural key."""
    if how == "label_shards":
        ranked = global_rank(df, [label, ident], "rank__")
        total = ranked.count()
        return ranked.withColumn("client", F.expr(f"cast(rank__ * {n} div {max(total, 1)} as int)")).drop("rank__")
    if how == "iid":
        drawn = with_uniform(df, "u__", ident, "0", seed)
        return drawn.withColumn("client", F.floor(F.col("u__") * n).cast("int")).drop("u__")
    if how == "key":
        return df.withColumn("client", F.col(key).cast("int"))
    raise ValueError(f"unknown partition {how!r}")


def split_subsets(df: DataFrame, parts: int | dict[int, int], seed: int = 12, ident: str = "row_id", exact: bool = True) -> DataFrame:
    """Add subset 0..parts-1 within each client: equal sizes by the place of hashes, or by the hash alone.

    parts may differ by client.  Places come from the global rank of (client, hash), whose tasks follow the rows and not the
    clients, less the rows of earlier clients (one number a client).
    """
    drawn = with_uniform(df, "u__", ident, "1", seed)
    if isinstance(parts, dict):
        pairs = [x for i, n in sorted(parts.items()) for x in (F.lit(i), F.lit(int(n)))]
        count = F.coalesce(F.create_map(*pairs)[F.col("client")], F.lit(1))
    else:
        count = F.lit(parts)
    if not exact:
        return drawn.withColumn("subset", F.floor(F.col("u__") * count).cast("int")).drop("u__")
    ranked = global_rank(drawn, ["client", "u__", ident], "rank__")
    first = ranked.groupBy("client").agg(F.min("rank__").alias("first__"))
    placed = ranked.join(F.broadcast(first), "client")
    return placed.withColumn("subset", ((F.col("rank__") - F.col("first__")) % count).cast("int")).select(*df.columns, "subset")


def disjoint_check(df: DataFrame, ident: str = "row_id") -> DataFrame:
    """clients, rows, ids and ids that lie in several clients."""
    per_id = df.groupBy(ident).agg(F.countDistinct("client").alias("in"), F.count("*").alias("n"))
    spread = per_id.agg(F.sum("n").alias("rows"), F.count("*").alias("ids"), F.sum(F.when(F.col("in") > 1, 1).otherwise(0)).alias("shared"))
    return spread.crossJoin(df.agg(F.countDistinct("client").alias("clients")))
