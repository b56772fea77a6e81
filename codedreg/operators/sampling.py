"""Mini-batches: exact sizes without replacement, independent draws, or a cycle through fixed subsets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codedreg.functions.hashrand import with_uniform

BATCH_SEED, SERVER_SEED = 404, 505


def sample_batch(ex: DataFrame, epochs: int, how: str = "fixed", b: str = "b", seed: int = 0, parts: int = 1, first_epoch: int = 0) -> DataFrame:
    """Rows of ex with epoch, for each epoch they are drawn in.

    fixed: the b rows of lowest hash of each client and epoch (all, if b exceeds them); bernoulli: each row with
    probability b / l; subset: the rows whose subset is epoch mod parts (no hashing, and partitions by subset prune).
    fixed and bernoulli need the columns b and l.  All epochs share one shuffle at most, and for fixed batches only rows
    under a threshold of the hash, little more than b of l, go through it; that fewer than b of a client should lie under
    it has a probability below 1e-10, and then the job fails rather than return a smaller batch.
    """
    wide = ex.withColumn("epoch", F.explode(F.sequence(F.lit(first_epoch), F.lit(first_epoch + epochs - 1))))
    if how == "subset":
        return wide.where(F.col("subset") == F.col("epoch") % parts)
    drawn = with_uniform(wide, "u__", "epoch", "row_id", BATCH_SEED + seed)
    if how == "bernoulli":
        return drawn.where(F.col("u__") * F.col("l") < F.col(b)).drop("u__")
    if how != "fixed":
        raise ValueError(f"unknown sampler {how!r}")
    low = drawn.where(F.col("u__") * F.col("l") <= F.col(b) + 8 * F.sqrt(F.col(b)) + 24)
    group = Window.partitionBy("epoch", "client")
    ranked = low.withColumn("i__", F.row_number().over(group.orderBy("u__", "row_id"))).withColumn("n__", F.count("*").over(group))
    enough = F.when(F.col("n__") >= F.least(F.col(b), F.col("l")), True).otherwise(F.raise_error(F.lit("fewer rows than the batch under the threshold")).cast("boolean"))
    return ranked.where((F.col("i__") <= F.col(b)) & enough).drop("u__", "i__", "n__")


def sample_composite(composite: DataFrame, epochs: int, b: int, seed: int = 0) -> DataFrame:
    """epoch with the b coded rows drawn in it."""
    wide = composite.withColumn("epoch", F.explode(F.sequence(F.lit(0), F.lit(epochs - 1))))
    drawn = with_uniform(wide, "u__", "epoch", "k", SERVER_SEED + seed)
    order = Window.partitionBy("epoch").orderBy("u__", "k")
    return drawn.withColumn("i__", F.row_number().over(order)).where(F.col("i__") <= b).drop("u__", "i__")
