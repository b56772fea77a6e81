"""Feature maps: max-abs scaling, one-hot labels, random Fourier features, text statistics."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.functions.hashrand import gauss, uniform

FREQUENCY_SEED, PHASE_SEED = 31, 32


def max_abs(df: DataFrame, column: str = "x") -> float:
    """One pass; one number to the driver."""
    largest = F.array_max(F.transform(column, F.abs))
    return df.agg(F.max(largest)).first()[0] or 0.0


def scale_unit(df: DataFrame, column: str = "x") -> DataFrame:
    """Divide by the largest absolute entry, so that none exceeds 1; all-zero data stays."""
    top = max_abs(df, column) or 1.0
    return df.withColumn(column, F.transform(column, lambda v: v / F.lit(top)))


def scale_columns(df: DataFrame, column: str = "x") -> DataFrame:
    """As scale_unit, column by column."""
    tops = df.select(F.posexplode(F.transform(column, F.abs)).alias("j", "v")).groupBy("j").agg(F.max("v").alias("v")).orderBy("j").collect()
    scale = F.array(*[F.lit(r["v"] or 1.0) for r in tops])
    return df.withColumn(column, F.zip_with(column, scale, lambda v, s: v / s))


def one_hot(label: str, classes: int):
    return F.transform(F.sequence(F.lit(0), F.lit(classes - 1)), lambda k: F.when(k == F.col(label), 1.0).otherwise(0.0))


def fourier_parameters(d: int, width: int, gamma: float, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Frequencies (d x width) and phases for the Gaussian kernel exp(-gamma |x - y|^2)."""
    frequencies = np.sqrt(2 * gamma) * gauss(FREQUENCY_SEED + seed, np.arange(d)[:, None], np.arange(width)[None, :])
    return frequencies, 2 * np.pi * uniform(PHASE_SEED + seed, np.arange(width), 0)


def fourier_features(df: DataFrame, width: int = 2000, gamma: float = 0.5, seed: int = 0, column: str = "x") -> DataFrame:
    """Replace x by its random Fourier features; the frequencies are made anew in each task, not sent."""
    names, schema = df.columns, df.schema

    def run(batches):
        made = None
        for batch in batches:
            rows = batch.column(column)
            if not len(rows):
                continue
            x = np.asarray(rows.flatten()).reshape(len(rows), -1)
            if made is None:
                made = fourier_parameters(x.shape[1], width, gamma, seed)
            z = np.sqrt(2 / width) * np.cos(x @ made[0] + made[1])
            lists = pa.ListArray.from_arrays(np.arange(len(z) + 1, dtype=np.int32) * width, z.ravel())
            yield batch.set_column(names.index(column), column, lists)

    return df.mapInArrow(run, schema)


def text_statistics(docs: DataFrame, languages: list[str]) -> DataFrame:
    """Add x: shares of letters, digits and upper case, length, word length, repeated lines, language, after a 1."""
    text = F.coalesce("text", F.lit(""))
    n = F.greatest(F.length(text), F.lit(1))
    share = lambda pattern: F.length(F.regexp_replace(text, f"[^{pattern}]", "")) / n
    lines = F.split(text, "\n")
    words = F.size(F.filter(F.split(text, "[ \n]+"), lambda w: w != ""))
    repeated = 1.0 - F.size(F.array_distinct(lines)) / F.size(lines)
    parts = [F.lit(1.0), share("a-zA-Z"), share("0-9"), share("A-Z"), F.least(F.length(text), F.lit(20000)) / F.lit(20000.0), F.length(text) / F.greatest(words, F.lit(1)) / 20.0, repeated]
    parts += [F.when(F.col("lang") == x, 1.0).otherwise(0.0) for x in languages]
    return docs.withColumn("x", F.array(*[p.cast("double") for p in parts]))


def page_statistics(pages: DataFrame) -> DataFrame:
    """page_id, length, tags and links of raw pages."""
    html = F.coalesce("html", F.lit(""))
    return pages.select("page_id", F.length(html).cast("long").alias("length"), F.regexp_count(html, F.lit("<[a-zA-Z]")).cast("long").alias("tags"), F.regexp_count(html, F.lit("<a ")).cast("long").alias("links"))
