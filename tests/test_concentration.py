import duckdb
import pytest

from codedreg import oracles
from codedreg.queries import QUERIES

NAMES = ["concentration_g", "concentration_n", "concentration_s"]


@pytest.mark.parametrize("name", NAMES)
def test_same_rows_as_sql(spark, sf_dir, name):
    engine = duckdb.connect()
    engine.execute(f"create view embeddings as select * from '{sf_dir}/embeddings.parquet'")
    frames = QUERIES[name](spark, sf_dir).toPandas(), engine.execute(oracles.build()[name]).df()
    found, meant = (sorted(map(tuple, f[sorted(f.columns)].astype(str).itertuples(index=False))) for f in frames)
    assert list(frames[0].columns) == list(frames[1].columns) and found == meant
    assert all(0.5 < r["measured"] / r["expected"] < 2 for _, r in frames[0].iterrows())


@pytest.mark.parametrize("name", NAMES)
def test_depends_on_the_given_table(spark, tmp_path, sf_dir, name):
    """Without rows there is nothing to measure; the queries once made their rows up."""
    spark.read.parquet(f"{sf_dir}/embeddings.parquet").limit(0).write.parquet(f"{tmp_path}/embeddings.parquet")
    assert all(r["measured"] is None for r in QUERIES[name](spark, str(tmp_path)).collect())
