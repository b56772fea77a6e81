import duckdb
import numpy as np

from codedreg.oracles import C, SIGMA
from codedreg.queries import QUERIES
from codedreg.sources import tables


def test_privacy_budget_sees_every_component(spark, sf_dir):
    found = {r["client"]: r for r in QUERIES["privacy_budget_whole"](spark, sf_dir).collect()}
    rows = duckdb.sql(f"select vec_id, label, embedding from '{sf_dir}/embeddings.parquet' order by label, vec_id").fetchall()
    x = np.array([e for _, _, e in rows], float)
    x /= np.abs(x).max()
    client = np.arange(len(x)) * tables.CLIENTS // len(x)
    for i, r in found.items():
        own = x[client == i] ** 2
        h2 = (own.sum(0) - own.max(0)).min()
        assert abs(r["h2"] - h2) < 1e-5 and abs(r["eps_bits"] - 0.5 * np.log2(1 + C / (h2 + SIGMA**2))) < 1e-5
    assert len(QUERIES["full_gradient_whole"](spark, sf_dir).collect()) == x.shape[1] == 64
    assert len(QUERIES["train_corrected_5_whole"](spark, sf_dir).collect()) == 64
    assert len(QUERIES["full_gradient"](spark, sf_dir).collect()) == 8
