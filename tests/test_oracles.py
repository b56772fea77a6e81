import duckdb
import pytest

from codedreg import oracles
from codedreg.queries import QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SQL = oracles.build()
CHECKED = ["shard_by_label", "subset_sizes", "text_features", "hash_gauss_moments", "arrival_trace", "load_plan", "encode_clients_noisy", "composite_incremental", "batch_fixed", "aggregated_gradient", "privacy_budget", "variance_bound_rederived", "exact_gradient_variance", "train_corrected_5", "train_weighted_mini_5", "stream_epoch_aggregate", "stream_sessions", "asof_model_version", "batch_subset", "load_plan", "smallest_deadline", "train_central_5", "train_server_only_full_5", "train_weighted_full_5", "train_first_arrivals_5", "privacy_overall", "information_bound", "step_sizes", "predict_classes", "method_cube", "delay_percentiles", "epoch_windows", "subset_set_operations", "labelled_semijoin", "order_features", "stream_sliding", "stream_parameter_server", "stream_incremental_coding", "stream_dedup"]


def rows(frame):
    frame = frame[sorted(frame.columns)].astype(str)
    return sorted(map(tuple, frame.itertuples(index=False)))


@pytest.fixture(scope="module")
def engine(sf_dir):
    own = duckdb.connect()
    for t in TABLES:
        own.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    return own


@pytest.mark.parametrize("name", CHECKED)
def test_same_rows_as_sql(spark, sf_dir, engine, name):
    assert rows(QUERIES[name](spark, sf_dir).toPandas()) == rows(engine.execute(SQL[name]).df())


def test_every_oracle_has_a_query():
    assert set(SQL) <= set(QUERIES)
