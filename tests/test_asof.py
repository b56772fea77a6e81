import duckdb

from codedreg.oracles import build
from codedreg.queries import QUERIES


def test_every_event_has_its_version(spark, sf_dir):
    duckdb.sql(f"create or replace view events as select * from '{sf_dir}/events.parquet'")
    found = sorted(map(str, ((r["event_id"], r["version"]) for r in QUERIES["asof_model_version"](spark, sf_dir).collect())))
    assert found == sorted(map(str, duckdb.sql(build()["asof_model_version"]).fetchall()))
    assert len(found) == duckdb.sql("select count(*) from events").fetchall()[0][0]
