import pytest

from codedreg.queries import QUERIES
from codedreg.sources import tables


@pytest.fixture(scope="module")
def folders(spark, sf_dir, tmp_path_factory):
    """The tables of the streams as folders of files that are in no order."""
    path = tmp_path_factory.mktemp("folders")
    for name in ("embeddings", "events"):
        tables.read(spark, sf_dir, name).repartition(3).write.parquet(f"{path}/{name}.parquet")
    return str(path)


@pytest.mark.parametrize("name", ["stream_incremental_coding", "stream_epoch_aggregate", "stream_dedup"])
def test_streams_read_folders_of_files(spark, sf_dir, folders, name):
    found, meant = (sorted(map(str, QUERIES[name](spark, d).collect())) for d in (folders, sf_dir))
    assert found == meant and found


def test_composite_of_an_empty_stream(spark, sf_dir, tmp_path):
    tables.read(spark, sf_dir, "embeddings").limit(0).write.parquet(f"{tmp_path}/embeddings.parquet")
    assert QUERIES["stream_incremental_coding"](spark, str(tmp_path)).count() == 0
