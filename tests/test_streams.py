import shutil

import pytest
from pyspark.sql import functions as F

from planepack import queries

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def several(spark, tmp_path_factory):
    """The events in seven part files, in order of time, taken one after the other."""
    at = tmp_path_factory.mktemp("sf")
    for f in ("lineitem", "customer", "orders", "part", "documents", "embeddings"):
        shutil.copy(f"{SF}/{f}.parquet", at)
    e = spark.read.parquet(f"{SF}/events.parquet")
    n = e.count()
    for i in range(7):
        e.filter(F.floor(F.col("event_id") * 7 / n) == i).coalesce(1).write.mode("append").parquet(f"{at}/events.parquet")
    return str(at)


@pytest.mark.parametrize("name", ["stream_tumbling", "stream_sessions", "stream_xor", "stream_blocks", "stream_dedup", "stream_stream_join"])
def test_many_files_give_what_one_gives(spark, several, name):
    run = lambda d: sorted(map(str, queries.QUERIES[name](spark, d).collect()))
    assert run(several) == run(SF)
