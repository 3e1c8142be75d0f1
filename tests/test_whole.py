import numpy as np

from planepack import container, pipeline, queries, studies
from planepack.codecs import CODECS
from planepack.fixtures import DATASETS, F32, F64, FLOATS
from planepack.packing import pack
from planepack.words import as_planes

SF = "/root/testdata/sf0.01"


def test_exhaustive_f64_takes_every_block_and_partition(spark, monkeypatch):
    rng = np.random.default_rng(5)
    data = [np.round(rng.normal(100, 20, 64), 2).astype("<f8").tobytes() for _ in range(3)]
    b = spark.createDataFrame([("DB64-retail", 8, i, bytearray(x)) for i, x in enumerate(data)], "dataset string, width int, block_id long, data binary")
    monkeypatch.setattr(studies, "_blocks", lambda *a: b)
    got = {(r.packing, r.partition): r.cr for r in queries.QUERIES["exhaustive_f64"](spark, SF).collect()}
    assert len(got) == 2 * 4140
    for c in ([list(range(8))], [[0, 1], [2, 3, 4], [5, 6, 7]]):
        for p in ("byte", "value"):
            enc = sum(len(CODECS["zstd"].encode(s, 1, pipeline.PlanSpec().level)) for x in data for s in pack(as_planes(x, 8), c, p))
            assert got[(p, str(c))] == sum(map(len, data)) / enc


def test_container_serialised_looks_at_the_last_block(spark, monkeypatch):
    whole = pipeline.compress(queries._blocks(spark, SF, "TS32-value"))
    last = max(r.block_id for r in whole.select("block_id").collect())
    assert last >= 4 and all(r.same for r in container.survives(whole).collect())
    # a length that the payload does not have is lost on the way
    bad = whole.withColumn("enc_len", queries.F.when(whole.block_id == last, queries.F.transform("enc_len", lambda x: x + 1)).otherwise(whole.enc_len))
    monkeypatch.setattr(queries.pipeline, "compress", lambda b: bad)
    got = {r.block_id: r.same for r in queries.QUERIES["container_serialised"](spark, SF).collect()}
    assert [k for k, same in got.items() if not same] == [last]


def test_studies_cover_the_registry(spark, monkeypatch):
    asked = []

    class Asked(Exception):
        pass

    def load(spark, d, names):
        asked.append(names if isinstance(names, list) else [names])
        raise Asked

    for module in (queries, studies, queries.blocks, __import__("planepack.registry").registry):
        monkeypatch.setattr(module, "load", load, raising=False)
    for name, want in (
        ("foundational_table", list(DATASETS)), ("block_sweep", FLOATS), ("feature_score_grid", F32 + F64), ("feature_score_gmean", F32 + F64), ("throughput_table", FLOATS), ("throughput_wall", FLOATS), ("plane_entropy", FLOATS),
        ("word_entropy", list(DATASETS)), ("cr_table", list(DATASETS)), ("order_table", FLOATS), ("decomposition_table", FLOATS), ("rival_float_codecs", FLOATS), ("entropy_before_after", FLOATS), ("objective_study", F32), ("partition_space", F32), ("parquet_baseline", F32 + F64), ("whole_file_table", list(DATASETS)),
    ):
        try:
            queries.QUERIES[name](spark, SF)
        except Asked:
            pass
        assert set(asked.pop()) == set(want), name
    assert (min(studies.SWEEP), max(studies.SWEEP), len(studies.SWEEP)) == (16 << 10, 32 << 20, 8)
