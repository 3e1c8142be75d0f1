"""Every stage of the pipeline against a plain Python version, and the cases each has to bear."""

import re

import numpy as np
import pytest
from pyspark.sql import types as T

import corpus_pipeline as p
from planepack import storage
from planepack.llm import pieces, secrets, toxicity

#: Column names that the operators use themselves.
CLASHES = ["__gone", "__fp", "__id", "__text", "__root", "d0", "d1", "__judged", "__kept", "node", "id", "g", "__jid"]
SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), *(T.StructField(c, T.StringType()) for c in CLASHES)])
WORDS = [f"word{i}" for i in range(300)]


def made(spark, rows):
    return spark.createDataFrame([(i, t, *(f"{c}{n}" for c in CLASHES)) for n, (i, t) in enumerate(rows)], SCHEMA)


def texts(seed, n, size=40):
    rng = np.random.default_rng(seed)
    return [" ".join(rng.choice(WORDS, size)) for _ in range(n)]


@pytest.fixture(scope="module")
def sf(spark, tmp_path_factory):
    """A labelled corpus: toxic texts have a word of their own; benchmark items of several lengths."""
    at = tmp_path_factory.mktemp("sf")
    rng = np.random.default_rng(3)
    bad = rng.random(240) < 0.3
    docs = [(i, t + (" vileness" if b else "")) for i, (t, b) in enumerate(zip(texts(1, 240), bad, strict=True))]
    items = [(0, " ".join(f"bench{i}" for i in range(25))), (1, "tiny item"), (2, None), (3, " ".join(f"test{i}" for i in range(14)))]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{at}/documents.parquet")
    spark.createDataFrame([(i, 1, int(b)) for i, b in enumerate(bad)], "doc_id long, quality int, toxic int").write.parquet(f"{at}/labels.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{at}/benchmark.parquet")
    return str(at)


ODD = [(None, "lonely words without a number"), (1007, None), (1007, None), (1008, ""), (1009, " \n\t "), (1010, "é漢字\U0001f600 x")]


def rows_of(df):
    return sorted((tuple(r) for r in df.collect()), key=str)


@pytest.mark.parametrize("stage", p.STAGES, ids=lambda s: s[0])
def test_empty_tables(spark, sf, stage):
    out = stage[1](spark, made(spark, ODD).limit(0), sf)
    assert out.collect() == []
    if stage is not p.STAGES[-1]:
        assert out.columns == SCHEMA.names


@pytest.mark.parametrize("stage", p.STAGES[:-1], ids=lambda s: s[0])
def test_clean_and_odd_rows_stay_with_all_their_columns(spark, sf, stage):
    docs = made(spark, ODD + [(2000 + i, t) for i, t in enumerate(texts(5, 20))])
    assert rows_of(stage[1](spark, docs, sf)) == rows_of(docs)


def test_toxicity_stage(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", *(SCHEMA_LIT(c) for c in CLASHES))
    got = {r.doc_id for r in p.drop_toxic(spark, docs, sf).collect()}
    chain = toxicity.fit_chain(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    want = set()
    for r in docs.collect():
        z = np.zeros(2)
        for w in set(re.findall(r"[^\W_]+", r.text.lower())):
            for f in [w] + [f"{w[:k]}*" for k in range(3, 7) if len(w) >= k]:
                z += chain.weights.get(f, (0.0, 0.0))
        first = 1 / (1 + np.exp(-(chain.bias[0] + z[0])))
        if 1 / (1 + np.exp(-(chain.bias[1] + chain.chained[1][0] * first + z[1]))) <= chain.threshold:
            want.add(r.doc_id)
    assert got == want
    toxic = {r.doc_id for r in spark.read.parquet(f"{sf}/labels.parquet").filter("toxic = 1").collect()}
    assert len(got & toxic) <= 0.02 * len(toxic) and len(got) >= 0.98 * (240 - len(toxic))


def SCHEMA_LIT(c):
    from pyspark.sql import functions as F

    return F.lit(c).alias(c)


def test_near_duplicate_stage(spark, sf):
    rng = np.random.default_rng(9)
    rows = []
    for t in texts(11, 12, 60):
        for _ in range(rng.integers(1, 5)):
            w = t.split()
            for _ in range(rng.integers(0, 4)):
                w[rng.integers(len(w))] = "changed"
            rows.append((int(rng.integers(1000)) if rng.random() < 0.8 else None, " ".join(w)))
    rows += [rows[0], rows[0], (5, None), (5, ""), (rows[1][0], "a text of its own under the same number as another")]
    sets = []
    for _, t in rows:
        w = (t or "").split()
        sets.append(frozenset(tuple(w[i : i + 5]) for i in range(len(w) - min(5, len(w)) + 1)) if w else frozenset())
    up = list(range(len(rows)))
    for i, x in enumerate(sets):
        for j, y in enumerate(sets[:i]):
            if x and y and 100 * len(x & y) >= 80 * len(x | y):
                up = [min(up[i], up[j]) if u in (up[i], up[j]) else u for u in up]
    kept = p.drop_near_copies(spark, made(spark, rows), sf).select("doc_id", "text").collect()
    by_group = {}
    for (i, t), g, s in zip(rows, up, sets, strict=True):
        if s:
            by_group.setdefault(g, []).append((i is None, i or 0, t))
    # one row of each group, of the least id in it; every row without words
    assert len(kept) == len(by_group) + sum(not s for s in sets)
    where = {}
    for (i, t), g, s in zip(rows, up, sets, strict=True):
        if s:
            where.setdefault((i, t), g)
    seen = [where[(r.doc_id, r.text)] for r in kept if (r.text or "").split()]
    assert sorted(seen) == sorted(by_group)
    for r in kept:
        if (r.text or "").split():
            assert (r.doc_id is None, r.doc_id or 0) == min(x[:2] for x in by_group[where[(r.doc_id, r.text)]])


def test_decontamination_stage(spark, sf):
    fill = texts(21, 1, 30)[0]
    long = " ".join(f"bench{i}" for i in range(25))
    rows = [(1, f"{fill} {long} {fill}"), (2, f"{fill} Tiny, ITEM {fill}"), (3, long), (4, f"{fill} bench3 bench4 bench5 {fill}"), (4, f"{fill} bench3 bench4 bench5 {fill}"), (5, f"{fill} {' '.join(f'bench{i}' for i in range(4, 15))} end")]
    got = [(r.doc_id, r.text.split()) for r in p.decontaminate(spark, made(spark, rows), sf).orderBy("doc_id").collect()]
    f = fill.split()
    assert got == [(1, f + f), (2, [*f, *f]), (4, [*f, "bench3", "bench4", "bench5", *f]), (4, [*f, "bench3", "bench4", "bench5", *f]), (5, [*f, "end"])]


def test_secrets_stage(spark, sf):
    rows = [(1, "see password = hunter22 here"), (2, "AKIA" + "Q7" * 9 + " x"), (3, "id " + "0f" * 13 + " end"), (4, "token: short"), (5, "run zQ8xK2vP9mL4tR7wB3nJ6yH1 out"), (1, "see password = hunter22 here")]
    got = sorted((r.doc_id, r.text) for r in p.redact_secrets(spark, made(spark, rows), sf).collect())
    assert got == [(1, "see <assign> here"), (1, "see <assign> here"), (2, "<access> x"), (3, "id <hex> end"), (4, "token: short"), (5, "run <random> out")]


def test_last_stage(spark, sf):
    docs = made(spark, ODD + [(1, "abc"), (1, "abc")])
    got = p.encode(spark, docs, sf).collect()
    raw = pieces.vocabulary()[2]
    assert len(got) == docs.count()
    back = sorted(((r.doc_id, None if r.ids is None else pieces.decode(r.ids, raw)) for r in got), key=str)
    assert back == sorted(((r.doc_id, r.text) for r in docs.collect()), key=str)
    assert len({tuple(r.ids) for r in got if r.doc_id == 1}) == 1


def test_run_is_its_stages_one_after_the_other(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for _, stage in p.STAGES[:-1]:
        docs = spark.createDataFrame(stage(spark, docs, sf).collect(), docs.schema)
    want = rows_of(p.STAGES[-1][1](spark, docs, sf))
    before = set(storage._made)
    got = p.run(spark, sf)
    left = [x for x in storage._made if x not in before]
    assert len(left) == 1 and "pp-secrets" in left[0]  # only what the result still reads
    assert rows_of(got) == want


@pytest.mark.parametrize("text", ["ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789abcdefghijklmnopqrstuvwxyz", "NXQWERTPLKJHGFDSAZXCVBNMQWERTYUIOP7x", "A" * 300_000 + "b", "a-" * 200_000, "token " * 100_000, "password='" * 50_000, "=" * 400_000, "0123456789abcdef" * 20_000, "Ab1" * 100_000])
def test_scans_end_on_long_runs(text):
    import time

    secrets.encoder()
    t = time.process_time()
    secrets.scan(f"see {text} here")
    assert time.process_time() - t < 6


def test_many_spans_in_one_text_take_linear_time():
    import time

    def took(n):
        t = time.process_time()
        base, spans = secrets.scan("password = abcdefgh1 zQ8xK2vP9mL4tR7wB3nJ6yH1 " * n)
        assert len(base) == n and len(spans) == 2 * n
        return time.process_time() - t

    took(500)
    assert took(16_000) < 5
