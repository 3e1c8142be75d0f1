import pytest

from planepack.llm import decontam


@pytest.mark.parametrize("min_words", [10, 20])
def test_short_items_are_cut(spark, min_words):
    bench = spark.createDataFrame([(0, "alpha beta gamma"), (1, "omega"), (2, " ".join(f"b{i}" for i in range(25)))], "item_id long, text string")
    fill = "one two three four five six seven eight nine ten eleven twelve thirteen"
    docs = spark.createDataFrame([(0, f"{fill} Alpha, beta gamma {fill}"), (1, f"{fill} omega {fill}"), (2, f"{fill} alpha beta {fill}"), (3, fill + " " + " ".join(f"b{i}" for i in range(12)) + " " + fill)], "doc_id long, text string")
    got = {r.doc_id: r.text.split() for r in decontam.remove_spans(docs, bench, min_words=min_words).collect()}
    f = fill.split()
    assert got[0] == f + f and got[1] == f + f
    assert got[2] == [*f, "alpha", "beta", *f]
    assert len(got[3]) == 26 + (12 if min_words == 20 else 0)
