from planepack.llm import jaccard

A, B = (" ".join(f"{c}{i}" for i in range(40)) for c in "ab")
A2 = A + " more"


def test_one_row_of_each_component_stays(spark):
    alone = "other words stand alone here"
    rows = [(1, A), (1, A), (2, A2), (2, B), (None, A), (None, "c d e f g h"), (None, "c d e f g h"), (3, ""), (4, ""), (5, None), (6, alone)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    kept = jaccard.drop_near_duplicates(docs)
    assert kept.schema.names == docs.schema.names
    # the clean text under id 2 stays though that id's other row goes
    want = [(1, A), (2, B), (None, "c d e f g h"), (3, ""), (4, ""), (5, None), (6, alone)]
    assert sorted((tuple(r) for r in kept.collect()), key=str) == sorted(want, key=str)
