from planepack.llm import toxicity


def test_sample_is_the_documented_bound():
    assert toxicity.SAMPLE == 8_000
