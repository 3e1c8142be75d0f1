import string

import numpy as np
import pytest

from planepack.llm import secrets


def found(run):
    return [k for _, k, _ in secrets.scan(f"see {run} here")[1]] == [3]


@pytest.mark.parametrize("letters,least", [(string.ascii_letters, 0.99), (string.ascii_lowercase, 0.9), (string.ascii_uppercase, 0.9)])
@pytest.mark.parametrize("size", [20, 32, 40])
def test_random_letters_are_exposed(letters, least, size):
    rng = np.random.default_rng(size)
    runs = ["".join(rng.choice(list(letters), size)) for _ in range(300)]
    assert np.mean([found(r) for r in runs]) >= least


def test_random_groups_are_exposed():
    rng = np.random.default_rng(0)
    runs = ["-".join("".join(rng.choice(list(string.ascii_uppercase if i % 2 == 0 else string.digits), 4)) for i in range(6)) for _ in range(300)]
    assert np.mean([found(r) for r in runs]) >= 0.99
    assert found("xKqPzRtWvBnMjHgFdSaQ")


@pytest.mark.parametrize("run", ["some_long_identifier_name_here", "getConnectionPoolSizeFromConfig", "home/user/projects/data/training", "x-to-the-power-of-y-and-z", "MAX_CONNECTION_RETRY_COUNT", "2024-01-02-03-04-05-06", "--------------------------", "12345678901234567890123", "internationalization"])
def test_words_and_numbers_are_not(run):
    assert not found(run)
