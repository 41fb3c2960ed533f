from hubloom.operators.measures import crossover, phase_shares, saved_fraction, topk_overlap


def test_measures():
    assert saved_fraction([(100, 25), (10, 5), (0, 0)]) == 0.625
    assert crossover({10: (2.0, 1.0), 100: (2.0, 2.5), 1000: (2.0, 3.0)}) == 100
    assert crossover({10: (1.0, 2.0), 100: (3.0, 2.0)}) is None
    assert topk_overlap([1, 2, 3, 4], [2, 1, 9, 4]) == 0.75
    assert phase_shares({"a": 1.0, "b": 3.0}) == {"a": 0.25, "b": 0.75}
