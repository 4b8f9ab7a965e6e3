import pandas as pd

from tilemine.sources.archives import LETTERS, pair_counts


def test_counts_neighbouring_letters_only():
    side, at = len(LETTERS), LETTERS.index
    got = pair_counts(pd.Series(["Ab ab.ba", "a b", "", None, "x\U0001f600y"]))
    assert got[0].sum() == 9999 and got[0][at("a") * side + at("b")] == 6666 and got[0][at("b") * side + at("a")] == 3333
    assert [x is None for x in got] == [False, True, True, True, True]
