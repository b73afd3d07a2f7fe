from hypothesis import given, settings
from hypothesis import strategies as st

from hypernear.llm.alignment import banded_distance, in_band, whole


def table(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


words = st.lists(st.integers(0, 4), max_size=40)


@settings(max_examples=400, deadline=None)
@given(words, words, st.integers(0, 20))
def test_equals_the_full_table(a, b, limit):
    want = table(a, b)
    assert banded_distance(a, b, limit) == (want if want <= limit else None)
    if a and b:
        assert whole(a, b) == want
    a, b = sorted((a, b), key=len)
    if limit < len(a) and len(b) - len(a) <= limit:
        assert in_band(a, b, limit) == (want if want <= limit else None)


def test_long_texts_with_few_edits():
    a = list(range(20_000))
    b = a[:500] + [-1] + a[500:9000] + a[9003:] + [-2, -3]
    assert banded_distance(a, b, 4000) == 6
    assert banded_distance(a, b, 5) is None
