from hypothesis import given, settings
from hypothesis import strategies as st

from pathtwin.metrics import kernels as K

PAIR = (list("abcde"), list("abxe"))
SEQ = st.lists(st.integers(0, 4), max_size=14)


def test_worked_pair():
    a, b = PAIR
    assert K.hamming(a, b) == 3 and K.hamming_free(a, b) == 2 and K.levenshtein(a, b) == 2
    assert K.lcs_length(a, b) == 3 and K.lcs(a, b) == 2 and K.alignment_score(a, b) == 3


def test_edges():
    for f in (K.hamming, K.levenshtein, K.lcs, K.damerau):
        assert f([], []) == 0 and f([1, 2], []) == 2 and f([1, 2], [1, 2]) == 0
    assert K.damerau([1, 2], [2, 1]) == 1 and K.levenshtein([1, 2], [2, 1]) == 2
    assert K.damerau("ca", "abc") == 2


def _levenshtein(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


@settings(max_examples=300, deadline=None)
@given(SEQ, SEQ, SEQ)
def test_axioms_and_nesting(a, b, c):
    assert K.levenshtein(a, b) == _levenshtein(a, b)
    assert K.alignment_score(a, b) == K.lcs_length(a, b)
    assert K.damerau(a, b) <= K.levenshtein(a, b) <= K.hamming(a, b) and K.lcs(a, b) <= K.levenshtein(a, b)
    for name, (f, _, _, is_metric) in K.REGISTRY.items():
        assert abs(f(a, b) - f(b, a)) < 1e-9 or name == "jaro_winkler"
        if is_metric:
            assert f(a, c) <= f(a, b) + f(b, c) + 1e-9
            assert (f(a, b) == 0) == (list(a) == list(b)) or name == "jaccard"


def test_subclone_rule():
    long, d = list(range(100, 140)), lambda p: K.path_distance(p, long, "lcs_mod")
    inside = long[5:15]
    assert d(inside) == 0.0 and d(inside[:9]) > 0.3
    assert d([*inside[:9], -1]) == 0.1 and d([*inside[:8], -1, -2]) > 0.3


def test_set_distance_is_symmetric_with_min_tie_and_weights_paths():
    a, b = [((1, 2, 3), 1), ((4, 5), 1)], [((1, 2, 3), 1), ((4, 6), 1)]
    assert K.set_distance(a, b, "lcs") == K.set_distance(b, a, "lcs") == 0.25
    assert K.set_distance([((1, 2), 3), ((9, 9), 1)], [((1, 2), 5)], "lcs") == 0.25


def test_edit_and_jaro_distances_count_symbols_beyond_127():
    """References that write symbols as characters count bytes from the 128th on; the kernels must not."""
    a = list(range(300))
    b = [x for x in a if x % 3] + list(range(1000, 1040))
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        old, row = row, [i]
        for j, y in enumerate(b, 1):
            row.append(min(old[j - 1] + (x != y), old[j] + 1, row[-1] + 1))
    assert K.levenshtein(a, b) == K.damerau(a, b) == row[-1] == 140
    assert abs(K.jaro_winkler(a, b) - K.jaro_winkler("".join(chr(200 + x) for x in a), "".join(chr(200 + x) for x in b))) < 1e-12
