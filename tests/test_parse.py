from itertools import product

import numpy as np
from pyspark.sql import functions as F

from stablegrammar.functions.hashing import make_family
from stablegrammar.operators import parse
from stablegrammar.operators.build import breaks_numpy, local_min_numpy


def by_definition(x):
    """Types from right to left; 0-based breaks."""
    n, kind = len(x), [None] * len(x)
    for i in range(n - 2, -1, -1):
        kind[i] = "L" if x[i] > x[i + 1] else "S" if x[i] < x[i + 1] else kind[i + 1]
    return [i for i in range(1, n) if kind[i] == "S" and kind[i - 1] == "L"], kind


def test_closed_form_on_all_short_strings():
    strings = [s for n in range(1, 9) for s in product((1, 2, 3), repeat=n)]
    sizes = np.array([len(s) for s in strings])
    starts = np.cumsum(sizes) - sizes
    mask = breaks_numpy(np.array([x for s in strings for x in s]), starts)
    for s, a in zip(strings, starts, strict=True):
        got = np.flatnonzero(mask[a + 1 : a + len(s)]) + 1
        assert got.tolist() == by_definition(s)[0]


def test_worked_examples():
    for text, want in {"mississippi": [2, 5, 8], "xmississippi": [3, 6, 9], "abab": [3], "abcabc": [4], "cbabc": [3], "baa": [], "aaaa": [], "a": []}.items():
        assert (np.flatnonzero(breaks_numpy(np.array([ord(c) for c in text]), np.array([0])))[1:] + 1).tolist() == want


def test_window_types_equal_definition(spark):
    strings = [s for n in range(1, 6) for s in product((1, 2, 3), repeat=n)]
    rows = [(k, i + 1, str(x), x) for k, s in enumerate(strings) for i, x in enumerate(s)]
    got = parse.position_types(spark.createDataFrame(rows, "string_id long, pos long, sym string, fp long")).collect()
    want = {(k, i + 1): (kind, i in b) for k, s in enumerate(strings) for b, kinds in [by_definition(s)] for i, kind in enumerate(kinds)}
    assert {(r["string_id"], r["pos"]): (r["type"], r["is_break"]) for r in got} == want


def test_local_minimum_rule_in_both_engines(spark):
    rng = np.random.default_rng(0)
    strings = [rng.integers(0, 6, n).tolist() for n in (1, 2, 5, 40)]
    rows = [(k, i + 1, str(x), x) for k, s in enumerate(strings) for i, x in enumerate(s)]
    got = {(r["string_id"], r["pos"]) for r in parse.local_min_breaks(spark.createDataFrame(rows, "string_id long, pos long, sym string, fp long")).where("is_break").collect()}
    sizes = np.array([len(s) for s in strings])
    starts = np.cumsum(sizes) - sizes
    mask = local_min_numpy(np.array([x for s in strings for x in s]), starts)
    mask[starts] = False
    assert got == {(k, i + 1) for k, s in enumerate(strings) for i in range(len(s)) if mask[starts[k] + i]}


def test_symbols_of_text_and_codes(spark):
    f = make_family()
    a = parse.symbols(spark.createDataFrame([(1, "añ"), (2, "")], "string_id long, text string"), f)
    b = parse.symbols(spark.createDataFrame([(1, [97, 241]), (2, [])], "string_id long, syms array<int>"), f)
    assert sorted(a.collect()) == sorted(b.collect()) and a.count() == 2
    assert a.where(F.col("pos") == 2).first()["sym"] == "241"
