import random

import pytest
from pyspark.sql import functions as F

from stablegrammar.functions.hashing import Level, affine_hash, fp_by_traversal, make_family, poly_hash, poly_hash_py, wide_fingerprint


def test_worked_hash():
    assert poly_hash_py([4, 1, 6], Level(13, 8, 3, 5, 2)) == 4


def test_family_is_reproducible_and_safe():
    f = make_family()
    assert f == make_family() and len({h.p for h in f.levels}) == 64
    assert all(2**31 < h.p < 1.4 * 2**31 and max(h.a, h.b, h.c) < h.p and h.p * h.p < 2**63 for h in f.levels)
    with pytest.raises(ValueError):
        make_family(levels=3)[3]


def test_columns_agree_with_integers(spark):
    f, rnd = make_family(), random.Random(1)
    rows = [(i, [rnd.randrange(2**31) for _ in range(rnd.randrange(1, 30))]) for i in range(50)]
    df = spark.createDataFrame(rows, "id long, xs array<long>")
    got = df.select("id", poly_hash(F.col("xs"), f[3]).alias("h"), affine_hash(F.get("xs", F.lit(0)), f[0]).alias("a"), wide_fingerprint(F.col("xs")).alias("w")).collect()
    for r in got:
        xs = rows[r["id"]][1]
        assert r["h"] == poly_hash_py(xs, f[3])
        assert r["a"] == (f[0].a * xs[0] + f[0].b) % f[0].p % f[0].m
        total = 0
        for x in reversed(xs):
            total = (total * 1_000_003 + x) % (2**61 - 1)
        assert r["w"] == total


def test_traversal_equals_stored():
    f = make_family()
    low = [fp_by_traversal([ord(c) for c in w], 1, f) for w in ("iss", "iss", "ippi")]
    assert fp_by_traversal([[ord(c) for c in w] for w in ("iss", "iss", "ippi")], 2, f) == poly_hash_py(low, f[2])
