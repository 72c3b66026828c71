import glob
import os
import re

import pytest
from pyspark.sql import functions as F

from stablegrammar.operators import naming, packed
from stablegrammar.operators.build import build_grammar
from stablegrammar.operators.lineage import shared_folder
from stablegrammar.plans import measures, queries

TEXTS = ["", "a", "z", "abracadabra " * 9, "abracadabra " * 9, "mississippi river, mississippi mud", "aaaaaaaaaaaaaaaaaaaab", "ünïcödé 𝄞 " * 5, None, *(f"page {i % 7}: the quick brown fox, {i * i} times. " * 4 for i in range(40))]


def rows(df):
    return sorted(map(str, df.collect()))


@pytest.fixture(scope="module")
def strings(spark):
    return spark.createDataFrame(list(enumerate(TEXTS)), "string_id long, text string").repartition(5)


@pytest.mark.parametrize("options", [{}, {"parcel": 1, "batch_symbols": 1}, {"batch_symbols": 64}])
def test_a_packed_grammar_is_the_grammar(strings, monkeypatch, options):
    if "parcel" in options:
        monkeypatch.setattr(packed, "PARCEL", options["parcel"])
    want = build_grammar(strings)
    got = packed.build_packed(strings, want.family, **{k: v for k, v in options.items() if k != "parcel"})
    assert rows(got.rules) == rows(want.rules) and rows(got.roots) == rows(want.roots)
    dense, own = naming.to_dense(want), naming.to_dense(got)
    assert own.rules.dtypes == dense.rules.dtypes and own.roots.dtypes == dense.roots.dtypes
    assert rows(own.rules) == rows(dense.rules) and rows(own.roots) == rows(dense.roots)
    assert rows(measures.key_bytes(own)) == rows(measures.key_bytes(dense))


def test_a_packed_grammar_of_codes_and_of_nothing(spark):
    codes = spark.createDataFrame([(1, [5, 1, 70000, 5, 1, 9] * 6), (2, []), (3, [5])], "string_id long, syms array<int>")
    for x in (codes, codes.where("string_id = 2"), codes.limit(0)):
        dense, own = naming.to_dense(build_grammar(x)), naming.to_dense(build_grammar(x, packed=True))
        assert rows(own.rules) == rows(dense.rules) and rows(own.roots) == rows(dense.roots)


def test_key_bytes_stores_less_than_twice_its_input(spark):
    """Before, phrases and rules were stored by name and once more by id, at 20 times the input."""
    sf = "/root/testdata/sf0.01"
    kept = lambda: {f for f in glob.glob(re.sub("^file:", "", shared_folder(spark)) + "/**", recursive=True) if os.path.isfile(f)}
    before = kept()
    got = queries.QUERIES["key_bytes"](spark, sf).agg(F.sum("fixed32"), F.sum("vbyte")).first()
    assert got[0] > got[1] > 0
    assert sum(map(os.path.getsize, kept() - before)) < 2 * os.path.getsize(f"{sf}/documents.parquet")
