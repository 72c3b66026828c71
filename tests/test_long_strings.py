import numpy as np
import pytest

from stablegrammar.functions.hashing import make_family
from stablegrammar.operators import build
from stablegrammar.plans import queries, reports, workloads

SF = "/root/testdata/sf0.001"


def grammar(rounds):
    """Rules with their children, and roots."""
    rules, roots = {}, []
    for kind, *x in rounds:
        if kind == "rules":
            level, hi, lo, exp, fp, width, _, child, below = x
            ends = np.cumsum(width)
            for i, (a, b) in enumerate(zip(ends - width, ends, strict=True)):
                rules[level, hi[i], lo[i]] = exp[i], fp[i], tuple(below[0][child[a:b]]), tuple(below[1][child[a:b]])
        else:
            roots.append((kind, *map(str, x)))
    return rules, roots


@pytest.mark.parametrize("size", [1, 2, 7, 50, 1000])
def test_segments_of_a_long_string_give_its_rules(size):
    draw, family = np.random.default_rng(size), make_family()
    for k in range(60):
        codes = draw.integers(0, (1, 2, 5, 50)[k % 4], draw.integers(1, 400)).astype(np.uint32)
        codes = np.repeat(codes, draw.integers(1, 9, len(codes))) if k % 3 == 0 else np.tile(codes[:20], 10) if k % 5 == 0 else codes
        segments = [codes[i : i + size] for i in range(0, len(codes), size)]
        whole = build._rounds(np.array([7]), codes, np.array([len(codes)]), family, build.breaks_numpy)
        assert grammar(build._long_rounds(7, segments, family)) == grammar(whole)


def test_a_build_takes_long_strings_by_segments(spark, monkeypatch):
    strings = spark.createDataFrame([(1, "abracadabra, " * 50), (2, "abc"), (3, "mississippi " * 30), (4, "")], "string_id long, text string")
    rows = lambda g: [sorted(map(str, t.collect())) for t in (g.rules, g.roots)]
    assert rows(build.build_grammar(strings, batch_symbols=100)) == rows(build.build_grammar(strings))
    told = []
    monkeypatch.setattr(build, "_long_rounds", lambda i, segments, family: told.append((i, sum(map(len, segments)))) or ())
    monkeypatch.setattr(build, "SEGMENT", 7)
    odd = spark.createDataFrame([(1, "aü𝄞 " * 9)], "string_id long, text string").toArrow()
    assert "".join(map(chr, np.concatenate(list(build._segments(odd.column(1)[0]))))) == "aü𝄞 " * 9
    batch = strings.toArrow().to_batches()
    list(build._kernel(make_family(), 100, build.breaks_numpy)(iter(batch)))
    assert told == [(1, 650), (3, 360)]


def test_scaling_reads_the_letters_of_w2_without_arrays_of_codes(spark, monkeypatch, tmp_path):
    """Before, a source's documents met in one array of codes, and in an array of one-letter strings."""
    given = []
    monkeypatch.setattr(reports, "scaling", lambda strings, workers: given.append(strings))
    queries.QUERIES["scaling"](spark, SF)
    assert not {"collect_list", "transform"} & set(given[0]._jdf.queryExecution().optimizedPlan().toString().lower().replace("(", " ").split())
    docs = [(5, "src1", "zz"), (5, "src1", "ab"), (-250, "src1", "x"), (3, "src2", "q"), (None, "src2", "r"), (4, "src3", ""), (9, "src3", "ünï𝄞")]
    spark.createDataFrame(docs, "doc_id long, source string, text string").write.parquet(f"{tmp_path}/documents.parquet")
    for sf in (SF, str(tmp_path)):
        want, got = (reports.as_text(workloads.w2(spark, sf, **x)) for x in ({}, {"text": True}))
        assert got.dtypes == want.dtypes and sorted(map(str, got.collect())) == sorted(map(str, want.collect()))
