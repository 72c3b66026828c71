import pytest
from pyspark.sql import functions as F

from stablegrammar.functions.hashing import make_family
from stablegrammar.operators import consistency, expand, merge, naming, post
from stablegrammar.operators.build import build_grammar, local_min_numpy
from stablegrammar.operators.parallel import build_parallel, compress
from stablegrammar.plans import measures

TEXTS = ["mississippi", "xmississippi", "", "a", "aaaa", "aaaaaaaabaaaaaaaa", "mississippi", "abcdefghij", "jihgfedcba", "abababababab", "añb🎉z" * 9, "the cat sat on the mat. " * 7, "on the mat sat the cat. " * 5, "x" * 300]


@pytest.fixture(scope="module")
def strings(spark):
    return spark.createDataFrame(list(enumerate(TEXTS)), "string_id long, text string").cache()


@pytest.fixture(scope="module")
def grammar(strings):
    return build_grammar(strings)


def texts_of(g, ids=None):
    return {r["string_id"]: r["text"] for r in expand.expand(g, ids).collect()}


def test_round_trip_and_structure(grammar):
    assert texts_of(grammar) == dict(enumerate(TEXTS))
    assert all(r["n"] == 0 for r in consistency.structure_faults(grammar).collect())
    roots = {r["string_id"]: r for r in grammar.roots.collect()}
    assert roots[2]["root_level"] == -1 and roots[3]["root_level"] == 0 and roots[0]["root_sym"] == roots[6]["root_sym"]
    assert all(r["n_symbols"] == len(TEXTS[i]) for i, r in roots.items())


def test_engines_agree(strings, grammar):
    other = build_grammar(strings, engine="dataframe")
    assert consistency.shape_equal(other, grammar).isEmpty()
    key = lambda g: sorted(tuple(r) for r in g.roots.select("string_id", "root_level", "n_symbols").collect())
    assert key(other) == key(grammar)
    assert texts_of(other) == dict(enumerate(TEXTS))


def test_rounds_are_bounded(grammar):
    for r in grammar.roots.where("n_symbols > 0").collect():
        assert r["root_level"] <= max(1, r["n_symbols"] - 1).bit_length() + (r["n_symbols"] > 1)


def test_collisions_and_other_rules_are_lossless(strings):
    assert texts_of(build_grammar(strings, make_family(bits=1))) == dict(enumerate(TEXTS))
    assert texts_of(build_grammar(strings, breaks=local_min_numpy)) == dict(enumerate(TEXTS))


def test_small_batches_give_the_same_rules(strings, grammar):
    other = build_grammar(strings.repartition(3), batch_symbols=1)
    e = consistency.equivalent(grammar, other).collect()
    assert all(r["only_a"] == r["only_b"] == 0 for r in e)


def test_merge_is_the_build_of_the_union(strings, grammar):
    a, b = (build_grammar(strings.where(F.col("string_id") % 2 == i)) for i in (0, 1))
    for m in (merge.merge_grammars(a, b), merge.merge_grammars(b, a), merge.merge_grammars(merge.merge_grammars(a, b), a)):
        assert all(r["only_a"] == r["only_b"] == 0 for r in consistency.equivalent(grammar, m).collect())
    assert texts_of(merge.merge_grammars(a, b)) == dict(enumerate(TEXTS))
    assert merge.name_conflicts(a, b).isEmpty()
    with pytest.raises(ValueError):
        merge.merge_grammars(a, build_grammar(strings, make_family(seed=7)))


@pytest.mark.parametrize("strategy", ["union", "fold", "tree"])
def test_parallel_build(strings, grammar, strategy):
    g = build_parallel(strings, 3, strategy=strategy, fan_in=2)
    assert all(r["only_a"] == r["only_b"] == 0 for r in consistency.equivalent(grammar, g).collect())


def test_dense_merge(strings, grammar):
    # both halves use every character, so that their dense terminals agree
    every = "".join(sorted(set("".join(TEXTS))))
    both = strings.union(strings.sparkSession.createDataFrame([(100, every), (101, every)], "string_id long, text string"))
    whole, halves = build_grammar(both), [naming.to_dense(build_grammar(both.where(F.col("string_id") % 2 == i))) for i in (0, 1)]
    merged, counts = merge.merge_dense(*halves, sigma=len(every))
    assert consistency.shape_equal(merged, whole).isEmpty()
    assert counts.agg(F.sum("matched")).first()[0] > 0
    alphabet = {i + 1: c for i, c in enumerate(every)}
    off = naming.dense_offsets(merged, len(every))
    rules = {r["sym"]: r["rhs"] for r in merged.rules.collect()}
    assert sorted(rules) == list(range(len(every) + 1, off[-1] + 1))

    def spell(s):
        return alphabet[s] if s <= len(every) else "".join(map(spell, rules[s]))

    want = dict(enumerate(TEXTS)) | {100: every, 101: every}
    assert {r["string_id"]: spell(r["root_sym"]) if r["root_sym"] else "" for r in merged.roots.collect()} == want


def test_passes(grammar):
    before = measures.totals(grammar)
    rl = post.run_length(grammar)
    mid = measures.totals(rl)
    done = post.inline_singletons(rl)
    after = measures.totals(done)
    assert mid["runs"] > 0 and mid["G"] - after["G"] == mid["g"] - after["g"] > 0
    assert texts_of(rl) == texts_of(done) == dict(enumerate(TEXTS))
    assert post.single_use(done).isEmpty()
    loose = post.inline_singletons(rl, protect_roots=False)
    assert texts_of(loose) == dict(enumerate(TEXTS)) and measures.totals(loose)["G"] <= after["G"]
    paid = measures.totals(post.run_length(grammar, only_if_smaller=True))
    assert paid["G"] <= min(before["G"], mid["G"])


def test_stage_subsets(strings):
    for stages in ((), ("rl",), ("inline",), ("rl", "inline")):
        assert texts_of(compress(strings, stages=stages)) == dict(enumerate(TEXTS))


def test_access_usage_and_search(grammar, strings):
    got = {r["string_id"]: r["piece"] for r in expand.access(grammar, 2, 7).collect()}
    assert got == {i: t[2:7] for i, t in enumerate(TEXTS) if t[2:7]}
    uses = expand.usage_counts(grammar).where("level = 0").agg(F.sum("uses")).first()[0]
    assert uses == sum(map(len, TEXTS))
    want = sorted((i, k + 1) for i, t in enumerate(TEXTS) for k in range(len(t)) if t.startswith("the cat", k))
    assert sorted(tuple(r) for r in consistency.find_pattern(grammar, strings, "the cat").collect()) == want


def test_planted_core_survives_in_any_context(spark):
    p = "local consistency keeps the middle of a pattern, whatever stands around it, through many rounds."
    f = make_family()
    core = consistency.pattern_core(p, f)
    assert max(x[0] for x in core) >= 2
    g = build_grammar(spark.createDataFrame([(1, "zq" + p + "ab"), (2, p + "!"), (3, "....." + p)], "string_id long, text string"), f)
    per = expand.usage_counts(g, per_string=True).join(g.rules, ["level", "sym"])
    for level, _, s, e, fp in core:
        assert per.where((F.col("level") == level) & (F.col("fp") == fp) & (F.col("exp_len") == e - s)).select("string_id").distinct().count() == 3


def test_families_of_different_seeds_disagree(spark):
    """Builds that share no hash family cut differently."""
    text = spark.createDataFrame([(1, "the cat sat on the mat")], "string_id long, text string")
    a, b = build_grammar(text, make_family(seed=1)), build_grammar(text, make_family(seed=2))
    assert not consistency.shape_equal(a, b).isEmpty()


def test_integers_as_symbols(spark):
    df = spark.createDataFrame([(1, [5, 70000, 5, 9, 5, 70000, 5, 9]), (2, [])], "string_id long, syms array<int>")
    g = build_grammar(df)
    got = sorted((r["at"], int.from_bytes(r["sym"])) for r in expand.leaves(g).collect())
    assert [x for _, x in got] == [5, 70000, 5, 9, 5, 70000, 5, 9]


def test_empty_table(spark):
    g = build_grammar(spark.createDataFrame([], "string_id long, text string"))
    assert g.rules.isEmpty() and g.roots.isEmpty() and expand.expand(g).isEmpty()
    assert post.inline_singletons(post.run_length(g)).rules.isEmpty()


def test_merge_by_lang_takes_null_languages(spark, tmp_path):
    from stablegrammar.plans import queries

    spark.createDataFrame([(1, "the cat sat on the mat", "en"), (2, "no language was given to this one", None)], "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    roots = [r["string_id"] for g in queries._parts_by(spark, str(tmp_path), "lang") for r in g.roots.collect()]
    assert sorted(roots) == [1, 2]


def test_inlining_equals_one_symbol_at_a_time(spark):
    texts = ["abcdefghijklmnopqrstuvwxyz" * 3 + f"{i}" for i in range(3)] + ["zyx" * 40, "the quick brown fox jumps over the lazy dog"]
    g = post.as_items(build_grammar(spark.createDataFrame(list(enumerate(texts)), "string_id long, text string")))
    rules = {(r["level"], bytes(r["sym"])): [(x["level"], bytes(x["sym"])) for x in r["rhs"]] for r in g.rules.collect()}
    roots = {(r["root_level"], bytes(r["root_sym"])) for r in g.roots.collect()}
    while True:
        uses = {}
        for rhs in rules.values():
            for x in rhs:
                uses[x] = uses.get(x, 0) + 1
        once = next((x for x, n in uses.items() if n == 1 and x in rules and x not in roots), None)
        if once is None:
            break
        own = rules.pop(once)
        rules = {k: [y for x in rhs for y in (own if x == once else [x])] for k, rhs in rules.items()}
    got = {(r["level"], bytes(r["sym"])): [(x["level"], bytes(x["sym"])) for x in r["rhs"]] for r in post.inline_singletons(g).rules.collect()}
    assert got == rules


def test_search_takes_every_pattern(strings, grammar, monkeypatch):
    monkeypatch.setattr(consistency, "BLOCK", 3)  # several blocks
    words = ["the cat", "on the mat", "a", "ississ", "xx", "nothing here", "aaaa", "abab"]
    patterns = strings.sparkSession.createDataFrame(list(enumerate(words)), "pattern_id long, pattern string")
    want = sorted((p, i, k + 1) for p, w in enumerate(words) for i, t in enumerate(TEXTS) for k in range(len(t)) if t.startswith(w, k))
    assert sorted(tuple(r) for r in consistency.find_patterns(grammar, strings, patterns).collect()) == want
    cores = {r["pattern_id"]: r for r in consistency.core_in_occurrences(grammar, strings, patterns).collect()}
    assert all(r["missing"] == 0 for r in cores.values()) and cores[0]["occurrences"] == sum(p == 0 for p, _, _ in want)


def test_search_without_a_stored_grammar(strings, grammar, monkeypatch):
    words = ["the cat", "on the mat", "a", "ississ", "sat on the mat. the cat sat on", "nothing here", "the mat sat the cat. on the mat", "añb🎉zañb🎉zañb🎉z"]
    patterns = strings.sparkSession.createDataFrame(list(enumerate(words)), "pattern_id long, pattern string")
    want = sorted(tuple(r) for r in consistency.find_patterns(grammar, strings, patterns).collect())
    assert len({p for p, _, _ in want}) == 7
    for block in (100_000, 2):
        monkeypatch.setitem(consistency.rule_stats.holding.__kwdefaults__, "block", block)
        monkeypatch.setitem(consistency.rule_stats.holding.__kwdefaults__, "batch_symbols", 1 << 20 if block > 2 else 100)
        assert sorted(tuple(r) for r in consistency.find_patterns_unstored(strings, patterns).collect()) == want


def test_symbol_jaccard_without_caps(spark):
    texts = ["the cat sat on the mat and the dog lay by the door of the old house near the lake"] * 30 + [f"the cat sat on the mat and the dog lay by the door of the old house near the {w}" for w in ("sea", "hill", "wood")] + ["something else altogether is written in this one"]
    g = build_grammar(spark.createDataFrame(list(enumerate(texts)), "string_id long, text string"))
    per = {}
    for r in expand.usage_counts(g, per_string=True).where("level = 1").collect():
        per.setdefault(r["string_id"], set()).add(bytes(r["sym"]))
    first = {}
    for i in sorted(per):
        first.setdefault(frozenset(per[i]), i)
    reps = sorted(first.values())
    want = {(a, b): round(len(per[a] & per[b]) / len(per[a] | per[b]), 6) for a in reps for b in reps if a < b and len(per[a] & per[b]) / len(per[a] | per[b]) >= 0.2}
    want |= {(first[frozenset(s)], i): 1.0 for i, s in per.items() if first[frozenset(s)] < i}
    assert {(r["a"], r["b"]): r["jaccard"] for r in consistency.symbol_jaccard(g, 1).collect()} == want
