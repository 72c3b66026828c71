"""Local consistency: cores of patterns, equivalence of grammars, stability of independent builds."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stablegrammar.functions.hashing import HashFamily, make_family
from stablegrammar.operators import rule_stats
from stablegrammar.operators.build import breaks_numpy
from stablegrammar.operators.lineage import settled
from stablegrammar.operators.model import Grammar


def pattern_core(pattern: str, family: HashFamily) -> list[tuple[int, int, int, int, int]]:
    """(level, node_no, start, end, fp) of the nodes of a pattern's parse that no context can change.

    Each round keeps the phrases between breaks that the pattern alone decides: a break needs its left neighbour and the first different
    fingerprint on its right, so the first stretch and what follows the last decided break go.
    """
    h = family[0]
    codes = np.array([ord(c) for c in pattern], np.int64)
    fps = (h.a * codes + h.b) % h.p % h.m
    spans = [(i, i + 1) for i in range(len(pattern))]
    out, level = [], 0
    while len(fps) >= 3:
        level += 1
        mask = breaks_numpy(fps, np.array([0]))
        at = np.flatnonzero(mask)[1:].tolist()  # decided breaks; 0 is only where the pattern begins
        if len(at) < 2:
            break
        h = family[level]
        nodes, new = [], []
        for a, b in zip(at, at[1:], strict=False):
            total = 0
            for f in reversed(fps[a:b].tolist()):
                total = (total * h.c + f) % h.p
            new.append((h.a * total + h.b) % h.p % h.m)
            nodes.append((spans[a][0], spans[b - 1][1]))
        out += [(level, k, s, e, f) for k, ((s, e), f) in enumerate(zip(nodes, new, strict=True))]
        fps, spans = np.array(new, np.int64), nodes
    return out


#: Patterns that one turn of a search broadcasts, about.
BLOCK = 10_000


def _holding(strings: DataFrame, patterns: DataFrame) -> DataFrame:
    """(pattern_id, pattern, string_id, text) wherever the text holds the pattern; patterns(pattern_id, pattern) in blocks of about BLOCK."""
    blocks = max(1, -(-patterns.count() // BLOCK))
    of = F.pmod(F.xxhash64("pattern_id", "pattern"), F.lit(blocks))
    hits = [strings.join(F.broadcast(patterns.where(of == b)), F.instr(F.col("text"), F.col("pattern")) > 0) for b in range(blocks)]
    return reduce(DataFrame.unionByName, hits).select(F.col("pattern_id").cast("long"), "pattern", F.col("string_id").cast("long"), "text")


def _places(text: str, pattern: str) -> Iterator[int]:
    at = text.find(pattern)
    while at >= 0:
        yield at
        at = text.find(pattern, at + 1)


def core_in_occurrences(g: Grammar, strings: DataFrame, patterns: DataFrame) -> DataFrame:
    """(pattern_id, occurrences, core_nodes, core_rounds, missing): core nodes that the parse of an occurrence's own string lacks there.

    A node counts as found if that parse has one of its level, length and fingerprint at its very place. Strings that hold a pattern are
    parsed again; patterns are taken in blocks.
    """
    from stablegrammar.sources.sql import parse_rounds_of

    family = g.family

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            out: dict[str, list] = {"pattern_id": [], "core_nodes": [], "core_rounds": [], "missing": []}
            for pid, p, t in zip(*(x.column(c).to_pylist() for c in ("pattern_id", "pattern", "text")), strict=True):
                core = pattern_core(p, family)
                nodes = {(r, s - 1, n, f) for r, _, s, n, f in parse_rounds_of(t, family)} if core else set()
                for at in _places(t, p):
                    lost = sum((r, at + s, e - s, int(f)) not in nodes for r, _, s, e, f in core)
                    for column, v in zip(out.values(), (pid, len(core), max((c[0] for c in core), default=0), lost), strict=True):
                        column.append(v)
            yield pa.RecordBatch.from_pydict(out, schema=pa.schema([("pattern_id", pa.int64()), ("core_nodes", pa.int64()), ("core_rounds", pa.int32()), ("missing", pa.int64())]))

    found = _holding(strings, patterns).mapInArrow(run, "pattern_id long, core_nodes long, core_rounds int, missing long")
    return found.groupBy("pattern_id").agg(F.count(F.lit(1)).alias("occurrences"), F.max("core_nodes").alias("core_nodes"), F.max("core_rounds").alias("core_rounds"), F.sum("missing").alias("missing"))


def equivalent(a: Grammar, b: Grammar) -> DataFrame:
    """level, only_a, only_b, both: rules by content name. Equal grammars have no rule on one side only."""
    x = a.rules.select("level", "sym").distinct().withColumn("_a", F.lit(True))
    y = b.rules.select("level", "sym").distinct().withColumn("_b", F.lit(True))
    both = x.join(y, ["level", "sym"], "full_outer")
    count = lambda c: F.sum(c.cast("long"))
    return both.groupBy("level").agg(count(F.col("_a").isNotNull() & F.col("_b").isNull()).alias("only_a"), count(F.col("_b").isNotNull() & F.col("_a").isNull()).alias("only_b"), count(F.col("_a").isNotNull() & F.col("_b").isNotNull()).alias("both"))


def shape_equal(dense: Grammar, content: Grammar) -> DataFrame:
    """level, n: the multiset difference of (level, exp_len, fp, rhs_len) between grammars with names of different kinds; empty if equal."""
    cols = ["level", "exp_len", "fp", "rhs_len"]
    a, b = dense.rules.select(*cols), content.rules.select(*cols)
    return a.exceptAll(b).union(b.exceptAll(a)).groupBy("level").agg(F.count(F.lit(1)).alias("n"))


def stability_report(a: Grammar, b: Grammar) -> DataFrame:
    """level, shared, of_a, of_b: symbols that two independent builds name alike, which they do exactly for equal trees."""
    e = equivalent(a, b)
    return e.select("level", F.col("both").alias("shared"), (F.col("only_a") + F.col("both")).alias("of_a"), (F.col("only_b") + F.col("both")).alias("of_b"))


def structure_faults(g: Grammar) -> DataFrame:
    """what, n, checked: violations of one rule per symbol, of levels (children from the level below), and of root lengths."""
    faults = lambda df, what, bad: df.agg(F.lit(what).alias("what"), F.coalesce(F.sum(bad.cast("long")), F.lit(0)).alias("n"), F.count(F.lit(1)).alias("checked"))
    twice = faults(g.rules.groupBy("level", "sym").count(), "several rules", F.col("count") > 1)
    kids = g.rules.where("level > 1").select((F.col("level") - 1).alias("level"), F.explode("rhs").alias("sym")).distinct()
    known = g.rules.select("level", "sym").distinct().withColumn("_known", F.lit(True))
    loose = faults(kids.join(known, ["level", "sym"], "left"), "children without a rule", F.col("_known").isNull())
    at = g.roots.where("root_level > 0").join(g.rules.select(F.col("level").alias("root_level"), F.col("sym").alias("root_sym"), "exp_len"), ["root_level", "root_sym"], "left")
    return twice.unionByName(loose).unionByName(faults(at, "roots of wrong length", ~F.col("exp_len").eqNullSafe(F.col("n_symbols"))))


def _anchors(patterns: DataFrame, family: HashFamily) -> DataFrame:
    """(pattern_id, level, exp_len, fp) of the longest node of the highest round of each pattern's core; level 0 without a core."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            best = [max(((c[0], c[3] - c[2], int(c[4])) for c in pattern_core(p, family)), default=(0, 0, 0)) for p in x.column(1).to_pylist()]
            level, size, fp = (pa.array([b[k] for b in best], t) for k, t in enumerate((pa.int32(), pa.int64(), pa.int64())))
            yield pa.RecordBatch.from_arrays([x.column(0), level, size, fp], ["pattern_id", "level", "exp_len", "fp"])

    return patterns.select(F.col("pattern_id").cast("long"), "pattern").mapInArrow(run, "pattern_id long, level int, exp_len long, fp long")


def find_patterns(g: Grammar, strings: DataFrame, patterns: DataFrame) -> DataFrame:
    """(pattern_id, string_id, at): all occurrences of all patterns(pattern_id, pattern), overlapping ones too, from 1.

    Each pattern's anchor, a node of its core, is in every occurrence. Symbols that hold an anchor are followed from level to level to
    the roots, so only strings that hold it are read. Patterns too short for a core are looked for in all strings, in blocks.
    """
    patterns = patterns.where("pattern <> ''").select(F.col("pattern_id").cast("long").alias("pattern_id"), "pattern")
    anchors = settled(_anchors(patterns, g.family))
    reached = settled(anchors.where("level > 0").join(g.rules.select("level", "exp_len", "fp", "sym"), ["level", "exp_len", "fp"]).select("pattern_id", "level", "sym").distinct())
    everywhere = [reached]
    top = g.rules.agg(F.max("level")).first()[0] or 0
    last = reached.limit(0)
    for level in range(1, top):
        last = settled(reached.where(F.col("level") == level).unionByName(last))
        kids = g.rules.where(F.col("level") == level + 1).select(F.col("sym").alias("_parent"), F.explode(F.array_distinct("rhs")).alias("sym"))
        last = settled(kids.join(last, "sym").select("pattern_id", F.lit(level + 1).alias("level"), F.col("_parent").alias("sym")).distinct())
        everywhere.append(last)
    held = reduce(DataFrame.unionByName, everywhere).join(g.roots, (F.col("level") == F.col("root_level")) & (F.col("sym") == F.col("root_sym")))
    held = held.select("pattern_id", "string_id").distinct().join(patterns, "pattern_id").join(strings.select("string_id", "text"), "string_id")
    return _occurrences(strings, patterns, anchors, held)


def find_patterns_unstored(strings: DataFrame, patterns: DataFrame, family: HashFamily | None = None) -> DataFrame:
    """The rows of find_patterns, for one search of strings without a stored grammar: each task follows anchors through the rules it makes."""
    family = family or make_family()
    patterns = patterns.where("pattern <> ''").select(F.col("pattern_id").cast("long").alias("pattern_id"), "pattern")
    anchors = settled(_anchors(patterns, family))
    held = rule_stats.holding(strings, anchors, family).join(patterns, "pattern_id")
    return _occurrences(strings, patterns, anchors, held)


def _occurrences(strings: DataFrame, patterns: DataFrame, anchors: DataFrame, held: DataFrame) -> DataFrame:
    """(pattern_id, string_id, at) in held(pattern_id, pattern, string_id, text), and of patterns without an anchor in all strings."""
    short = patterns.join(anchors.where("level = 0").select("pattern_id"), "pattern_id", "left_semi")
    both = held.select("pattern_id", "pattern", "string_id", "text")
    if not short.isEmpty():
        both = both.unionByName(_holding(strings, short))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            out: list = []
            for pid, sid, p, t in zip(x.column(0).to_pylist(), x.column(1).to_pylist(), x.column(2), x.column(3), strict=True):
                out += ((pid, sid, at + 1) for at in _places(t.as_py(), p.as_py()))
            columns = zip(*out, strict=True) if out else ([], [], [])
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int64(), pa.int32()), strict=True)], ["pattern_id", "string_id", "at"])

    return both.where(F.instr("text", F.col("pattern")) > 0).select("pattern_id", "string_id", "pattern", "text").mapInArrow(run, "pattern_id long, string_id long, at int")


def find_pattern(g: Grammar, strings: DataFrame, pattern: str) -> DataFrame:
    """(string_id, at): occurrences of one pattern."""
    one = strings.sparkSession.createDataFrame([(0, pattern)], "pattern_id long, pattern string")
    return find_patterns(g, strings, one).select("string_id", "at")


def symbol_jaccard(g: Grammar, level: int, least: float = 0.2) -> DataFrame:
    """(a, b, jaccard), a < b, of strings by their sets of symbols of a level, where it is at least `least`."""
    from stablegrammar.operators.expand import usage_counts

    sets = usage_counts(g, per_string=True).where(F.col("level") == level)
    return _similar_sets(settled(sets.groupBy("string_id").agg(F.array_sort(F.collect_set("sym")).alias("own"))), least)


def symbol_jaccard_unstored(strings: DataFrame, level: int, least: float = 0.2, family: HashFamily | None = None) -> DataFrame:
    """The rows of symbol_jaccard without a stored grammar: each task gives the sets of the strings that it parses."""
    sets = settled(rule_stats.symbol_sets(strings, level, family))
    twice = settled(sets.groupBy("string_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("string_id"))
    if twice.isEmpty():
        return _similar_sets(sets, least)
    merged = sets.join(twice, "string_id", "left_semi").groupBy("string_id").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("own")))).alias("own"))
    return _similar_sets(settled(sets.join(twice, "string_id", "left_anti").unionByName(merged)), least)


def _similar_sets(sets: DataFrame, least: float) -> DataFrame:
    """symbol_jaccard() of sets(string_id, own), a table of one sorted set for each string.

    Strings with equal sets are one class: pairs are of classes, named by their smallest string, and of a class's smallest string with each
    other one of it (jaccard 1). Classes meet by exact prefix filtering: with symbols ordered from rare to frequent, similar sets share
    one of their first n - ceil(least * n) + 1, and what follows the first shared one leaves room for the overlap, so no pair is left out,
    however frequent its symbols. Sets are classed by digest. Symbols meet as hashes, of which two may
    be equal: that brings pairs together that share less, and the whole sets decide. What only one class has goes first, and no further.
    """
    binary = "binary" in dict(sets.dtypes)["own"]
    digest = F.sha2(F.array_join(F.transform("own", lambda x: F.hex(x) if binary else x), ",").cast("binary"), 256)
    groups = settled(sets.groupBy(digest.alias("_d")).agg(F.min("string_id").alias("rep"), F.collect_list("string_id").alias("all")).drop("_d"))
    classes = settled(sets.join(groups.select(F.col("rep").alias("string_id")), "string_id", "left_semi").select(F.col("string_id").alias("rep"), "own"))
    each = classes.select("rep", F.size("own").alias("n"), F.explode(F.transform("own", lambda x: F.xxhash64(x))).alias("sym"))
    common = settled(each.groupBy("sym").agg(F.count(F.lit(1)).alias("df")).where("df > 1"))
    met = each.join(common, "sym")
    alone = F.col("n") - F.count(F.lit(1)).over(Window.partitionBy("rep"))
    ranked = met.withColumn("at", F.row_number().over(Window.partitionBy("rep").orderBy("df", "sym")) + alone)
    prefix = settled(ranked.where(F.col("at") <= F.col("n") - F.ceil(F.col("n") * least) + 1).select("rep", "n", "sym", "at"))
    side = lambda c: prefix.select("sym", F.col("rep").alias(c), F.col("n").alias(f"n{c}"), F.col("at").alias(f"at{c}"))
    sizes = F.least("na", "nb") >= least * F.greatest("na", "nb")
    room = (1 + least) * (1 + F.least(F.col("na") - F.col("ata"), F.col("nb") - F.col("atb"))) >= (least - 1e-6) * (F.col("na") + F.col("nb"))
    pairs = settled(side("a").join(side("b"), "sym").where((F.col("a") < F.col("b")) & sizes & room).select("a", "b").distinct())
    own = lambda c: classes.select(F.col("rep").alias(c), F.col("own").alias(f"s{c}"))
    sized = pairs.join(own("a"), "a").join(own("b"), "b").select("a", "b", F.size(F.array_intersect("sa", "sb")).alias("_both"), (F.size("sa") + F.size("sb")).alias("_all"))
    jaccard = sized.select("a", "b", F.round(F.col("_both") / (F.col("_all") - F.col("_both")), 6).alias("jaccard")).where(F.col("jaccard") >= least)
    members = groups.select(F.col("rep").alias("a"), F.explode("all").alias("b")).where("a < b").select("a", "b", F.lit(1.0).alias("jaccard"))
    return jaccard.unionByName(members)


def consistency_radius(strings: DataFrame, patterns: DataFrame, family: HashFamily) -> DataFrame:
    """(pattern_id, round, occurrences, differing): phrase borders inside a pattern that not all of its occurrences share.

    Only strings that hold a pattern are parsed; patterns(pattern_id, pattern) are taken in blocks.
    """
    from stablegrammar.sources.sql import parse_rounds_of

    hit = _holding(strings, patterns).select("pattern_id", "string_id", "pattern", "text")

    def run(batches):
        for x in batches:
            out: dict[str, list] = {"pattern_id": [], "place": [], "round": [], "at": []}
            for pid, sid, p, t in zip(*(x.column(i).to_pylist() for i in range(4)), strict=True):
                rounds = [(r, s - 1) for r, _, s, _, _ in parse_rounds_of(t, family)]
                for at in _places(t, p):
                    for r, s in rounds:
                        if at < s < at + len(p):
                            for k, v in zip(out, (pid, f"{sid}:{at}", r, s - at), strict=True):
                                out[k].append(v)
            yield pa.RecordBatch.from_pydict(out, schema=pa.schema([("pattern_id", pa.int64()), ("place", pa.string()), ("round", pa.int32()), ("at", pa.int64())]))

    borders = hit.select(F.col("pattern_id").cast("long"), F.col("string_id").cast("string"), "pattern", "text").mapInArrow(run, "pattern_id long, place string, round int, at long")
    n = borders.groupBy("pattern_id").agg(F.count_distinct("place").alias("occurrences"))
    per = borders.groupBy("pattern_id", "round", "at").agg(F.count_distinct("place").alias("c"))
    return per.join(n, "pattern_id").groupBy("pattern_id", "round", "occurrences").agg(F.sum((F.col("c") < F.col("occurrences")).cast("long")).alias("differing"))
