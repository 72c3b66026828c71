"""SQL surface: functions, table functions and views."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from stablegrammar.functions.hashing import HashFamily, make_family, poly_hash_py
from stablegrammar.operators.build import breaks_numpy, build_strings
from stablegrammar.operators.model import Grammar


def grammar_size_of(texts: list[str], family: HashFamily) -> int:
    """Size of the grammar of a group of texts: distinct rules' right-hand sides."""
    held = [np.frombuffer((t or "").encode("utf-32-le"), np.uint32) for t in texts]
    if not held:
        return 0
    seen: dict = {}
    for b in build_strings(np.arange(len(held)), np.concatenate(held), np.array([len(c) for c in held]), family):
        if b.column("rhs").null_count < b.num_rows:
            for level, sym, rhs in zip(b.column("level").to_pylist(), b.column("sym").to_pylist(), b.column("rhs"), strict=True):
                seen[level, sym] = len(rhs)
    return sum(seen.values())


def parse_rounds_of(text: str, family: HashFamily) -> Iterator[tuple[int, int, int, int, int]]:
    """(round, phrase_no, start, len, fp) of every phrase of every round of one text."""
    if not text or len(text) < 2:
        return
    h = family[0]
    fps = np.array([(h.a * ord(c) + h.b) % h.p % h.m for c in text], np.int64)
    spans = [(i, i + 1) for i in range(len(text))]
    level = 0
    while len(fps) > 1:
        level += 1
        at = [*np.flatnonzero(breaks_numpy(fps, np.array([0]))).tolist(), len(fps)]
        new, nodes = [], []
        for k, (a, b) in enumerate(zip(at, at[1:], strict=False)):
            new.append(poly_hash_py(fps[a:b].tolist(), family[level]))
            nodes.append((spans[a][0], spans[b - 1][1]))
            yield level, k + 1, nodes[-1][0] + 1, nodes[-1][1] - nodes[-1][0], new[-1]
        fps, spans = np.array(new, np.int64), nodes


def register(spark: SparkSession, g: Grammar | None = None, family: HashFamily | None = None) -> None:
    """poly_hash(array, level), grammar_size(text) over groups, parse_rounds(text) as a table; with g, views g_rules, g_roots, g_runs, g_alphabet."""
    family = family or (g.family if g else make_family())

    @F.udf("long")
    def poly(xs, level):
        return None if xs is None else poly_hash_py(list(xs), family[level])

    @F.pandas_udf("long")
    def size(texts: pd.Series) -> int:
        return grammar_size_of(texts.tolist(), family)

    class Rounds:
        def eval(self, text: str):
            yield from parse_rounds_of(text, family)

    spark.udf.register("poly_hash", poly)
    spark.udf.register("grammar_size", size)
    spark.udtf.register("parse_rounds", F.udtf(Rounds, returnType="round int, phrase_no int, start int, len int, fp long"))
    if g is not None:
        g.rules.createOrReplaceTempView("g_rules")
        g.roots.createOrReplaceTempView("g_roots")
        g.alphabet().createOrReplaceTempView("g_alphabet")
        if g.runs is not None:
            g.runs.createOrReplaceTempView("g_runs")
