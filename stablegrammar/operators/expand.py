"""Expansion, random access and usage: top-down joins, one for each level; without a stored grammar, in the tasks that make the rules."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stablegrammar.functions.hashing import HashFamily, make_family
from stablegrammar.operators.build import _pieces, _rounds, breaks_numpy
from stablegrammar.operators.lineage import checkpointed, settled
from stablegrammar.operators.model import Grammar, char_of
from stablegrammar.operators.post import as_items


def _frontier(g: Grammar, ids: DataFrame | None) -> DataFrame:
    roots = g.roots if ids is None else g.roots.join(ids, "string_id", "left_semi")
    return roots.where("root_level >= 0").select("string_id", F.lit(0).cast("long").alias("at"), F.col("root_level").alias("level"), F.col("root_sym").alias("sym"))


def leaves(g: Grammar, ids: DataFrame | None = None, lo: int | None = None, hi: int | None = None) -> DataFrame:
    """(string_id, at, sym) of terminals, by levels from the top; with lo and hi, only subtrees that overlap [lo, hi) are opened."""
    g = as_items(g)
    lengths = g.rules.select(F.col("level").alias("_l"), F.col("sym").alias("_s"), "exp_len")
    child = g.rules.select("level", "sym", F.posexplode("rhs").alias("_p", "_x"))
    child = child.join(lengths, (F.col("_l") == F.col("_x.level")) & (F.col("_s") == F.col("_x.sym")), "left").withColumn("_e", F.coalesce("exp_len", F.lit(1)))
    sized = child.groupBy("level", "sym").agg(F.array_sort(F.collect_list(F.struct("_p", F.col("_x.level").alias("level"), F.col("_x.sym").alias("sym"), F.col("_x.n").alias("n"), F.col("_e").alias("e")))).alias("kids"))
    sized = checkpointed(sized.select(F.col("level").alias("_l"), F.col("sym").alias("_s"), "kids"))
    before = lambda k: F.aggregate(F.slice("kids", F.lit(1), k), F.lit(0).cast("long"), lambda acc, x: acc + x["e"] * x["n"])
    sized = checkpointed(sized.select("_l", "_s", F.transform("kids", lambda x, k: F.struct(before(k).alias("off"), x["level"].alias("level"), x["sym"].alias("sym"), x["n"].alias("n"), x["e"].alias("e"))).alias("kids")))
    out, front = [], _frontier(g, ids)
    top = g.rules.agg(F.max("level")).first()[0] or 0
    for level in range(top, 0, -1):
        here = front.where(F.col("level") == level).join(sized.where(F.col("_l") == level), F.col("sym") == F.col("_s"))
        kids = here.select("string_id", "at", F.explode("kids").alias("x")).select("string_id", F.col("at").alias("_at"), "x.*")
        kids = kids.select("string_id", "_at", "off", "level", "sym", "e", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("_i"))
        kids = kids.select("string_id", (F.col("_at") + F.col("off") + F.col("_i") * F.col("e")).alias("at"), "level", "sym", "e")
        if lo is not None:
            kids = kids.where((F.col("at") < hi) & (F.col("at") + F.col("e") > lo))
        front = settled(front.where(F.col("level") != level).unionByName(kids.drop("e")))
    return front.select("string_id", "at", "sym")


def _code(sym: Column, kind: str) -> Column:
    return F.conv(F.hex(sym), 16, 10).cast("int") if kind == "binary" else sym.cast("int")


def expand(g: Grammar, ids: DataFrame | None = None) -> DataFrame:
    """(string_id, text) of all strings, or of those named in ids."""
    kind = dict(g.roots.dtypes)["root_sym"]
    text = leaves(g, ids).select("string_id", "at", char_of(_code(F.col("sym"), kind)).alias("ch")).groupBy("string_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("at", "ch"))), lambda x: x["ch"]), "").alias("text"))
    roots = g.roots if ids is None else g.roots.join(ids, "string_id", "left_semi")
    return roots.select("string_id").join(text, "string_id", "left").select("string_id", F.coalesce("text", F.lit("")).alias("text"))


def access(g: Grammar, lo: int, hi: int, ids: DataFrame | None = None) -> DataFrame:
    """(string_id, piece): characters lo to hi - 1 (from 0) of each string, opening only what overlaps them."""
    kind = dict(g.roots.dtypes)["root_sym"]
    got = leaves(g, ids, lo, hi).where((F.col("at") >= lo) & (F.col("at") < hi))
    return got.select("string_id", "at", char_of(_code(F.col("sym"), kind)).alias("ch")).groupBy("string_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("at", "ch"))), lambda x: x["ch"]), "").alias("piece"))


class _Rules:
    """The distinct rules of one level of a batch: what names stand for, by the places of their children among the rules below."""

    def __init__(self, hi: np.ndarray, lo: np.ndarray, exp: np.ndarray, width: np.ndarray, kids: np.ndarray):
        order = np.argsort(hi, kind="stable")
        self.hi, self.lo, self.order = hi[order], lo[order], order
        self.exp, self.width, self.first, self.kids = exp, width, np.cumsum(width) - width, kids

    def places(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        at = np.searchsorted(self.hi, hi)
        while (other := self.lo[at] != lo).any():  # names that share their first half
            at[other] += 1
        return self.order[at]


def _terminals(rounds: Iterator[tuple], lo: int | None, hi: int | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(string, at, code) of the terminals of a batch, opened from the roots by its rules; with lo and hi, only subtrees that overlap [lo, hi)."""
    rules: list[_Rules | None] = [None]
    roots: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    for kind, *x in rounds:
        if kind == "rules":
            _, names_hi, names_lo, exp, _, width, _, child, below = x
            kids = below[1][child].astype(np.int64) if rules[-1] is None else rules[-1].places(below[0][child], below[1][child])
            rules.append(_Rules(names_hi, names_lo, exp, width, kids))
        elif kind == "root":
            level, names_hi, names_lo, _, _, own = x
            roots[level] = own, names_lo.astype(np.int64) if level == 0 else rules[level].places(names_hi, names_lo)
    none = np.zeros(0, np.int64)
    own, at, sym = none, none, none
    for level in range(len(rules) - 1, -1, -1):
        s, r = roots.get(level, (none, none))
        own, at, sym = np.concatenate([own, s]), np.concatenate([at, np.zeros(len(s), np.int64)]), np.concatenate([sym, r])
        if level:
            g = rules[level]
            n = g.width[sym]
            ends = np.cumsum(n)
            kids = g.kids[np.repeat(g.first[sym] - (ends - n), n) + np.arange(len(own) and int(ends[-1]))]
            size = np.ones(len(kids), np.int64) if level == 1 else rules[level - 1].exp[kids]
            before = np.cumsum(size) - size
            at = before + np.repeat(at - before[ends - n], n) if len(own) else at
            own, sym = np.repeat(own, n), kids
            if lo is not None:
                keep = (at < hi) & (at + size > lo)
                own, at, sym = own[keep], at[keep], sym[keep]
    return own, at, sym


def expand_unstored(strings: DataFrame, lo: int | None = None, hi: int | None = None, family: HashFamily | None = None, *, batch_symbols: int = 1 << 20, breaks: Callable = breaks_numpy) -> DataFrame:
    """(string_id, text) of a build without a stored grammar: each task opens the roots by the rules that it made itself.

    Without lo and hi the rows of expand(). With them those of access(): characters lo to hi - 1 (from 0), of strings that have some.
    """
    family = family or make_family()
    text = lambda codes: codes.astype("<u4").tobytes().decode("utf-32-le")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, codes, sizes in _pieces(batches, batch_symbols):
            own, at, sym = _terminals(_rounds(np.arange(len(ids)), codes, sizes, family, breaks), lo, hi)
            if lo is not None:
                keep = (at >= lo) & (at < hi)
                own, at, sym = own[keep], at[keep], sym[keep]
            sym = sym[np.lexsort((at, own))]
            n = np.bincount(own, minlength=len(ids))
            ends = np.cumsum(n)
            rows = np.arange(len(ids)) if lo is None else np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array(ids[rows]), pa.array([text(sym[ends[i] - n[i] : ends[i]]) for i in rows.tolist()], pa.string())], ["string_id", "text"])

    col = "syms" if "syms" in strings.columns else "text"
    return strings.select(F.col("string_id").cast("long"), col).mapInArrow(run, "string_id long, text string")


def usage_counts(g: Grammar, per_string: bool = False) -> DataFrame:
    """(level, sym, uses[, string_id]): how often each symbol occurs in the parse trees of all strings, summed top-down."""
    g = as_items(g)
    key = ["string_id"] if per_string else []
    mult = g.roots.where("root_level >= 0").groupBy(*key, F.col("root_level").alias("level"), F.col("root_sym").alias("sym")).agg(F.count(F.lit(1)).alias("uses"))
    edges = settled(g.rules.select(F.col("level").alias("_l"), F.col("sym").alias("_s"), F.explode("rhs").alias("x")).groupBy("_l", "_s", F.col("x.level").alias("cl"), F.col("x.sym").alias("cs")).agg(F.sum("x.n").alias("occ")))
    top = g.rules.agg(F.max("level")).first()[0] or 0
    for level in range(top, 0, -1):
        down = mult.where(F.col("level") == level).join(edges.where(F.col("_l") == level), F.col("sym") == F.col("_s")).select(*key, F.col("cl").alias("level"), F.col("cs").alias("sym"), (F.col("uses") * F.col("occ")).alias("uses"))
        mult = settled(mult.unionByName(down).groupBy(*key, "level", "sym").agg(F.sum("uses").alias("uses")))
    return mult


def shared_passages(g: Grammar, least_len: int = 50) -> DataFrame:
    """(level, sym, exp_len, strings): symbols of at least `least_len` characters that occur in two strings or more."""
    per = usage_counts(g, per_string=True)
    shared = per.where("level > 0").groupBy("level", "sym").agg(F.count(F.lit(1)).alias("strings")).where("strings > 1")
    return shared.join(g.rules.select("level", "sym", "exp_len"), ["level", "sym"]).where(F.col("exp_len") >= least_len).select("level", "sym", "exp_len", "strings")
