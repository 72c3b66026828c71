"""A build stored as parcels: rules by their places in the task that made them, without a name.

A name follows from the names of a rule's children, so a parcel keeps only the places of the children, level by level, and a rule's place is
its rank by name in its level of the parcel. Dense ids then take one exchange of names: the receiver of a range of names, which is a stretch
of the dense order, answers each parcel with the ranks of what it sent. One parcel owns a rule that several hold.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stablegrammar.functions.hashing import HashFamily
from stablegrammar.operators.build import SCHEMA, _names, _pieces, _rounds, breaks_numpy, phrase_names
from stablegrammar.operators.lineage import settled
from stablegrammar.operators.model import Grammar
from stablegrammar.operators.rule_stats import _ranges

_U = np.uint64
#: Children that a parcel holds, about, before it is closed.
PARCEL = 1 << 24
#: Children whose names are made at once, input rows of one Arrow batch at most, and answers of one.
CHUNK, ARROW_ROWS, SENT = 1 << 20, 256, 128
PARCELS = "parcel long, counts array<long>, widths array<binary>, children array<binary>, root_ids array<long>, root_levels array<int>, root_places array<int>"
DENSE = "level int, sym long, rhs array<long>, rhs_len int, exp_len long, fp long, string_id long"
#: Rows of one batch of dense rules on their way back.
ROWS = 1 << 17


def _coded(x: np.ndarray) -> bytes:
    """Numbers byte by byte, compressed."""
    return pa.compress(np.ascontiguousarray(x).view(np.uint8).reshape(len(x), -1).T.tobytes(), codec="zstd", asbytes=True) if len(x) else b""


def _decoded(block: bytes, n: int, kind: type) -> np.ndarray:
    if not n:
        return np.zeros(0, kind)
    width = np.dtype(kind).itemsize
    raw = np.frombuffer(pa.decompress(block, n * width, codec="zstd", asbytes=True), np.uint8)
    return np.ascontiguousarray(raw.reshape(width, n).T).view(kind).ravel()


def _spread(starts: np.ndarray, widths: np.ndarray) -> np.ndarray:
    """The places starts[i], starts[i] + 1, … of widths[i] each, end to end."""
    ends = np.cumsum(widths)
    return np.repeat(starts - (ends - widths), widths) + np.arange(int(ends[-1]) if len(ends) else 0)


def _give_back() -> None:
    """Free memory goes back to the system; a worker that waits for its next task would keep it."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc
    if trim:
        trim(0)


def _lean(run: Callable) -> Callable:
    """A task's function that gives its memory back at the end, when its own arrays are gone."""

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _give_back()
        yield from run(batches)
        _give_back()

    return whole


def _small_batches(strings: DataFrame) -> None:
    """Bound the rows of the session's Arrow batches, which is a matter of memory only; a lower bound stays."""
    name, spark = "spark.sql.execution.arrow.maxRecordsPerBatch", strings.sparkSession
    if not 0 < int(spark.conf.get(name)) <= ARROW_ROWS:
        spark.conf.set(name, str(ARROW_ROWS))


class _Parcel:
    """Rules of several batches, for one parcel: level -> (hi, lo, widths, children) of each batch, and roots."""

    def __init__(self) -> None:
        self.levels: dict[int, list[list]] = {}
        self.terminals: list[np.ndarray] = []
        self.roots: list[tuple] = []
        self.batches = self.size = 0

    def add(self, rounds: Iterator[tuple], codes: np.ndarray) -> None:
        self.terminals.append(np.unique(codes).astype(np.int32))
        for kind, *x in rounds:
            if kind == "rules":
                level, hi, lo, _, _, width, _, child, below = x
                kept = self.levels.setdefault(level, [])
                kept += [None] * (self.batches - len(kept))  # batches of shorter strings
                kept.append([hi, lo, width.astype(np.int32), below[3][child]])
                self.size += len(child)
            elif kind == "root":
                level, hi, lo, _, _, own = x
                self.roots.append((level, hi, lo, own))
            else:
                self.roots.append((-1, None, None, x[0]))
        self.batches += 1

    def closed(self, parcel: int) -> pa.RecordBatch:
        codes = np.unique(np.concatenate(self.terminals)) if self.terminals else np.zeros(0, np.int32)
        names = {0: (np.zeros(len(codes), _U), codes.astype(_U))}
        counts, widths, children = [len(codes)], [], [_coded(codes)]
        places = None  # of each batch's rules of the level below, in the parcel
        for level in range(1, max(self.levels, default=0) + 1):
            kept = self.levels.pop(level)
            kept += [None] * (self.batches - len(kept))
            own = [x for x in kept if x]
            hi, lo, width = (np.concatenate([x[k] for x in own]) for k in range(3))
            below = np.concatenate([np.searchsorted(codes, x[3]).astype(np.int32) if level == 1 else places[i][x[3]] for i, x in enumerate(kept) if x])
            order = np.lexsort((lo, hi))
            hi, lo = hi[order], lo[order]
            new = np.append(True, (hi[1:] != hi[:-1]) | (lo[1:] != lo[:-1]))
            place = np.empty(len(order), np.int32)
            place[order] = np.cumsum(new) - 1
            ends = np.cumsum([len(x[0]) if x else 0 for x in kept])
            places = [place[e - (len(x[0]) if x else 0) : e] for x, e in zip(kept, ends, strict=True)]
            pick = order[new]
            at = (np.cumsum(width) - width)[pick]
            width = width[pick]
            names[level] = hi[new], lo[new]
            counts.append(len(pick))
            widths.append(_coded(width))
            children.append(_coded(below[_spread(at, width)]))
        ids, levels, own = [], [], []
        for level, hi, lo, of in self.roots:
            ids += of.tolist()
            levels += [level] * len(of)
            own += [-1] * len(of) if level < 0 else _found(*names[level], hi, lo).tolist()
        return pa.RecordBatch.from_arrays([pa.array([parcel]), pa.array([counts]), pa.array([widths], pa.list_(pa.binary())), pa.array([children], pa.list_(pa.binary())), pa.array([ids], pa.list_(pa.int64())), pa.array([levels], pa.list_(pa.int32())), pa.array([own], pa.list_(pa.int32()))], ["parcel", "counts", "widths", "children", "root_ids", "root_levels", "root_places"])


def _found(hi: np.ndarray, lo: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Places of names (a, b), all of which are among (hi, lo), in order."""
    at = np.searchsorted(hi, a)
    while (other := (hi[at] != a) | (lo[at] != b)).any():  # names that share their first half
        at[other] += 1
    return at


def _levels(row: dict, names: bool = True, family: HashFamily | None = None) -> Iterator[tuple]:
    """(level, hi, lo, exp, fp, widths, starts, children) of a parcel's levels, from the terminals, which have no children.

    Names are made only if `names`, and characters below and fingerprints only with a family.
    """
    codes = _decoded(row["children"][0], row["counts"][0], np.int32)
    hi, lo, exp, fp = np.zeros(len(codes), _U), codes.astype(_U), np.ones(len(codes), np.int64), None
    if family:
        h = family[0]
        fp = (np.int64(h.a) * codes.astype(np.int64) + h.b) % h.p % h.m
    yield 0, hi, lo, exp, fp, None, None, None
    for level, (n, w, c) in enumerate(zip(row["counts"][1:], row["widths"], row["children"][1:], strict=True), 1):
        width = _decoded(w, n, np.int32).astype(np.int64)
        at = np.cumsum(width) - width
        child = _decoded(c, int(width.sum()), np.int32)
        below = hi, lo, exp, fp
        if names:
            hi, lo = np.empty(n, _U), np.empty(n, _U)
        if family:
            h, longest = family[level], int(width.max())
            exp, fp, power = np.empty(n, np.int64), np.empty(n, np.int64), np.ones(longest, np.int64)
            for j in range(1, longest):
                power[j] = power[j - 1] * h.c % h.p
        cuts = np.unique(np.append(np.searchsorted(at, np.arange(0, len(child), CHUNK)), n)).tolist()
        for i, j in zip(cuts, cuts[1:], strict=False):
            first, last = int(at[i]), int(at[j]) if j < n else len(child)
            own, some = at[i:j] - first, child[first:last]
            offset = np.arange(len(some)) - np.repeat(own, width[i:j])
            if names:
                hi[i:j], lo[i:j] = phrase_names(level, below[0][some], below[1][some], own, width[i:j], offset)
            if family:
                total = np.add.reduceat(below[3][some] * power[offset] % h.p, own) % h.p
                exp[i:j], fp[i:j] = np.add.reduceat(below[2][some], own), (total * h.a + h.b) % h.p % h.m
        yield level, hi, lo, exp, fp, width, at, child


def _rows(batches: Iterator[pa.RecordBatch], large: bool = True) -> Iterator[dict]:
    for x in batches:
        for i in range(len(x)):
            yield x.slice(i, 1).to_pylist()[0]
            if large:
                _give_back()


def build_packed(strings: DataFrame, family: HashFamily, *, batch_symbols: int = 1 << 20, breaks: Callable = breaks_numpy) -> Grammar:
    """The grammar of strings, stored as parcels; the tables of its rules, with content names, and roots are read from them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, n, parcel = TaskContext.get().partitionId(), 0, _Parcel()
        for ids, codes, sizes in _pieces(batches, batch_symbols):
            parcel.add(_rounds(ids, codes, sizes, family, breaks, indexed=True), codes)
            if parcel.size >= PARCEL:
                yield parcel.closed(part << 32 | n)
                n, parcel = n + 1, _Parcel()
        if parcel.batches:
            yield parcel.closed(part << 32 | n)

    def named(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        columns = ["level", "sym", "rhs", "exp_len", "fp", "string_id"]
        for row in _rows(batches):
            below, ids, levels, places = None, *(np.array(row[k], np.int64) for k in ("root_ids", "root_levels", "root_places"))
            if (k := int((levels < 0).sum())):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(k, -1, np.int32)), pa.nulls(k, pa.binary()), pa.nulls(k, pa.list_(pa.binary())), pa.array(np.zeros(k, np.int64)), pa.nulls(k, pa.int64()), pa.array(ids[levels < 0])], columns)
            for level, hi, lo, exp, fp, width, at, child in _levels(row, family=family):
                if level:
                    rhs = pa.ListArray.from_arrays(pa.array(np.append(at, len(child)).astype(np.int32)), _names(below[0][child], below[1][child]))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(hi), level, np.int32)), _names(hi, lo), rhs, pa.array(exp), pa.array(fp), pa.nulls(len(hi), pa.int64())], columns)
                own = levels == level
                if own.any():
                    p, k = places[own], int(own.sum())
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(k, level, np.int32)), _names(hi[p], lo[p]), pa.nulls(k, pa.list_(pa.binary())), pa.array(exp[p]), pa.array(fp[p]), pa.array(ids[own])], columns)
                below = hi, lo

    col = "syms" if "syms" in strings.columns else "text"
    _small_batches(strings)
    packed = settled(strings.select(F.col("string_id").cast("long"), col).mapInArrow(_lean(run), PARCELS))
    rows = packed.mapInArrow(_lean(named), SCHEMA)
    rules = rows.where("rhs is not null").drop("string_id").dropDuplicates(["level", "sym"]).select("level", "sym", "rhs", F.size("rhs").alias("rhs_len"), "exp_len", "fp")
    roots = rows.where("rhs is null").select("string_id", F.col("sym").alias("root_sym"), F.col("level").alias("root_level"), F.col("exp_len").alias("n_symbols"))
    return Grammar(rules, roots, family, packed=packed)


def ranks(packed: DataFrame) -> DataFrame:
    """Answers (bucket, parcel, sent, block) to parcels: of what each sent to a range of names, level by level, the ranks there and whether
    it owns the rule. A row of each range without a parcel has `counts` of the range's distinct names by level."""
    ranges = _ranges(packed)
    shift = _U(64 - ranges.bit_length() + 1)

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            hi, lo = zip(*((x[1], x[2]) for x in _levels(row)), strict=True)
            level = np.repeat(np.arange(len(hi)), [len(x) for x in hi])
            hi, lo = np.concatenate(hi), np.concatenate(lo)
            bucket = (hi >> shift).astype(np.int64)
            if not len(bucket):  # of empty strings only
                continue
            order = np.argsort(bucket, kind="stable")
            hi, lo, level, bucket = hi[order], lo[order], level[order], bucket[order]
            at = np.flatnonzero(np.diff(bucket, prepend=-1))
            ends = np.append(at[1:], len(bucket))
            for k in range(0, len(at), SENT):
                places = list(zip(at[k : k + SENT].tolist(), ends[k : k + SENT].tolist(), strict=True))
                sent = [np.bincount(level[a:b]).astype(np.int32).tobytes() for a, b in places]
                blocks = [lo[a:b].tobytes() + _coded(np.diff(hi[a:b], prepend=_U(0))) for a, b in places]
                yield pa.RecordBatch.from_arrays([pa.array(bucket[at[k : k + SENT]]), pa.array([row["parcel"]] * len(places)), pa.array(sent, pa.binary()), pa.array(blocks, pa.binary())], ["bucket", "parcel", "sent", "block"])

    def receive(table: pa.Table) -> pa.Table:
        rows = sorted(table.select(["parcel", "sent", "block"]).to_pylist(), key=lambda r: r["parcel"])
        sent = [np.frombuffer(r["sent"], np.int32) for r in rows]
        sizes = [int(x.sum()) for x in sent]
        lo = np.concatenate([np.frombuffer(r["block"], _U, n) for r, n in zip(rows, sizes, strict=True)])
        hi = np.concatenate([np.cumsum(_decoded(r["block"][8 * n :], n, _U), dtype=_U) for r, n in zip(rows, sizes, strict=True)])
        level = np.concatenate([np.repeat(np.arange(len(x), dtype=np.uint8), x) for x in sent])
        order = np.lexsort((lo, hi, level))  # equal names stay in order of parcels
        a, b, c = hi[order], lo[order], level[order]
        new = np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1]) | (c[1:] != c[:-1]))
        counts = np.bincount(c[new])
        rank, owner = np.empty(len(order), np.uint32), np.empty(len(order), bool)
        rank[order] = np.cumsum(new) - 1 - (np.cumsum(counts) - counts)[c]
        owner[order] = new
        bucket, out = table.column("bucket")[0].as_py(), []
        _give_back()
        for r, n, end in zip(rows, sizes, np.cumsum(sizes).tolist(), strict=True):
            own = np.packbits(owner[end - n : end]).tobytes() + _coded(np.diff(rank[end - n : end], prepend=np.uint32(0)))
            out.append({"bucket": bucket, "parcel": r["parcel"], "sent": r["sent"], "block": own, "counts": None})
        out.append({"bucket": bucket, "parcel": None, "sent": None, "block": None, "counts": counts.tolist()})
        return pa.Table.from_pylist(out, schema=arrow)

    arrow = pa.schema([("bucket", pa.int64()), ("parcel", pa.int64()), ("sent", pa.binary()), ("block", pa.binary()), ("counts", pa.list_(pa.int64()))])
    names = packed.select("parcel", "counts", "widths", "children").mapInArrow(_lean(send), "bucket long, parcel long, sent binary, block binary")
    return names.groupBy("bucket").applyInArrow(receive, "bucket long, parcel long, sent binary, block binary, counts array<long>")


def dense_packed(g: Grammar) -> Grammar:
    """Dense long ids of a packed grammar: terminals 1..sigma by code, then level after level by content name. Its tables aren't stored."""
    family, answers = g.family, settled(ranks(g.packed), once=True)
    each = answers.where("parcel is null").select("bucket", F.posexplode("counts").alias("level", "n"))
    below = Window.orderBy("level").rowsBetween(Window.unboundedPreceding, -1)
    off = each.groupBy("level").agg(F.sum("n").alias("n")).select("level", F.coalesce(F.sum("n").over(below), F.lit(0)).alias("off"))  # one row per level
    base = F.sum("n").over(Window.partitionBy("level").orderBy("bucket")) - F.col("n") + F.col("off")
    bases = each.join(F.broadcast(off), "level").withColumn("base", base).groupBy("bucket").agg(F.array_sort(F.collect_list(F.struct("level", "base"))).alias("_x")).select("bucket", F.col("_x.base").alias("bases"))
    answers = answers.where("parcel is not null").drop("counts").join(bases, "bucket")

    def numbered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Each parcel comes before its answers, and these in order of their ranges."""
        parcel = None
        for r in _rows(batches, False):
            if r["bucket"] is None:
                if parcel:
                    yield from made(parcel, ids, owner)
                parcel, ids, owner = r, [[] for _ in r["counts"]], [[] for _ in r["counts"]]
                continue
            sent = np.frombuffer(r["sent"], np.int32)
            n = int(sent.sum())
            bits = np.unpackbits(np.frombuffer(r["block"], np.uint8, -(-n // 8)), count=n).astype(bool)
            rank = np.cumsum(_decoded(r["block"][-(-n // 8) :], n, np.uint32), dtype=np.uint32)
            for level, (k, end) in enumerate(zip(sent.tolist(), np.cumsum(sent).tolist(), strict=True)):
                if k:
                    ids[level].append(rank[end - k : end] + np.int64(r["bases"][level] + 1))
                    owner[level].append(bits[end - k : end])
        if parcel:
            yield from made(parcel, ids, owner)

    def made(parcel: dict, ids: list, owner: list) -> Iterator[pa.RecordBatch]:
        root_ids, levels, places = (np.array(parcel[k], np.int64) for k in ("root_ids", "root_levels", "root_places"))
        null = lambda n, kind=pa.int64(): pa.nulls(n, kind)  # noqa: B008, E731
        batch = lambda *x: pa.RecordBatch.from_arrays(list(x), ["level", "sym", "rhs", "rhs_len", "exp_len", "fp", "string_id"])
        lists, below = pa.list_(pa.int64()), None
        if (k := int((levels < 0).sum())):
            yield batch(pa.array(np.full(k, -1, np.int32)), null(k), null(k, lists), null(k, pa.int32()), pa.array(np.zeros(k, np.int64)), null(k), pa.array(root_ids[levels < 0]))
        for level, _, _, exp, fp, width, at, child in _levels(parcel, False, family):
            sym = np.concatenate(ids[level] or [np.zeros(0, np.int64)])
            mine = np.flatnonzero(np.concatenate(owner[level])) if level else []
            for i in range(0, len(mine), ROWS):
                m = mine[i : i + ROWS]
                rhs = pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(width[m])).astype(np.int32)), pa.array(below[child[_spread(at[m], width[m])]]))
                yield batch(pa.array(np.full(len(m), level, np.int32)), pa.array(sym[m]), rhs, pa.array(width[m].astype(np.int32)), pa.array(exp[m]), pa.array(fp[m]), null(len(m)))
            if (own := levels == level).any():
                p, k = places[own], int(own.sum())
                yield batch(pa.array(np.full(k, level, np.int32)), pa.array(sym[p]), null(k, lists), null(k, pa.int32()), pa.array(exp[p]), pa.array(fp[p]), pa.array(root_ids[own]))
            below, ids[level], owner[level] = sym, None, None
        _give_back()

    both = g.packed.unionByName(answers, allowMissingColumns=True).repartition("parcel").sortWithinPartitions("parcel", F.asc_nulls_first("bucket"))
    rows = both.mapInArrow(_lean(numbered), DENSE)
    rules = rows.where("rhs is not null").drop("string_id")
    roots = rows.where("rhs is null").select("string_id", F.col("sym").alias("root_sym"), F.col("level").alias("root_level"), F.col("exp_len").alias("n_symbols"))
    return Grammar(rules, roots, g.family)
