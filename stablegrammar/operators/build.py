"""Build: strings to one grammar. The default engine runs all rounds of a batch of strings in one task, because cuts depend on content only;
what partitions name equally is then deduplicated in one shuffle."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stablegrammar.functions.hashing import HashFamily, make_family
from stablegrammar.operators import parse
from stablegrammar.operators.lineage import checkpointed, settled
from stablegrammar.operators.model import Grammar

SCHEMA = "level int, sym binary, rhs array<binary>, exp_len long, fp long, string_id long"
#: Bytes or integers of a long string that are parsed at once.
SEGMENT = 1 << 20
_U = np.uint64
_LANES = ((_U(0x9E3779B97F4A7C15), _U(0xD6E8FEB86659FD93)), (_U(0xC2B2AE3D27D4EB4F), _U(0xA0761D6478BD642F)))


def _mix(x: np.ndarray) -> np.ndarray:
    y = x >> _U(32)
    y ^= x
    y *= _U(0xD6E8FEB86659FD93)
    z = y >> _U(32)
    y ^= z
    y *= _U(0xD6E8FEB86659FD93)
    np.right_shift(y, _U(32), out=z)
    y ^= z
    return y


def breaks_numpy(fps: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Mask of phrase starts (string starts and breaks) of strings laid end to end; `starts` are their first places."""
    n = len(fps)
    first = np.zeros(n, bool)
    first[starts] = True
    run = first.copy()
    run[1:] |= fps[1:] != fps[:-1]
    at = np.flatnonzero(run)
    f, head = fps[at], first[at]
    inner = np.zeros(len(at), bool)
    if len(at) > 2:
        inner[1:-1] = ~head[1:-1] & ~head[2:] & (f[:-2] > f[1:-1]) & (f[2:] > f[1:-1])
    first[at[inner]] = True
    return first


def local_min_numpy(fps: np.ndarray, starts: np.ndarray, width: int = 2) -> np.ndarray:
    n = len(fps)
    first = np.zeros(n, bool)
    first[starts] = True
    owner = np.cumsum(first)
    low = np.ones(n, bool)
    for k in range(1, width + 1):
        ok = np.zeros(n, bool)
        ok[k:] = (owner[k:] == owner[:-k]) & (fps[:-k] > fps[k:])
        low &= ok
        ok = np.zeros(n, bool)
        ok[:-k] = (owner[k:] == owner[:-k]) & (fps[k:] > fps[:-k])
        low &= ok
    return first | low


def _names(hi: np.ndarray, lo: np.ndarray) -> pa.Array:
    """Binary(16) array of big-endian halves."""
    data = np.empty((len(hi), 2), ">u8")
    data[:, 0], data[:, 1] = hi, lo
    return pa.Array.from_buffers(pa.binary(), len(hi), [None, pa.py_buffer(np.arange(0, 16 * len(hi) + 1, 16, dtype=np.int32)), pa.py_buffer(data.tobytes())])


def phrase_names(level: int, hi: np.ndarray, lo: np.ndarray, at: np.ndarray, length: np.ndarray, offset: np.ndarray) -> list[np.ndarray]:
    """Both halves of the names of phrases that begin at `at`; `offset` is each symbol's place in its phrase."""
    lanes, longest = [], int(length.max())
    for salt, factor in _LANES:
        power = np.cumprod(np.full(longest, factor, _U)) if longest < 1 << 16 else np.multiply.accumulate(np.full(longest, factor, _U))
        t = np.add.reduceat(_mix(lo ^ (hi * factor + salt)) * power[offset], at)
        lanes.append(_mix(t ^ _mix(length.astype(_U) * factor + np.array([level], _U) * salt)))
    return lanes


def _round(level: int, fps: np.ndarray, hi: np.ndarray, lo: np.ndarray, exp: np.ndarray, mask: np.ndarray, family: HashFamily) -> tuple[tuple, tuple, tuple]:
    """The distinct phrases that a mask of phrase starts makes: what _rounds() gives of them but the symbols below, the symbols of the level
    (fps, hi, lo, exp), and (places of phrases, their order by name, which are new there, order of the distinct ones)."""
    at = np.flatnonzero(mask)
    length = np.diff(np.append(at, len(fps)))
    offset = np.arange(len(fps)) - np.repeat(at, length)
    longest = int(length.max())
    h = family[level]
    power = np.ones(longest, np.int64)
    for j in range(1, longest):
        power[j] = power[j - 1] * h.c % h.p
    total = np.add.reduceat(fps * power[offset] % h.p, at) % h.p
    lanes = phrase_names(level, hi, lo, at, length, offset)
    next_exp = np.add.reduceat(exp, at)
    next_fp = (total * h.a + h.b) % h.p % h.m
    order = np.lexsort((lanes[1], lanes[0])) if len(at) < 64 else np.argsort(lanes[0])  # a tie there may repeat a rule, which the merge drops
    a, b = lanes[0][order], lanes[1][order]
    new = np.ones(len(order), bool)
    new[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
    pick = order[new]
    uses = np.diff(np.append(np.flatnonzero(new), len(order)))
    back = np.argsort(pick)
    pick, uses = pick[back], uses[back]
    width = length[pick]
    ends = np.cumsum(width)
    child = np.repeat(at[pick] - (ends - width), width) + np.arange(int(ends[-1]))
    return ("rules", level, lanes[0][pick], lanes[1][pick], next_exp[pick], next_fp[pick], width, uses, child), (next_fp, lanes[0], lanes[1], next_exp), (at, order, new, back)


def _rounds(ids: np.ndarray, codes: np.ndarray, sizes: np.ndarray, family: HashFamily, breaks: Callable, on_round: Callable | None = None, on_symbols: Callable | None = None, indexed: bool = False) -> Iterator[tuple]:
    """All rounds over the strings of a batch: ("root", level, hi, lo, exp, fp, ids), ("empty", ids), and for each round
    ("rules", level, hi, lo, exp, fp, lengths, uses, child, (hi, lo, exp) below) of its distinct phrases: `child` has the places of their
    children, end to end, among the symbols below. on_symbols(level, ids, sizes, hi, lo) is told of the strings that a round leaves, end to end.
    If `indexed`, what is below has a fourth array, each symbol's place among the rules of its level as they were given (terminals: their codes).
    """
    h = family[0]
    fps = (np.int64(h.a) * codes.astype(np.int64) + h.b) % h.p % h.m
    hi, lo, exp = np.zeros(len(codes), _U), codes.astype(_U), np.ones(len(codes), np.int64)
    index = codes.astype(np.int32) if indexed else None
    level = 0
    while len(ids):
        ended = sizes <= 1
        if ended.any():
            place = (np.cumsum(sizes) - sizes)[ended]
            full = sizes[ended] == 1
            own, at = ids[ended], place[full]
            if full.any():
                yield "root", level, hi[at], lo[at], exp[at], fps[at], own[full]
            if not full.all():
                yield "empty", own[~full]
            keep = np.repeat(~ended, sizes)
            fps, hi, lo, exp, ids, sizes = fps[keep], hi[keep], lo[keep], exp[keep], ids[~ended], sizes[~ended]
            index = index[keep] if indexed else None
            if not len(ids):
                break
        level += 1
        starts = np.cumsum(sizes) - sizes
        mask = breaks(fps, starts)
        rules, above, (at, order, new, back) = _round(level, fps, hi, lo, exp, mask, family)
        if on_round:
            on_round(level, len(ids), len(fps), len(at), len(back))
        yield (*rules, (hi, lo, exp, index)) if indexed else (*rules, (hi, lo, exp))
        if indexed:
            place, index = np.empty(len(back), np.int32), np.empty(len(at), np.int32)
            place[back] = np.arange(len(back), dtype=np.int32)
            index[order] = place[np.cumsum(new) - 1]
        sizes = np.add.reduceat(mask.astype(np.int64), starts)
        fps, hi, lo, exp = above
        if on_symbols:
            on_symbols(level, ids, sizes, hi, lo)


def _long_rounds(string_id: int, segments: Iterable[np.ndarray], family: HashFamily) -> Iterator[tuple]:
    """_rounds() of one long string, whose codes come in segments. Each level keeps only what follows its last certain break.

    Whether a run starts a phrase by breaks_numpy() is certain once a symbol of the next run is there. Rules are distinct within a segment only.
    """
    kept: list[tuple] = []  # for each level: fps, hi, lo, exp that wait
    sent: list[bool] = []  # whether a level has given phrases

    def feed(level: int, fps: np.ndarray, hi: np.ndarray, lo: np.ndarray, exp: np.ndarray, last: bool) -> Iterator[tuple]:
        if level == len(kept):
            kept.append((fps[:0], hi[:0], lo[:0], exp[:0]))
            sent.append(False)
        fps, hi, lo, exp = (np.concatenate(x) for x in zip(kept[level], (fps, hi, lo, exp), strict=True))
        if last and not sent[level] and len(fps) == 1:
            yield "root", level, hi, lo, exp, fps, np.array([string_id])
            return
        mask = breaks_numpy(fps, np.zeros(1, np.int64))
        end = len(fps) if last else int(np.flatnonzero(mask)[-1])
        kept[level] = fps[end:], hi[end:], lo[end:], exp[end:]
        if end:
            sent[level] = True
            rules, above, _ = _round(level + 1, fps[:end], hi[:end], lo[:end], exp[:end], mask[:end], family)
            yield *rules, (hi, lo, exp)
            yield from feed(level + 1, *above, last)

    h, codes = family[0], None
    for following in chain(segments, [None]):
        if codes is not None:
            fps = (np.int64(h.a) * codes.astype(np.int64) + h.b) % h.p % h.m
            yield from feed(0, fps, np.zeros(len(codes), _U), codes.astype(_U), np.ones(len(codes), np.int64), following is None)
        codes = following


def build_strings(ids: np.ndarray, codes: np.ndarray, sizes: np.ndarray, family: HashFamily, breaks: Callable = breaks_numpy, on_round: Callable | None = None) -> Iterator[pa.RecordBatch]:
    """All rounds over the strings of a batch: rows of distinct rules (string_id null), and of roots (rhs null).

    on_round(level, strings, symbols, phrases, distinct) is told of each round.
    """
    return _tables(_rounds(ids, codes, sizes, family, breaks, on_round))


def _tables(rounds: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
    columns = ["level", "sym", "rhs", "exp_len", "fp", "string_id"]
    for kind, *x in rounds:
        if kind == "root":
            level, hi, lo, exp, fp, own = x
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), level, np.int32)), _names(hi, lo), pa.nulls(len(own), pa.list_(pa.binary())), pa.array(exp), pa.array(fp), pa.array(own)], columns)
        elif kind == "empty":
            k = len(x[0])
            yield pa.RecordBatch.from_arrays([pa.array(np.full(k, -1, np.int32)), pa.nulls(k, pa.binary()), pa.nulls(k, pa.list_(pa.binary())), pa.array(np.zeros(k, np.int64)), pa.nulls(k, pa.int64()), pa.array(x[0])], columns)
        else:
            level, hi, lo, exp, fp, width, _, child, below = x
            rhs = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(width)]).astype(np.int32)), _names(below[0][child], below[1][child]))
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(hi), level, np.int32)), _names(hi, lo), rhs, pa.array(exp), pa.array(fp), pa.nulls(len(hi), pa.int64())], columns)


def _pieces(batches: Iterator[pa.RecordBatch], batch_symbols: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(ids, symbols end to end, sizes) of about `batch_symbols` symbols each, one long string making a piece of its own; without null strings."""
    ids, held, n = [], [], 0
    done = lambda: (np.array(ids, np.int64), np.concatenate(held) if len(held) > 1 else held[0], np.array([len(c) for c in held], np.int64))
    for x in batches:
        for i, v in zip(x.column(0).to_pylist(), x.column(1), strict=True):
            if v.is_valid:
                c = np.frombuffer(v.as_py().encode("utf-32-le"), np.uint32) if pa.types.is_string(v.type) else np.asarray(v.values.to_numpy(zero_copy_only=False), np.uint32)
                if held and n + len(c) > batch_symbols:
                    yield done()
                    ids, held, n = [], [], 0
                ids.append(i)
                held.append(c)
                n += len(c)
    if held:
        yield done()


def _segments(v: pa.Scalar) -> Iterator[np.ndarray]:
    """A long string's codes, SEGMENT bytes of its text or SEGMENT of its integers at once, without a copy of the whole."""
    if not pa.types.is_string(v.type):
        for i in range(0, len(v.values), SEGMENT):
            yield np.asarray(v.values.slice(i, SEGMENT).to_numpy(zero_copy_only=False), np.uint32)
        return
    data, at = memoryview(v.as_buffer()), 0
    while at < len(data):
        end = min(at + SEGMENT, len(data))
        while end < len(data) and data[end] & 0xC0 == 0x80:  # within a character
            end += 1
        yield np.frombuffer(str(data[at:end], "utf-8").encode("utf-32-le"), np.uint32)
        at = end


def _apart(batches: Iterator[pa.RecordBatch], least: int) -> Iterator[pa.RecordBatch | tuple]:
    """The batches without the strings of more than `least` bytes of text or integers, and these alone, as (id, value)."""
    for x in batches:
        short = []
        for i, v in enumerate(x.column(1)):
            if v.is_valid and (v.as_buffer().size if pa.types.is_string(v.type) else len(v.values)) > least:
                yield x.column(0)[i].as_py(), v
            else:
                short.append(i)
        yield x if len(short) == len(x) else x.take(pa.array(short, pa.int64()))


def _kernel(family: HashFamily, batch_symbols: int, breaks: Callable) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        todo = _apart(batches, batch_symbols) if breaks is breaks_numpy else iter(batches)
        while True:
            met: list[tuple] = []

            def short(met: list = met) -> Iterator[pa.RecordBatch]:
                for x in todo:
                    if isinstance(x, tuple):
                        met.append(x)
                        return
                    yield x

            for ids, codes, sizes in _pieces(short(), batch_symbols):
                yield from build_strings(ids, codes, sizes, family, breaks)
            if not met:
                break
            yield from _tables(_long_rounds(met[0][0], _segments(met[0][1]), family))

    return run


def build_grammar(strings: DataFrame, family: HashFamily | None = None, *, engine: str = "arrow", batch_symbols: int = 1 << 22, breaks: Callable | None = None, staged: bool = True, packed: bool = False) -> Grammar:
    """The grammar of strings(string_id, text) or strings(string_id, syms).

    engine "arrow": all rounds in one narrow pass, then one shuffle by (level, sym). engine "dataframe": a driver loop of window rounds
    with string names, for SQL parity. Null strings are left out; empty ones get a root without symbol at level -1.
    `packed` stores the rules as parcels (operators/packed.py), about as large as the input; its tables of rules and roots are read from them.
    """
    family = family or make_family()
    if packed:
        from stablegrammar.operators.packed import build_packed

        return build_packed(strings, family, breaks=breaks or breaks_numpy)
    if engine == "dataframe":
        return _build_by_windows(strings, family, breaks or parse.position_types)
    col = "syms" if "syms" in strings.columns else "text"
    rows = strings.select(F.col("string_id").cast("long"), col).mapInArrow(_kernel(family, batch_symbols, breaks or breaks_numpy), SCHEMA)
    rows = checkpointed(rows) if staged else rows  # read twice below
    rules = rows.where("string_id is null").drop("string_id").dropDuplicates(["level", "sym"]).select("level", "sym", "rhs", F.size("rhs").alias("rhs_len"), "exp_len", "fp")
    roots = rows.where("string_id is not null").select("string_id", F.col("sym").alias("root_sym"), F.col("level").alias("root_level"), F.col("exp_len").alias("n_symbols"))
    return Grammar(checkpointed(rules) if staged else rules, roots, family)


def _build_by_windows(strings: DataFrame, family: HashFamily, breaks: Callable) -> Grammar:
    spark = strings.sparkSession
    seq = settled(parse.symbols(strings, family).withColumn("exp_len", F.lit(1).cast("long")))
    col = "syms" if "syms" in strings.columns else "text"
    empty = strings.where(F.size(col) == 0 if col == "syms" else F.col(col) == "").select("string_id", F.lit(None).cast("string").alias("root_sym"), F.lit(-1).alias("root_level"), F.lit(0).cast("long").alias("n_symbols"))
    roots, rules = empty, spark.createDataFrame([], "level int, sym string, rhs array<string>, rhs_len int, exp_len long, fp long")
    level = 0
    while True:
        alone = seq.groupBy("string_id").agg(F.count(F.lit(1)).alias("_n")).where("_n = 1").select("string_id")
        done = seq.join(alone, "string_id", "left_semi").select("string_id", F.col("sym").alias("root_sym"), F.lit(level).alias("root_level"), F.col("exp_len").alias("n_symbols"))
        roots = roots.unionByName(done)
        seq = settled(seq.join(alone, "string_id", "left_anti"))
        if seq.isEmpty():
            break
        level += 1
        marked = breaks(seq)
        phrases = parse.cut_phrases(marked, level, family)
        no = marked.groupBy("string_id").agg(F.array_sort(F.collect_list(F.struct("pos", "exp_len"))).alias("_e"))
        whole = settled(phrases.join(no, "string_id").withColumn("exp_len", F.aggregate(F.slice("_e.exp_len", F.col("start").cast("int"), F.col("len")), F.lit(0).cast("long"), lambda a, x: a + x)).drop("_e"))
        rules = rules.unionByName(whole.dropDuplicates(["sym"]).select(F.lit(level).alias("level"), "sym", "rhs", F.col("len").alias("rhs_len"), "exp_len", "fp"))
        seq = whole.select("string_id", F.col("phrase_no").alias("pos"), "sym", "fp", "exp_len")
    return Grammar(settled(rules), settled(roots), family)
