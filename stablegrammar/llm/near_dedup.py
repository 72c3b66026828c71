"""MinHash near-dedup with SetSketch registers.

A register is the minimum of one exponential hash over a document's shingles, truncated to exponentially spaced steps. Registers merge
by maximum of steps and their equality is locality-sensitive: bands of register values bring candidates together, a joint likelihood of
the register comparisons and the two set sizes discards candidates that cannot reach the threshold, and the full sets confirm the rest.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stablegrammar.llm.common import give_back, map_texts, settled, small_batches, small_or_shuffled, texts
from stablegrammar.llm.components import components

BANDS, ROWS = 28, 6
#: A pair at the threshold may be missed with about this probability at most; lower thresholds take fewer rows a band.
MISSED = 3e-6
#: Turns in which each bucket that spans components is compared with one hub of its own, before what is left is joined exactly.
HUB_TURNS = 2
#: Documents that share a prefix shingle are compared in pairs up to this number; larger crowds by what sets them apart from their centre.
CROWD = 64
#: Turns in which crowds get centres; what is crowded still is then compared in pairs.
CENTRE_TURNS = 3
#: About so many documents of a crowd, drawn by hash, say where its centre lies. Any centre gives the same links; a near one gives less work.
CENTRE_OF = 15
#: UTF-8 bytes of the texts that a kernel takes at once, and words whose hashes it keeps: a worker's memory grows with both.
BATCH_BYTES, CACHED_WORDS = 1 << 20, 100_000
#: SetSketch parameters: base of the steps, rate of the exponentials, number of steps.
BASE, RATE, STEPS = 1.001, 20.0, 65_534
_MASK = (1 << 64) - 1


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


class Shingler:
    """Sets of hashed word shingles: A-Z in lower case, words between ASCII white space; a shorter text is one shingle."""

    def __init__(self, words: int = 5, cached: int = CACHED_WORDS):
        self.words, self.cached, self.cache = words, cached, {}
        self.factors = _mix(np.arange(1, words + 1, dtype=np.uint64)) | np.uint64(1)

    def __call__(self, text: str) -> np.ndarray:
        cache = self.cache
        if len(cache) > self.cached:
            cache.clear()
        own = text.encode().lower().split()  # of bytes: A-Z only, and exactly the six ASCII white-space characters
        if not own:
            return np.zeros(0, np.uint64)
        found = list(map(cache.get, own))
        if None in found:
            for k, x in enumerate(found):
                if x is None:
                    found[k] = cache[own[k]] = xxhash.xxh3_64_intdigest(own[k])
        w = np.fromiter(found, np.uint64, len(found))
        k = min(self.words, len(w))
        total = np.full(len(w) - k + 1, k, np.uint64)
        for j in range(k):
            total += w[j : len(w) - k + 1 + j] * self.factors[j]
        return np.unique(_mix(total))


def registers(hashes: np.ndarray, starts: np.ndarray, m: int = BANDS * ROWS) -> np.ndarray:
    """Sketches (one row of `m` uint16 steps each) of sets laid end to end; every set has an element."""
    salts = _mix(np.arange(1, 2 * m + 1, dtype=np.uint64))
    least = np.empty((m, len(starts)), np.uint64)
    for j in range(m):
        least[j] = np.minimum.reduceat((hashes ^ salts[j]) * (salts[m + j] | np.uint64(1)), starts)
    x = -np.log1p(-(least.T.astype(np.float64) + 1) / 2.0**64 * (1 - 2.0**-53)) / RATE
    return np.clip(np.floor(1 - np.log(x) / np.log(BASE)), 0, STEPS + 1).astype(np.uint16)


def banding(percent: int) -> tuple[int, int]:
    """(bands, rows) of BANDS * ROWS registers: the most rows that miss no more than MISSED of the pairs at the threshold."""
    for rows in range(ROWS, 1, -1):
        bands = BANDS * ROWS // rows
        if (1 - (percent / 100) ** rows) ** bands <= MISSED:
            return bands, rows
    return BANDS * ROWS, 1


def band_keys(regs: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    r = regs[:, : bands * rows].astype(np.uint64).reshape(len(regs), bands, rows)
    key = np.broadcast_to(_mix(np.arange(bands, dtype=np.uint64) + np.uint64(77)), r.shape[:2]).copy()
    for k in range(rows):
        key = _mix(key ^ r[:, :, k]) + np.uint64(k + 1)
    return key.view(np.int64)


def may_reach(a: np.ndarray, b: np.ndarray, na: np.ndarray, nb: np.ndarray, least: float, slack: float = 20.0) -> np.ndarray:
    """Whether the joint likelihood leaves a similarity of `least` possible: its best value there is within e^-slack of the best anywhere."""
    up, down = (a > b).sum(1), (a < b).sum(1)
    same = a.shape[1] - up - down
    u, v = na / (na + nb), nb / (na + nb)
    grid = np.linspace(0, 1, 101)
    top = np.minimum(u / v, v / u)
    j = np.minimum(grid[None], top[:, None])
    p = lambda x: np.clip(-np.log1p(-np.clip(x, 0, 1) * (BASE - 1) / BASE) / np.log(BASE), 1e-12, 1)
    # a larger step means a smaller minimum, which the larger set is likelier to have
    more, fewer = p(u[:, None] - v[:, None] * j), p(v[:, None] - u[:, None] * j)
    value = up[:, None] * np.log(more) + down[:, None] * np.log(fewer) + same[:, None] * np.log(np.clip(1 - more - fewer, 1e-12, 1))
    there = np.where(j >= least - 0.01, value, -np.inf).max(1)
    return (top >= least - 1e-9) & (there >= value.max(1) - slack)


def sketch(docs: DataFrame, words: int = 5) -> DataFrame:
    """(doc_id, n, set_key, regs) per row; empty sets have null keys and sketches."""

    def kernel(lists: Iterator) -> Iterator[dict]:
        shingles = Shingler(words)
        for ids, held in lists:
            sets = [shingles(t) for t in held]
            sizes = np.array([len(s) for s in sets], np.int64)
            full = np.flatnonzero(sizes)
            keys: list = [None] * len(ids)
            regs: list = [None] * len(ids)
            if len(full):
                flat = np.concatenate(sets)
                starts = (np.cumsum(sizes) - sizes)[full]
                r = registers(flat, starts)
                one, two = np.add.reduceat(_mix(flat + np.uint64(1)), starts), np.bitwise_xor.reduceat(_mix(flat + np.uint64(2)), starts)
                for i, x, y, z in zip(full.tolist(), one.tolist(), two.tolist(), r, strict=True):
                    keys[i], regs[i] = f"{x:016x}{y:016x}{sizes[i]:x}", z.tobytes()
            yield {"doc_id": ids, "n": sizes.tolist(), "set_key": keys, "regs": regs}

    return map_texts(docs, kernel, "doc_id long, n long, set_key string, regs binary", BATCH_BYTES)


def _banded(reps: DataFrame, bands: int, rows: int) -> DataFrame:
    """(rep, key) for each band of each representative."""
    import pyarrow as pa

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            if x.num_rows:
                keys = band_keys(np.frombuffer(b"".join(x.column("regs").to_pylist()), np.uint16).reshape(x.num_rows, -1), bands, rows)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(x.column("rep").to_numpy(), keys.shape[1])), pa.array(keys.ravel())], ["rep", "key"])

    return reps.select("rep", "regs").mapInArrow(kernel, "rep long, key long")


def _plausible(pairs: DataFrame, reps: DataFrame, percent: int) -> DataFrame:
    """Of pairs (a, b), those that size and the joint likelihood leave possible."""
    import pyarrow as pa

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            if x.num_rows:
                left, right = (np.frombuffer(b"".join(x.column(c).to_pylist()), np.uint16).reshape(x.num_rows, -1) for c in ("ra", "rb"))
                ok = may_reach(left, right, *(x.column(c).to_numpy().astype(float) for c in ("na", "nb")), percent / 100)
                yield pa.RecordBatch.from_arrays([x.column("a"), x.column("b")], ["a", "b"]).filter(pa.array(ok))

    side = lambda c: reps.select(F.col("rep").alias(c), F.col("n").alias(f"n{c}"), F.col("regs").alias(f"r{c}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").where(f"100 * least(na, nb) >= {percent} * greatest(na, nb)")
    return both.select("a", "b", "na", "nb", "ra", "rb").mapInArrow(kernel, "a long, b long")


def _confirmed(pairs: DataFrame, docs: DataFrame, percent: int, words: int) -> DataFrame:
    """Pairs whose full shingle sets have 100 * |intersection| >= percent * |union|."""
    import pyarrow as pa

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingles = Shingler(words)
        last, kept = None, None
        for x in batches:
            ok = []
            for b, ta, tb in zip(x.column("b").to_pylist(), x.column("ta"), x.column("tb"), strict=True):
                if b != last or kept[0] != tb.as_py():
                    last, kept = b, (tb.as_py(), shingles(tb.as_py()))
                own = shingles(ta.as_py())
                both = len(np.intersect1d(own, kept[1], assume_unique=True))
                ok.append(both > 0 and 100 * both >= percent * (len(own) + len(kept[1]) - both))
            yield pa.RecordBatch.from_arrays([x.column("a"), x.column("b")], ["a", "b"]).filter(pa.array(ok, pa.bool_()))
        del shingles
        give_back()

    ids = settled(pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct())
    docs = docs.join(small_or_shuffled(ids), "doc_id")
    side = lambda c: docs.select(F.col("doc_id").alias(c), F.col("text").alias(f"t{c}"))
    return pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "ta", "tb").mapInArrow(kernel, "a long, b long")


def _sets(ids: DataFrame, docs: DataFrame, words: int) -> DataFrame:
    """(rep, own) of the documents that ids(doc_id) names: their shingles, unless there are none."""

    def kernel(lists: Iterator) -> Iterator[dict]:
        shingles = Shingler(words)
        for ids, held in lists:
            yield {"rep": ids, "own": [shingles(t).view(np.int64) for t in held]}

    mine = docs.join(small_or_shuffled(settled(ids)), "doc_id", "left_semi")
    return map_texts(mine.select("doc_id", "text"), kernel, "rep long, own array<long>", BATCH_BYTES).where("size(own) > 0")


def _from_rare(each: DataFrame, within: list[str], own: list[str], size: str) -> DataFrame:
    """each(..., shingle) with `at`: the shingle's place, from 1, in its set, which `own` names, from rare to frequent within groups.

    Shingles that only one set of a group has take the first places but aren't returned: nothing can meet there.
    """
    common = settled(each.groupBy(*within, "shingle").agg(F.count(F.lit(1)).alias("df")).where("df > 1"))
    mine = each.join(common, [*within, "shingle"])
    by_set = Window.partitionBy(*within, *own, size)
    alone = F.col(size) - F.count(F.lit(1)).over(by_set)
    return mine.withColumn("at", F.row_number().over(by_set.orderBy("df", "shingle")) + alone).drop("df")


def _prefixes(reps: DataFrame, docs: DataFrame, percent: int, words: int) -> DataFrame:
    """(rep, n, shingle, at): the first n - ceil(n * percent / 100) + 1 shingles of each document, from rare to frequent, `at` from 1."""
    sets = _sets(reps.select(F.col("rep").alias("doc_id")), docs, words)
    each = settled(sets.select("rep", F.size("own").cast("long").alias("n"), F.explode("own").alias("shingle")))
    return _from_rare(each, [], ["rep"], "n").where(f"at <= n - cast(ceil(n * {percent} / 100) as long) + 1").select("rep", "n", "shingle", "at")


def _with_partners(placed: DataFrame, percent: int) -> DataFrame:
    """Rows (rep, root, n, shingle, at) whose place leaves room for a link with the sizes and places that their shingle's rows have."""
    room = (100 + percent) * (F.col("n") - F.col("at") + 1)
    best = placed.groupBy("shingle").agg(F.min("n").alias("_n"), F.max(room - percent * F.col("n")).alias("_room"))
    least = F.greatest("_n", F.ceil(F.col("n") * percent / 100))
    met = placed.join(settled(best), "shingle").where((room >= percent * (F.col("n") + least)) & (F.col("_room") >= percent * F.col("n")))
    return settled(met.drop("_n", "_room"))


def _lists(placed: DataFrame, by: list[str]) -> DataFrame:
    """Rows whose key has documents of several components, with one of the key's documents, drawn by hash, and whether it is too long for pairs."""
    keys = placed.groupBy(*by).agg(F.min("root").alias("_lo"), F.max("root").alias("_hi"), F.count(F.lit(1)).alias("_rows"), F.min_by("rep", F.xxhash64("rep")).alias("_hub"))
    return settled(placed.join(settled(keys.where("_lo < _hi").select(*by, (F.col("_rows") > CROWD).alias("_long"), "_hub")), by))


def _lists_across(placed: DataFrame, by: list[str]) -> DataFrame:
    """_lists() by the pairs that are left to compare, those across components: too long is a list with more than CROWD / 2 of them a row."""
    own = placed.groupBy(*by, "root").agg(F.count(F.lit(1)).alias("_n"), F.min(F.struct(F.xxhash64("rep").alias("h"), "rep")).alias("_first"))
    keys = own.groupBy(*by).agg(F.count(F.lit(1)).alias("_roots"), F.sum("_n").alias("_rows"), F.sum(F.col("_n") * F.col("_n")).alias("_alike"), F.min("_first")["rep"].alias("_hub"))
    long = F.col("_rows") * F.col("_rows") - F.col("_alike") > CROWD * F.col("_rows")
    return settled(placed.join(settled(keys.where("_roots > 1").select(*by, long.alias("_long"), "_hub")), by))


def _crowds(lists: DataFrame) -> DataFrame:
    """(g, rep, root): documents of the lists that are too long for pairs. Lists that drew the same document are one crowd."""
    return settled(lists.where("_long").groupBy(F.col("_hub").alias("g"), "rep").agg(F.min("root").alias("root")))


def _joined_to_stars(delta: DataFrame) -> DataFrame:
    """delta with one root for all components of a crowd that its star joins."""
    joined = delta.where("v + least.v <= 0").select("g", "root").distinct().withColumn("_joined", F.lit(True))
    both = delta.join(settled(joined), ["g", "root"], "left")
    return settled(both.withColumn("root", F.when(F.col("_joined"), F.col("least.root")).otherwise(F.col("root"))).drop("_joined"))


def _apart_from_centre(crowds: DataFrame, docs: DataFrame, percent: int, words: int) -> DataFrame:
    """(g, rep, root, own, v, d, delta, least) of crowds(g, rep, root): how each document differs from its crowd's centre.

    The centre holds the shingles that more than half of some of the crowd have, and delta is the symmetric difference, of d shingles. With v = (100 +
    percent) * d - (100 - percent) * n, two documents link exactly if 2 * (100 + percent) * |their deltas' intersection| >= the sum of
    their v. `least` is the crowd's smallest (v, rep, root), and `own` tells apart the sets of rows that share an id.
    """
    sizes = settled(crowds.groupBy("g").agg(F.count(F.lit(1)).alias("_size")))
    sets = settled(_sets(crowds.select(F.col("rep").alias("doc_id")).distinct(), docs, words).dropDuplicates(["rep", "own"]))
    held = crowds.join(sets, "rep")
    drawn = crowds.join(sizes, "g").where(F.pmod(F.xxhash64("g", "rep"), F.ceil(F.col("_size") / CENTRE_OF)) == 0)
    drawn = settled(drawn.join(drawn.groupBy("g").agg(F.count(F.lit(1)).alias("_drawn")), "g").select("g", "rep", "_drawn"))
    each = drawn.join(sets, "rep").select("g", "_drawn", F.explode("own").alias("shingle"))
    centre = each.groupBy("g", "_drawn", "shingle").agg(F.count(F.lit(1)).alias("_n")).where("2 * _n > _drawn").groupBy("g").agg(F.collect_list("shingle").alias("_c"))
    none = F.array().cast("array<long>")
    both = held.join(settled(centre), "g", "left").withColumn("_c", F.coalesce("_c", none))
    delta = both.select("g", "rep", "root", F.xxhash64("own").alias("own"), F.size("own").cast("long").alias("n"), F.concat(F.array_except("own", "_c"), F.array_except("_c", "own")).alias("delta"))
    delta = delta.withColumn("d", F.size("delta").cast("long")).withColumn("v", (100 + percent) * F.col("d") - (100 - percent) * F.col("n")).drop("n")
    delta = settled(delta)
    least = settled(delta.groupBy("g").agg(F.min(F.struct("v", "rep", "root")).alias("least")))
    return settled(delta.join(least, "g"))


def _linked_in_crowds(crowds: DataFrame, docs: DataFrame, percent: int, words: int) -> DataFrame:
    """Pairs of documents of a crowd that join components as all its links do: no pair that links is between components that these leave apart.

    Pairs whose v add up to 0 at most link, and both then link with the document of the least v: these links make a star. All others that
    link share shingles of their deltas, of which near copies have few, so that prefix filtering over deltas tells apart what whole sets
    don't. What a star joins is one component from then on, so that of near copies only those outside it meet the others. Lists of it that
    are crowded again get centres of their own.
    """
    out, twice = None, 2 * (100 + percent)
    for turn in range(CENTRE_TURNS):
        delta = _apart_from_centre(crowds, docs, percent, words)
        pairs = delta.where("v + least.v <= 0 and root <> least.root").select(F.least("rep", "least.rep").alias("a"), F.greatest("rep", "least.rep").alias("b"))
        delta = _joined_to_stars(delta)
        open_ = settled(delta.groupBy("g").agg(F.count_distinct("root").alias("_roots")).where("_roots > 1").select("g"))
        still = delta.join(open_, "g", "left_semi")
        each = settled(still.select("g", "rep", "root", "own", "v", "d", F.col("least.v").alias("_v"), F.explode("delta").alias("shingle")))
        ranked = _from_rare(each, ["g"], ["rep", "own"], "d")
        lists = _lists_across(ranked.where(f"at <= d - greatest(1, cast(ceil((v + _v) / {twice}) as long)) + 1"), ["g", "shingle"])
        short = lists if turn == CENTRE_TURNS - 1 else lists.where("not _long")
        side = lambda c: short.select("g", "shingle", *(F.col(x).alias(x + c) for x in ("rep", "root", "v", "d", "at")))  # noqa: E731, B023
        apart = "repa < repb and roota <> rootb and va + vb > 0"
        first = f"{twice} * (1 + least(da - ata, db - atb)) >= va + vb"
        met = side("a").hint("merge").join(side("b"), ["g", "shingle"]).where(f"{apart} and {first}")
        met = settled(met.select("g", F.col("repa").alias("a"), F.col("repb").alias("b")).distinct())
        of = lambda c: delta.select("g", F.col("rep").alias(c), *(F.col(x).alias(x + c) for x in ("v", "delta")))  # noqa: E731, B023
        both = met.join(of("a"), ["g", "a"]).join(of("b"), ["g", "b"])
        pairs = settled(pairs.unionByName(both.where(f"{twice} * size(array_intersect(deltaa, deltab)) >= va + vb").select("a", "b")).distinct())
        out = pairs if out is None else out.unionByName(pairs)
        crowds = _crowds(lists)
        if crowds.isEmpty():
            break
    return out


def _sharing_prefix(reps: DataFrame, docs: DataFrame, percent: int, words: int) -> DataFrame:
    """Pairs of reps(rep, root) in different components that may link: exact prefix filtering.

    Linked sets share a shingle of both prefixes, and what follows the first shared one bounds the overlap. Rows of that join hold ids,
    sizes and places only, so memory for a document grows with its prefix. The prefixes' whole intersection then bounds the overlap of the
    pairs that are left, whose prefixes alone are fetched. Where more than CROWD documents share a prefix shingle, pairs would grow with
    the square of their number: they are compared by what sets them apart from their common centre.
    """
    prefix = settled(_prefixes(reps, docs, percent, words))
    lists = _lists(_with_partners(settled(prefix.join(reps, "rep")), percent), ["shingle"])
    short = lists.where("not _long")
    side = lambda c: short.select("shingle", *(F.col(x).alias(x + c) for x in ("rep", "root", "n", "at")))
    apart = "repa < repb and roota <> rootb"
    sizes = f"100 * least(na, nb) >= {percent} * greatest(na, nb)"
    first = f"{100 + percent} * (1 + least(na - ata, nb - atb)) >= {percent} * (na + nb)"
    met = side("a").hint("merge").join(side("b"), "shingle").where(f"{apart} and {sizes} and {first}")
    pairs = settled(met.select(F.col("repa").alias("a"), F.col("repb").alias("b")).distinct())

    own = prefix.groupBy("rep", "n").agg(F.array_sort(F.collect_list(F.struct("at", "shingle"))).alias("_p"))
    own = own.select("rep", "n", F.col("_p.shingle").alias("p"), (F.col("_p")[0]["at"] - 1).alias("u"))
    of = lambda c: own.select(F.col("rep").alias(c), *(F.col(x).alias(x + c) for x in ("n", "p", "u")))
    both = pairs.join(of("a"), "a").join(of("b"), "b").withColumn("_common", F.array_intersect("pa", "pb"))
    last = F.element_at("_common", -1)
    beyond = lambda c: F.col(f"n{c}") - F.col(f"u{c}") - F.array_position(F.col(f"p{c}"), last)
    reach = F.size("_common") + F.least(beyond("a"), beyond("b"))
    pairs = both.where((100 + percent) * reach >= percent * (F.col("na") + F.col("nb"))).select("a", "b")
    crowds = _crowds(lists)
    return pairs if crowds.isEmpty() else pairs.unionByName(_linked_in_crowds(crowds, docs, percent, words)).distinct()


def near_duplicates(docs: DataFrame, *, percent: int = 85, words: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable over links), kept (doc_id = component_id), for every row.

    Two documents link if their sets of word shingles have 100 * |intersection| >= percent * |union|. Equal sets are one class, whose
    smallest doc_id stands for it. Buckets of equal band values don't emit all their pairs: turn by turn, each bucket that still spans
    several components compares its classes with one hub, drawn by hash, and components grow; after HUB_TURNS turns the documents of buckets that
    span components are joined by prefix filtering over their full sets, so that no candidate pair that could join two components is
    left out, though near-copies below the threshold never meet in bulk. Null and empty texts link with nothing.
    Rows with a null id stay apart: component_id null, kept true. Rows that share an id are one document. Other columns are ignored;
    an empty table gives an empty result. Texts of any length are compared whole. Candidates come from 28 bands of 6 registers at 85 %, 33 of 5 at 80 %: a pair at the
    threshold is missed with a probability of about 2 in a million.
    """
    small_batches(docs.sparkSession)
    own = texts(docs, id_col, text_col)
    sketches = settled(sketch(own, words))
    reps = settled(sketches.where("n > 0 and doc_id is not null").groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.first("n").alias("n"), F.first("regs").alias("regs")))
    banded = _banded(reps, *banding(percent))
    keys = banded.groupBy("key").agg(F.min("rep").alias("_min"), F.max("rep").alias("_max")).where("_min < _max")
    shared = settled(banded.join(settled(keys.select("key")), "key"))
    links, roots = None, reps.select(F.col("rep").alias("node"), F.col("rep").alias("root"))
    for turn in range(HUB_TURNS + 1):
        placed = settled(shared.join(roots, shared["rep"] == roots["node"], "left").select("key", "rep", F.coalesce("root", "rep").alias("root")))
        spans = placed.groupBy("key").agg(F.min("root").alias("_lo"), F.max("root").alias("_hi"), F.min(F.xxhash64("rep", F.lit(turn))).alias("_hub")).where("_lo < _hi")
        rest = settled(placed.join(settled(spans.select("key", "_hub")), "key"))
        if rest.isEmpty():
            break
        if turn < HUB_TURNS:
            hubs = settled(rest.where(F.xxhash64("rep", F.lit(turn)) == F.col("_hub")).select("key", F.col("rep").alias("b"), F.col("root").alias("_b")))
            pairs = rest.join(hubs, "key").where("root <> _b").select(F.least("rep", "b").alias("a"), F.greatest("rep", "b").alias("b")).distinct()
            pairs = _plausible(pairs, reps, percent)
        else:
            pairs = _sharing_prefix(rest.select("rep", "root").distinct(), own, percent, words)
        new = settled(_confirmed(settled(pairs), own, percent, words))
        links = new if links is None else links.unionByName(new)
        if not new.isEmpty():
            roots = components(links)

    found = settled(reps.join(roots, reps["rep"] == roots["node"], "left").select("set_key", F.coalesce("root", "rep").alias("_root")))
    out = sketches.select("doc_id", F.col("n").alias("n_shingles"), "set_key").join(found, "set_key", "left")
    component = F.least(F.coalesce("_root", "doc_id"), F.col("doc_id"))
    component = F.when(F.col("doc_id").isNotNull(), component)
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))
