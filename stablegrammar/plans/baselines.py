"""Compressors to compare with. Each returns one row: baseline, plain_bytes, compressed_bytes."""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def chunks(strings: DataFrame, chunk_bytes: int, order: tuple[str, ...] = ("string_id",)) -> DataFrame:
    """strings with `chunk`: texts in the given order, cut every chunk_bytes. Sizes are summed per range of the order first, so that no
    task sorts more than its range and the cut doesn't depend on partitions."""
    from stablegrammar.operators.lineage import settled

    rows = strings.where("text is not null").withColumn("_size", F.octet_length("text") + 1)
    ranged = settled(rows.repartitionByRange(*order, "text").withColumn("_range", F.spark_partition_id()))
    sizes = ranged.groupBy("_range").agg(F.sum("_size").alias("_all"))  # one row per range
    base = sizes.select("_range", (F.sum("_all").over(Window.orderBy("_range")) - F.col("_all")).alias("_base"))
    before = F.sum("_size").over(Window.partitionBy("_range").orderBy(*order, "text").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("_size")
    placed = ranged.withColumn("_before", before).join(F.broadcast(base), "_range")
    return placed.withColumn("chunk", F.floor((F.col("_base") + F.col("_before")) / chunk_bytes)).drop("_size", "_range", "_before", "_base")


def _coded(strings: DataFrame, name: str, encode: Callable[[bytes], tuple[int, int]], chunk_bytes: int, order: tuple[str, ...] = ("string_id",)) -> DataFrame:
    """Sums over chunks of about chunk_bytes of newline-joined texts: their bytes, coded bytes, and the largest coder state."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held = None, []

        def flush() -> pa.RecordBatch:
            coded, state = encode("\n".join(held).encode())
            return pa.RecordBatch.from_pydict({"plain": [sum(len(t.encode()) for t in held)], "coded": [coded], "state": [state]})

        for x in batches:
            for c, t in zip(x.column(0).to_pylist(), x.column(1).to_pylist(), strict=True):
                if held and c != key:
                    yield flush()
                    held = []
                key = c
                held.append(t)
        if held:
            yield flush()

    ordered = chunks(strings, chunk_bytes, order).repartition("chunk").sortWithinPartitions("chunk", *order, "text")
    rows = ordered.select("chunk", "text").mapInArrow(run, "plain long, coded long, state long")
    return rows.agg(F.lit(name).alias("baseline"), F.sum("plain").alias("plain_bytes"), F.sum("coded").alias("compressed_bytes"), F.max("state").alias("state_bytes"))


#: The published window: 2 GiB, one chunk for each, so a task needs that memory and the coder's own.
WIDE_WINDOW = {"window_log": 31, "chunk_bytes": 2 << 30}


def lz_codec(strings: DataFrame, level: int = 15, window_log: int | None = None, chunk_bytes: int = 64 << 20, order: tuple[str, ...] = ("string_id",), name: str = "lz_codec") -> DataFrame:
    """A window-bounded dictionary coder with entropy coding; WIDE_WINDOW holds the published options."""

    def encode(data: bytes) -> tuple[int, int]:
        import zstandard

        params = zstandard.ZstdCompressionParameters.from_level(level, source_size=len(data), **({"window_log": window_log} if window_log else {}))
        return len(zstandard.ZstdCompressor(compression_params=params).compress(data)), params.estimated_compression_context_size()

    return _coded(strings, name, encode, chunk_bytes, order)


def deflate(strings: DataFrame, level: int = 6, chunk_bytes: int = 64 << 20) -> DataFrame:
    """A coder with a window of 32 KiB, whose state is 2**(15 + 2) + 2**(8 + 9) bytes."""
    return _coded(strings, "deflate", lambda data: (len(zlib.compress(data, level)), (1 << 17) + (1 << 17)), chunk_bytes)


def similarity_key(strings: DataFrame, words: int = 3) -> DataFrame:
    """With `_k`, the smallest hash of a text's word triples: similar texts often share it."""
    split = strings.withColumn("_w", F.split("text", r"\s+"))
    triples = F.transform(F.sequence(F.lit(1), F.greatest(F.size("_w") - words + 1, F.lit(1))), lambda i: F.xxhash64(F.slice("_w", i, words)))
    return split.withColumn("_k", F.array_min(triples)).drop("_w")


def reorder_then_lz(strings: DataFrame, **options) -> DataFrame:
    """Similar strings next to each other, then the window-bounded coder."""
    return lz_codec(similarity_key(strings), order=("_k",), name="reorder_then_lz", **options)


def greedy_pairs(text: list[int], sigma: int, max_rules: int | None = None) -> tuple[int, int, int]:
    """(rules, size, last sequence length) of replacing the commonest pair of neighbours until none repeats. Ties: the smaller pair."""
    seq, rules = text, 0
    while max_rules is None or rules < max_rules:
        count: Counter = Counter()
        last = -2
        for i, p in enumerate(zip(seq, seq[1:], strict=False)):
            if p[0] == p[1] and last == i - 1 and seq[i - 1] == p[0]:
                last = -2
                continue
            if p[0] >= 0 and p[1] >= 0:
                count[p] += 1
                last = i
        if not count:
            break
        pair, n = min(count.items(), key=lambda x: (-x[1], x[0]))
        if n < 2:
            break
        new, out, i = sigma + rules, [], 0
        while i < len(seq):
            if i + 1 < len(seq) and (seq[i], seq[i + 1]) == pair:
                out.append(new)
                i += 2
            else:
                out.append(seq[i])
                i += 1
        seq, rules = out, rules + 1
    return rules, 2 * rules + sum(x >= 0 for x in seq), len(seq)


def _joined(strings: DataFrame) -> list[int]:
    """Code points of all strings by id, separated by -1, which no pair may hold; for small inputs."""
    out: list[int] = []
    for _, t in sorted(tuple(r) for r in strings.select("string_id", "text").collect()):
        out += [*map(ord, t), -1]
    return out


def pair_replacement(strings: DataFrame, max_rules: int | None = None) -> DataFrame:
    """Exact greedy pairs; sequential by nature, so the input must fit one process."""
    text = _joined(strings)
    sigma = max(text, default=0) + 1
    g, size, rest = greedy_pairs(text, sigma, max_rules)
    bits = size * max(1, (g + sigma).bit_length())
    return strings.sparkSession.createDataFrame([("pair_replacement", sum(len(chr(x).encode()) for x in text if x >= 0), bits // 8, g, size)], "baseline string, plain_bytes long, compressed_bytes long, rules long, size long")


def window_phrases(strings: DataFrame, w: int = 6, d: int = 16) -> DataFrame:
    """(string_id, no, phrase) of prefix-free parsing: phrases end with a w-gram whose digest is 0 modulo d, and overlap by w."""
    chars = strings.select("string_id", F.split("text", "").alias("_c"))
    n = F.size("_c")
    gram = lambda i: F.array_join(F.slice("_c", i, w), "")
    hit = lambda i: F.conv(F.substring(F.md5(gram(i)), 1, 8), 16, 10).cast("long") % d == 0
    inner = F.filter(F.sequence(F.lit(2), F.greatest(n - w, F.lit(2))), lambda i: (i <= n - w) & hit(i))
    cut = chars.withColumn("_end", F.concat(inner, F.array(F.greatest(n - w + 1, F.lit(1)))))
    begin = lambda k: F.when(k == 0, F.lit(1)).otherwise(F.get("_end", k - 1))
    parts = F.transform("_end", lambda e, k: F.array_join(F.slice("_c", begin(k), e + w - begin(k)), ""))
    return cut.select("string_id", F.posexplode(parts).alias("no", "phrase"))


def prefix_free_pairs(strings: DataFrame, w: int = 6, d: int = 16) -> DataFrame:
    """Prefix-free parsing, then greedy pairs on its dictionary and on its parse."""
    phrases = window_phrases(strings, w, d)
    words = [r[0] for r in phrases.select("phrase").distinct().orderBy("phrase").collect()]
    rank = {p: i for i, p in enumerate(words)}
    parse: list[int] = []
    last = None
    for s, _, p in sorted((r["string_id"], r["no"], r["phrase"]) for r in phrases.collect()):
        parse += [-1] * (last is not None and s != last) + [rank[p]]
        last = s
    text: list[int] = []
    for p in words:
        text += [*map(ord, p), -1]
    sigma = max(text, default=0) + 1
    g1, s1, _ = greedy_pairs(text, sigma)
    g2, s2, _ = greedy_pairs(parse, len(words) + 1)
    from stablegrammar.plans.measures import plain_bytes

    return strings.sparkSession.createDataFrame([("prefix_free_pairs", plain_bytes(strings), ((s1 + s2) * max(1, (g1 + g2 + sigma).bit_length())) // 8, g1 + g2, s1 + s2)], "baseline string, plain_bytes long, compressed_bytes long, rules long, size long")


def segments(strings: DataFrame, k: int = 8, d: int = 32) -> DataFrame:
    """(string_id, no, left, right, segment): strings cut after k-grams whose digest is 0 modulo d, keyed by the k-grams at both ends.

    A segment doesn't repeat the k-gram that it begins after, so the segments of a string spell it.
    """
    own = F.when(F.col("no") == 0, F.col("phrase")).otherwise(F.substr("phrase", F.lit(k + 1), F.length("phrase")))
    left, right = F.substr("phrase", F.lit(1), F.lit(k)), F.substr("phrase", F.greatest(F.length("phrase") - k + 1, F.lit(1)), F.lit(k))
    return window_phrases(strings, k, d).select("string_id", "no", left.alias("left"), right.alias("right"), own.alias("segment"))


def segment_groups(strings: DataFrame, k: int = 8, d: int = 32) -> DataFrame:
    """Segments with equal keys coded together, in parts of at most 64 MB."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        params = zstandard.ZstdCompressionParameters.from_level(15, write_content_size=False, write_checksum=False)
        coder, state = zstandard.ZstdCompressor(compression_params=params), params.estimated_compression_context_size()
        key, held, size = None, [], 0

        def flush() -> pa.RecordBatch:
            return pa.RecordBatch.from_pydict({"plain": [size], "coded": [len(coder.compress(b"\n".join(held)))], "state": [state]})

        for x in batches:
            for a, b, s in zip(*(x.column(i).to_pylist() for i in range(3)), strict=True):
                if held and ((a, b) != key or size > 64 << 20):
                    yield flush()
                    held, size = [], 0
                key = (a, b)
                held.append(s.encode())
                size += len(held[-1])
        if held:
            yield flush()

    near = segments(strings, k, d).select("left", "right", "segment").repartition("left", "right").sortWithinPartitions("left", "right", "segment")
    rows = near.mapInArrow(run, "plain long, coded long, state long")
    return rows.agg(F.lit("segment_groups").alias("baseline"), F.sum("plain").alias("plain_bytes"), F.sum("coded").alias("compressed_bytes"), F.max("state").alias("state_bytes"))


class DigramGrammar:
    """Online grammar of one sequence: no pair of neighbours stands in two places, and every rule is used twice or more.

    Symbols are linked nodes in circles, one circle for each rule around a guard; rule r is written as -1 - r, rule 0 is the sequence.
    """

    def __init__(self) -> None:
        self.sym: list[int | None] = []
        self.next: list[int] = []
        self.prev: list[int] = []
        self.place: dict[tuple[int, int], int] = {}
        self.guard: dict[int, int] = {}
        self.owner: dict[int, int] = {}
        self.users: dict[int, set[int]] = {}
        self.made = 0
        self._rule()

    def _node(self, x: int | None) -> int:
        n = len(self.sym)
        self.sym.append(x)
        self.next.append(n)
        self.prev.append(n)
        return n

    def _rule(self) -> int:
        r, g = self.made, self._node(None)
        self.made += 1
        self.guard[r], self.owner[g], self.users[r] = g, r, set()
        return r

    def _put(self, left: int, x: int) -> int:
        n, right = self._node(x), self.next[left]
        self._forget(left)
        self.next[left], self.prev[n], self.next[n], self.prev[right] = n, left, right, n
        if x < 0:
            self.users[-1 - x].add(n)
        return n

    def _pair(self, n: int) -> tuple[int, int] | None:
        a, b = self.sym[n], self.sym[self.next[n]]
        return None if a is None or b is None else (a, b)

    def _forget(self, n: int) -> None:
        if (p := self._pair(n)) and self.place.get(p) == n:
            del self.place[p]

    def _take(self, n: int) -> None:
        left, right = self.prev[n], self.next[n]
        self._forget(left)
        self._forget(n)
        if self.sym[n] < 0:
            self.users[-1 - self.sym[n]].discard(n)
        self.next[left], self.prev[right] = right, left

    def _replace(self, n: int, r: int) -> None:
        left = self.prev[n]
        self._take(self.next[n])
        self._take(n)
        self._put(left, -1 - r)
        if not self._check(left):
            self._check(self.next[left])

    def _check(self, n: int) -> bool:
        p = self._pair(n)
        if p is None:
            return False
        m = self.place.setdefault(p, n)
        if m == n or self.next[m] == n or self.next[n] == m:
            return False
        before, after = self.prev[m], self.next[self.next[m]]
        if before == after and self.sym[before] is None:  # the other place is a whole rule
            r = self.owner[before]
            self._replace(n, r)
        else:
            r = self._rule()
            last = self._put(self._put(self.guard[r], p[0]), p[1])
            self._replace(m, r)
            self._replace(n, r)
            self.place[p] = self.prev[last]
        self._expand_lonely(r)
        return True

    def _expand_lonely(self, r: int) -> None:
        """A rule that only r's first or last symbol uses any more goes into its place."""
        if r not in self.guard:
            return
        for n in {self.next[self.guard[r]], self.prev[self.guard[r]]}:
            x = self.sym[n]
            if x is not None and x < 0 and len(self.users[-1 - x]) == 1:
                g, left, right = self.guard.pop(-1 - x), self.prev[n], self.next[n]
                del self.users[-1 - x]
                first, last = self.next[g], self.prev[g]
                self._forget(left)
                self._forget(n)
                self.next[left], self.prev[first], self.next[last], self.prev[right] = first, left, right, last
                for k in (left, last):
                    if p := self._pair(k):
                        self.place.setdefault(p, k)

    def append(self, x: int) -> None:
        last = self.prev[self.guard[0]]
        self._put(last, x)
        self._check(last)

    def rules(self) -> dict[int, list[int]]:
        out = {}
        for r, g in self.guard.items():
            n, own = self.next[g], []
            while n != g:
                own.append(self.sym[n])
                n = self.next[n]
            out[r] = own
        return out


def digram_grammar(strings: DataFrame) -> DataFrame:
    """(string_id, rules, size): digram uniqueness and rule utility, online within each string; rule 0 of a string counts in the size only."""

    def measured(text: str) -> tuple[int, int]:
        g = DigramGrammar()
        for c in text:
            g.append(ord(c))
        rules = g.rules()
        return len(rules) - 1, sum(map(len, rules.values()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            got = [measured(t or "") for t in x.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([x.column(0), pa.array([g for g, _ in got], pa.int64()), pa.array([s for _, s in got], pa.int64())], ["string_id", "rules", "size"])

    return strings.select(F.col("string_id").cast("long"), "text").mapInArrow(run, "string_id long, rules long, size long")


def lz_factors(strings: DataFrame) -> DataFrame:
    """Number of factors when each string is parsed into longest earlier-occurring pieces."""

    def count(t: str) -> int:
        n, i, out = len(t), 0, 0
        while i < n:
            size = 1
            while i + size < n and t.find(t[i : i + size + 1], 0, i + size) >= 0:
                size += 1
            i += size if t.find(t[i : i + size], 0, i + size - 1) >= 0 else 1
            out += 1
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            yield pa.RecordBatch.from_arrays([x.column(0), pa.array([count(t or "") for t in x.column(1).to_pylist()], pa.int64())], ["string_id", "factors"])

    return strings.select(F.col("string_id").cast("long"), "text").mapInArrow(run, "string_id long, factors long")


def first_pairs(strings: DataFrame) -> DataFrame:
    """(left, right, uses) of neighbouring characters, distributed: the first turn of the batch form of greedy pairs."""
    from stablegrammar.operators.post import adjacent_pairs

    seq = strings.where("text <> ''").select(F.col("string_id").alias("sequence"), F.posexplode(F.split("text", "")).alias("pos", "sym"))
    return adjacent_pairs(seq)


def pair_turns(strings: DataFrame, turns: int, batch: int = 8) -> DataFrame:
    """Distributed greedy pairs: each turn replaces the `batch` commonest pairs that share no symbol; (turn, left, right, uses) chosen."""
    from stablegrammar.operators.lineage import settled

    seq = settled(strings.where("text <> ''").select(F.col("string_id").alias("sequence"), F.posexplode(F.split("text", "")).alias("pos", "sym")))
    from stablegrammar.operators.post import adjacent_pairs

    chosen = []
    for turn in range(turns):
        top = adjacent_pairs(seq).where("uses > 1").orderBy(F.desc("uses"), "left", "right").limit(8 * batch).collect()  # a bounded report
        seen: set = set()
        picks = []
        for left, right, uses in top:
            if not {left, right} & seen and len(picks) < batch:
                seen |= {left, right}
                picks.append((turn, left, right, uses))
        if not picks:
            break
        chosen += picks
        w = Window.partitionBy("sequence").orderBy("pos")
        new = F.create_map(*(F.lit(x) for _, a, b, _ in picks for x in (f"{a}\x01{b}", f"<{turn}:{a}{b}>")))
        pair = seq.withColumn("_name", new[F.concat_ws("\x01", "sym", F.lead("sym").over(w))])
        pair = pair.withColumn("_start", F.col("_name").isNotNull() & (F.coalesce(F.lead("sym").over(w) != F.col("sym"), F.lit(True))))
        pair = pair.withColumn("_gone", F.coalesce(F.lag("_start").over(w), F.lit(False)))
        seq = settled(pair.where("not _gone").select("sequence", "pos", F.when(F.col("_start"), F.col("_name")).otherwise(F.col("sym")).alias("sym")))
    return strings.sparkSession.createDataFrame(chosen, "turn int, left string, right string, uses long")
