"""Benchmark decontamination by template canonicalisation. DataFrame operations only.

Numbers, names and units become typed placeholders, so that a question whose values were changed keeps its template. Windows of
template words are hash-joined with the benchmark's; the values that the placeholders stand for must then agree between an item and a
document, equal values with equal values, in both directions. Windows of plain lower-case words stand beside them: case tells names
from words, so a copy whose letter case was changed has another template.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stablegrammar.llm.common import settled, small_or_shuffled

WINDOW = 8
#: So many plain words in a row count, whatever their share of the item.
EXACT_RUN = 13
#: Second argument of the hashes of plain windows.
_PLAIN = "plain"
#: Words of units that may follow a number.
UNITS = "mm|cm|m|km|mg|g|kg|t|ml|l|s|ms|min|h|hours?|minutes?|seconds?|days?|weeks?|months?|years?|miles?|feet|inch(?:es)?|pounds?|dollars?|euros?|percent|mph|kmh|usd|eur"


#: A character that is neither letter, digit nor white space. Patterns begin with it, or with a digit or capital, so that most characters fail at once.
_MARK = r"[^\p{L}\p{N}\s]"


def _only_words(text: Column) -> Column:
    """Without marks that stand alone, and without white space at the ends: words are then what is between white space."""
    run = rf"{_MARK}(?:(?<!{_MARK}{{2}})|(?<=[\uDC00-\uDFFF]{_MARK})){_MARK}*+(?=\s|$)"  # tried where a run begins, or after a code point of two chars
    return F.trim(F.regexp_replace(F.regexp_replace(text, run, ""), r"\s(?:\s++|(?<! ))", " "))


def template(plain: Column) -> Column:
    """Lower-case template words of a text from _only_words; white space is kept, so that places agree with the text's own words.

    A capitalised word is a name at a text's start too, as it is there in the middle of another text.
    """
    units = F.regexp_replace(plain, rf"(\d ?)(?i:{UNITS})(?![\p{{L}}\p{{N}}])", "$1\u0001")
    numbers = F.regexp_replace(units, r"\d+(?:[.,:/]\d+)*", "\u0002")
    names = F.regexp_replace(numbers, r"\p{Lu}(?<=(?:^|[\p{L}\p{N},;:\x01\x02] )[^\p{L}\p{N}\s\x01-\x03]{0,2}\p{Lu})[\p{L}'-]*", "\u0003")
    return F.lower(F.regexp_replace(names, r"[^\p{L}\p{N}\s\x01-\x03]+", ""))


def plain_words(plain: Column) -> Column:
    """Lower-case words of a text from _only_words, without placeholders; of marks only single ones between digits stay."""
    return F.lower(F.regexp_replace(plain, rf"{_MARK}(?:{_MARK}++|(?<![0-9]{_MARK}{{1,2}})|(?![0-9]))", ""))


def _word_hashes(words: Column) -> Column:
    """Each word is hashed once, and windows hash longs: a word is in as many windows as they have words."""
    return F.transform(words, lambda w: F.xxhash64(w))


def _windows(words: DataFrame, lengths: list[int]) -> DataFrame:
    """(doc_id, _h, _at, _k) of all windows of the given lengths, from word hashes _w of templates and _p of plain words.

    Both arrays lie end to end, and each place hashes the slices that begin there: no function runs over an array, so that slices and
    hashes are compiled. Plain windows have no values to compare: their length is 0.
    """
    laid = words.select("doc_id", F.size("_w").alias("_nw"), F.concat("_w", "_p").alias("_all"))
    places = laid.select("doc_id", "_nw", "_all", F.posexplode("_all").alias("_pos", "_"))
    literal = F.col("_pos") >= F.col("_nw")
    end = F.when(literal, F.size("_all")).otherwise(F.col("_nw"))

    def window(k: int) -> tuple[Column, Column]:
        run = F.slice("_all", F.col("_pos") + 1, k)
        h = F.when(F.col("_pos") + k <= end, F.when(literal, F.xxhash64(run, F.lit(_PLAIN))).otherwise(F.xxhash64(run)))
        return h.alias("_h"), F.when(literal, 0).otherwise(k).alias("_k")

    at = F.when(literal, F.col("_pos") - F.col("_nw")).otherwise(F.col("_pos")).alias("_at")
    if len(lengths) == 1:
        out = places.select("doc_id", at, *window(lengths[0]))
    else:
        out = places.select("doc_id", at, F.inline(F.array(*(F.struct(*window(k)) for k in lengths))))
    return out.where("_h is not null")


def _consistent(pairs: DataFrame, found: DataFrame, places: DataFrame, least_share: float) -> DataFrame:
    """(doc_id, item_id, exact) of pairs whose values agree jointly, over all windows of one copy of the item.

    A copy's windows lie at nearly one shift between document and item. Shifts are gathered in cells of 2 * WINDOW, in two gridings, so that
    a copy with a few words put in falls into one cell; there each place of the item takes the document's place whose shift is nearest to
    the commonest one. Equal values must then stand for equal values over all these places, in both directions.
    """
    bare = lambda s: F.regexp_replace(s, r"^[^\p{L}\p{N}]+|[^\p{L}\p{N}]+$", "")
    own = F.arrays_zip(F.col("_win"), F.col("_values"), F.col("_own"))
    slots = F.transform(F.filter(own, lambda x: x["_win"].rlike("[\x01-\x03]")), lambda x: F.struct(bare(x["_values"]).alias("v"), bare(x["_own"]).alias("o")))
    met = found.join(places.select("item_id", "_h", F.col("_at").alias("_p"), "_win", "_values"), "_h").join(pairs.select("doc_id", "item_id", "item_windows"), ["doc_id", "item_id"])
    met = met.select("doc_id", "item_id", "item_windows", "_h", "_p", (F.col("_at") - F.col("_p")).alias("_shift"), slots.alias("_slots"))
    cells = F.array(*(F.struct(F.lit(g).alias("g"), F.floor((F.col("_shift") + g * WINDOW) / F.lit(2 * WINDOW)).alias("c")) for g in (0, 1)))
    met = met.withColumn("_cell", F.explode(cells))
    by = ["doc_id", "item_id", "_cell"]
    main = met.groupBy(*by, "_shift").agg(F.count_distinct("_p").alias("_c")).groupBy(*by).agg(F.max_by("_shift", F.struct("_c", -F.col("_shift"))).alias("_main"))
    near = F.struct(F.abs(F.col("_shift") - F.col("_main")), F.col("_shift"))
    placed = met.join(main, by).groupBy(*by, "item_windows", "_p").agg(F.min_by("_slots", near).alias("_slots"), F.min_by("_h", near).alias("_h"))
    cell = placed.groupBy(*by, "item_windows").agg(F.count_distinct("_h").alias("_n"), F.array_distinct(F.flatten(F.collect_set("_slots"))).alias("_one"))  # bounded by the item
    distinct = lambda k: F.size(F.array_distinct(F.transform("_one", lambda x: x[k])))
    agree = (distinct("v") == F.size("_one")) & (distinct("o") == F.size("_one")) & (F.col("_n") >= least_share * F.col("item_windows"))
    return cell.where(agree).groupBy("doc_id", "item_id").agg(F.max(F.forall("_one", lambda x: x["v"] == x["o"])).alias("exact"))


def contamination(docs: DataFrame, benchmark: DataFrame, *, window: int = WINDOW, least_share: float = 0.5, exact_run: int = EXACT_RUN, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, item_id, n_windows (of the item, found), item_windows, exact (whether all values are the item's): contaminated pairs only.

    A pair counts if at least `least_share` of the item's distinct windows of `window` template words occur in one place of the document
    and the values of all of them agree jointly, or if that share of its windows of plain lower-case words occurs, or as many of them as
    a run of `exact_run` words has; the figures are then of plain windows. Template windows that are placeholders by half or more are
    looked for as plain windows only. Items of fewer words are one window of their own length, which is a template from 4 words on
    and plain words at any length. Hashes of benchmark windows, and ids of documents that hold one, are
    broadcast if a count shows that they are few, else joined by shuffle. Null and empty texts match nothing; rows with a null id of either side are left out; repeated rows count once; rows that share an id count as one document;
    texts of any length are searched whole; other columns are ignored; empty tables give an empty result.
    """
    items = benchmark.where("item_id is not null and text is not null").select("item_id", _only_words(F.col("text")).alias("_t")).where("_t <> ''").distinct()
    items = items.select("item_id", F.split("_t", " ").alias("_raw"), F.split(template(F.col("_t")), " ").alias("_w"), F.split(plain_words(F.col("_t")), " ").alias("_p"))
    size = F.least(F.size("_w"), F.lit(window))
    pos = items.select("item_id", "_raw", "_w", "_p", size.alias("_k"), F.explode(F.sequence(F.lit(1), F.size("_w") - size + 1)).alias("_at"))
    placeholders = F.size(F.filter("_win", lambda w: w.rlike("[\x01-\x03]")))
    literal = pos.select("item_id", "_k", F.slice("_p", F.col("_at"), F.col("_k")).alias("_win"))
    literal = literal.select("item_id", F.lit(True).alias("_plain"), "_k", F.xxhash64(_word_hashes(F.col("_win")), F.lit(_PLAIN)).alias("_h"))
    places = pos.select("item_id", "_k", "_at", F.slice("_w", F.col("_at"), F.col("_k")).alias("_win"), F.slice("_raw", F.col("_at"), F.col("_k")).alias("_values"))
    places = settled(places.where("_k >= 4").where(2 * placeholders < F.col("_k")).withColumn("_h", F.xxhash64(_word_hashes(F.col("_win")))))
    bench = literal.unionByName(places.select("item_id", F.lit(False).alias("_plain"), "_k", "_h"))
    bench = settled(bench.groupBy("item_id", "_plain", "_k", "_h").agg(F.when(F.col("_plain"), F.count(F.lit(1))).otherwise(F.lit(1)).alias("_n")))
    lengths = sorted(r[0] for r in bench.select("_k").distinct().collect()) or [window]  # at most `window` numbers
    keys = small_or_shuffled(settled(bench.select("_h").distinct()))

    plain = docs.where(F.col(id_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), _only_words(F.col(text_col)).alias("_t"))
    words = plain.select("doc_id", F.split(template(F.col("_t")), " ").alias("_w"), F.split(plain_words(F.col("_t")), " ").alias("_p"))
    words = words.select("doc_id", _word_hashes(F.col("_w")).alias("_w"), _word_hashes(F.col("_p")).alias("_p"))
    met = _windows(words, lengths).join(keys, "_h")
    at = settled(met.groupBy("doc_id").agg(F.collect_set(F.struct("_h", "_at", "_k")).alias("_found")))  # of one document: as many as its windows
    hit = plain.join(small_or_shuffled(settled(at.select("doc_id"))), "doc_id", "left_semi")  # ids alone may be broadcast
    found = hit.join(at.hint("merge"), "doc_id").select("doc_id", F.split("_t", " ").alias("_raw"), F.explode("_found").alias("_x"))
    found = settled(found.select("doc_id", "_x._h", "_x._at", F.slice("_raw", F.col("_x._at") + 1, F.col("_x._k")).alias("_own")).distinct())

    # ids first: only pairs with enough of an item's windows have their values fetched
    seen = found.select("doc_id", "_h").distinct().join(small_or_shuffled(bench), "_h")
    pairs = seen.groupBy("doc_id", "item_id", "_plain").agg(F.count(F.lit(1)).alias("n_windows"), F.sum("_n").alias("_places"))
    totals = bench.groupBy("item_id", "_plain").agg(F.count(F.lit(1)).alias("item_windows"))
    share = F.col("n_windows") >= least_share * F.col("item_windows")
    run = F.col("_plain") & (F.col("_places") >= max(1, exact_run - window + 1))
    pairs = settled(pairs.join(small_or_shuffled(settled(totals)), ["item_id", "_plain"]).where(share | run).drop("_places"))
    templates = _consistent(pairs.where("not _plain"), found, places, least_share)
    plains = pairs.where("_plain").withColumn("exact", F.lit(True))
    pairs = plains.unionByName(pairs.where("not _plain").join(templates, ["doc_id", "item_id"]))
    figures = F.min_by(F.struct("n_windows", "item_windows", "exact"), "_plain").alias("_x")  # of template windows where they suffice
    return pairs.groupBy("doc_id", "item_id").agg(figures).select("doc_id", "item_id", "_x.*")
