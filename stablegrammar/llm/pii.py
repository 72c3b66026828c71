"""PII: format-preserving Feistel pseudonyms for validated numbers, dates and addresses. DataFrame operations only.

A value found by its pattern and confirmed by its check digits or ranges is a number in a product domain; a keyed Feistel network
permutes that domain, and the result is written back over the value's own digits, letters and separators. Equal values get equal pseudonyms in every
document, and text lengths stay.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from stablegrammar.llm.common import unused

_BYTE = r"(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)"
_IP = rf"(?<![\w.]){_BYTE}(?:\.{_BYTE}){{3}}(?![\w]|\.\d)"
_DATE = r"(?<![\w-])(?:19|20)\d\d-(?:0[1-9]|1[0-2])-(?:0[1-9]|[12]\d|3[01])(?![\w-])"
_SSN = r"(?<![\w-])(?!000|666|9)\d{3}-(?!00)\d\d-(?!0000)\d{4}(?![\w-])"
#: Candidate values, the more specific first. A card candidate is a whole run of digit groups (and a letter glued to its end), in which
#: card numbers are then looked for; a value of another kind ends it.
PATTERNS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}",
    "ip": _IP,
    "date": _DATE,
    "ssn": _SSN,
    "phone": r"(?<!\w)\+\d{1,3}[ -]?\(?\d{2,4}\)?(?:[ -]?\d{2,4}){2,4}(?!\w)",
    "card": rf"(?<![\w.-])\d(?:(?! (?:{_IP}|{_DATE}|{_SSN}))[ -]?\d){{12,}}+\w?",
}
#: One test of the character before spares all others inside words; all kinds but addresses begin with a digit or +.
ANY = rf"(?<!\w)(?:{PATTERNS['email']}|(?=[0-9+])(?:{'|'.join(p for k, p in PATTERNS.items() if k != 'email')}))"
#: Digits of card numbers.
CARD_DIGITS = (13, 19)
#: Digits of the first and of any further group of a card number that is written in groups.
FIRST_GROUP, NEXT_GROUP = 4, (3, 7)
#: Country calling codes of one and two digits; all others have three.
CALLING_CODE = r"^\+(?:1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|\d{1,3})"
#: Setting with the key of the permutations.
KEY_SETTING = "spark.stablegrammar.pseudonym.key"
ROUNDS = 8


def bound(value: Column, f: Callable[[Column], Column]) -> Column:
    """f of a value that is computed once, however often f names it."""
    return F.get(F.transform(F.array(value), f), F.lit(0))


def _noise(key: str, kind: Column | str, turn: Column, value: Column) -> Column:
    """60 keyed bits of a half."""
    kind = F.lit(kind) if isinstance(kind, str) else kind
    return F.conv(F.substring(F.sha2(F.concat_ws("|", F.lit(key), kind, turn.cast("string"), value.cast("string")), 256), 1, 15), 16, 10).cast("long")


def feistel(x: Column, a: int, b: int, key: str, kind: str) -> Column:
    """A keyed permutation of 0 .. a * b - 1: the two mixed-radix digits of x are shifted in turn by noise of the other."""
    halves = lambda v: F.struct(F.floor(v / F.lit(b)).cast("long").alias("l"), F.pmod(v, F.lit(b)).cast("long").alias("r"))
    return bound(x, lambda v: _run(halves(v), a, b, key, kind))


def _run(start: Column, a: int, b: int, key: str, kind: str) -> Column:
    turns = F.array(*(F.lit(i) for i in range(ROUNDS)))
    step = lambda s, i: F.when(i % 2 == 0, F.struct(F.pmod(s["l"] + _noise(key, kind, i, s["r"]), F.lit(a)).alias("l"), s["r"].alias("r"))).otherwise(
        F.struct(s["l"].alias("l"), F.pmod(s["r"] + _noise(key, kind, i, s["l"]), F.lit(b)).alias("r"))
    )
    return F.aggregate(turns, start, step, lambda s: s["l"] * F.lit(b) + s["r"])


def permuted_digits(digits: Column, key: str, kind: str) -> Column:
    """A keyed permutation of digit strings of each length: halves are shifted modulo powers of ten."""
    return bound(digits, lambda d: _permuted(d, key, kind))


def _permuted(digits: Column, key: str, kind: str) -> Column:
    n = F.length(digits)
    h = F.floor(n / 2).cast("int")
    half = lambda at, size: F.coalesce(F.substr(digits, at, size).try_cast("long"), F.lit(0)).cast("long")
    start = F.struct(half(F.lit(1), h).alias("l"), half(h + 1, n).alias("r"))
    size = lambda k: F.pow(F.lit(10), k).cast("long")
    kind_n = F.concat(F.lit(kind), n.cast("string"))
    shifted = lambda s, i, own, other, k: F.pmod(s[own] + _noise(key, kind_n, i, s[other]), size(k))
    left = lambda s, i: F.struct(shifted(s, i, "l", "r", h).alias("l"), s["r"].alias("r"))
    right = lambda s, i: F.struct(s["l"].alias("l"), shifted(s, i, "r", "l", n - h).alias("r"))
    padded = lambda x, k: F.when(k > 0, F.lpad(x.cast("string"), k, "0")).otherwise(F.lit(""))
    turns = F.array(*(F.lit(i) for i in range(ROUNDS)))
    return F.aggregate(turns, start, lambda s, i: F.when(i % 2 == 0, left(s, i)).otherwise(right(s, i)), lambda s: F.concat(padded(s["l"], h), padded(s["r"], n - h)))


def only_digits(m: Column) -> Column:
    return F.regexp_replace(m, r"[^0-9]", "")


def over_digits(m: Column, digits: Column) -> Column:
    """The value with its digits replaced in order and everything else kept."""
    char = lambda i: F.substr(m, i, F.lit(1))
    place = lambda i: F.length(only_digits(F.substr(m, F.lit(1), i)))
    places = F.sequence(F.lit(1), F.greatest(F.length(m), F.lit(1)))
    written = lambda d: F.transform(places, lambda i: F.when(char(i).rlike("[0-9]"), F.substr(d, place(i), F.lit(1))).otherwise(char(i)))
    return bound(digits, lambda d: F.array_join(written(d), ""))


def luhn_sum(digits: Column, check: bool) -> Column:
    """Luhn sum of a number with its check digit, or of its other digits if `check` is false."""
    odd = 1 if check else 0

    def total(d: Column) -> Column:
        at = lambda i: F.substr(d, F.length(d) - i, F.lit(1)).cast("int")
        doubled = lambda x: (x * 2) % 10 + F.floor(x / 5).cast("int")
        places = F.sequence(F.lit(0), F.greatest(F.length(d) - 1, F.lit(0)))
        return F.aggregate(places, F.lit(0), lambda acc, i: acc + F.when(i % 2 == odd, doubled(at(i))).otherwise(at(i)))

    return bound(digits, total)


def _card_number(digits: Column, key: str) -> Column:
    """The pseudonym of a number with a valid check digit, which it has too."""
    checked = lambda body: F.concat(body, F.pmod(-luhn_sum(body, False), F.lit(10)).cast("string"))
    return bound(permuted_digits(F.substr(digits, F.lit(1), F.length(digits) - 1), key, "card"), checked)


def _is_card(digits: Column) -> Column:
    return bound(digits, lambda d: F.length(d).between(*CARD_DIGITS) & (luhn_sum(d, True) % 10 == 0))


def _card(m: Column, key: str) -> Column:
    """A run of digit groups with the card numbers in it replaced: 13 to 19 digits whose check digit holds, in one group or in several,
    the first of 4 digits and the others of 3 to 7.

    From left to right, the fewest groups that make one are taken; a span of several groups has none that is a card number by itself.
    """
    whole = F.size(F.regexp_extract_all(m, F.lit("[0-9]+"), F.lit(0))) - m.rlike("[^0-9]$").cast("int")  # a group that a letter is glued to is no candidate
    spans = lambda groups: bound(_card_ends(groups, whole), _first_spans)
    new = lambda groups, spans: F.when(F.size(spans) > 0, over_digits(m, _with_cards(groups, spans, key))).otherwise(m)
    return bound(F.regexp_extract_all(m, F.lit("[0-9]+"), F.lit(0)), lambda groups: bound(spans(groups), lambda found: new(groups, found)))


def _joined(groups: Column, i: Column, j: Column) -> Column:
    return F.array_join(F.slice(groups, i + 1, j - i + 1), "")


def _card_ends(groups: Column, count: Column) -> Column:
    """For each group the last group of the shortest card number that begins with it, or -1."""
    sizes = lambda i, j: F.transform(F.slice(groups, i + 2, j - i), lambda g: F.length(g))
    grouped = lambda i, j: F.forall(sizes(i, j), lambda n: n.between(*NEXT_GROUP)) & ~F.exists(F.slice(groups, i + 1, j - i + 1), _is_card)
    until = lambda i: F.sequence(i + 1, F.greatest(i + 1, F.least(count - 1, i + 5)))
    last = lambda i: F.filter(until(i), lambda j: (j < count) & grouped(i, j) & _is_card(_joined(groups, i, j)))
    several = lambda i: F.coalesce(F.get(last(i), F.lit(0)), F.lit(-1))
    end = lambda g, i: F.when(_is_card(g), i).when(F.length(g) == FIRST_GROUP, several(i)).otherwise(F.lit(-1))
    return F.transform(groups, lambda g, i: F.when(i < count, end(g, i)).otherwise(F.lit(-1)))


def _first_spans(ends: Column) -> Column:
    """Spans (i, j) of groups from left to right, none of which overlap."""
    start = F.struct(F.lit(0).alias("next"), F.array().cast("array<struct<i:int,j:int>>").alias("spans"))
    taken = lambda s, x: F.struct((x["j"] + 1).alias("next"), F.concat(s["spans"], F.array(x)).alias("spans"))
    step = lambda s, x: F.when((x["j"] >= 0) & (x["i"] >= s["next"]), taken(s, x)).otherwise(s)
    return F.aggregate(F.transform(ends, lambda j, i: F.struct(i.alias("i"), j.alias("j"))), start, step, lambda s: s["spans"])


def _with_cards(groups: Column, spans: Column, key: str) -> Column:
    """The digits of all groups, those of each span replaced."""
    own = lambda i: F.get(F.filter(spans, lambda x: (x["i"] <= i) & (x["j"] >= i)), F.lit(0))
    number = lambda x, i: F.when(x["i"] == i, _card_number(_joined(groups, x["i"], x["j"]), key)).otherwise(F.lit(""))
    piece = lambda g, i: bound(own(i), lambda x: F.when(x.isNull(), g).otherwise(number(x, i)))
    return F.array_join(F.transform(groups, piece), "")


def _phone(m: Column, key: str) -> Column:
    permuted = lambda rest: over_digits(rest, permuted_digits(only_digits(rest), key, "phone"))
    return bound(F.regexp_extract(m, CALLING_CODE, 0), lambda code: F.concat(code, bound(F.substr(m, F.length(code) + 1, F.length(m)), permuted)))


def _ssn(m: Column, key: str) -> Column:
    """Areas 001 to 899 but 666, groups 01 to 99 and serials 0001 to 9999 are the whole domain, 898 * 99 by 9999."""
    area, group, serial = (F.substring(m, at, n).cast("long") for at, n in ((1, 3), (5, 2), (8, 4)))
    rank = area - 1 - (area > 666).cast("long")
    padded = lambda x, n: F.lpad(x.cast("string"), n, "0")
    place = lambda x: F.floor(x / F.lit(99 * 9999)).cast("long")
    parts = lambda x: (place(x) + 1 + (place(x) >= 665).cast("long"), F.floor(x / F.lit(9999)).cast("long") % 99 + 1, x % 9999 + 1)
    written = lambda x: F.concat_ws("-", *(padded(v, n) for v, n in zip(parts(x), (3, 2, 4), strict=True)))
    return bound(feistel((rank * 99 + group - 1) * 9999 + serial - 1, 898 * 99, 9999, key, "ssn"), written)


def _date(m: Column, key: str) -> Column:
    """The 17 * 4297 days from 1900-01-01 to 2099-12-31, all that the pattern admits; impossible dates stay."""
    day = F.try_to_timestamp(m, F.lit("yyyy-MM-dd")).cast("date")
    since = F.datediff(day, F.lit("1900-01-01").cast("date")).cast("long")
    return F.coalesce(F.date_format(F.date_add(F.lit("1900-01-01").cast("date"), feistel(since, 17, 4297, key, "date").cast("int")), "yyyy-MM-dd"), m)


def _ip(m: Column, key: str) -> Column:
    part = F.transform(F.split(m, r"\."), lambda x: x.cast("long"))
    start = F.struct((part[0] * 256 + part[1]).alias("l"), (part[2] * 256 + part[3]).alias("r"))
    turns = F.array(*(F.lit(i) for i in range(ROUNDS)))
    half = lambda v, i, o: F.pmod(v + _noise(key, "ip", i, o), F.lit(65536))
    step = lambda s, i: F.when(i % 2 == 0, F.struct(half(s["l"], i, s["r"]).alias("l"), s["r"].alias("r"))).otherwise(F.struct(s["l"].alias("l"), half(s["r"], i, s["l"]).alias("r")))
    byte = lambda v: F.concat_ws(".", F.floor(v / 256).cast("string"), (v % 256).cast("string"))
    return F.aggregate(turns, start, step, lambda s: F.concat_ws(".", byte(s["l"]), byte(s["r"])))


def _email(m: Column, key: str) -> Column:
    """The local part's letters and digits shifted within their classes, each half in turn by noise of the other; the domain stays."""
    local = F.substring_index(m, "@", 1)
    n = F.length(local)
    h = F.floor(n / 2).cast("int")

    def shifted(s: Column, other: Column, turn: Column) -> Column:
        noise = F.sha2(F.concat_ws("|", F.lit(key), F.lit("email"), turn.cast("string"), other), 512)
        by = lambda i: F.conv(F.substr(noise, F.pmod(i * 2, F.lit(126)) + 1, F.lit(2)), 16, 10).cast("int")
        c = lambda i: F.substr(s, i, F.lit(1))
        move = lambda i, first, size: F.char(F.pmod(F.ascii(c(i)) - first + by(i), F.lit(size)) + first)
        out = F.transform(F.sequence(F.lit(1), F.greatest(F.length(s), F.lit(1))), lambda i: F.when(c(i).rlike("[a-z]"), move(i, 97, 26)).when(c(i).rlike("[A-Z]"), move(i, 65, 26)).when(c(i).rlike("[0-9]"), move(i, 48, 10)).otherwise(c(i)))
        return F.array_join(out, "")

    start = F.struct(F.substr(local, F.lit(1), h).alias("l"), F.substr(local, h + 1, n).alias("r"))
    step = lambda s, i: F.when(i % 2 == 1, F.struct(shifted(s["l"], s["r"], i).alias("l"), s["r"].alias("r"))).otherwise(F.struct(s["l"].alias("l"), shifted(s["r"], s["l"], i).alias("r")))
    return F.concat(F.aggregate(F.array(*(F.lit(i) for i in range(4))), start, step, lambda s: F.concat(s["l"], s["r"])), F.substr(m, n + 1, F.length(m)))


def pseudonym(m: Column, key: str) -> Column:
    """The pseudonym of one candidate; what validation rejects stays as it is."""
    whole = {k: m.rlike(f"^(?:{p})$") for k, p in PATTERNS.items()}
    return (
        F.when(m.contains("@"), _email(m, key)).when(whole["ip"], _ip(m, key)).when(whole["date"], _date(m, key))
        .when(whole["ssn"], _ssn(m, key)).when(m.startswith("+"), _phone(m, key)).otherwise(_card(m, key))
    )


def pseudonymised(text: Column, key: str) -> Column:
    """A text with every validated value replaced; candidates and the text between them are found by one pattern."""
    found = F.transform(F.regexp_extract_all(text, F.lit(ANY), F.lit(0)), lambda m: pseudonym(m, key))
    gaps = F.split(text, ANY, -1)
    joined = F.array_join(F.transform(gaps, lambda g, i: F.concat(g, F.coalesce(F.get(found, i), F.lit("")))), "")
    return F.when(text.rlike(ANY), joined).otherwise(text)


def pseudonymise(docs: DataFrame, *, key: str, text_col: str = "text", count_col: str | None = None) -> DataFrame:
    """The same rows and columns with the text's validated values replaced; with `count_col`, also how many values changed.

    One narrow scan; texts without a candidate end there. Null texts stay null (count 0), empty ones empty; texts of any length are
    replaced whole. Candidates that begin together are taken in the order of PATTERNS, and don't overlap. Other columns and ids of any kind
    are kept as they are, and `count_col` must be an unused name; repeated rows stay equal; an empty table gives an empty result.
    `key` keys the permutations, each over the whole domain of its kind, so distinct values stay distinct and valid.
    """
    if not key:
        raise ValueError("pseudonyms need a key")
    out = docs.withColumn(text_col, pseudonymised(docs[text_col], key))
    if count_col is None:
        return out
    if unused(docs.columns, count_col) != count_col:
        raise ValueError(f"there is a column {count_col} already")
    values = F.regexp_extract_all(docs[text_col], F.lit(ANY), F.lit(0))
    changed = F.size(F.filter(F.transform(values, lambda m: m != pseudonym(m, key)), lambda x: x))
    return docs.withColumns({text_col: pseudonymised(docs[text_col], key), count_col: F.when(docs[text_col].rlike(ANY), changed).otherwise(F.lit(0))})


def key_of(spark: SparkSession) -> str:
    """The key in the session's settings; without one a fixed key that is no secret, for trials."""
    return spark.conf.get(KEY_SETTING, "trial key, not secret")
