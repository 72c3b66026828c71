"""The grammar as a record of lazy tables."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stablegrammar.functions.hashing import HashFamily


@dataclass(frozen=True)
class Grammar:
    """rules(level, sym, rhs, rhs_len, exp_len, fp), roots(string_id, root_sym, root_level, n_symbols), runs(level, sym, base, run_len).

    sym and the elements of rhs have one type: binary(16) content names, or strings (decimal code points, hex digests). A terminal's
    binary name is 8 zero bytes, then its code point.
    """

    rules: DataFrame
    roots: DataFrame
    family: HashFamily
    runs: DataFrame | None = None
    k: int | None = None
    #: The parcels that the tables are read from, if the build stored these alone.
    packed: DataFrame | None = None

    def with_rules(self, rules: DataFrame) -> Grammar:
        return replace(self, rules=rules, packed=None)

    def alphabet(self) -> DataFrame:
        """sym, ch of the terminals in use."""
        binary = dict(self.rules.dtypes)["sym"] == "binary"
        code = lambda s: F.conv(F.hex(s), 16, 10).cast("int") if binary else s.cast("int")
        used = self.rules.where("level = 1").select(F.explode("rhs").alias("sym")).union(self.roots.where("root_level = 0").select("root_sym")).distinct()
        return used.select("sym", char_of(code(F.col("sym"))).alias("ch"))


def char_of(code):
    """The character of any code point (SQL's char() stops at 255)."""
    return F.decode(F.unhex(F.lpad(F.hex(code), 8, "0")), "UTF-32")
