"""Universal hashing of integers and sequences, and the family that gives each grammar level its own function."""

from __future__ import annotations

import random
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _is_prime(n: int) -> bool:
    if n < 2 or any(n % q == 0 and n != q for q in (2, 3, 5, 7, 11, 13, 17, 19, 23, 29, 31, 37)):
        return False
    d, s = n - 1, 0
    while d % 2 == 0:
        d, s = d // 2, s + 1
    for a in (2, 3, 5, 7, 11, 13, 17, 19, 23, 29, 31, 37):
        x = pow(a, d, n)
        if a % n and x not in (1, n - 1):
            for _ in range(s - 1):
                x = x * x % n
                if x == n - 1:
                    break
            else:
                return False
    return True


@dataclass(frozen=True)
class Level:
    """One function: prime, range, and multipliers (the last for sequences)."""

    p: int
    m: int
    a: int
    b: int
    c: int


@dataclass(frozen=True)
class HashFamily:
    """Independent functions of levels 0, 1, …; grammars merge only if they share one."""

    seed: int
    bits: int
    levels: tuple[Level, ...]

    def __getitem__(self, i: int) -> Level:
        if i >= len(self.levels):
            raise ValueError(f"a string needs more than {len(self.levels) - 1} rounds; make a family of more levels")
        return self.levels[i]

    def rows(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(i, x.p, x.m, x.a, x.b, x.c) for i, x in enumerate(self.levels)], "level int, p long, m long, a long, b long, c long")


def make_family(seed: int = 42, levels: int = 64, bits: int = 31) -> HashFamily:
    """Ranges are 2**bits; primes lie in (2**31, 1.4 * 2**31), so that products stay below 2**63 in every engine."""
    if not 1 <= bits <= 31:
        raise ValueError("bits must be 1 to 31; 61-bit fingerprints are wide_fingerprint()'s")
    draw, used, out = random.Random(seed), set(), []
    while len(out) < levels:
        p = draw.randrange(2**31 + 1, int(1.4 * 2**31)) | 1
        while p in used or not _is_prime(p):
            p += 2
        used.add(p)
        out.append(Level(p, 1 << bits, *(draw.randrange(1, p) for _ in range(3))))
    return HashFamily(seed, bits, tuple(out))


def affine_hash(x: Column, h: Level) -> Column:
    """((a x + b) mod p) mod m of an integer column."""
    return F.pmod(F.pmod(F.lit(h.a).cast("long") * x.cast("long") + F.lit(h.b).cast("long"), F.lit(h.p)), F.lit(h.m))


def poly_hash(xs: Column, h: Level) -> Column:
    """The polynomial hash of an array of fingerprints; its first element has power 0."""
    total = F.aggregate(F.reverse(xs), F.lit(0).cast("long"), lambda acc, x: F.pmod(acc * F.lit(h.c).cast("long") + x, F.lit(h.p)))
    return affine_hash(total, h)


def wide_fingerprint(xs: Column, p: int = 2**61 - 1, c: int = 1_000_003) -> Column:
    """A 61-bit polynomial hash in decimal arithmetic, for fingerprints of billions of symbols per level."""
    wide = lambda v: v.cast("decimal(38,0)")
    return F.aggregate(F.reverse(xs), wide(F.lit(0)), lambda acc, x: wide(F.pmod(wide(acc * wide(F.lit(c))) + wide(x), wide(F.lit(p))))).cast("long")


def poly_hash_py(xs: list[int], h: Level) -> int:
    total = 0
    for x in reversed(xs):
        total = (total * h.c + x) % h.p
    return (h.a * total + h.b) % h.p % h.m


def fp_by_traversal(tree, level: int, family: HashFamily) -> int:
    """A symbol's fingerprint from its whole parse tree (nested lists over code points), without stored fingerprints below it."""
    if level == 0:
        h = family[0]
        return (h.a * tree + h.b) % h.p % h.m
    return poly_hash_py([fp_by_traversal(x, level - 1, family) for x in tree], family[level])
