"""Permutations of the universe 0..D-1, as column expressions, SQL text and numpy."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Identity:
    """For sets that are given permuted."""

    size: int

    def pos(self, elem: Column) -> Column:
        return elem

    def sql(self, elem: str) -> str:
        return elem

    def numpy(self, elem: np.ndarray) -> np.ndarray:
        return elem


@dataclass(frozen=True)
class Affine:
    """(a * x + b) mod D with a prime to D: a bijection. Low bits stay weak for D = 2^q, so only for hashed ids."""

    size: int
    a: int
    b: int

    def __post_init__(self):
        if np.gcd(self.a, self.size) != 1 or max(self.a, self.size) >= 1 << 31:
            raise ValueError("a must be prime to D, and both below 2^31")

    def pos(self, elem: Column) -> Column:
        return (elem * F.lit(self.a) + F.lit(self.b)) % F.lit(self.size)

    def sql(self, elem: str) -> str:
        return f"(({elem}) * {self.a} + {self.b}) % {self.size}"

    def numpy(self, elem: np.ndarray) -> np.ndarray:
        return (elem.astype(np.int64) * self.a + self.b) % self.size


@dataclass(frozen=True)
class Universal:
    """((a * x + b) mod p) mod D, p prime above D: nearly a permutation, with collisions."""

    size: int
    a: int
    b: int
    p: int = 2147483647

    def pos(self, elem: Column) -> Column:
        return (elem * F.lit(self.a) + F.lit(self.b)) % F.lit(self.p) % F.lit(self.size)

    def sql(self, elem: str) -> str:
        return f"((({elem}) * {self.a} + {self.b}) % {self.p}) % {self.size}"

    def numpy(self, elem: np.ndarray) -> np.ndarray:
        return (elem.astype(np.int64) * self.a + self.b) % self.p % self.size


@dataclass(frozen=True)
class Digest:
    """The first 28 bits of md5(seed:x), mod D: the same in any SQL engine."""

    size: int
    seed: int

    def pos(self, elem: Column) -> Column:
        text = F.concat(F.lit(f"{self.seed}:"), elem.cast("string"))
        return F.conv(F.substring(F.md5(text.cast("binary")), 1, 7), 16, 10).cast("long") % F.lit(self.size)

    def sql(self, elem: str) -> str:
        return f"('0x' || substring(md5('{self.seed}:' || CAST({elem} AS VARCHAR)), 1, 7))::BIGINT % {self.size}"


@dataclass(frozen=True)
class Feistel:
    """Four keyed rounds over the two halves of the bits: a bijection of 0..2^q-1 with nothing stored (q up to 62)."""

    bits: int
    seed: int

    @property
    def size(self) -> int:
        return 1 << self.bits

    def pos(self, elem: Column) -> Column:
        low = self.bits // 2
        high = self.bits - low
        left, right = F.shiftrightunsigned(elem, low), elem.bitwiseAND(F.lit((1 << low) - 1))
        for r in range(4):  # the halves swap widths each round
            width = high if r % 2 == 0 else low
            left, right = right, left.bitwiseXOR(F.xxhash64(right, F.lit(r), F.lit(self.seed)).bitwiseAND(F.lit((1 << width) - 1)))
        return F.shiftleft(left, low).bitwiseOR(right)


@dataclass(frozen=True)
class Hash64:
    """xxhash64 over the whole 64-bit universe; positions are compared unsigned through a flipped sign bit."""

    seed: int
    size: int = 1 << 64

    def pos(self, elem: Column) -> Column:
        return F.xxhash64(elem, F.lit(self.seed))


def unsigned_order(pos: Column) -> Column:
    """A signed long that orders as the unsigned one does."""
    return pos.bitwiseXOR(F.lit(-(1 << 63)))


def unsigned_bin(pos: Column, bits: int) -> Column:
    """The top ``bits`` of 64 as the bin."""
    return F.shiftrightunsigned(pos, 64 - bits).cast("int")


def permutation_vector(spark: SparkSession, size: int, seed: int) -> DataFrame:
    """elem, pos: a materialised permutation (rank by digest). For universes of 2^20 at most; others are computed."""
    if size > 1 << 20:
        raise ValueError("a stored permutation is for small universes; use Affine or Feistel")
    ids = spark.range(size).select(F.col("id").alias("elem"))
    key = F.md5(F.concat(F.lit(f"{seed}:"), F.col("elem").cast("string")).cast("binary"))
    return ids.select("elem", (F.row_number().over(Window.orderBy(key, "elem")) - 1).cast("long").alias("pos"))


def permutation_matrix(spark: SparkSession, size: int, seeds: list[int]) -> DataFrame:
    """perm, elem, pos: one vector for each seed (the classic sketch's storage; small universes only)."""
    out = None
    for j, s in enumerate(seeds):
        one = permutation_vector(spark, size, s).withColumn("perm", F.lit(j))
        out = one if out is None else out.unionByName(one)
    return out.select("perm", "elem", "pos")


def to_json(permuter) -> str:
    return json.dumps({"kind": type(permuter).__name__, **asdict(permuter)}, sort_keys=True)


def from_json(text: str):
    spec = json.loads(text)
    kinds = {c.__name__: c for c in (Identity, Affine, Universal, Digest, Feistel, Hash64)}
    return kinds[spec.pop("kind")](**spec)
