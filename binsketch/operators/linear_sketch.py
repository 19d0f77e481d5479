"""Comparators that sum instead of taking minima: bin sums, debiased and signed, projections."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def bin_sums(sets: DataFrame, bin_hash, k: int, sign: Column | None = None) -> DataFrame:
    """set_id, bin, val: how many elements of a set fall in each of k hashed bins (times a sign, if given)."""
    one = F.lit(1) if sign is None else sign
    return sets.distinct().groupBy("set_id", F.pmod(bin_hash.pos(F.col("elem")), F.lit(k)).cast("int").alias("bin")).agg(F.sum(one).cast("long").alias("val"))


def signed_sums(sets: DataFrame, bin_hash, sign_hash, k: int) -> DataFrame:
    """Each element counts +1 or -1, so that chance meetings cancel in the mean."""
    return bin_sums(sets, bin_hash, k, F.lit(1) - 2 * (sign_hash.pos(F.col("elem")) % 2))


def dots(sums: DataFrame, pairs: DataFrame) -> DataFrame:
    """i, j, dot of bin sums."""
    x = pairs.join(sums.select(F.col("set_id").alias("i"), "bin", F.col("val").alias("x")), "i")
    both = x.join(sums.select(F.col("set_id").alias("j"), "bin", F.col("val").alias("y")), ["j", "bin"])
    n = both.groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("dot"))
    return pairs.join(n, ["i", "j"], "left").fillna(0, ["dot"])


def debiased(dot: Column, f1: Column, f2: Column, k: int) -> Column:
    """The intersection's size without what k bins bring together by chance."""
    return (dot - f1 * f2 / F.lit(float(k))) * F.lit(k / (k - 1)) if k > 1 else dot.cast("double")


def random_projection(sets: DataFrame, sign_hash_seed: int, k: int) -> DataFrame:
    """set_id, bin, val: k sums of +1 / -1 signs over all elements, from the bits of one hash for each 62 of them."""
    words = [F.xxhash64("elem", F.lit(sign_hash_seed), F.lit(w)) for w in range(-(-k // 62))]
    sums = [F.sum(F.lit(1) - 2 * F.shiftrightunsigned(words[j // 62], j % 62).bitwiseAND(F.lit(1))).alias(f"s{j}") for j in range(k)]
    wide = sets.distinct().groupBy("set_id").agg(*sums)
    return wide.select("set_id", F.posexplode(F.array(*[F.col(f"s{j}") for j in range(k)])).alias("bin", "val"))


def projected_intersection(sums: DataFrame, pairs: DataFrame, k: int) -> DataFrame:
    """i, j, a_hat: the mean product of projections."""
    return dots(sums, pairs).select("i", "j", (F.col("dot") / F.lit(float(k))).alias("a_hat"))


def projection_sums(sets: DataFrame, permuters: list) -> DataFrame:
    """The same with one permutation's upper half a sign: any engine computes them alike."""
    sums = [F.sum(F.lit(1) - 2 * F.floor(p.pos(F.col("elem")) / F.lit(p.size // 2))).cast("long").alias(f"s{j}") for j, p in enumerate(permuters)]
    wide = sets.distinct().groupBy("set_id").agg(*sums)
    return wide.select("set_id", F.posexplode(F.array(*[F.col(f"s{j}") for j in range(len(permuters))])).alias("bin", "val"))


def frequency_counters(elements: DataFrame, hashes: list, cells: int) -> DataFrame:
    """r, cell, n: how many elements fall in each cell of each row; len(hashes) * cells rows at most, after partial sums."""
    places = F.explode(F.array(*[F.struct(F.lit(j).alias("r"), (h.pos(F.col("elem")) % F.lit(cells)).alias("cell")) for j, h in enumerate(hashes)]))
    return elements.select(places.alias("p")).groupBy("p.r", "p.cell").agg(F.count(F.lit(1)).alias("n"))


def frequency_estimates(counters: DataFrame, asked: DataFrame, hashes: list, cells: int) -> DataFrame:
    """``asked`` (elem and more) with the least of its cells' counts: never below the true count."""
    places = F.explode(F.array(*[F.struct(F.lit(j).alias("r"), (h.pos(F.col("elem")) % F.lit(cells)).alias("cell")) for j, h in enumerate(hashes)]))
    rows = asked.withColumn("p", places).select(*asked.columns, "p.r", "p.cell")
    return rows.join(counters.withColumnRenamed("n", "in_cell"), ["r", "cell"]).groupBy(*asked.columns).agg(F.min("in_cell").alias("estimate"))
