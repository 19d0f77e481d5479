"""Closed forms for the binned-minimum sketch: laws of holes and matches, variances, rules of thumb.

q(c) is the chance that c given bins hold none of the union's f elements. All
functions take D, k, f (size of the union), a (size of the intersection). The
column forms are the same expressions over columns d, k, f, a.
"""

from __future__ import annotations

import math
from fractions import Fraction

from pyspark.sql import Column
from pyspark.sql import functions as F


def q(d: int, k: int, f: int, c: int) -> float:
    free = d - c * d // k
    if f > free:
        return 0.0
    lg = math.lgamma
    return math.exp(lg(free + 1) - lg(free - f + 1) - lg(d + 1) + lg(d - f + 1))


def q_exact(d: int, k: int, f: int, c: int) -> Fraction:
    return Fraction(math.comb(d - c * d // k, f), math.comb(d, f))


def empty_mean(d, k, f, q=q):
    return k * q(d, k, f, 1)


def empty_var(d, k, f, q=q):
    q1 = q(d, k, f, 1)
    return k * q1 + k * (k - 1) * q(d, k, f, 2) - (k * q1) ** 2


def empty_mean_bound(k, f):
    """Never below the mean: k (1 - 1/k)^f."""
    return k * (1 - 1 / k) ** f


def empty_share_expanded(d: int, k: int, f: int) -> float:
    """Share of holes: the power form times a correction for drawing without replacement, summed exactly over the draws."""
    return (1 - 1 / k) ** f * math.exp(sum(math.log1p(-i / (d * (1 - 1 / k))) - math.log1p(-i / d) for i in range(f)))


def empty_share_sparse(k: int, f: int) -> float:
    return (1 - 1 / k) ** f


def empty_pmf(d: int, k: int, f: int) -> list[Fraction]:
    """P(j holes) for j = 0..k, exactly, by inclusion and exclusion over further bins (small k)."""
    w, total = d // k, math.comb(d, f)
    out = []
    for j in range(k + 1):
        s = sum((-1) ** i * math.comb(k - j, i) * math.comb(w * (k - j - i), f) for i in range(k - j + 1))
        out.append(Fraction(math.comb(k, j) * s, total))
    return out


def match_mean(d, k, f, a, q=q):
    return k * (1 - q(d, k, f, 1)) * a / f


def match_var(d, k, f, a, q=q):
    mean = match_mean(d, k, f, a, q)
    if f == 1:
        return mean - mean * mean
    both = 1 - 2 * q(d, k, f, 1) + q(d, k, f, 2)
    pair = both * a * (a - 1) / (f * (f - 1)) if isinstance(both, Fraction) else both * (a / f) * ((a - 1) / (f - 1))
    return mean + k * (k - 1) * pair - mean * mean


def match_empty_cov(d, k, f, a, q=q):
    q1, q2 = q(d, k, f, 1), q(d, k, f, 2)
    return k * (k - 1) * (q1 - q2) * a / f - k * k * (1 - q1) * q1 * a / f


def inv_nonempty(d: int, k: int, f: int, exact: bool = False) -> float:
    """E[1/(k - holes)]: exactly (small k), or its lower bound, which serves as the approximation."""
    if exact:
        return float(sum(p / (k - j) for j, p in enumerate(empty_pmf(d, k, f)) if j < k))
    return 1 / (k - empty_mean(d, k, f))


def unbiased_var(d: int, k: int, f: int, a: int, exact: bool = False) -> float:
    if f <= 1:
        return 0.0
    r = a / f
    return r * (1 - r) * (inv_nonempty(d, k, f, exact) * f - 1) / (f - 1)


def classic_var(k: int, r: float) -> float:
    return r * (1 - r) / k


def variance_ratio(f: int, k: int) -> float:
    """Variance of one permutation's estimator over that of k permutations, D large; at most 1."""
    if f <= 1:
        return 0.0
    return (k * f / (k * -math.expm1(f * math.log1p(-1 / k))) - k) / (f - 1) if k > 1 else (f - 1) / (f - 1)


def ragged_empty_mean(k: int, f: int) -> float:
    return k * (1 - 1 / k) ** f


def ragged_empty_var(k: int, f: int) -> float:
    p1, p2 = (1 - 1 / k) ** f, (1 - 2 / k) ** f
    return k * p1 + k * (k - 1) * p2 - (k * p1) ** 2


def widths_gap(d: int, k: int, f: int) -> float:
    """Ragged less equal widths, in mean holes; never negative."""
    return ragged_empty_mean(k, f) - empty_mean(d, k, f)


def suggest_k(f: int, most_holes: float = 0.0067) -> int:
    """The largest power of two whose expected share of holes stays within ``most_holes``."""
    k = 1
    while (1 - 1 / (2 * k)) ** f <= most_holes:
        k *= 2
    return k


def joint_pmf(d: int, k: int, f: int, a: int) -> dict[tuple[int, int], Fraction]:
    """P(holes, matches): given the holes, matches are a sample without replacement."""
    out = {}
    for j, p in enumerate(empty_pmf(d, k, f)):
        r = k - j
        for m in range(min(r, a) + 1):
            if p and f - a >= r - m:
                out[j, m] = p * Fraction(math.comb(a, m) * math.comb(f - a, r - m), math.comb(f, r))
    return out


def interval(matches: Column, filled: Column, f: Column, z: float = 1.96) -> tuple[Column, Column]:
    """Bounds of the resemblance from matches among filled bins (normal, with the finite correction), within 0..1."""
    r = F.try_divide(matches, filled)
    half = F.lit(z) * F.sqrt(r * (1 - r) / filled * F.greatest((f - filled) / F.greatest(f - 1, F.lit(1)), F.lit(0.0)))
    return F.greatest(r - half, F.lit(0.0)), F.least(r + half, F.lit(1.0))


def q_col(c: int) -> Column:
    """q(c) over columns d, k, f: the product over draws, as a sum of logarithms; 0 where it can't be."""
    free = F.col("d") - F.lit(c) * F.expr("d div k")
    logs = F.aggregate(F.sequence(F.lit(0).cast("long"), F.col("f") - 1), F.lit(0.0), lambda s, i: s + F.log((free - i) / (F.col("d") - i)))
    return F.when(F.col("f") > free, F.lit(0.0)).otherwise(F.exp(logs))


def law_columns(params):
    """Adds every quantity to rows (d, k, f, a): one pass, native expressions."""
    k, f, a = (F.col(x).cast("double") for x in "kfa")
    q1, q2, r = F.col("q1"), F.col("q2"), a / f
    p1, p2 = F.pow(1 - 1 / k, f), F.pow(1 - 2 / k, f)
    t = params.withColumn("q1", q_col(1)).withColumn("q2", q_col(2))
    t = t.withColumn("empty_mean", k * q1).withColumn("empty_var", k * q1 + k * (k - 1) * q2 - k * k * q1 * q1)
    t = t.withColumn("match_mean", k * r * (1 - q1))
    t = t.withColumn("match_var", F.col("match_mean") + k * (k - 1) * r * (a - 1) / (f - 1) * (1 - 2 * q1 + q2) - F.pow("match_mean", F.lit(2)))
    t = t.withColumn("cov", k * (k - 1) * r * (q1 - q2) - k * k * r * (1 - q1) * q1)
    t = t.withColumn("h", 1 / (k - F.col("empty_mean"))).withColumn("unbiased_var", r * (1 - r) * (F.col("h") * f - 1) / (f - 1))
    t = t.withColumn("classic_var", r * (1 - r) / k).withColumn("ratio", f / ((f - 1) * (1 - p1)) - k / (f - 1))
    return t.withColumn("ragged_mean", k * p1).withColumn("ragged_var", k * p1 + k * (k - 1) * p2 - k * k * p1 * p1).withColumn("sparse_share", p1)
