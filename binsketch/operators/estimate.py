"""Resemblance: exact, and from sketches of pairs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..tables import written


def pair_resemblance(sets: DataFrame, pairs: DataFrame) -> DataFrame:
    """i, j, f1, f2, a, r_exact of given pairs; both empty: null."""
    own = sets.distinct()
    n = own.groupBy("set_id").agg(F.count(F.lit(1)).alias("f"))
    left = pairs.join(own.select(F.col("set_id").alias("i"), "elem"), "i")
    a = left.join(own.select(F.col("set_id").alias("j"), "elem"), ["j", "elem"]).groupBy("i", "j").agg(F.count(F.lit(1)).alias("a"))
    t = pairs.join(n.select(F.col("set_id").alias("i"), F.col("f").alias("f1")), "i", "left").join(n.select(F.col("set_id").alias("j"), F.col("f").alias("f2")), "j", "left").join(a, ["i", "j"], "left").fillna(0, ["f1", "f2", "a"])
    return t.select("i", "j", "f1", "f2", "a", resemblance(F.col("f1"), F.col("f2"), F.col("a")).alias("r_exact"))


def resemblance(f1: Column, f2: Column, a: Column) -> Column:
    return F.try_divide(a.cast("double"), f1 + f2 - a)


def all_pairs(sets: DataFrame, min_r: float = 0.0) -> DataFrame:
    """i < j, f1, f2, a, r_exact of all pairs that share an element and have r >= min_r.

    With min_r above 0 the elements of a set are ranked from rare to common and
    only the first f - ceil(min_r f) + 1 join, with a bound on sizes; every
    survivor is counted exactly. With 0 all elements join: the exhaustive baseline, whose
    output is all pairs that share anything.
    """
    own = written(sets.distinct(), "own")
    n = own.groupBy("set_id").agg(F.count(F.lit(1)).alias("f"))
    if min_r <= 0:
        x, y = own.select(F.col("set_id").alias("i"), "elem"), own.select(F.col("set_id").alias("j"), "elem")
        shared = x.join(y, "elem").filter("i < j").groupBy("i", "j").agg(F.count(F.lit(1)).alias("a"))
        t = shared.join(n.select(F.col("set_id").alias("i"), F.col("f").alias("f1")), "i").join(n.select(F.col("set_id").alias("j"), F.col("f").alias("f2")), "j")
        return t.select("i", "j", "f1", "f2", "a", resemblance(F.col("f1"), F.col("f2"), F.col("a")).alias("r_exact"))
    df = own.groupBy("elem").agg(F.count(F.lit(1)).alias("df"))
    ranked = own.join(df, "elem").groupBy("set_id").agg(F.sort_array(F.collect_list(F.struct("df", "elem"))).alias("e"))
    ranked = ranked.select("set_id", F.size("e").alias("f"), F.transform("e", lambda s: s["elem"]).alias("e"))
    head = ranked.select("set_id", "f", F.explode(F.slice("e", F.lit(1), (F.col("f") - F.ceil(F.lit(min_r) * F.col("f") - 1e-9) + 1).cast("int"))).alias("elem"))
    x, y = (head.select(F.col("set_id").alias(s), F.col("f").alias(f"f{s}"), "elem") for s in "ij")
    pairs = written(x.join(y, "elem").filter((F.col("i") < F.col("j")) & (F.least("fi", "fj") >= F.lit(min_r) * F.greatest("fi", "fj"))).select("i", "j").distinct(), "prefix-pairs")
    return pair_resemblance(own, pairs).filter(F.col("r_exact") >= min_r)


def pair_counters(sketch: DataFrame, pairs: DataFrame, k: int, value: str = "offset") -> DataFrame:
    """i, j, n_mat, n_both, n_emp, n_emp_i, n_emp_j.

    Matches and doubly filled bins are counted where both have the bin;
    jointly empty ones are k less the union of filled bins.
    """
    filled = sketch.groupBy("set_id").agg(F.count("bin").cast("int").alias("c"))
    x = pairs.join(sketch.select(F.col("set_id").alias("i"), "bin", F.col(value).alias("x")), "i")
    both = x.join(sketch.select(F.col("set_id").alias("j"), "bin", F.col(value).alias("y")), ["j", "bin"])
    n = both.groupBy("i", "j").agg(F.count_if(F.col("x") == F.col("y")).alias("n_mat"), F.count(F.lit(1)).alias("n_both"))
    t = pairs.join(filled.select(F.col("set_id").alias("i"), F.col("c").alias("ci")), "i", "left").join(filled.select(F.col("set_id").alias("j"), F.col("c").alias("cj")), "j", "left").join(n, ["i", "j"], "left").fillna(0, ["ci", "cj", "n_mat", "n_both"])
    whole = lambda c: c.cast("int")
    return t.select("i", "j", whole(F.col("n_mat")).alias("n_mat"), whole(F.col("n_both")).alias("n_both"), whole(F.lit(k) - F.col("ci") - F.col("cj") + F.col("n_both")).alias("n_emp"), whole(F.lit(k) - F.col("ci")).alias("n_emp_i"), whole(F.lit(k) - F.col("cj")).alias("n_emp_j"))


def unbiased(k: int) -> Column:
    """Matches among bins not jointly empty; null if both sets are empty."""
    return F.try_divide(F.col("n_mat").cast("double"), F.lit(k) - F.col("n_emp"))


def separable(k: int) -> Column:
    """By each set's own filled bins: an inner product of scaled sketches; too high for very unequal sizes."""
    return F.try_divide(F.col("n_mat").cast("double"), F.sqrt((F.lit(k) - F.col("n_emp_i")).cast("double") * (F.lit(k) - F.col("n_emp_j"))))


def over_k(k: int) -> Column:
    """The denominator of noise coding."""
    return F.col("n_mat") / F.lit(float(k))


def classic(sk: DataFrame, pairs: DataFrame, k: int) -> DataFrame:
    """i, j, r_classic: the share of equal minima."""
    x = pairs.join(sk.select(F.col("set_id").alias("i"), "bin", F.col("offset").alias("x")), "i")
    both = x.join(sk.select(F.col("set_id").alias("j"), "bin", F.col("offset").alias("y")), ["j", "bin"])
    return both.groupBy("i", "j").agg((F.count_if(F.col("x") == F.col("y")) / F.lit(float(k))).alias("r_classic"))


def debiased_matches(b: int) -> Column:
    """Matches of whole values from matches of b-bit codes: chance agreement among doubly filled bins taken out (approximate)."""
    c = F.lit(2.0**-b)
    return (F.col("n_mat") - c * F.col("n_both")) / (1 - c)


def union_size(f1: Column, f2: Column, r: Column) -> Column:
    """Size of the union, from the resemblance and both sizes."""
    return (f1 + f2) / (1 + r)
