"""The worked examples."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.permute import Identity
from ..operators import codes, estimate, lsh, sketch
from .base import query

#: Three sets already permuted (D = 16, k = 4), and three bin minima.
TOY_SETS = {1: [2, 4, 7, 13], 2: [0, 6, 13], 3: [0, 1, 10, 12]}
TOY_VALUES = [12013, 25964, 20191]
#: Point 6 has codes (0,0) and (3,3); which table the other points sit in is our choice.
TOY_POINTS = {6: (0, 15), 110: (0, 7), 143: (0, 3), 26: (4, 15), 15: (9, 15), 79: (2, 15), 8: (1, 1), 5: (13, 3), 33: (7, 12), 3: (14, 2), 74: (11, 0)}


def toy_sets(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(i, e) for i, s in TOY_SETS.items() for e in s], "set_id long, elem long")


def _values(rows) -> str:
    return ", ".join(f"({', '.join(map(str, r))})" for r in rows)


TOY_SQL = f"t(set_id, elem) AS (VALUES {_values((i, e) for i, s in TOY_SETS.items() for e in s)}), sk AS (SELECT set_id::BIGINT AS set_id, CAST(elem // 4 AS INTEGER) AS bin, min(elem % 4)::BIGINT AS \"offset\" FROM t GROUP BY 1, 2)"
TOY_PAIRS = "p(i, j) AS (VALUES (1::BIGINT, 2::BIGINT), (1, 3), (2, 3))"


@query(f"WITH {TOY_SQL} SELECT set_id, bin, \"offset\" FROM sk")
def toy_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sketch.bin_minima(toy_sets(spark), Identity(16), 4)


@query(f"""WITH {TOY_SQL}, {TOY_PAIRS}, c AS (SELECT set_id, count(*) c FROM sk GROUP BY 1)
SELECT p.i, p.j, CAST(count(*) FILTER (x."offset" = y."offset") AS INTEGER) AS n_mat, CAST(4 - any_value(a.c) - any_value(b.c) + count(y.bin) AS INTEGER) AS n_emp,
round(count(*) FILTER (x."offset" = y."offset") / (any_value(a.c) + any_value(b.c) - count(y.bin))::DOUBLE, 6) AS r_unbiased, round(count(*) FILTER (x."offset" = y."offset") / sqrt(any_value(a.c) * any_value(b.c)), 6) AS r_separable
FROM p JOIN sk x ON x.set_id = p.i LEFT JOIN sk y ON y.set_id = p.j AND y.bin = x.bin JOIN c a ON a.set_id = p.i JOIN c b ON b.set_id = p.j GROUP BY 1, 2""")
def toy_pair_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = spark.createDataFrame([(1, 2), (1, 3), (2, 3)], "i long, j long")
    t = estimate.pair_counters(sketch.bin_minima(toy_sets(spark), Identity(16), 4), pairs, 4)
    return t.select("i", "j", "n_mat", "n_emp", F.round(estimate.unbiased(4), 6).alias("r_unbiased"), F.round(estimate.separable(4), 6).alias("r_separable"))


def _toy_codes(spark: SparkSession) -> DataFrame:
    return codes.low_bits(spark.createDataFrame([(1, j, v) for j, v in enumerate(TOY_VALUES)], "set_id long, bin int, offset long"), 2)


TOY_BITS = f"v(bin, x) AS (VALUES {_values(enumerate(TOY_VALUES))})"


@query(f"WITH {TOY_BITS} SELECT 1::BIGINT AS set_id, bin, CAST(x & 3 AS INTEGER) AS code FROM v")
def toy_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _toy_codes(spark)


@query(f"WITH {TOY_BITS} SELECT 1::BIGINT AS set_id, (bin * 4 + 3 - (x & 3))::BIGINT AS idx, round(1 / sqrt(3), 6) AS val FROM v")
def toy_expand(spark: SparkSession, sf_dir: str) -> DataFrame:
    return codes.expand_long(codes.blank(_toy_codes(spark)), 2).select("set_id", "idx", F.round("val", 6).alias("val"))


@query(f"WITH pt(set_id, t0, t1) AS (VALUES {_values((i, *b) for i, b in TOY_POINTS.items())}) SELECT 6::BIGINT AS query_id, y.set_id::BIGINT AS set_id FROM pt x JOIN pt y ON x.t0 = y.t0 OR x.t1 = y.t1 WHERE x.set_id = 6")
def toy_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [(i, 2 * t + s, bucket >> 2 * s & 3) for i, buckets in TOY_POINTS.items() for t, bucket in enumerate(buckets) for s in (0, 1)]
    index = lsh.build_index(spark.createDataFrame(rows, "set_id long, bin int, offset long"), 2, 2, 2)
    return lsh.candidates(index, index.filter("set_id = 6"))
