"""Queries over the theory: closed forms on a grid, the printed table, simulations."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from ..functions import theory
from ..functions.permute import Digest
from ..operators import estimate, sets
from ..sources.tables import table
from ..tables import written
from .base import query, r6

#: Number of the row in the printed table (its words are left out), f1, f2, f, R as printed, D = 65536.
#: Rows 08 and 15 are impossible as printed (f1 + f2 < f, f < f1), so GRID leaves them out.
TABLE = [
    ("01", 12234, 11272, 12526, 0.877), ("02", 37339, 36289, 41572, 0.771), ("03", 27695, 17522, 31647, 0.429), ("04", 26668, 17909, 31638, 0.409), ("05", 16836, 16339, 24974, 0.328),
    ("06", 12067, 11006, 17953, 0.285), ("07", 2999, 2697, 4433, 0.285), ("08", 1402, 12718, 21770, 0.229), ("09", 4353, 4241, 7017, 0.225), ("10", 12406, 11744, 19782, 0.221),
    ("11", 9151, 8284, 14992, 0.163), ("12", 5153, 4608, 8542, 0.143), ("13", 12386, 3263, 13874, 0.128), ("14", 3197, 1944, 4769, 0.078), ("15", 39063, 2278, 2060, 0.052),
]
SIZE = 1 << 16
KS = [1 << e for e in range(3, 16)]
GRID = [(p, SIZE, 1 << e, f, f1 + f2 - f) for p, f1, f2, f, _ in TABLE if f1 <= f <= f1 + f2 and f2 <= f for e in range(3, 16)]
VALUES = ", ".join(f"('{p}', {d}, {k}, {f}, {a})" for p, d, k, f, a in GRID)


def _q(c: int) -> str:
    return f"CASE WHEN f > d - {c} * (d // k) THEN 0.0 ELSE exp(list_sum(list_transform(range(f), lambda i: ln((d - {c} * (d // k) - i)::DOUBLE / (d - i))))) END"


#: q1 and q2 in one place; the laws are plain algebra over them.
LAWS = f"""WITH g(pair, d, k, f, a) AS (VALUES {VALUES}), q AS (SELECT pair, d::BIGINT AS d, k::BIGINT AS k, f::BIGINT AS f, a::BIGINT AS a, {_q(1)} AS q1, {_q(2)} AS q2 FROM g),
t AS (SELECT *, k * q1 AS empty_mean, k * q1 + k * (k - 1) * q2 - k * k * q1 * q1 AS empty_var, k * (a::DOUBLE / f) * (1 - q1) AS match_mean, a::DOUBLE / f AS r, pow(1 - 1 / k::DOUBLE, f) AS p1, pow(1 - 2 / k::DOUBLE, f) AS p2 FROM q)"""


def grid(spark, rows=GRID):
    return spark.createDataFrame(rows, "pair string, d long, k long, f long, a long")


#: Pairs of neighbouring suppliers of a given table: f1, f2, f and a are the sizes of their sets of parts, of the union and of the intersection.
SUPPLIERS = 30
SUPPLIER_PAIRS = f"""b AS (SELECT DISTINCT l_suppkey AS s, l_partkey AS e FROM lineitem WHERE l_suppkey < {SUPPLIERS}), n AS (SELECT s, count(*) AS f FROM b GROUP BY 1),
m AS (SELECT x.s, count(*) AS a FROM b x JOIN b y ON y.s = x.s + 1 AND y.e = x.e GROUP BY 1),
sp AS (SELECT CAST(x.s // 2 AS VARCHAR) AS pair, x.f AS f1, y.f AS f2, x.f + y.f - coalesce(a, 0) AS f, coalesce(a, 0) AS a FROM n x JOIN n y ON y.s = x.s + 1 LEFT JOIN m ON m.s = x.s WHERE x.s % 2 = 0)"""


def supplier_pairs(spark, sf_dir) -> list[tuple[str, int, int, int, int]]:
    """pair, f1, f2, f, a of ``SUPPLIER_PAIRS``: a row for each two suppliers, half of SUPPLIERS at most."""
    own = sets.baskets(table(spark, sf_dir, "lineitem"), "l_suppkey", "l_partkey").filter(F.col("set_id") < SUPPLIERS).distinct()
    parts = own.groupBy(F.expr("set_id div 2").alias("m"), "elem").agg(F.max(F.when(F.col("set_id") % 2 == 0, 1).otherwise(0)).alias("x"), F.max(F.when(F.col("set_id") % 2 == 1, 1).otherwise(0)).alias("y"))
    rows = parts.groupBy("m").agg(F.sum("x").alias("f1"), F.sum("y").alias("f2"), F.count(F.lit(1)).alias("f"), F.sum(F.col("x") * F.col("y")).alias("a")).filter("f1 > 0 and f2 > 0").orderBy("m").collect()
    return [(str(r.m), r.f1, r.f2, r.f, r.a) for r in rows]


def _law(name: str, columns: dict[str, str], sql: dict[str, str], measured: bool = False):
    """A law over the printed pairs, or over the ``measured`` ones of a table."""
    picked = ", ".join(f"{v} AS {c}" for c, v in sql.items())
    given = f"g(pair, d, k, f, a) AS (VALUES {VALUES})"
    laws = LAWS.replace(given, f"{SUPPLIER_PAIRS}, g AS (SELECT pair, {SIZE} AS d, k, f, a FROM sp, (SELECT CAST(pow(2, unnest(range(3, 16))) AS BIGINT) AS k))") if measured else LAWS

    @query(f"{laws} SELECT pair, k, {picked} FROM t")
    def run(spark, sf_dir):
        t = theory.law_columns(grid(spark, [(p, SIZE, k, f, a) for p, _, _, f, a in supplier_pairs(spark, sf_dir) for k in KS]) if measured else grid(spark))
        return t.select("pair", "k", *[F.expr(e).alias(c) for c, e in columns.items()])

    from .base import ORACLES, QUERIES

    QUERIES[name], ORACLES[name] = QUERIES.pop("run"), ORACLES.pop("run")


_law("theory_empty_mean", {"share": "round(empty_mean / k, 6)", "bound": "round(ragged_mean / k, 6)"}, {"share": "round(empty_mean / k, 6)", "bound": "round(p1, 6)"})
_law("theory_empty_var", {"v": "round(empty_var / k, 4)"}, {"v": "round(empty_var / k, 4)"})
_law("theory_match_mean", {"share": "round(match_mean / k, 6)"}, {"share": "round(match_mean / k, 6)"})
_law("theory_match_var", {"v": "round(match_var / k, 4)"}, {"v": "round((match_mean + k * (k - 1) * r * (a - 1)::DOUBLE / (f - 1) * (1 - 2 * q1 + q2) - match_mean * match_mean) / k, 4)"})
_law("theory_cov", {"v": "round(cov / k, 4)", "not_positive": "cov <= 1e-6"}, {"v": "round((k * (k - 1) * r * (q1 - q2) - k * k * r * (1 - q1) * q1) / k, 4)", "not_positive": "true"}, measured=True)
_law("theory_unbiased_var", {"v": "round(unbiased_var, 8)", "classic": "round(classic_var, 8)"}, {"v": "round(r * (1 - r) * (f / (k - empty_mean) - 1) / (f - 1), 8)", "classic": "round(r * (1 - r) / k, 8)"})
_law("theory_ratio_g", {"g": "round(ratio, 6)"}, {"g": "round(f / ((f - 1) * (1 - p1)) - k / (f - 1)::DOUBLE, 6)"})
_law("theory_ragged", {"gap": "round((ragged_mean - empty_mean) / k, 6)"}, {"gap": "round((k * p1 - empty_mean) / k, 6)"})

_law("theory_empty_sparse", {"share": "round(sparse_share, 6)", "v": "round((sparse_share * (1 - sparse_share) - (k - 1) * (sparse_share * sparse_share - pow(1 - 2 / k, f))) , 4)"}, {"share": "round(p1, 6)", "v": "round(p1 * (1 - p1) - (k - 1) * (p1 * p1 - p2), 4)"})


@query(f"""WITH {SUPPLIER_PAIRS}, g AS (SELECT pair, {SIZE} AS d, k, f FROM sp, (SELECT unnest([8, 16, 32, 64]) AS k)), q AS (SELECT pair, k, d, f, {_q(1)} AS q1, exp(f * ln(1 - 1 / k::DOUBLE) + list_sum(list_transform(range(f), lambda i: ln(1 - i / (d * (1 - 1 / k::DOUBLE))) - ln(1 - i / d::DOUBLE)))) AS e FROM g) SELECT pair, k, round(e, 6) AS expanded, round(q1, 6) AS exact FROM q""")
def theory_empty_expanded(spark, sf_dir):
    """The refined expansion beside the exact share of holes, on the unions of suppliers' sets of parts."""
    rows = [(p, k, theory.empty_share_expanded(SIZE, k, f), theory.empty_mean(SIZE, k, f) / k) for p, _, _, f, _ in supplier_pairs(spark, sf_dir) for k in KS if k <= 64]
    return spark.createDataFrame(rows, "pair string, k int, expanded double, exact double").select("pair", "k", r6("expanded", "expanded"), r6("exact", "exact"))


#: A small case in which every law is an exact fraction.
SMALL = [(16, 4, 5, 2), (12, 4, 4, 2), (12, 3, 5, 2), (12, 6, 6, 1)]


def _choose(n: str, r: str) -> str:
    return f"CASE WHEN {r} < 0 OR {r} > {n} THEN 0 ELSE coalesce(list_product(list_transform(range(CAST({r} AS BIGINT)), lambda v: ({n} - v)::DOUBLE / (v + 1))), 1.0) END"


#: The distribution of holes by inclusion and exclusion over further bins, as rows (d, k, f, a, j, p).
PMF = "g(d, k, f, a) AS (VALUES " + ", ".join(map(str, SMALL)) + f"""), js AS (SELECT *, unnest(range(0, k + 1)) AS j FROM g), ts AS (SELECT *, unnest(range(0, k - j + 1)) AS s FROM js),
pmf AS (SELECT d, k, f, a, j, sum(pow(-1, s) * ({_choose('k', 'j')}) * ({_choose('(k - j)', 's')}) * ({_choose('(d - (j + s) * (d // k))', 'f')}) / ({_choose('d', 'f')})) AS p FROM ts GROUP BY d, k, f, a, j)"""


@query(f"WITH {PMF} SELECT d, k, f, round(sum(p / (k - j)), 6) AS exact, round(1 / (k - sum(j * p)), 6) AS bound FROM pmf WHERE j < k GROUP BY d, k, f")
def theory_inv_nonempty(spark, sf_dir):
    """E[1 / filled bins] exactly and by its bound, on small cases."""
    rows = [(d, k, f, theory.inv_nonempty(d, k, f, exact=True), theory.inv_nonempty(d, k, f)) for d, k, f, _ in SMALL]
    return spark.createDataFrame(rows, "d int, k int, f int, exact double, bound double").select("d", "k", "f", r6("exact", "exact"), r6("bound", "bound"))


@query(f"WITH {PMF} SELECT d, k, f, CAST(j AS INTEGER) AS j, round(p, 6) AS p FROM pmf")
def theory_empty_pmf(spark, sf_dir):
    """P(j holes), from exact fractions."""
    rows = [(d, k, f, j, float(p)) for d, k, f, _ in SMALL for j, p in enumerate(theory.empty_pmf(d, k, f))]
    return spark.createDataFrame(rows, "d int, k int, f int, j int, p double").select("d", "k", "f", "j", r6("p", "p"))


@query(f"WITH {PMF}, m AS (SELECT *, unnest(range(0, least(k - j, a) + 1)) AS m FROM pmf WHERE p > 1e-12) SELECT d, k, f, a, CAST(j AS INTEGER) AS holes, CAST(m AS INTEGER) AS matches, round(p * ({_choose('a', 'm')}) * ({_choose('(f - a)', '(k - j - m)')}) / ({_choose('f', '(k - j)')}), 6) AS p FROM m WHERE f - a >= k - j - m")
def theory_joint_pmf(spark, sf_dir):
    rows = [(d, k, f, a, j, m, float(p)) for d, k, f, a in SMALL for (j, m), p in theory.joint_pmf(d, k, f, a).items()]
    return spark.createDataFrame(rows, "d int, k int, f int, a int, holes int, matches int, p double").select("d", "k", "f", "a", "holes", "matches", r6("p", "p"))


SIZES = "n AS (SELECT doc_id, count(DISTINCT ('0x' || substring(md5('e:' || w), 1, 7))::BIGINT % 16777216) AS f FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+')) AS w FROM documents) GROUP BY 1)"


@query(f"WITH {SIZES}, q AS (SELECT unnest([0.1, 0.5, 0.9]) AS share), f AS (SELECT share, CAST(ceil((SELECT quantile_cont(f, 0.1) FROM n)) AS BIGINT) AS f FROM q WHERE share = 0.1 UNION ALL SELECT 0.5, CAST(ceil((SELECT quantile_cont(f, 0.5) FROM n)) AS BIGINT) UNION ALL SELECT 0.9, CAST(ceil((SELECT quantile_cont(f, 0.9) FROM n)) AS BIGINT)) SELECT CAST(share AS DOUBLE) AS share, f, CAST(max(k) AS BIGINT) AS k FROM f, (SELECT CAST(pow(2, unnest(range(0, 20))) AS BIGINT) AS k) WHERE k = 1 OR pow(1 - 1 / k::DOUBLE, f) <= 0.0067 GROUP BY 1, 2")
def theory_suggested_k(spark, sf_dir):
    """The largest k for each quantile of set sizes, by the rule of thumb."""
    n = sets.sizes(sets.word_sets(table(spark, sf_dir, "documents"), "doc_id", "text", 1 << 24))
    shares = [0.1, 0.5, 0.9]
    q = n.select(F.percentile("f", F.array(*[F.lit(x) for x in shares])).alias("q")).select(F.explode(F.arrays_zip(F.array(*[F.lit(x) for x in shares]).alias("share"), F.col("q"))).alias("x")).select("x.share", F.ceil("x.q").alias("f"))
    ks = F.transform(F.sequence(F.lit(0), F.lit(19)), lambda e: F.pow(F.lit(2.0), e).cast("long"))
    fit = F.filter(ks, lambda k: (k == 1) | (F.pow(1 - 1 / k.cast("double"), F.col("f")) <= 0.0067))
    return q.select("share", "f", F.array_max(fit).alias("k"))


_CONSISTENT = "f1 <= f AND f2 <= f AND f <= f1 + f2"
_PRINTED = ", ".join(f"('{p}', {f1}, {f2}, {f})" for p, f1, f2, f, _ in TABLE)


@query(f"WITH {SUPPLIER_PAIRS}, t AS (SELECT 'printed ' || pair AS pair, f1, f2, f FROM (VALUES {_PRINTED}) v(pair, f1, f2, f) UNION ALL SELECT 'suppliers ' || pair, f1, f2, f FROM sp) SELECT pair, f1::BIGINT AS f1, f2::BIGINT AS f2, f::BIGINT AS f, CASE WHEN {_CONSISTENT} THEN round((f1 + f2 - f) / f::DOUBLE, 3) END AS r, {_CONSISTENT} AS consistent FROM t")
def table1_consistency(spark, sf_dir):
    """Sizes of pairs that can be, and their resemblance: those of the printed table, and of suppliers' sets of parts."""
    rows = [(f"printed {p}", f1, f2, f) for p, f1, f2, f, _ in TABLE] + [(f"suppliers {p}", f1, f2, f) for p, f1, f2, f, _ in supplier_pairs(spark, sf_dir)]
    t = spark.createDataFrame(rows, "pair string, f1 long, f2 long, f long")
    ok = (F.col("f1") <= F.col("f")) & (F.col("f2") <= F.col("f")) & (F.col("f") <= F.col("f1") + F.col("f2"))
    return t.select("pair", "f1", "f2", "f", F.when(ok, F.round((F.col("f1") + F.col("f2") - F.col("f")) / F.col("f"), 3)).alias("r"), ok.alias("consistent"))


SEEDS, WORD_D = list(range(1, 9)), 1 << 20


def _seed_rows() -> str:
    return " UNION ALL ".join(f"SELECT {s} AS seed, word, {Digest(WORD_D, s).sql('doc')} AS pos FROM top" for s in SEEDS)


@query(f"""WITH post AS (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[\\p{{L}}\\p{{N}}]+')) AS word, doc_id AS doc FROM documents),
w AS (SELECT word, count(*) AS f, row_number() OVER (ORDER BY count(*) DESC, word) AS n FROM post GROUP BY 1), top AS (SELECT post.word, doc FROM post JOIN w USING (word) WHERE n <= 6),
pos AS ({_seed_rows()}), c AS (SELECT seed, word, CAST(pos // {WORD_D // 64} AS INTEGER) AS bin, min(pos) AS p FROM pos GROUP BY 1, 2, 3),
pr AS (SELECT x.word AS i, y.word AS j FROM w x JOIN w y ON x.word < y.word WHERE x.n <= 6 AND y.n <= 6), n AS (SELECT seed, word, count(*) AS c FROM c GROUP BY 1, 2),
m AS (SELECT x.seed, x.word AS i, y.word AS j, count(*) FILTER (x.p = y.p) AS n_mat, count(*) AS n_both FROM c x JOIN c y ON x.seed = y.seed AND x.bin = y.bin AND x.word < y.word GROUP BY 1, 2, 3)
SELECT CAST(a.seed AS INTEGER) AS seed, pr.i, pr.j, CAST(coalesce(n_mat, 0) AS INTEGER) AS n_mat, CAST(64 - a.c - b.c + coalesce(n_both, 0) AS INTEGER) AS n_emp FROM pr JOIN n a ON a.word = pr.i JOIN n b ON b.word = pr.j AND b.seed = a.seed LEFT JOIN m ON m.seed = a.seed AND m.i = pr.i AND m.j = pr.j""")
def emp_counters_by_seed(spark, sf_dir):
    """Counters of the 15 pairs of the most frequent words under several permutations, k = 64."""
    post = sets.postings(table(spark, sf_dir, "documents"))
    words = post.groupBy("word").agg(F.count(F.lit(1)).alias("f")).orderBy(F.desc("f"), "word").limit(6)
    top = post.join(F.broadcast(words.select("word")), "word")
    pos = F.explode(F.array(*[F.struct(F.lit(s).alias("seed"), Digest(WORD_D, s).pos(F.col("doc")).alias("pos")) for s in SEEDS]))
    rows = top.select("word", pos.alias("p")).select("p.seed", "word", "p.pos")
    cells = rows.groupBy("seed", "word", F.expr(f"pos div {WORD_D // 64}").cast("int").alias("bin")).agg(F.min("pos").alias("offset"))
    sk = cells.select(F.concat_ws("|", F.col("seed").cast("string"), "word").alias("set_id"), "bin", "offset")
    x, y = words.select(F.col("word").alias("x")), words.select(F.col("word").alias("y"))
    grid_ = x.join(F.broadcast(y), F.col("x") < F.col("y")).withColumn("seed", F.explode(F.array(*[F.lit(s) for s in SEEDS])))
    pairs = grid_.select(F.concat_ws("|", F.col("seed").cast("string"), "x").alias("i"), F.concat_ws("|", F.col("seed").cast("string"), "y").alias("j"))
    t = estimate.pair_counters(sk, pairs, 64)
    return t.select(F.split_part("i", F.lit("|"), F.lit(1)).cast("int").alias("seed"), F.split_part("i", F.lit("|"), F.lit(2)).alias("i"), F.split_part("j", F.lit("|"), F.lit(2)).alias("j"), "n_mat", "n_emp")


SIMULATED = "pair string, k int, n long, emp double, emp2 double, mat double, mat2 double, em double, err double, err2 double"


def simulate(spark, reps: int, ks: list[int], seed: int = 1, per_task: int = 10, cases: list[tuple[str, int, int, int, int]] | None = None):
    """Sums over ``reps`` random permutations for each consistent pair (``cases``: pair, f1, f2, f, a; else the printed ones) and k, by tasks of a few repetitions each; only sums leave a worker."""
    if cases is None:
        cases = [(p, f1, f2, f, f1 + f2 - f) for p, f1, f2, f, _ in TABLE if f1 <= f <= f1 + f2 and f2 <= f]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = []
        for batch in batches:
            for task in batch.column("id").to_pylist():
                rng = np.random.default_rng([seed, task])
                for p, f1, f2, f, a in cases:
                    stats = {k: [] for k in ks}
                    for _ in range(per_task):
                        pos = rng.permutation(SIZE)[:f]  # shared elements first, then those of one set alone
                        for k in ks:
                            bins, low = pos * k // SIZE, np.full((2, k), SIZE)
                            np.minimum.at(low[0], bins[:f1], pos[:f1])
                            np.minimum.at(low[1], np.r_[bins[:a], bins[f1:]], np.r_[pos[:a], pos[f1:]])
                            empty = int(((low[0] == SIZE) & (low[1] == SIZE)).sum())
                            match = int(((low[0] == low[1]) & (low[0] < SIZE)).sum())
                            stats[k].append((empty, match, match / (k - empty) - a / f))
                    for k, s in stats.items():
                        e, m, d = np.array(s).T
                        rows.append((p, k, len(s), e.sum(), (e * e).sum(), m.sum(), (m * m).sum(), (e * m).sum(), d.sum(), (d * d).sum()))
        names = [c.split()[0] for c in SIMULATED.split(", ")]
        kinds = [pa.string(), pa.int32(), pa.int64(), *[pa.float64()] * 7]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * len(names), kinds, strict=True)], names=names)

    tasks = -(-reps // per_task)
    sums = spark.range(0, tasks, 1, min(tasks, 64)).mapInArrow(run, SIMULATED).groupBy("pair", "k").agg(*[F.sum(c.split()[0]).alias(c.split()[0]) for c in SIMULATED.split(", ")[2:]])
    n = F.col("n")
    mean_e, mean_m = F.col("emp") / n, F.col("mat") / n
    t = sums.select("pair", "k", "n", mean_e.alias("e"), (F.col("emp2") / n - mean_e * mean_e).alias("var_e"), mean_m.alias("m"), (F.col("mat2") / n - mean_m * mean_m).alias("var_m"), (F.col("em") / n - mean_e * mean_m).alias("cov_em"), (F.col("err") / n).alias("bias"), (F.col("err2") / n).alias("mse"))
    law = theory.law_columns(grid(spark, [(p, SIZE, k, f, a) for p, _, _, f, a in cases for k in ks])).select("pair", F.col("k").cast("int").alias("k"), "empty_mean", "empty_var", "match_mean", "match_var", "cov", "unbiased_var", "classic_var")
    return t.join(law, ["pair", "k"])


def agreement(t):
    """Simulated figures beside their laws: gaps relative to the law, z-scores of the means, and squared errors against both variances."""
    n = F.col("n")
    gap = lambda a, b: F.try_divide(F.col(a) - F.col(b), F.abs(F.col(b)))
    z = lambda a, b, v: F.when(F.col(v) > 1e-9, (F.col(a) - F.col(b)) / F.sqrt(F.col(v) / n))
    return t.withColumns({"z_e": z("e", "empty_mean", "empty_var"), "z_m": z("m", "match_mean", "match_var"), "z_bias": F.when(F.col("unbiased_var") > 1e-15, F.col("bias") / F.sqrt(F.col("unbiased_var") / n)), "gap_var_e": gap("var_e", "empty_var"), "gap_var_m": gap("var_m", "match_var"), "mse_over_law": F.try_divide("mse", "unbiased_var"), "mse_over_classic": F.try_divide("mse", "classic_var")})


@query()
def theory_simulation(spark, sf_dir, reps: int = 100):
    """Means, variances, covariance, bias and squared error of ``reps`` permutations beside their laws, k = 8 .. 32768."""
    return agreement(simulate(spark, reps, KS))


@query()
def theory_agreement(spark, sf_dir, reps: int = 100):
    """One row for each k over pairs of suppliers' sets of parts: largest |z| of the means, covariances above 0 beyond chance, squared error over k permutations' variance."""
    t = agreement(simulate(spark, reps, KS, cases=supplier_pairs(spark, sf_dir)))
    worst = lambda c: F.round(F.max(F.abs(c)), 3)
    return t.groupBy("k").agg(F.count(F.lit(1)).alias("pairs"), F.max("n").alias("n"), worst("z_e").alias("worst_z_e"), worst("z_m").alias("worst_z_m"), worst("z_bias").alias("worst_z_bias"), F.count_if(F.col("cov_em") > 4 * F.sqrt(F.col("empty_var") * F.col("match_var") / F.col("n")) + 1e-9).alias("positive_cov"), F.round(F.avg("mse_over_law"), 4).alias("mse_over_law"), F.round(F.avg("mse_over_classic"), 4).alias("mse_over_classic")).orderBy("k")


UNEQUAL_SEEDS = list(range(21, 37))


def _unequal_rows() -> str:
    return " UNION ALL ".join(f"SELECT {s} AS seed, word, {Digest(WORD_D, s).sql('doc')} AS pos FROM top" for s in UNEQUAL_SEEDS)


@query(f"""WITH post AS (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[\\p{{L}}\\p{{N}}]+')) AS word, doc_id AS doc FROM documents),
w AS (SELECT word, count(*) AS f, row_number() OVER (ORDER BY count(*) DESC, word) AS n FROM post GROUP BY 1), big AS (SELECT word, f FROM w WHERE n <= 6),
small AS (SELECT word, f FROM w WHERE f * 10 <= (SELECT min(f) FROM big) AND f >= 5 ORDER BY f DESC, word LIMIT 6), top AS (SELECT post.word, doc FROM post JOIN (SELECT * FROM big UNION ALL SELECT * FROM small) USING (word)),
pos AS ({_unequal_rows()}), c AS (SELECT seed, word, CAST(pos // {WORD_D // 64} AS INTEGER) AS bin, min(pos) AS p FROM pos GROUP BY 1, 2, 3), n AS (SELECT seed, word, count(*) AS c FROM c GROUP BY 1, 2),
pr AS (SELECT x.word AS i, y.word AS j, x.f AS f1, y.f AS f2, (SELECT count(*) FROM top a JOIN top b ON a.doc = b.doc WHERE a.word = x.word AND b.word = y.word) AS a FROM big x, small y),
m AS (SELECT x.seed, x.word AS i, y.word AS j, count(*) FILTER (x.p = y.p) AS n_mat, count(*) AS n_both FROM c x JOIN c y ON x.seed = y.seed AND x.bin = y.bin JOIN pr ON pr.i = x.word AND pr.j = y.word GROUP BY 1, 2, 3),
e AS (SELECT pr.i, pr.j, a / (f1 + f2 - a)::DOUBLE AS r, coalesce(n_mat, 0) AS n_mat, x.c AS ci, y.c AS cj, coalesce(n_both, 0) AS n_both FROM pr JOIN n x ON x.word = pr.i JOIN n y ON y.word = pr.j AND y.seed = x.seed LEFT JOIN m ON m.i = pr.i AND m.j = pr.j AND m.seed = x.seed),
u AS (SELECT 'unbiased' AS estimator, r, n_mat::DOUBLE / (ci + cj - n_both) AS v FROM e UNION ALL SELECT 'separable', r, n_mat / sqrt(ci::DOUBLE * cj) FROM e UNION ALL SELECT 'over k', r, n_mat / 64.0::DOUBLE FROM e)
SELECT estimator, count(*) AS n, round(avg(r), 6) AS r, round(avg(v - r), 6) AS bias, round(avg((v - r) * (v - r)), 6) AS mse FROM u GROUP BY 1""")
def unequal_estimates(spark, sf_dir):
    """Bias and squared error of the three estimators on pairs of words of which one is in ten times as many documents, 16 permutations, k = 64."""
    post = written(sets.postings(table(spark, sf_dir, "documents")), "postings")
    w = written(post.groupBy("word").agg(F.count(F.lit(1)).alias("f")), "words")
    big = w.orderBy(F.desc("f"), "word").limit(6)
    least = big.agg(F.min("f")).first()[0] or 0
    small = w.filter((F.col("f") * 10 <= least) & (F.col("f") >= 5)).orderBy(F.desc("f"), "word").limit(6)
    top = written(post.join(F.broadcast(big.union(small).select("word")), "word"), "top")
    a = top.select(F.col("word").alias("i"), "doc").join(top.select(F.col("word").alias("j"), "doc"), "doc").groupBy("i", "j").agg(F.count(F.lit(1)).alias("a"))
    pairs = big.select(F.col("word").alias("i"), F.col("f").alias("f1")).crossJoin(F.broadcast(small.select(F.col("word").alias("j"), F.col("f").alias("f2")))).join(a, ["i", "j"], "left").fillna(0)
    pos = F.explode(F.array(*[F.struct(F.lit(s).alias("seed"), Digest(WORD_D, s).pos(F.col("doc")).alias("pos")) for s in UNEQUAL_SEEDS]))
    rows = top.select("word", pos.alias("p")).select("p.seed", "word", "p.pos")
    sk = rows.groupBy(F.concat_ws("|", F.col("seed").cast("string"), "word").alias("set_id"), F.expr(f"pos div {WORD_D // 64}").cast("int").alias("bin")).agg(F.min("pos").alias("offset"))
    named = lambda s: F.concat_ws("|", F.col("seed").cast("string"), s)
    asked = written(pairs.withColumn("seed", F.explode(F.array(*[F.lit(s) for s in UNEQUAL_SEEDS]))).select(named("i").alias("i"), named("j").alias("j"), estimate.resemblance(F.col("f1"), F.col("f2"), F.col("a")).alias("r")), "pairs")
    t = written(estimate.pair_counters(sk, asked.select("i", "j"), 64).join(asked, ["i", "j"]), "counters")
    out = None
    for name, value in (("unbiased", estimate.unbiased(64)), ("separable", estimate.separable(64)), ("over k", estimate.over_k(64))):
        one = t.select(F.lit(name).alias("estimator"), "r", value.alias("v"))
        out = one if out is None else out.unionByName(one)
    off = F.col("v") - F.col("r")
    return out.groupBy("estimator").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("r"), 6).alias("r"), F.round(F.avg(off), 6).alias("bias"), F.round(F.avg(off * off), 6).alias("mse"))
