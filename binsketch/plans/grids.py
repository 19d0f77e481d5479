"""Accuracy over grids of k, b, cost, coding, method and learner, repeated over permutations."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.permute import Feistel
from ..operators import cells, codes, sets, sketch
from ..sources.tables import table
from ..tables import scratch, written
from .base import DIGEST, WORD_SETS, D, doc_words, query, r6, sketch_sql

BITS, TOP = 24, 4096
NEWS = [1 << e for e in range(3, 13)]
WEB = [1 << e for e in range(5, 10)]
NEAR = 0.1
BS, COSTS, SOLVERS = (1, 2, 4, 6, 8), (0.1, 1.0, 10.0, 100.0), ("logistic", "svm")


def labels_of(spark, sf_dir: str, task: str) -> DataFrame:
    """set_id, label: ``toxic`` and ``quality`` are the labelled documents', ``lang`` is English or not of every document."""
    if task == "lang":
        return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("set_id"), (F.col("lang") == "en").cast("double").alias("label"))
    return table(spark, sf_dir, "labels").select(F.col("doc_id").alias("set_id"), F.col(task).cast("double").alias("label"))


def grid(spark, sf_dir: str, task: str, test_share: float, ks, bs=BS, costs=COSTS, reps: int = 2, methods=("blank", "noise", "classic", "original"), solvers=SOLVERS, w: int = 1) -> DataFrame:
    """``cells.RESULT`` rows of the whole grid, over all labelled rows. One sketch of them for each repetition, at the largest k."""
    top = max(ks)
    with scratch(spark) as temp:
        y = written(cells.labelled(labels_of(spark, sf_dir, task)), "labels")
        docs = table(spark, sf_dir, "documents").join(y.select(F.col("set_id").alias("doc_id")), "doc_id", "left_semi")
        arrays = written(sets.word_sets(docs, "doc_id", "text", 1 << BITS, w).groupBy("set_id").agg(F.collect_set("elem").alias("elems")), "words")
        words = arrays.select("set_id", F.explode("elems").alias("elem"))
        data: dict = {}
        for rep in range(reps):
            sk = sketch.bin_minima(words, Feistel(BITS, 50 + rep), top)
            data["binned", rep] = cells.Stored.of(written(codes.to_binary(codes.low_bits(sk, 8), top, 8).select("set_id", "codes", "holes"), "binned"), top)
            if "classic" in methods:
                data["classic", rep] = cells.Stored.of(written(cells.classic_codes(arrays, top, 70 + rep), "classic"), top)
        if "original" in methods:
            data["original", 0] = cells.files_of(arrays)

        def test_of(ids: np.ndarray) -> np.ndarray:
            return (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)).astype(np.float64) / (1 << 24) < test_share

        plan = [(m, s, k, b, rep) for m in methods if m != "original" for s in solvers for k in ks for b in bs for rep in range(reps)]
        plan += [("original", s, 0, 0, 0) for s in solvers if "original" in methods]
        return temp.keep(written(cells.run_cells(spark, data, cells.files_of(y), test_of, plan, list(costs)), "grid"))


def best_over_c(rows: DataFrame) -> DataFrame:
    """Each cell's mean over repetitions, at the cost with the best mean area under the curve (ties: the smaller cost)."""
    key = ["method", "solver", "k", "b"]
    mean = rows.groupBy(*key, "c").agg(F.count(F.lit(1)).alias("reps"), F.max("n_train").alias("n_train"), F.max("n").alias("n"), *(F.avg(x).alias(x) for x in ("nonzeros", "accuracy", "balanced", "auc", "majority")), F.stddev_pop("accuracy").alias("spread"))
    best = mean.withColumn("at", F.row_number().over(Window.partitionBy(*key).orderBy(F.desc("auc"), "c"))).filter("at = 1")
    return best.select(*key, F.col("c").alias("best_c"), "reps", "n_train", "n", *(r6(x, x) for x in ("nonzeros", "accuracy", "spread", "balanced", "auc", "majority")))


@query()
def accuracy_news_grid(spark, sf_dir):
    """Half and half: k = 8 .. 4096, five b, three costs, two permutations, blank and noise coding, k permutations, unhashed; best over costs."""
    return best_over_c(grid(spark, sf_dir, "toxic", 0.5, NEWS, costs=(1.0, 10.0, 100.0)))


@query()
def accuracy_web_grid(spark, sf_dir):
    """Four fifths to train: k = 32 .. 512 over 3-shingles, all documents, English or not."""
    return best_over_c(grid(spark, sf_dir, "lang", 0.2, WEB, costs=(1.0, 100.0), solvers=("logistic", "svm"), w=3))


@query()
def accuracy_cost_grid(spark, sf_dir):
    """Every cost and repetition of one (k, b) row, both learners: what the choice of cost is worth."""
    rows = grid(spark, sf_dir, "quality", 0.2, [64, 512], (4, 8), (0.01, 0.1, 1.0, 10.0, 100.0), 3, ("blank", "classic", "original"))
    return rows.select("method", "solver", "k", "b", "c", "rep", "n", *(r6(x, x) for x in ("accuracy", "balanced", "auc", "majority")))


@query()
def accuracy_orderings(spark, sf_dir):
    """What the publication reports, as rows (claim, left, right, holds): area under the curve at b = 8, mean of both learners and two permutations.

    Alike means within NEAR, which is about what few permutations and some thousand rows can tell.
    """
    ks = [16, 64, 256, 1024, 4096]
    t = best_over_c(grid(spark, sf_dir, "toxic", 0.5, ks, (8,), (1.0, 10.0))).groupBy("method", "k").agg(F.avg("auc").alias("auc"), F.avg("accuracy").alias("accuracy"), F.avg("nonzeros").alias("nonzeros"))
    of = {(r.method, r.k): r for r in t.collect()}
    blank, noise, classic = ({k: of[m, k].auc for k in ks} for m in ("blank", "noise", "classic"))
    rows = [(f"k={k}: one permutation is like k permutations" if k < 256 else f"k={k}: one permutation is like k permutations or better", blank[k], classic[k], blank[k] >= classic[k] - NEAR and (k >= 256 or blank[k] <= classic[k] + NEAR)) for k in ks]
    rows += [(f"k={k}: noise coding is like blank coding" if k <= 64 else f"k={k}: noise coding is poorer than blank coding", blank[k], noise[k], abs(blank[k] - noise[k]) <= NEAR if k <= 64 else blank[k] > noise[k]) for k in ks if k != 256]
    rows += [("accuracy with blank coding grows with k: 4096 against 16", of["blank", 4096].auc, of["blank", 16].auc, of["blank", 4096].auc > of["blank", 16].auc)]
    rows += [("k=4096 against the original data", of["blank", 4096].accuracy, of["original", 0].accuracy, of["blank", 4096].accuracy >= of["original", 0].accuracy - 0.03)]
    rows += [("nonzeros at k=4096: blank against noise", of["blank", 4096].nonzeros, of["noise", 4096].nonzeros, of["blank", 4096].nonzeros < of["noise", 4096].nonzeros)]
    return spark.createDataFrame(rows, "claim string, left_value double, right_value double, holds boolean")


#: Weights that both engines can compute, so that scoring and all measures have a twin.
def given_weight(idx):
    return (idx * F.lit(7919) + F.lit(104729)) % F.lit(1009) - F.lit(504)


SCORES = f"""WITH {WORD_SETS}, {sketch_sql('words', DIGEST.sql('elem'), 128)}, z AS (SELECT set_id, sum((((bin::BIGINT * 256 + 255 - ("offset" & 255)) * 7919 + 104729) % 1009) - 504)::BIGINT AS z FROM sk GROUP BY 1),
s AS (SELECT doc_id, z, (lang = 'en')::INTEGER AS y FROM z JOIN documents ON doc_id = set_id)"""


@query(f"""{SCORES}, r AS (SELECT *, rank() OVER (ORDER BY z) + (count(*) OVER (PARTITION BY z) - 1) / 2.0::DOUBLE AS place FROM s)
SELECT count(*) AS n, round(avg(((z > 0)::INTEGER = y)::INTEGER), 6) AS accuracy, round((avg(CASE WHEN y = 1 THEN (z > 0)::INTEGER END) + avg(CASE WHEN y = 0 THEN (z <= 0)::INTEGER END)) / 2, 6) AS balanced,
 round(greatest(avg(y), 1 - avg(y)), 6) AS majority, round((sum(place * y) - sum(y) * (sum(y) + 1) / 2) / (sum(y) * (count(*) - sum(y))), 6) AS auc FROM r""")
def accuracy_of_given_weights(spark, sf_dir):
    """Expanded codes scored by fixed weights, and every accuracy measure of the scores."""
    from ..operators import learn

    c = codes.low_bits(sketch.bin_minima(doc_words(spark, sf_dir), DIGEST, 128), 8)
    z = codes.expand_long(codes.blank(c), 8).groupBy("set_id").agg(F.sum(given_weight(F.col("idx"))).alias("z"))
    rows = z.join(labels_of(spark, sf_dir, "lang"), "set_id").withColumn("prediction", (F.col("z") > 0).cast("double"))
    rows = written(rows, "scores")
    return learn.evaluate(rows).crossJoin(learn.auc(rows, F.col("z"))).select("n", r6("accuracy", "accuracy"), r6("balanced", "balanced"), r6("majority", "majority"), r6("auc", "auc"))
