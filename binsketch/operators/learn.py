"""Linear learning on coded sketches: MLlib solvers, a SQL-only solver, evaluation."""

from __future__ import annotations

from pyspark.ml.classification import LinearSVC, LogisticRegression
from pyspark.ml.feature import HashingTF
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..tables import written


def reg_from_c(c: float, n: int) -> float:
    """Spark's regParam for a cost C: the objective divided by C n."""
    return 1.0 / (c * n)


def split(df: DataFrame, share: float, seed: int, id_col: str = "set_id") -> tuple[DataFrame, DataFrame]:
    """Training and test rows by a hash of the id: the same rows whenever computed."""
    spot = F.pmod(F.xxhash64(id_col, F.lit(seed)), F.lit(10_000))
    return df.filter(spot < int(share * 10_000)), df.filter(spot >= int(share * 10_000))


def logistic(train: DataFrame, c: float = 1.0, iters: int = 30):
    return LogisticRegression(regParam=reg_from_c(c, train.count()), elasticNetParam=0.0, fitIntercept=False, standardization=False, maxIter=iters).fit(train)


def linear_svm(train: DataFrame, c: float = 1.0, iters: int = 30):
    return LinearSVC(regParam=reg_from_c(c, train.count()), fitIntercept=False, standardization=False, maxIter=iters).fit(train)


def original_vectors(sets: DataFrame, dims: int = 1 << 18) -> DataFrame:
    """set_id, features: the unhashed baseline, each element one binary feature."""
    rows = sets.groupBy("set_id").agg(F.collect_set(F.col("elem").cast("string")).alias("words"))
    return HashingTF(numFeatures=dims, binary=True, inputCol="words", outputCol="features").transform(rows).select("set_id", "features")


def score(rows: DataFrame, model) -> DataFrame:
    """Adds prediction; works on batches and on streams (the model's weights are broadcast)."""
    return model.transform(rows)


def evaluate(scored: DataFrame) -> DataFrame:
    """One row: n, accuracy, balanced accuracy, the majority's share."""
    hit = (F.col("prediction") == F.col("label")).cast("double")
    t = scored.agg(F.count(F.lit(1)).alias("n"), F.avg(hit).alias("accuracy"), F.avg(F.when(F.col("label") == 1, hit)).alias("p"), F.avg(F.when(F.col("label") == 0, hit)).alias("q"), F.avg("label").alias("ones"))
    return t.select("n", "accuracy", ((F.coalesce("p", "q") + F.coalesce("q", "p")) / 2).alias("balanced"), F.greatest("ones", 1 - F.col("ones")).alias("majority"))


def auc(scored: DataFrame, margin: Column, steps: int = 4096) -> DataFrame:
    """One row: area under the curve, from summed ranks of the positives (ties share theirs).

    Margins are counted first; ranges of them (``steps``, by approximate quantiles) get their first rank from the
    ranges' sums, so that no task sees more than a range.
    """
    at = written(scored.select("label", margin.cast("double").alias("m")).groupBy("m").agg(F.sum("label").alias("pos"), F.count(F.lit(1)).alias("n")), "margins")
    cuts = at.agg(F.percentile_approx("m", F.array(*[F.lit(i / steps) for i in range(1, steps)]), 10 * steps)).first()[0] if at.count() > steps else []
    edges = F.array(*[F.lit(c) for c in sorted(set(cuts or []))]) if cuts else F.array().cast("array<double>")
    ranged = written(at.withColumn("part", F.size(F.filter(edges, lambda c: c <= F.col("m")))), "ranges")
    first = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    before = ranged.groupBy("part").agg(F.sum("n").alias("n")).select("part", F.coalesce(F.sum("n").over(first), F.lit(0)).alias("before"))
    within = F.coalesce(F.sum("n").over(Window.partitionBy("part").orderBy("m").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranked = ranged.join(F.broadcast(before), "part").withColumn("rank", F.col("before") + within + (F.col("n") + 1) / 2)
    t = ranked.agg(F.sum(F.col("rank") * F.col("pos")).alias("s"), F.sum("pos").alias("p"), F.sum("n").alias("n"))
    return t.select(F.try_divide(F.col("s") - F.col("p") * (F.col("p") + 1) / 2, F.col("p") * (F.col("n") - F.col("p"))).alias("auc"))


def sgd_long(train: DataFrame, labels: DataFrame, c: float = 1.0, iters: int = 10, rate: float = 1.0) -> DataFrame:
    """idx, w: L2 logistic regression by full gradients in SQL, for dimensions no driver could hold.

    ``train`` has set_id, idx, val; ``labels`` set_id, y in {-1, 1}. Each round joins
    the weights on idx and sums twice; the weights are written to the shared folder.
    """
    data = written(train.join(labels, "set_id").select("set_id", "idx", "val", "y"), "train")
    n = data.select("set_id").distinct().count()
    w = written(data.select("idx").distinct().withColumn("w", F.lit(0.0)), "weights")
    for t in range(iters):
        z = data.join(w, "idx").groupBy("set_id", "y").agg(F.sum(F.col("w") * F.col("val")).alias("z"))
        g = z.select("set_id", (-F.col("y") / (1 + F.exp(F.col("y") * F.col("z")))).alias("g"))
        grad = data.join(g, "set_id").groupBy("idx").agg(F.sum(F.col("g") * F.col("val")).alias("grad"))
        step = rate / (1 + 0.1 * t)
        w = written(w.join(grad, "idx").select("idx", (F.col("w") * (1 - step / (c * n)) - step * F.col("grad") / n * 4).alias("w")), "weights")
    return w
