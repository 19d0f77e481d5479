"""Accuracy of linear learners on coded sketches, original data and the classic sketch."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.permute import Digest
from ..operators import codes, learn, sketch
from ..sources.tables import load_times, table
from ..tables import fresh_path, written
from .base import D, doc_words, query, r6

SEED = 3


def labelled(spark, sf_dir):
    """set_id, label: English or not, which covers every document and is nearly balanced."""
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("set_id"), (F.col("lang") == "en").cast("double").alias("label"))


def measured(spark, vectors, labels, method: str, share: float = 0.8, c: float = 1.0, solver: str = "logistic"):
    rows = written(vectors.join(labels, "set_id"), "labelled") if labels is not None else vectors
    train, test = learn.split(rows, share, SEED)
    model = learn.logistic(train, c) if solver == "logistic" else learn.linear_svm(train, c)
    e = learn.evaluate(learn.score(test, model))
    return e.select(F.lit(method).alias("method"), F.lit(solver).alias("solver"), F.lit(c).alias("c"), "n", r6("accuracy", "accuracy"), r6("balanced", "balanced"), r6("majority", "majority"))


def sketched(spark, sf_dir, k: int, b: int, coding: str = "blank", classic: bool = False):
    words = doc_words(spark, sf_dir)
    sk = sketch.classic(words, [Digest(D, 200 + j) for j in range(k)]) if classic else sketch.bin_minima(words, Digest(D, 7), k)
    c = codes.low_bits(sk, b)
    return codes.to_vectors(codes.noise(c, k, b, 1) if coding == "noise" else c, k, b)


def _union(rows):
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


@query()
def accuracy_by_coding(spark, sf_dir):
    """News-like split (half and half): blank and noise coding at small and large k, and the unhashed data."""
    y = labelled(spark, sf_dir)
    rows = [measured(spark, sketched(spark, sf_dir, k, 4, coding), y, f"{coding} k={k} b=4", 0.5) for k in (64, 512) for coding in ("blank", "noise")]
    return _union([*rows, measured(spark, learn.original_vectors(doc_words(spark, sf_dir)), y, "original", 0.5)])


@query()
def accuracy_by_method(spark, sf_dir):
    """One permutation against k permutations at the same k and b, with both learners."""
    y = labelled(spark, sf_dir)
    rows = {c: written(sketched(spark, sf_dir, 64, 4, classic=c).join(y, "set_id"), "labelled") for c in (False, True)}  # one sketch for both learners
    return _union([measured(spark, rows[c], None, "classic" if c else "one permutation", solver=s) for c in (False, True) for s in ("logistic", "svm")])


@query()
def accuracy_grid(spark, sf_dir):
    """k and b from one sketch at the largest of both (rolled up and masked), over two costs."""
    y, top, bits = labelled(spark, sf_dir), 256, 8
    raw = written(sketch.bin_minima(doc_words(spark, sf_dir), Digest(D, 7), top, reindex=False), "raw")
    rows = []
    for k in (64, 256):
        sk = sketch.coarsen(raw, D, top, k)
        for b in (2, bits):
            v = written(codes.to_vectors(codes.low_bits(codes.low_bits(sk, bits), b), k, b), "vectors")
            rows += [measured(spark, v, y, f"k={k} b={b}", c=c) for c in (0.1, 10.0)]
    return _union(rows)


@query()
def quality_labels(spark, sf_dir):
    """The documents' own labels (imbalanced: read accuracy beside the majority)."""
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("set_id"), F.col("toxic").cast("double").alias("label"))
    return measured(spark, sketched(spark, sf_dir, 512, 4), labels, "blank k=512 b=4")


@query()
def sql_learner(spark, sf_dir):
    """The SQL-only solver beside MLlib's, on the same rows."""
    y = labelled(spark, sf_dir)
    c = codes.low_bits(sketch.bin_minima(doc_words(spark, sf_dir), Digest(D, 7), 64), 2)
    rows = codes.expand_long(codes.blank(c), 2).join(y, "set_id")
    train, test = learn.split(rows, 0.8, SEED)
    w = learn.sgd_long(train.select("set_id", "idx", "val"), train.select("set_id", (2 * F.col("label") - 1).alias("y")).distinct(), 1.0, 6, 4.0)
    scored = test.join(w, "idx").groupBy("set_id", "label").agg(F.sum(F.col("w") * F.col("val")).alias("z")).withColumn("prediction", (F.col("z") > 0).cast("double"))
    return learn.evaluate(scored).select("n", r6("accuracy", "accuracy"), r6("balanced", "balanced"), r6("majority", "majority"))


@query()
def stream_scored_points(spark, sf_dir):
    """New documents arrive in files; each batch is sketched, coded, expanded and scored by a stored model."""
    from ..streaming.sketches import drained

    y = labelled(spark, sf_dir)
    v = written(sketched(spark, sf_dir, 64, 4).join(y, "set_id"), "vectors")
    train, test = learn.split(v, 0.5, SEED)
    model = learn.logistic(train)
    folder = fresh_path(spark, "arrivals")
    test.repartition(3, "set_id").write.parquet(folder)
    stream = spark.readStream.schema(v.schema).option("maxFilesPerTrigger", 1).parquet(folder)
    return drained(learn.score(stream, model).select("set_id", "label", "prediction"), "scored")


@query()
def training_times(spark, sf_dir):
    """Seconds to fit on codes of one permutation and of k permutations, the same k and b."""
    import time

    y, rows = labelled(spark, sf_dir), []
    for classic in (False, True):
        v = written(sketched(spark, sf_dir, 64, 4, classic=classic).join(y, "set_id"), "vectors")
        t = time.perf_counter()
        learn.logistic(v)
        rows.append(("classic" if classic else "one permutation", time.perf_counter() - t))
    return spark.createDataFrame(rows, "method string, seconds double")


@query()
def sketching_times(spark, sf_dir):
    """Seconds and hash evaluations to sketch all documents: one permutation, three, k = 64."""
    from ..sources.tables import timed

    words = written(doc_words(spark, sf_dir), "words")
    n = words.count()
    many = [Digest(D, 300 + j) for j in range(64)]
    rows = [(m, n * p, timed(df)) for m, p, df in (("one permutation", 1, sketch.bin_minima(words, many[0], 64)), ("striped", 4, sketch.striped(words, many[:4], 64)), ("classic", 64, sketch.classic(words, many)))]
    return spark.createDataFrame(rows, "method string, hashes long, seconds double")


@query()
def loading_times(spark, sf_dir):
    """Seconds to load the same expanded vectors from the sparse text format and from Parquet."""
    v = sketched(spark, sf_dir, 128, 8).join(labelled(spark, sf_dir), "set_id").select("label", "features")
    return load_times(spark, written(v, "vectors"), fresh_path(spark, "loads"), 128 << 8)


@query()
def preprocessing_ratio(spark, sf_dir):
    """Seconds to sketch all documents at k = 512 (one permutation, four, k), to load the coded result from text and from Parquet, and their ratios."""
    from ..functions.permute import Affine
    from ..sources.tables import timed

    words = written(doc_words(spark, sf_dir), "words")
    many = [Affine(D, 2 * (1_000_003 * (j + 1) % (1 << 22)) + 1, 12_345 + j) for j in range(512)]
    v = codes.to_vectors(codes.low_bits(sketch.bin_minima(words, many[0], 512), 8), 512, 8).join(labelled(spark, sf_dir), "set_id").select("label", "features")
    load = load_times(spark, written(v, "vectors"), fresh_path(spark, "loads"), 512 << 8).first()
    rows = [(m, p, timed(df)) for m, p, df in (("one permutation", 1, sketch.bin_minima(words, many[0], 512)), ("four permutations", 4, sketch.striped(words, many[:4], 512)), ("k permutations", 512, sketch.classic(words, many)))]
    one = rows[0][2]
    return spark.createDataFrame([(m, p, s, s / one, load.text_s, load.binary_s, s / load.text_s, s / load.binary_s) for m, p, s in rows], "method string, perms int, seconds double, over_one double, text_load_s double, binary_load_s double, over_text_load double, over_binary_load double")
