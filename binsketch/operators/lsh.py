"""Search tables: codes of a few bits, joined to bucket numbers of L tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..tables import written
from .components import components
from .estimate import pair_resemblance


def signatures(codes: DataFrame, b: int, k: int, L: int, hole_policy: str = "skip_band") -> DataFrame:
    """set_id, table_no, bucket: band t holds bins t k .. t k + k - 1, b bits of each.

    A band with holes: ``skip_band`` leaves it out; ``sentinel`` gives a hole a code
    of its own (bits b + 1). Noise-filled codes have no holes. Up to 62 bits the
    bucket is the codes themselves, beyond that their hash.
    """
    if hole_policy not in ("skip_band", "sentinel"):
        raise ValueError(hole_policy)
    rows = codes.filter(F.col("bin") < k * L).select("set_id", F.expr(f"bin div {k}").cast("int").alias("table_no"), F.expr(f"bin % {k}").cast("int").alias("slot"), "code")
    width = b if hole_policy == "skip_band" else b + 1
    coded = F.col("code").cast("long") + (0 if hole_policy == "skip_band" else 1)
    if width * k <= 62:
        weight = F.pow(F.lit(2.0), F.col("slot") * F.lit(width)).cast("long")
        grouped = rows.groupBy("set_id", "table_no").agg(F.sum(coded * weight).alias("bucket"), F.count(F.lit(1)).alias("n"))
    else:
        grouped = rows.groupBy("set_id", "table_no").agg(F.xxhash64(F.sort_array(F.collect_list(F.struct("slot", "code")))).alias("bucket"), F.count(F.lit(1)).alias("n"))
    return (grouped.filter(F.col("n") == k) if hole_policy == "skip_band" else grouped).select("set_id", "table_no", "bucket")


def build_index(sketch: DataFrame, b: int, k: int, L: int, hole_policy: str = "skip_band") -> DataFrame:
    """The index rows of a sketch with k L bins (or k L permutations): table_no, bucket, set_id."""
    codes = sketch.select("set_id", "bin", F.col("offset").bitwiseAND(F.lit((1 << b) - 1)).alias("code"))
    return signatures(codes, b, k, L, hole_policy).select("table_no", "bucket", "set_id")


def signatures_by(sketch: DataFrame, settings: DataFrame, hole_policy: str = "skip_band") -> DataFrame:
    """b, k, tables, set_id, table_no, bucket for all ``settings`` (b, k, tables; few rows) at once, each from the first k * tables bins."""
    extra = 0 if hole_policy == "skip_band" else 1
    rows = sketch.join(F.broadcast(settings), F.col("bin") < F.col("k") * F.col("tables"))
    code = F.col("offset").bitwiseAND((F.pow(F.lit(2), F.col("b")) - 1).cast("long")) + extra
    weight = F.pow(F.lit(2.0), (F.col("b") + extra) * (F.col("bin") % F.col("k"))).cast("long")
    grouped = rows.groupBy("b", "k", "tables", "set_id", F.expr("bin div k").cast("int").alias("table_no")).agg(F.sum(code * weight).alias("bucket"), F.count(F.lit(1)).alias("n"))
    return (grouped.filter(F.col("n") == F.col("k")) if not extra else grouped).drop("n")


def skipped_share(index: DataFrame, sketch: DataFrame, L: int) -> DataFrame:
    """One row: share of (set, table) places that holes left out."""
    n = sketch.select("set_id").distinct().agg((F.count(F.lit(1)) * L).alias("places"))
    return index.agg(F.count(F.lit(1)).alias("used")).crossJoin(n).select((1 - F.try_divide("used", "places")).alias("skipped"))


def write_index(index: DataFrame, path: str) -> DataFrame:
    """The index as a folder for each table, sorted by bucket, and read again: a query of some tables reads only their folders."""
    index.repartition("table_no", F.col("bucket") % 16).sortWithinPartitions("table_no", "bucket").write.partitionBy("table_no").parquet(path)
    return index.sparkSession.read.schema(index.schema).parquet(path).select(*index.columns)


def candidates(index: DataFrame, queries: DataFrame) -> DataFrame:
    """query_id, set_id: the union of the matching buckets of all tables."""
    q = queries.select("table_no", "bucket", F.col("set_id").alias("query_id"))
    return q.join(index, ["table_no", "bucket"]).select("query_id", "set_id").distinct()


def near_pairs(index: DataFrame) -> DataFrame:
    """i < j that share a bucket in some table."""
    x, y = index.select("table_no", "bucket", F.col("set_id").alias("i")), index.select("table_no", "bucket", F.col("set_id").alias("j"))
    return x.join(y, ["table_no", "bucket"]).filter("i < j").select("i", "j").distinct()


def star_pairs(index: DataFrame, *more: str) -> DataFrame:
    """j and its bucket's smallest set i: linear in a bucket's size, for hot buckets of near copies. It connects as near_pairs does only if nothing is verified afterwards."""
    key = ["table_no", "bucket", *more]
    head = index.groupBy(key).agg(F.min("set_id").alias("i"))
    return index.join(head, key).filter("set_id > i").select("i", F.col("set_id").alias("j")).distinct()


def linked_pairs(index: DataFrame, sets: DataFrame, min_r: float) -> DataFrame:
    """i < j with r >= min_r that connect as all near_pairs with r >= min_r do, and exact copies (whether or not they have a bucket).

    Copies collapse first. Pairs of a bucket's smallest set, and of those that share two
    neighbouring buckets, link most near copies; after that only sets of one bucket that
    are not connected yet are compared, each with each, so a bucket of near copies costs no
    square, but one of unrelated sets does.
    """
    own = written(sets.distinct(), "own")
    whole = own.groupBy("set_id").agg(F.sort_array(F.collect_list("elem")).alias("e"))
    same = written(whole.groupBy("e").agg(F.min("set_id").alias("i"), F.collect_list("set_id").alias("js"), F.size(F.first("e")).alias("f")).select("i", "f", F.explode("js").alias("j")), "same")
    sizes = same.filter("i = j").select(F.col("i").alias("set_id"), "f")
    own = written(own.join(sizes.select("set_id"), "set_id", "left_semi"), "singles")
    index = written(index.join(sizes, "set_id"), "index")

    def verified(pairs: DataFrame) -> DataFrame:
        f = lambda s: sizes.select(F.col("set_id").alias(s), F.col("f").alias(f"f{s}"))
        fit = pairs.join(f("i"), "i").join(f("j"), "j").filter(F.least("fi", "fj") >= F.lit(min_r) * F.greatest("fi", "fj")).select("i", "j")
        return written(pair_resemblance(own, written(fit, "fit")).filter(F.col("r_exact") >= min_r).select("i", "j"), "linked")

    both = index.join(index.select("set_id", (F.col("table_no") - 1).alias("table_no"), F.col("bucket").alias("next")), ["set_id", "table_no"])
    tried = written(star_pairs(index).union(star_pairs(both, "next")).distinct(), "tried")
    links = verified(tried)
    known = components(links, "i", "j").withColumnRenamed("node", "set_id")
    members = written(index.join(known, "set_id", "left").select("table_no", "bucket", F.coalesce("component", "set_id").alias("c"), "set_id", "f"), "members")
    groups = members.select("table_no", "bucket", "c").distinct()
    key = ["table_no", "bucket"]
    apart = groups.withColumnRenamed("c", "ci").join(groups.withColumnRenamed("c", "cj"), key).filter("ci < cj")
    x, y = (members.select(*key, F.col("c").alias(f"c{s}"), F.col("set_id").alias(s), F.col("f").alias(f"f{s}")) for s in "ij")
    rest = apart.join(x, [*key, "ci"]).join(y, [*key, "cj"]).filter(F.least("fi", "fj") >= F.lit(min_r) * F.greatest("fi", "fj"))
    rest = rest.select(F.least("i", "j").alias("i"), F.greatest("i", "j").alias("j")).distinct().join(tried, ["i", "j"], "left_anti")
    return links.union(verified(rest)).union(same.filter("i < j").select("i", "j"))


def short_index(index: DataFrame, sets: DataFrame, L: int, min_r: float) -> DataFrame:
    """Index rows (table_no -1, bucket = an element) by which each set that lacks one of the L bands meets all sets with r >= min_r.

    An exact prefix filter: with one order of the elements, rare ones first, two such
    sets share one of the first f - ceil(min_r f) + 1 of each. Elements that are in no
    short set's prefix have no row.
    """
    own = written(sets.distinct(), "own")
    ranked = own.join(own.groupBy("elem").agg(F.count(F.lit(1)).alias("df")), "elem").groupBy("set_id").agg(F.sort_array(F.collect_list(F.struct("df", "elem"))).alias("e"))
    first = F.slice("e", F.lit(1), (F.size("e") - F.ceil(F.lit(min_r) * F.size("e") - 1e-9) + 1).cast("int"))
    bands = index.groupBy("set_id").agg(F.count(F.lit(1)).alias("bands"))
    head = written(ranked.select("set_id", F.explode(F.transform(first, lambda s: s["elem"])).alias("bucket")).join(bands, "set_id", "left"), "prefix")
    short = head.filter(F.coalesce("bands", F.lit(0)) < L).select("bucket").distinct()
    return head.join(short, "bucket", "left_semi").select(F.lit(-1).alias("table_no"), "bucket", "set_id")


def top_k(scored: DataFrame, k: int, score: str = "score") -> DataFrame:
    """The k best of each query_id: rank from 1, ties to smaller set_id."""
    w = Window.partitionBy("query_id").orderBy(F.desc(score), "set_id")
    return scored.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def clusters(pairs: DataFrame) -> DataFrame:
    """set_id, cluster (smallest set reached)."""
    return components(pairs, "i", "j").select(F.col("node").alias("set_id"), F.col("component").alias("cluster"))


def recall(truth: DataFrame, found: DataFrame) -> DataFrame:
    """One row: true pairs, found ones, hits, recall, precision."""
    hit = truth.select("i", "j").join(found.select("i", "j"), ["i", "j"], "left_semi")
    n = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    t = n(truth, "n_true").crossJoin(n(found, "n_found")).crossJoin(n(hit, "hits"))
    return t.select("n_true", "n_found", "hits", F.try_divide(F.col("hits").cast("double"), "n_true").alias("recall"), F.try_divide(F.col("hits").cast("double"), "n_found").alias("precision"))
