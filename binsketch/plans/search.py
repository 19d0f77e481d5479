"""Queries of near-neighbour search, contamination, pages, baskets and comparators."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.permute import Affine, Digest
from ..operators import blocks, estimate, linear_sketch, lsh, sets, sketch, ways
from ..sources.tables import table
from ..tables import fresh_path, written
from .base import BAND, DIGEST, K, TABLES, WORD_SETS, B, D, band_sql, counters_sql, doc_shingles, doc_words, exact_sql, near_sql, query, r6, shingle_sql, sketch_sql
from .sketches import CLASSIC_SH, COUNTED, NEAR, POS, SHINGLES3, SIZED, TRUE_PAIRS, docs_alike, near_docs, near_measured, shingle_sketch

INDEX = f"{SHINGLES3}, {sketch_sql('sh', POS, K)}, {band_sql('sk', B, BAND)}"


def doc_index(spark, sf_dir):
    return lsh.build_index(shingle_sketch(spark, sf_dir), B, BAND, TABLES)


@query(f"WITH {INDEX} SELECT * FROM idx")
def lsh_index_docs(spark, sf_dir):
    return doc_index(spark, sf_dir)


@query(f"WITH {SHINGLES3}, {CLASSIC_SH}, {band_sql('cl', B, BAND)} SELECT * FROM idx")
def lsh_index_classic(spark, sf_dir):
    """Tables from four permutations each instead of four bins of one."""
    from .base import CLASSIC

    return lsh.build_index(sketch.classic(doc_shingles(spark, sf_dir), CLASSIC), B, BAND, 4)


@query(f"WITH {INDEX}, q AS (SELECT * FROM idx WHERE set_id % 10 = 0) SELECT DISTINCT q.set_id AS query_id, idx.set_id FROM q JOIN idx USING (table_no, bucket)")
def lsh_candidates(spark, sf_dir):
    index = written(doc_index(spark, sf_dir), "index")
    return lsh.candidates(index, index.filter("set_id % 10 = 0"))


@query(f"WITH {INDEX}, q AS (SELECT * FROM idx WHERE set_id % 100 = 0) SELECT DISTINCT q.set_id AS query_id, idx.set_id FROM q JOIN idx USING (table_no, bucket) WHERE table_no < 8")
def lsh_stored_index(spark, sf_dir):
    """A stored index, a folder for each table: eight of them are asked, and only those are read."""
    index = lsh.write_index(doc_index(spark, sf_dir), fresh_path(spark, "stored-index")).filter("table_no < 8")
    return lsh.candidates(index, index.filter("set_id % 100 = 0"))


@query(f"WITH {NEAR} SELECT * FROM near")
def lsh_near_pairs(spark, sf_dir):
    return near_docs(spark, sf_dir)[1]


@query(f"WITH {NEAR}, {exact_sql('sh', 'near')}, e AS (SELECT i, j FROM ex WHERE r_exact >= 0.5) SELECT count(*) AS pairs, count(DISTINCT i) AS heads FROM e")
def lsh_verified_pairs(spark, sf_dir):
    t = near_measured(spark, sf_dir, SIZED, blocks.exact(D), elems=True)
    e = t.filter(estimate.resemblance(F.col("f1"), F.col("f2"), F.col("a")) >= 0.5)
    return e.agg(F.count(F.lit(1)).alias("pairs"), F.countDistinct("i").alias("heads"))


TRUTH = """{s}_d AS (SELECT DISTINCT set_id, elem FROM {s}), {s}_f AS (SELECT set_id, count(*) AS f FROM {s}_d GROUP BY 1),
truth AS (SELECT i, j, a, x.f AS f1, y.f AS f2, a::DOUBLE / (x.f + y.f - a) AS r FROM (SELECT x.set_id AS i, y.set_id AS j, count(*) AS a FROM {s}_d x JOIN {s}_d y ON x.elem = y.elem AND x.set_id < y.set_id GROUP BY 1, 2) p JOIN {s}_f x ON x.set_id = i JOIN {s}_f y ON y.set_id = j)"""


@query(f"WITH {SHINGLES3}, {TRUTH.format(s='sh')} SELECT i, j, f1, f2, a, round(r, 6) AS r_exact FROM truth WHERE r >= 0.8")
def exact_pairs_docs(spark, sf_dir):
    t = docs_alike(spark, sf_dir, 0.8)
    return t.select("i", "j", "f1", "f2", "a", r6(estimate.resemblance(F.col("f1"), F.col("f2"), F.col("a")), "r_exact"))


PARTS = "b AS (SELECT l_partkey AS set_id, l_orderkey AS elem FROM lineitem)"


@query(f"WITH {PARTS}, {TRUTH.format(s='b')} SELECT i, j, f1, f2, a, round(r, 6) AS r_exact FROM truth")
def exact_pairs_parts(spark, sf_dir):
    return estimate.all_pairs(sets.baskets(table(spark, sf_dir, "lineitem"), "l_partkey", "l_orderkey")).select("i", "j", "f1", "f2", "a", r6("r_exact", "r_exact"))


@query(f"WITH {NEAR}, {TRUTH.format(s='sh')}, t AS (SELECT i, j FROM truth WHERE r >= 0.8), h AS (SELECT t.* FROM t JOIN near USING (i, j)) SELECT (SELECT count(*) FROM t) AS n_true, (SELECT count(*) FROM near) AS n_found, (SELECT count(*) FROM h) AS hits, round((SELECT count(*) FROM h)::DOUBLE / (SELECT count(*) FROM t), 6) AS recall, round((SELECT count(*) FROM h)::DOUBLE / (SELECT count(*) FROM near), 6) AS precision")
def lsh_recall(spark, sf_dir):
    _, near, sh = near_docs(spark, sf_dir)
    t = lsh.recall(estimate.all_pairs(sh, 0.8), near)
    return t.select("n_true", "n_found", "hits", r6("recall", "recall"), r6("precision", "precision"))


@query(f"WITH {NEAR}, {counters_sql('sk', 'near', K)}, s AS (SELECT i AS query_id, j AS set_id, round(n_mat::DOUBLE / nullif({K} - n_emp, 0), 6) AS score FROM counters UNION ALL SELECT j, i, round(n_mat::DOUBLE / nullif({K} - n_emp, 0), 6) FROM counters), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, set_id) AS INTEGER) AS rank FROM s) SELECT * FROM r WHERE rank <= 5")
def lsh_top5(spark, sf_dir):
    c = near_measured(spark, sf_dir, COUNTED, blocks.counters()).select("i", "j", r6(estimate.unbiased(K), "score"))
    ways = F.explode(F.array(F.struct(F.col("i").alias("query_id"), F.col("j").alias("set_id"), "score"), F.struct(F.col("j").alias("query_id"), F.col("i").alias("set_id"), "score")))
    return lsh.top_k(c.select(ways.alias("w")).select("w.*"), 5).select("query_id", "set_id", "score", F.col("rank").cast("int").alias("rank"))


CLUSTERS = f"""WITH RECURSIVE {INDEX}, {TRUTH.format(s='sh')}, n AS (SELECT set_id, count(*) AS c FROM idx GROUP BY 1),
near AS (SELECT DISTINCT x.set_id AS i, y.set_id AS j FROM idx x JOIN idx y ON x.table_no = y.table_no AND x.bucket = y.bucket AND x.set_id < y.set_id),
l AS (SELECT t.i, t.j FROM truth t LEFT JOIN near USING (i, j) LEFT JOIN n x ON x.set_id = t.i LEFT JOIN n y ON y.set_id = t.j WHERE t.r >= 0.5 AND (near.i IS NOT NULL OR t.r = 1 OR least(coalesce(x.c, 0), coalesce(y.c, 0)) < {TABLES})),
e AS (SELECT i AS a, j AS b FROM l UNION ALL SELECT j, i FROM l), reach AS (SELECT a AS root, a AS node FROM e UNION SELECT root, b FROM reach JOIN e ON node = a)
SELECT root AS set_id, min(node) AS cluster FROM reach GROUP BY 1"""


@query(CLUSTERS)
def lsh_clusters(spark, sf_dir):
    """Near-duplicate clusters: components of the pairs with a resemblance of 0.5 or more that share a bucket, or one of which lacks a band."""
    own = blocks.packed(table(spark, sf_dir, "documents"), "doc_id", "text", D, 3, DIGEST, K, elems=True)
    return lsh.clusters(blocks.measured(own, K, B, BAND, [blocks.counters()], "n_mat int", find=blocks.linked(blocks.alike(D, 0.5), blocks.bucket_or_short(B, BAND))))


BENCH = shingle_sql("benchmark", "item_id", "text", 3, "bn")


@query(f"""WITH {SHINGLES3}, {BENCH}, s AS (SELECT DISTINCT set_id, elem FROM sh), b AS (SELECT DISTINCT set_id, elem FROM bn), n AS (SELECT set_id, count(*) AS f FROM b GROUP BY 1),
c AS (SELECT b.set_id AS item_id, s.set_id AS doc_id, count(*) AS a FROM b JOIN s USING (elem) GROUP BY 1, 2) SELECT item_id, doc_id, round(a / f::DOUBLE, 6) AS contained FROM c JOIN n ON n.set_id = item_id WHERE a >= 0.5 * f""")
def contamination_bench(spark, sf_dir):
    """Benchmark items half of which or more a document contains."""
    docs = doc_shingles(spark, sf_dir).distinct()
    items = sets.word_sets(table(spark, sf_dir, "benchmark"), "item_id", "text", D, 3).distinct().withColumnRenamed("set_id", "item_id")
    n = items.groupBy("item_id").agg(F.count(F.lit(1)).alias("f"))
    shared = items.join(docs, "elem").groupBy("item_id", F.col("set_id").alias("doc_id")).agg(F.count(F.lit(1)).alias("a"))
    return shared.join(n, "item_id").filter("a >= 0.5 * f").select("item_id", "doc_id", r6(F.col("a") / F.col("f"), "contained"))


PAGES = "pt AS (SELECT page_id, regexp_replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '&[#\\w]+;', ' ', 'g') AS text FROM pages)"
PAGE_SH = shingle_sql("pt", "page_id", "text", 3, "pg")


@query(f"WITH {PAGES}, {PAGE_SH}, {sketch_sql('pg', POS, K)}, {band_sql('sk', B, BAND)}, {near_sql('idx')}, {exact_sql('pg', 'near')} SELECT i, j, round(r_exact, 6) AS r_exact FROM ex WHERE r_exact >= 0.5")
def page_near_dups(spark, sf_dir):
    pages = table(spark, sf_dir, "pages").select("page_id", sets.html_text(F.col("html")).alias("text"))
    sh = written(sets.word_sets(pages, "page_id", "text", D, 3), "page-shingles")
    near = lsh.near_pairs(lsh.build_index(sketch.bin_minima(sh, DIGEST, K), B, BAND, TABLES))
    return estimate.pair_resemblance(sh, near).filter("r_exact >= 0.5").select("i", "j", r6("r_exact", "r_exact"))


CONV = "cv AS (SELECT conv_id, string_agg(text, ' ' ORDER BY turn, role, text) AS text FROM conversations GROUP BY 1)"
CONV_SH = shingle_sql("cv", "conv_id", "text", 3, "cs")


@query(f"WITH {CONV}, {CONV_SH}, {sketch_sql('cs', POS, K)}, {band_sql('sk', B, BAND, 'qi')}, {SHINGLES3}, {sketch_sql('sh', POS, K, name='ds')}, {band_sql('ds', B, BAND)} SELECT DISTINCT qi.set_id AS query_id, idx.set_id FROM qi JOIN idx USING (table_no, bucket)")
def conv_queries(spark, sf_dir):
    """Whole conversations asked of the documents' index."""
    turns = F.sort_array(F.collect_list(F.struct("turn", "role", "text")))
    conv = table(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(turns, lambda t: t["text"]), " ").alias("text"))
    q = lsh.build_index(sketch.bin_minima(sets.word_sets(conv, "conv_id", "text", D, 3), DIGEST, K), B, BAND, TABLES)
    return lsh.candidates(doc_index(spark, sf_dir), q)


SUPP = "b AS (SELECT l_suppkey AS set_id, l_partkey AS elem FROM lineitem)"
ALL = "near AS (SELECT x.set_id AS i, y.set_id AS j FROM (SELECT DISTINCT set_id FROM sk) x JOIN (SELECT DISTINCT set_id FROM sk) y ON x.set_id < y.set_id)"


def _similar(name: str, source_sql: str, rows, k: int, owners: str):
    """The three most alike sets of each, of those that share a minimum; ``owners`` is the table of the sets' keys."""
    top = f"t AS (SELECT i, j, round(n_mat::DOUBLE / nullif({k} - n_emp, 0), 6) AS r FROM counters), s AS (SELECT i AS query_id, j AS set_id, r AS score FROM t UNION ALL SELECT j, i, r FROM t), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, set_id) AS INTEGER) AS rank FROM s)"

    pair = "near AS (SELECT DISTINCT x.set_id AS i, y.set_id AS j FROM sk x JOIN sk y ON x.bin = y.bin AND x.\"offset\" = y.\"offset\" AND x.set_id < y.set_id)"

    @query(f"WITH {source_sql}, {sketch_sql('b', POS, k)}, {pair}, {counters_sql('sk', 'near', k)}, {top} SELECT * FROM r WHERE rank <= 3")
    def run(spark, sf_dir):
        own = blocks.packed_rows(rows(spark, sf_dir), DIGEST, k, table(spark, sf_dir, owners).count())
        c = blocks.measured(own, k, (D // k).bit_length(), 1, [blocks.counters()], COUNTED).select("i", "j", r6(estimate.unbiased(k), "score"))
        ways = F.explode(F.array(F.struct(F.col("i").alias("query_id"), F.col("j").alias("set_id"), "score"), F.struct(F.col("j").alias("query_id"), F.col("i").alias("set_id"), "score")))
        both = c.select(ways.alias("w")).select("w.*")
        return lsh.top_k(both, 3).select("query_id", "set_id", "score", F.col("rank").cast("int").alias("rank"))

    from .base import ORACLES, QUERIES

    QUERIES[name], ORACLES[name] = QUERIES.pop("run"), ORACLES.pop("run")


_similar("supp_similar", SUPP, lambda s, d: sets.baskets(table(s, d, "lineitem"), "l_suppkey", "l_partkey"), 64, "supplier")
_similar("part_similar", PARTS, lambda s, d: sets.baskets(table(s, d, "lineitem"), "l_partkey", "l_orderkey"), 32, "part")
_similar("cust_similar", "b AS (SELECT o_custkey AS set_id, l_partkey AS elem FROM orders JOIN lineitem ON l_orderkey = o_orderkey)", lambda s, d: sets.baskets(table(s, d, "lineitem").join(table(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")), "o_custkey", "l_partkey"), 32, "customer")


@query("WITH v AS (SELECT vec_id AS set_id, unnest(range(len(embedding))) AS elem, unnest(embedding) AS x FROM embeddings) SELECT set_id, CAST(elem // 8 AS INTEGER) AS bin, min(elem % 8) AS \"offset\" FROM v WHERE x > 0 GROUP BY 1, 2")
def dense_sign_sets(spark, sf_dir):
    """A tiny dense universe: D = 64, k = 8, the identity as permutation."""
    from ..functions.permute import Identity

    return sketch.bin_minima(sets.sign_sets(table(spark, sf_dir, "embeddings")), Identity(64), 8)


BINS, SIGNS = Digest(1 << 28, 31), Digest(1 << 28, 32)
SIGNED = SIGNS.sql("elem")


def _sums_sql(value: str) -> str:
    return f"s0 AS (SELECT DISTINCT set_id, elem FROM sh), sk AS (SELECT set_id, ({BINS.sql('elem')}) % 256 AS bin, sum({value})::BIGINT AS val FROM s0 GROUP BY 1, 2), d AS (SELECT near.i, near.j, sum(x.val * y.val)::BIGINT AS dot FROM near JOIN sk x ON x.set_id = near.i JOIN sk y ON y.set_id = near.j AND y.bin = x.bin GROUP BY 1, 2), dots AS (SELECT near.i, near.j, coalesce(dot, 0) AS dot FROM near LEFT JOIN d USING (i, j))"


NEAR_ONLY = f"near AS MATERIALIZED (WITH {NEAR} SELECT * FROM near), {SHINGLES3}"


@query(f"WITH {NEAR_ONLY}, {_sums_sql('1')} SELECT * FROM dots")
def binsum_dot(spark, sf_dir):
    return near_measured(spark, sf_dir, "dot long", blocks.dots(), extra=blocks.summed(BINS, 256), kind="i4")


@query(f"WITH {NEAR_ONLY}, {_sums_sql('1')}, {exact_sql('sh', 'near')} SELECT ex.i, ex.j, a, round((dot - f1 * f2 / 256.0::DOUBLE) * 256 / 255, 4) AS a_hat FROM dots JOIN ex USING (i, j)")
def debiased_dot(spark, sf_dir):
    t = near_measured(spark, sf_dir, f"dot long, {SIZED}", blocks.dots(), blocks.exact(D), extra=blocks.summed(BINS, 256), kind="i4", elems=True)
    return t.select("i", "j", "a", F.round(linear_sketch.debiased(F.col("dot"), F.col("f1"), F.col("f2"), 256), 4).alias("a_hat"))


@query(f"WITH {NEAR_ONLY}, {_sums_sql(f'1 - 2 * (({SIGNED}) % 2)')} SELECT * FROM dots")
def signed_dot(spark, sf_dir):
    return near_measured(spark, sf_dir, "dot long", blocks.dots(), extra=blocks.summed(BINS, 256, SIGNS), kind="i4")


PROJECTIONS = [Affine(D, 2 * (7_919 * (j + 3)) + 1, 104_729 * (j + 1) % D) for j in range(64)]


def _signed(p: Affine) -> str:
    return f"1 - 2 * (({p.sql('elem')}) // {D // 2})"


@query(f"WITH {NEAR_ONLY}, s0 AS (SELECT DISTINCT set_id, elem FROM sh), w AS (SELECT set_id, " + ", ".join(f"sum({_signed(p)})::BIGINT AS s{j}" for j, p in enumerate(PROJECTIONS)) + " FROM s0 GROUP BY 1) SELECT near.i, near.j, round((" + " + ".join(f"x.s{j} * y.s{j}" for j in range(len(PROJECTIONS))) + f") / {len(PROJECTIONS)}.0::DOUBLE, 6) AS a_hat FROM near JOIN w x ON x.set_id = near.i JOIN w y ON y.set_id = near.j")
def random_projections(spark, sf_dir):
    _, near, sh = near_docs(spark, sf_dir)
    return linear_sketch.projected_intersection(linear_sketch.projection_sums(sh, PROJECTIONS), near, len(PROJECTIONS)).select("i", "j", r6("a_hat", "a_hat"))


CK = 256


def _comparators_sql() -> str:
    sums = lambda value: f"SELECT set_id, ({BINS.sql('elem')}) % {CK} AS bin, sum({value})::BIGINT AS val FROM d0 GROUP BY 1, 2"
    dot = lambda t: f"SELECT tp.i, tp.j, sum(x.val * y.val)::DOUBLE AS dot FROM tp JOIN {t} x ON x.set_id = tp.i JOIN {t} y ON y.set_id = tp.j AND y.bin = x.bin GROUP BY 1, 2"
    return f"""WITH {SHINGLES3}, {TRUE_PAIRS}, s1 AS ({sums('1')}), s2 AS ({sums(f'1 - 2 * (({SIGNED}) % 2)')}), d1 AS ({dot('s1')}), d2 AS ({dot('s2')}),
w AS (SELECT set_id, {', '.join(f"sum({_signed(p)})::BIGINT AS s{j}" for j, p in enumerate(PROJECTIONS))} FROM d0 GROUP BY 1),
{sketch_sql('d0', POS, CK, name='bm')}, {counters_sql('bm', 'tp', CK)},
e AS (SELECT 'bin sums' AS method, i, j, dot AS v FROM d1 UNION ALL SELECT 'debiased bin sums', i, j, (dot - f1 * f2 / {CK}.0::DOUBLE) * {CK} / {CK - 1} FROM d1 JOIN tp USING (i, j) UNION ALL SELECT 'signed bin sums', i, j, dot FROM d2
 UNION ALL SELECT 'projections', tp.i, tp.j, ({' + '.join(f"x.s{j} * y.s{j}" for j in range(len(PROJECTIONS)))}) / {len(PROJECTIONS)}.0::DOUBLE FROM tp JOIN w x ON x.set_id = tp.i JOIN w y ON y.set_id = tp.j
 UNION ALL SELECT 'bin minima', tp.i, tp.j, (n_mat::DOUBLE / ({CK} - n_emp)) * (f1 + f2) / (1 + n_mat::DOUBLE / ({CK} - n_emp)) FROM tp JOIN counters c USING (i, j))
SELECT method, count(*) AS pairs, round(avg((v - a) / a), 5) AS bias, round(avg(((v - a) / a) * ((v - a) / a)), 5) AS mse FROM e JOIN tp USING (i, j) GROUP BY 1"""


@query(_comparators_sql())
def comparator_errors(spark, sf_dir):
    """Relative bias and squared error of the intersection's size by sums of bins (plain, debiased, signed), projections and bin minima,
    over all pairs of documents with a resemblance of 0.5 or more; 256 values a set (projections: 64)."""
    extra = blocks.beside(blocks.summed(BINS, CK), blocks.summed(BINS, CK, SIGNS), blocks.projected(PROJECTIONS))
    parts = {"plain": (0, CK), "signed": (CK, 2 * CK), "thrown": (2 * CK, 2 * CK + len(PROJECTIONS))}
    t = docs_alike(spark, sf_dir, 0.5, ", n_mat int, n_emp int, plain long, signed long, thrown long", blocks.counters(), blocks.dots_of(parts), k=CK, extra=extra, kind="i4", block=16_384)
    f1, f2, a, r = F.col("f1"), F.col("f2"), F.col("a"), estimate.unbiased(CK)
    ways = {"bin sums": F.col("plain").cast("double"), "debiased bin sums": linear_sketch.debiased(F.col("plain"), f1, f2, CK), "signed bin sums": F.col("signed").cast("double"), "projections": F.col("thrown") / F.lit(float(len(PROJECTIONS))), "bin minima": estimate.union_size(f1, f2, r) * r}
    out = t.select(F.explode(F.array(*[F.struct(F.lit(name).alias("method"), ((v - a) / a).alias("off")) for name, v in ways.items()])).alias("e")).select("e.*")
    return out.groupBy("method").agg(F.count(F.lit(1)).alias("pairs"), F.round(F.avg("off"), 5).alias("bias"), F.round(F.avg(F.col("off") * F.col("off")), 5).alias("mse"))


COUNTERS = [Digest(1 << 28, 61 + j) for j in range(4)]
CELLS = 2048


@query(f"""WITH {WORD_SETS}, c AS (SELECT 0 AS r, 0 AS cell, 0 AS n WHERE false""" + "".join(f" UNION ALL SELECT {j}, ({p.sql('elem')}) % {CELLS}, count(*) FROM words GROUP BY 2" for j, p in enumerate(COUNTERS)) + """), top AS (SELECT elem, count(*) AS n FROM words GROUP BY 1 ORDER BY n DESC, elem LIMIT 10)
SELECT elem, top.n, min(c.n)::BIGINT AS estimate FROM top JOIN c ON """ + " OR ".join(f"(r = {j} AND cell = ({p.sql('elem')}) % {CELLS})" for j, p in enumerate(COUNTERS)) + " GROUP BY 1, 2")
def element_frequencies(spark, sf_dir):
    """The classical counting structure over all words (4 rows of 2048 counters): estimates beside the ten largest counts."""
    words = doc_words(spark, sf_dir)
    top = words.groupBy("elem").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "elem").limit(10)
    counters = linear_sketch.frequency_counters(words, COUNTERS, CELLS)
    return linear_sketch.frequency_estimates(counters, top, COUNTERS, CELLS).select("elem", "n", "estimate")


@query(f"WITH {SHINGLES3}, {sketch_sql('sh', POS, K)}, n AS (SELECT set_id, CAST(bin // {BAND} AS INTEGER) AS t, count(*) AS c FROM sk GROUP BY 1, 2), p AS (SELECT count(DISTINCT set_id) * {TABLES} AS places FROM sk) SELECT round(1 - count(*) FILTER (c = {BAND}) / any_value(places)::DOUBLE, 6) AS skipped, 'skip_band' AS policy FROM n, p UNION ALL SELECT round(1 - count(*) / any_value(places)::DOUBLE, 6), 'sentinel' FROM n, p")
def skipped_bands(spark, sf_dir):
    """Share of (document, table) places that holes leave out of the index, by hole policy."""
    sk = written(shingle_sketch(spark, sf_dir), "sketch")
    out = None
    for policy in ("skip_band", "sentinel"):
        one = lsh.skipped_share(lsh.build_index(sk, B, BAND, TABLES, policy), sk, TABLES).select(r6("skipped", "skipped"), F.lit(policy).alias("policy"))
        out = one if out is None else out.unionByName(one)
    return out


#: Every (b, k, L) of the search experiment that fits 128 bins of one sketch; 64 permutations of the classic one.
SETTINGS = [(b, k, L) for b in (1, 2, 4) for k in (4, 8) for L in (1, 4, 16)]
CLASSIC64 = [Affine(D, 2 * (15_485_863 * (j + 1) % (1 << 22)) + 1, 32_452_843 * (j + 1) % D) for j in range(64)]


def _grid_sql() -> str:
    values = ", ".join(f"({b}, {k}, {L})" for b, k, L in SETTINGS)
    index = lambda sk, source, policy, width, plus, keep: f"SELECT '{source}' AS source, '{policy}' AS policy, s.b, s.k, s.l, set_id, CAST(bin // s.k AS INTEGER) AS t, sum(((\"offset\" & ((1 << s.b) - 1)) + {plus}) * CAST(pow(2, {width} * (bin % s.k)) AS BIGINT))::HUGEINT AS bucket FROM {sk} JOIN settings s ON bin < s.k * s.l{keep[0]} GROUP BY ALL{keep[1]}"
    return f"""WITH {SHINGLES3}, {sketch_sql('sh', POS, K)}, settings(b, k, l) AS (VALUES {values}),
cl AS (SELECT set_id, CAST(bin AS INTEGER) AS bin, min(p) AS "offset" FROM ({' UNION ALL '.join(f"SELECT set_id, {j} AS bin, {p.sql('elem')} AS p FROM sh" for j, p in enumerate(CLASSIC64))}) GROUP BY 1, 2),
ix AS MATERIALIZED (SELECT * EXCLUDE (n) FROM ({index('sk', 'one permutation', 'skip_band', 's.b', 0, ('', '')).replace('::HUGEINT AS bucket', '::HUGEINT AS bucket, count(*) AS n')}) WHERE n = k UNION ALL {index('sk', 'one permutation', 'sentinel', '(s.b + 1)', 1, ('', ''))} UNION ALL {index('cl', 'classic', 'none', 's.b', 0, (' AND s.k * s.l <= 64', ''))}),
{TRUTH.format(s='sh')}, t8 AS (SELECT i, j FROM truth WHERE r >= 0.8), ways AS (SELECT DISTINCT source, policy, b, k, l FROM ix),
hit AS (SELECT source, policy, b, k, l, count(*) AS hits FROM (SELECT DISTINCT x.source, x.policy, x.b, x.k, x.l, i, j FROM t8 JOIN ix x ON x.set_id = i JOIN ix y ON y.set_id = j AND x.source = y.source AND x.policy = y.policy AND x.b = y.b AND x.k = y.k AND x.l = y.l AND x.t = y.t AND x.bucket = y.bucket) GROUP BY ALL),
cand AS (SELECT source, policy, b, k, l, count(*) AS candidates FROM (SELECT DISTINCT x.source, x.policy, x.b, x.k, x.l, x.set_id AS i, y.set_id AS j FROM ix x JOIN ix y ON x.source = y.source AND x.policy = y.policy AND x.b = y.b AND x.k = y.k AND x.l = y.l AND x.t = y.t AND x.bucket = y.bucket AND x.set_id <> y.set_id WHERE x.set_id % 100 = 0) GROUP BY ALL)
SELECT w.source, w.policy, w.b, w.k, w.l AS tables, (SELECT count(*) FROM t8) AS n_true, coalesce(hits, 0) AS hits, round(coalesce(hits, 0) / (SELECT count(*) FROM t8)::DOUBLE, 6) AS recall, coalesce(candidates, 0) AS candidates,
 round(coalesce(candidates, 0) / ((SELECT count(DISTINCT set_id) FROM sk WHERE set_id % 100 = 0) * ((SELECT count(DISTINCT set_id) FROM sk) - 1))::DOUBLE, 6) AS fraction
FROM ways w LEFT JOIN hit h ON h.source = w.source AND h.policy = w.policy AND h.b = w.b AND h.k = w.k AND h.l = w.l LEFT JOIN cand c ON c.source = w.source AND c.policy = w.policy AND c.b = w.b AND c.k = w.k AND c.l = w.l"""


@query(_grid_sql())
def search_grid(spark, sf_dir):
    """Recall of all pairs with a resemblance of 0.8 or more, and the share of the table that a query meets, by b, k, L, hole policy
    and sketch. Queries of the second are the rows whose id is divisible by 100. All settings read one sketch of each kind, packed once, by blocks."""
    grid = ways.Ways(SETTINGS, K, len(CLASSIC64))
    own = blocks.packed(table(spark, sf_dir, "documents"), "doc_id", "text", D, 3, DIGEST, K, ways.classic_minima(CLASSIC64), elems=True)
    truth = blocks.measured(own, K, B, BAND, [grid.shared()], "ways long", "i4", blocks.alike(D, 0.8), ways.SETS)
    sums = [F.coalesce(F.sum(F.shiftright("ways", n).bitwiseAND(F.lit(1))), F.lit(0)) for n in range(len(grid.all))]
    hits = truth.agg(F.count(F.lit(1)).alias("n_true"), F.array(*sums).alias("h")).select("n_true", F.posexplode("h").alias("way", "hits"))
    facts = own.agg(F.count(F.lit(1)).alias("sets"), F.count_if(F.col("set_id") % 100 == 0).alias("asked"))
    names = spark.createDataFrame([(n, *w) for n, w in enumerate(grid.all)], "way int, source string, policy string, b int, k int, tables int")
    t = F.broadcast(names).join(ways.candidates(own, grid, "set_id % 100 = 0").filter("used"), "way").join(hits, "way").crossJoin(facts)
    return t.select("source", "policy", "b", "k", "tables", "n_true", "hits", r6(F.try_divide("hits", "n_true"), "recall"), "candidates", r6(F.try_divide("candidates", F.col("asked") * (F.col("sets") - 1)), "fraction"))
