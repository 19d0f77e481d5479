"""The registered queries of this folder, with production parameters over whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, written


def vocabulary(name: str) -> str:
    """Where a public vocabulary file lies; replace to use another place."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffix_dedup import removal_digests

    return removal_digests(table(spark, sf_dir, "documents"))


def op2_warc_archives(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .warc import archive_digests

    return archive_digests(table(spark, sf_dir, "pages"))


def op3_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_files import token_digests

    return token_digests(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))


def op4_site_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The documents that the classifier keeps, with their posteriors."""
    from .quality import classified

    rows = classified(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), ["doc_id", "source", "lang"])
    return rows.filter("keep").select("doc_id", "source", "lang", "quality_evidence", "toxic_evidence", "p_quality", "p_toxic", "keep")


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_counts import token_counts

    return token_counts(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))


def op6_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .jaccard_join import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op7_telephony_audio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All three formats; the resampled samples are a column of the result, stored with it."""
    from .audio import media_digests, stored

    return media_digests(written(stored(table(spark, sf_dir, "documents")), "media"), with_pcm=True)


def op8_piece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .piece_codec import piece_digests

    return piece_digests(table(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"))


def op9_lexical_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import packed

    return packed(table(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"))


def op10_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .exact_topk import quantised, top_k

    return top_k(quantised(table(spark, sf_dir, "embeddings")), F.col("vec_id") % 50 == 0)


OP1_SQL = """
WITH t AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS hx FROM documents),
u AS (SELECT doc_id, c, substr(hx, 1000 * c + 1, 1198) AS part FROM (SELECT doc_id, hx, unnest(range(0, (length(hx) // 2 - 99 + 499) // 500)) AS c FROM t WHERE length(hx) >= 200)),
s AS MATERIALIZED (SELECT doc_id, 500 * c + i AS st, md5(substr(part, 2 * i + 1, 200)) AS h, doc_id * 1000000000 + 500 * c + i AS place FROM (SELECT doc_id, c, part, unnest(range(0, length(part) // 2 - 99)) AS i FROM u)),
f AS (SELECT h, min(place) AS place FROM s GROUP BY 1 HAVING count(*) > 1),
r AS (SELECT doc_id, st, CASE WHEN st <= lag(st) OVER (PARTITION BY doc_id ORDER BY st) + 100 THEN 0 ELSE 1 END AS fresh FROM s JOIN f USING (h) WHERE s.place <> f.place),
g AS (SELECT doc_id, st, sum(fresh) OVER (PARTITION BY doc_id ORDER BY st) AS nr FROM r),
sp AS (SELECT doc_id, min(st) AS a, max(st) + 100 AS b FROM g GROUP BY doc_id, nr),
c AS (SELECT doc_id, a, b, lag(b, 1, 0) OVER (PARTITION BY doc_id ORDER BY a) AS before FROM sp),
k AS (SELECT doc_id, string_agg(substr(hx, 2 * before + 1, 2 * (a - before)), '' ORDER BY a) AS kept, max(b) AS tail, sum(b - a) AS gone, count(*) AS spans FROM c JOIN t USING (doc_id) GROUP BY 1)
SELECT doc_id, CAST(length(hx) // 2 AS BIGINT) AS n_bytes, CAST(coalesce(gone, 0) AS BIGINT) AS n_removed, CAST(coalesce(spans, 0) AS BIGINT) AS n_spans,
 sha256(unhex(coalesce(kept, '') || substr(hx, 2 * coalesce(tail, 0) + 1))) AS kept_sha256 FROM t LEFT JOIN k USING (doc_id)
"""

OP2_SQL = """
WITH p AS (SELECT page_id, strlen(coalesce(html, '')) AS n, sha1(coalesce(html, '')) AS hx, coalesce(url, '') AS url FROM pages),
r AS (SELECT *, row_number() OVER (PARTITION BY hx ORDER BY page_id DESC NULLS LAST, url DESC) AS nr, max(page_id) OVER (PARTITION BY hx) AS top FROM p)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes,
 array_to_string(list_transform(range(32), lambda j: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST(1 + ((('0x' || substr(hx, CAST(5 * (j // 4) + 1 AS BIGINT), 5))::BIGINT // CAST(pow(2, 15 - 5 * (j % 4)) AS BIGINT)) % 32) AS BIGINT), 1)), '') AS payload_digest,
 CASE WHEN nr = 1 THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN nr > 1 THEN top END AS refers_to FROM r
"""

OP6_SQL = r"""
WITH RECURSIVE t AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, x FROM (SELECT doc_id, unnest(CASE WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS x FROM t WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM s a JOIN s b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * k >= 80 * (x.n + y.n - k)),
e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
reach AS (SELECT doc_id AS root, doc_id AS node FROM documents UNION SELECT root, b FROM reach JOIN e ON node = a)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, c.component_id FROM documents d LEFT JOIN n USING (doc_id) JOIN (SELECT root, min(node) AS component_id FROM reach GROUP BY 1) c ON c.root = d.doc_id
"""

OP10_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(CAST(q.v AS DOUBLE[]), CAST(c.v AS DOUBLE[])) AS BIGINT) AS score
      FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_suffix_dedup, op2_warc_archives, op3_token_files, op4_site_quality, op5_token_counts, op6_jaccard_join, op7_telephony_audio, op8_piece_codec, op9_lexical_packing, op10_exact_top_k)}
ORACLES: dict[str, str] = {"op1_suffix_dedup": OP1_SQL, "op2_warc_archives": OP2_SQL, "op6_jaccard_join": OP6_SQL, "op10_exact_top_k": OP10_SQL}
