"""How a query and its DuckDB twin are registered, and the pieces that many of them share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.permute import Affine, Digest, Universal
from ..operators import sets
from ..sources.tables import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def register(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return register


#: The universe and permutations of the queries that both engines compute.
D = 1 << 24
AFFINE = Affine(D, 1140671485, 12820163)
DIGEST = Digest(D, 7)
STRIPES = [Digest(D, 11), Digest(D, 12), Digest(D, 13)]
CLASSIC = [Universal(D, 15_485_863 * (j + 1) % 2_147_483_647, 32_452_843 * (j + 7) % 2_147_483_647) for j in range(16)]
K, B, BAND, TABLES = 128, 4, 4, 32

_WORDS = r"regexp_extract_all(lower(text), '[\p{L}\p{N}]+')"


def elem_sql(value: str, size: int = D) -> str:
    return f"('0x' || substring(md5('e:' || {value}), 1, 7))::BIGINT % {size}"


#: set_id, elem of document words, pages' words and 3-shingles (repeats stay).
WORD_SETS = f"words AS (SELECT doc_id AS set_id, {elem_sql('w')} AS elem FROM (SELECT doc_id, unnest({_WORDS}) AS w FROM documents))"


def shingle_sql(table_name: str, id_col: str, text: str, w: int, name: str) -> str:
    words = _WORDS.replace("text", text)
    return f"""{name}_w AS (SELECT {id_col} AS set_id, {words} AS ws FROM {table_name}),
{name} AS (SELECT set_id, {elem_sql('s')} AS elem FROM (SELECT set_id, array_to_string(ws[i:i + {w - 1}], ' ') AS s FROM
 (SELECT set_id, ws, unnest(range(1, len(ws) - {w - 2})) AS i FROM {name}_w WHERE len(ws) >= {w})))"""


def sketch_sql(source: str, pos: str, k: int, size: int = D, name: str = "sk") -> str:
    width = size // k
    return f"{name} AS (SELECT set_id, CAST(({pos}) // {width} AS INTEGER) AS bin, min(({pos}) % {width}) AS \"offset\" FROM {source} GROUP BY 1, 2)"


def counters_sql(sk: str, pairs: str, k: int, value: str = '"offset"', name: str = "counters") -> str:
    return f"""{name}_c AS (SELECT set_id, count(*) AS c FROM {sk} GROUP BY 1),
{name}_m AS (SELECT p.i, p.j, count(*) FILTER (x.{value} = y.{value}) AS n_mat, count(*) AS n_both FROM {pairs} p JOIN {sk} x ON x.set_id = p.i JOIN {sk} y ON y.set_id = p.j AND y.bin = x.bin GROUP BY 1, 2),
{name} AS (SELECT p.i, p.j, CAST(coalesce(n_mat, 0) AS INTEGER) AS n_mat, CAST(coalesce(n_both, 0) AS INTEGER) AS n_both,
 CAST({k} - coalesce(a.c, 0) - coalesce(b.c, 0) + coalesce(n_both, 0) AS INTEGER) AS n_emp, CAST({k} - coalesce(a.c, 0) AS INTEGER) AS n_emp_i, CAST({k} - coalesce(b.c, 0) AS INTEGER) AS n_emp_j
 FROM {pairs} p LEFT JOIN {name}_m m ON m.i = p.i AND m.j = p.j LEFT JOIN {name}_c a ON a.set_id = p.i LEFT JOIN {name}_c b ON b.set_id = p.j)"""


def band_sql(sk: str, b: int, k: int, name: str = "idx") -> str:
    return f"""{name} AS (SELECT CAST(bin // {k} AS INTEGER) AS table_no, CAST(sum(("offset" & {(1 << b) - 1}) << CAST({b} * (bin % {k}) AS BIGINT)) AS BIGINT) AS bucket, set_id
 FROM {sk} GROUP BY table_no, set_id HAVING count(*) = {k})"""


def near_sql(index: str, name: str = "near") -> str:
    return f"{name} AS (SELECT DISTINCT x.set_id AS i, y.set_id AS j FROM {index} x JOIN {index} y ON x.table_no = y.table_no AND x.bucket = y.bucket AND x.set_id < y.set_id)"


def exact_sql(source: str, pairs: str, name: str = "ex") -> str:
    return f"""{name}_s AS (SELECT DISTINCT set_id, elem FROM {source}), {name}_n AS (SELECT set_id, count(*) AS f FROM {name}_s GROUP BY 1),
{name}_a AS (SELECT p.i, p.j, count(*) AS a FROM {pairs} p JOIN {name}_s x ON x.set_id = p.i JOIN {name}_s y ON y.set_id = p.j AND y.elem = x.elem GROUP BY 1, 2),
{name} AS (SELECT p.i, p.j, coalesce(u.f, 0) AS f1, coalesce(v.f, 0) AS f2, coalesce(a.a, 0) AS a, coalesce(a.a, 0)::DOUBLE / nullif(coalesce(u.f, 0) + coalesce(v.f, 0) - coalesce(a.a, 0), 0) AS r_exact
 FROM {pairs} p LEFT JOIN {name}_n u ON u.set_id = p.i LEFT JOIN {name}_n v ON v.set_id = p.j LEFT JOIN {name}_a a ON a.i = p.i AND a.j = p.j)"""


def doc_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sets.word_sets(table(spark, sf_dir, "documents"), "doc_id", "text", D)


def doc_shingles(spark: SparkSession, sf_dir: str, w: int = 3) -> DataFrame:
    return sets.word_sets(table(spark, sf_dir, "documents"), "doc_id", "text", D, w)


def r6(c, name: str | None = None):
    c = F.col(c) if isinstance(c, str) else c
    return F.round(c, 6).alias(name) if name else F.round(c, 6)
