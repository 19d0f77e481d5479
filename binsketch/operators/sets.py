"""Sets from the tables, as long rows (set_id, elem) or arrays."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD = r"[\p{L}\p{N}]+"


def tokens(text: Column) -> Column:
    """Lower-cased words; null text gives an empty array."""
    return F.coalesce(F.regexp_extract_all(F.lower(text), F.lit(f"({WORD})"), F.lit(1)), F.array().cast("array<string>"))


def shingles(words: Column, w: int) -> Column:
    """w consecutive words joined by spaces; shorter texts have none."""
    n = F.greatest(F.size(words) - F.lit(w - 1), F.lit(0))
    rows = F.arrays_zip(*[F.slice(words, j + 1, n) for j in range(w)])
    return F.transform(rows, lambda x: F.concat_ws(" ", *[x[str(j)] for j in range(w)]))


def digest_id(value: Column, size: int) -> Column:
    """An id in 0..size-1 that any SQL engine computes alike (28 bits of md5)."""
    return F.conv(F.substring(F.md5(F.concat(F.lit("e:"), value).cast("binary")), 1, 7), 16, 10).cast("long") % F.lit(size)


def hashed_id(value: Column, size: int) -> Column:
    """The production id: xxhash64, mod size."""
    return F.pmod(F.xxhash64(value), F.lit(size))


def word_sets(docs: DataFrame, id_col: str, text_col: str, size: int, w: int = 1, ident=digest_id) -> DataFrame:
    """set_id, elem: one row per word or shingle (repeats stay: the sketches don't mind them)."""
    words = tokens(F.col(text_col))
    parts = words if w == 1 else shingles(words, w)
    return docs.select(F.col(id_col).alias("set_id"), F.explode(parts).alias("word")).select("set_id", ident(F.col("word"), size).alias("elem"))


def window_sets(docs: DataFrame, id_col: str, text_col: str, size: int, w: int, strides: tuple[int, ...], ident=digest_id) -> DataFrame:
    """set_id, elem of windows of a text: at each stride, windows of twice so many shingles, one from each multiple on.

    set_id is id * 4,000,000 + (number of the stride) * 1,000,000 + (number of the window), for texts of less than a million strides.
    """
    parts = docs.select(F.col(id_col).alias("id"), F.posexplode(shingles(tokens(F.col(text_col)), w)).alias("p", "word")).select("id", "p", ident(F.col("word"), size).alias("elem"))
    number = F.array(*[F.when(F.expr(f"p div {s}") >= back, F.lit(n * 1_000_000) + F.expr(f"p div {s}") - F.lit(back)) for n, s in enumerate(strides) for back in (0, 1)])
    return parts.select("id", "elem", F.explode(F.array_compact(number)).alias("win")).select((F.col("id") * F.lit(4_000_000) + F.col("win")).alias("set_id"), "elem")


def html_text(html: Column) -> Column:
    """Text of a page: scripts and styles out, then tags, then entities as spaces."""
    bare = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    return F.regexp_replace(F.regexp_replace(bare, r"(?s)<[^>]*>", " "), r"&[#\w]+;", " ")


def json_items(props: Column) -> Column:
    """key=value strings of a flat JSON object; null or broken JSON gives none."""
    m = F.from_json(props, "map<string,string>")
    return F.coalesce(F.transform(F.map_entries(m), lambda e: F.concat_ws("=", e["key"], e["value"])), F.array().cast("array<string>"))


def postings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """word, doc: distinct occurrences, a word's set of documents."""
    return docs.select(F.explode(F.array_distinct(tokens(F.col(text_col)))).alias("word"), F.col(id_col).alias("doc"))


def baskets(lineitem: DataFrame, set_col: str, elem_col: str) -> DataFrame:
    return lineitem.select(F.col(set_col).alias("set_id"), F.col(elem_col).alias("elem")).filter("set_id is not null and elem is not null")


def sign_sets(vectors: DataFrame) -> DataFrame:
    """set_id, elem: the places of positive components."""
    return vectors.select(F.col("vec_id").alias("set_id"), F.posexplode("embedding").alias("elem", "x")).filter("x > 0").select("set_id", F.col("elem").cast("long").alias("elem"))


def sizes(sets: DataFrame) -> DataFrame:
    """set_id, f: distinct elements."""
    return sets.groupBy("set_id").agg(F.countDistinct("elem").alias("f"))
