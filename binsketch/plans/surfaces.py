"""The same sketch through a pipeline stage and through an aggregate function."""

from __future__ import annotations

from pyspark.ml.functions import vector_to_array
from pyspark.sql import functions as F

from ..functions.sqlapi import sketch_agg
from ..operators import sets
from ..operators.ml import BinMinTransformer
from ..sources.tables import table
from .base import DIGEST, WORD_SETS, D, doc_words, query, sketch_sql
from .sketches import POS


@query(f"WITH {WORD_SETS}, {sketch_sql('words', POS, 64)}, n AS (SELECT set_id, count(*)::BIGINT AS filled, sum(\"offset\")::BIGINT AS total FROM sk GROUP BY 1) SELECT * FROM n")
def sketch_as_aggregate(spark, sf_dir):
    rows = doc_words(spark, sf_dir).select("set_id", DIGEST.pos(F.col("elem")).alias("pos")).groupBy("set_id").agg(sketch_agg("pos", D, 64).alias("m"))
    full = F.filter("m", lambda x: x >= 0)
    return rows.select("set_id", F.size(full).cast("long").alias("filled"), F.aggregate(full, F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))


@query(f"WITH {WORD_SETS} SELECT documents.doc_id, CAST(count(DISTINCT ((elem * 1140671485 + 12820163) % {D}) // {D // 128}) AS INTEGER) AS nnz FROM documents LEFT JOIN words ON set_id = doc_id GROUP BY 1")
def pipeline_stage_vectors(spark, sf_dir):
    """Nonzeros of the vectors that the pipeline stage makes."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.transform(sets.tokens(F.col("text")), lambda w: sets.digest_id(w, D)).alias("elems"))
    made = BinMinTransformer(inputCol="elems", outputCol="features", k=128, b=4).transform(docs)
    return made.select("doc_id", F.size(F.filter(vector_to_array("features"), lambda x: x != 0)).alias("nnz"))
