"""Queries that once made their data up read a given table."""

import pytest
from pyspark.errors import AnalysisException

from binsketch import registry
from binsketch.session import ship


@pytest.mark.parametrize("name", ["op_recursive_cte", "op_scan_range", "perm_bijectivity", "perm_universal", "perm_vector_check", "table1_consistency", "theory_agreement", "theory_cov", "theory_empty_expanded"])
def test_table_is_needed(spark, tmp_path, name):
    ship(spark)
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        registry.queries()[name](spark, str(tmp_path)).collect()
