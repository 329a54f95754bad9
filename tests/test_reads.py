"""Queries that once made their data up read a given table: without one they cannot be planned."""

import pytest
from pyspark.errors import AnalysisException

from clustercost import catalog

NAMES = [
    "udtf_index_gadget",
    "gadget_source",
    "op_cast_decimal",
    "op_cte_recursive",
    "op_generate_grid",
    "op_math_sizes",
    "space_ledger_emb",
    "pass_ledger_emb",
    "tail_bounds",
    "theory_sizes",
]


@pytest.mark.parametrize("name", NAMES)
def test_a_table_is_read(spark, tmp_path, name):
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        catalog.QUERIES[name](spark, str(tmp_path)).collect()
