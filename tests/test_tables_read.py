"""Queries that once made their data up read a given table: without the tables they fail."""

import pytest
from pyspark.errors import AnalysisException

from patternlm.queries import catalogue

READERS = ["q_canon_dyn", "q_canon_enum", "q_canon_rw", "q_edge_naive", "q_edge_weights", "q_edit1_neigh", "q_edit2", "q_edit_hist", "q_edit_pos", "q_enc_all", "q_enc_count", "q_enc_ratio"]


@pytest.mark.parametrize("name", READERS)
def test_a_table_is_read(spark, tmp_path, name):
    with pytest.raises(AnalysisException):
        catalogue()[0][name](spark, str(tmp_path)).collect()
