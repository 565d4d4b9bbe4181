"""Queries that once made their rows up read a given table."""

from __future__ import annotations

import compare
import pytest
from pyspark.errors import AnalysisException

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
READERS = [
    "bound_mu_example",
    "fn_bits",
    "fn_null_safe",
    "toy_lexicographic",
    "toy_p0",
    "zipf_rows",
]


@pytest.mark.parametrize("name", READERS)
def test_reads_a_given_table(spark, tmp_path, name):
    with pytest.raises(AnalysisException):
        entry.queries()[name](spark, str(tmp_path)).collect()
    mine, theirs = compare.both(entry.queries()[name](spark, SF), compare.connect(SF), entry.oracle_sql()[name])
    assert mine == theirs
