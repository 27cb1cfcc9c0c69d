"""Queries that once made their data up: Spark reads a given table for each."""

import pytest
from novelspark import registry

READ = {
    "udtf_bands": "customer",
    "udf_sql_macro": "lineitem",
    "op_cte_recursive": "orders",
    "met_probit": "lineitem",
    "met_cost": "lineitem",
    "lsh_table_count": "lineitem",
    "source_snippets": "orders",
}


@pytest.mark.parametrize("name", READ)
def test_spark_reads_the_table(spark, sf, name):
    files = registry.queries()[name](spark, sf).inputFiles()
    assert [f.rsplit("/", 1)[1] for f in files] == [READ[name] + ".parquet"]
