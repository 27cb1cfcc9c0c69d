"""SQL names for the library: functions, a table function and views."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .text import tokens


class ExplodeBands:
    """Rows (table_no, bucket) of a band array; ``posexplode`` does the same without Python."""

    def eval(self, bands):
        for i, bucket in enumerate(bands or []):
            yield i, bucket


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Temporary SQL functions stay expressions of the optimiser; with a folder, views ``novel_docs`` and ``vsm_weights`` as well."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION detection_cost(p_miss DOUBLE, p_fa DOUBLE) RETURNS DOUBLE RETURN (0.02D * p_miss + 0.098D * p_fa) / 0.02D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION letter_runs(t STRING) RETURNS ARRAY<STRING> RETURN regexp_extract_all(lower(coalesce(t, '')), '(\\\\p{L}+)', 1)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bits_apart(a BIGINT, b BIGINT) RETURNS INT RETURN bit_count(a ^ b)")
    spark.udtf.register("explode_bands", F.udtf(ExplodeBands, returnType="table_no: int, bucket: bigint"))
    if sf_dir:
        from ..operators import model

        docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
        docs.createOrReplaceTempView("novel_docs")
        cut = docs.select("doc_id", tokens(F.col("text")).alias("terms"))
        model.weights(model.term_counts(cut), model.corpus_size(cut)).createOrReplaceTempView("vsm_weights")
