"""Functions for SQL text: format strings, edits, majority and runs."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..operators.augment import edit_to_format, runs_python


@udtf(returnType="pos: int, sym: string, text: string")
class Runs:
    """runs(text): one row for each run of a string."""

    def eval(self, text: str):
        for i, (sym, part) in enumerate(runs_python(text or "")):
            yield i, sym, part


def register(spark: SparkSession) -> None:
    """Temporary functions format_map, format_bigrams, majority, edit_to_format and the table function runs."""
    spark.sql(r"CREATE OR REPLACE TEMPORARY FUNCTION format_map(v STRING) RETURNS STRING RETURN regexp_replace(regexp_replace(regexp_replace(v, '\\p{L}', 'A'), '\\p{Nd}', 'N'), '(?s)[^AN]', 'S')")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION format_bigrams(v STRING) RETURNS MAP<STRING, INT> RETURN (SELECT map_from_entries(transform(array('AA','AN','AS','NA','NN','NS','SA','SN','SS'), g -> struct(g, size(filter(transform(sequence(1, greatest(length(format_map(v)) - 1, 1)), i -> substr(format_map(v), i, 2)), x -> x = g))))))")
    spark.udf.register("edit_to_format", edit_to_format)
    spark.udtf.register("runs", Runs)
