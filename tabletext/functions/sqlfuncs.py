"""The scalar methods under names in SQL.  They are inlined into the plan: no Python runs."""

from __future__ import annotations

from pyspark.sql import SparkSession

FUNCTIONS = {
    "tt_f1": "(p DOUBLE, r DOUBLE) RETURNS DOUBLE RETURN try_divide(2 * p * r, p + r)",
    "tt_prf": "(tp BIGINT, found BIGINT, truth BIGINT) RETURNS STRUCT<p: DOUBLE, r: DOUBLE, f1: DOUBLE> RETURN named_struct('p', try_divide(cast(tp AS DOUBLE), found), 'r', try_divide(cast(tp AS DOUBLE), truth), 'f1', try_divide(2.0D * tp, cast(found + truth AS DOUBLE)))",
    "tt_within": "(truth DECIMAL(24,6), found DECIMAL(24,6)) RETURNS BOOLEAN RETURN abs(truth - found) <= abs(truth) * cast('0.001' AS DECIMAL(4,3))",
    "tt_sim_edit": "(a STRING, b STRING) RETURNS DOUBLE RETURN CASE WHEN lower(a) = lower(b) THEN 1.0D ELSE 1.0D - levenshtein(lower(a), lower(b)) / greatest(length(a), length(b)) END",
    "tt_text_quality": "(f DOUBLE, h DOUBLE, c DOUBLE) RETURNS DOUBLE RETURN (f + h + c) / 3",
    "tt_rubric_level": "(share DOUBLE) RETURNS INT RETURN CASE WHEN share >= 1 THEN 5 WHEN share >= 0.9 THEN 4 WHEN share >= 0.7 THEN 3 WHEN share >= 0.4 THEN 2 ELSE 1 END",
}


def register_functions(spark: SparkSession) -> list[str]:
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    _register_tables(spark)
    return [*FUNCTIONS, "tt_mentions", "tt_claims"]


def _register_tables(spark: SparkSession) -> None:
    """Table functions, for SQL users; the DataFrame forms stay in the JVM."""
    import re

    from pyspark.sql.functions import udtf

    from . import temporal

    pattern = temporal.PATTERN

    class Mentions:
        def eval(self, text: str):
            for m in re.finditer(pattern, text or ""):
                yield m.group(0), m.start()

    class Claims:
        def eval(self, text: str):
            yield from enumerate(re.split(r"(?<=\.) +(?=[A-Z])", text or ""))

    spark.udtf.register("tt_mentions", udtf(Mentions, returnType="surface string, at int"))
    spark.udtf.register("tt_claims", udtf(Claims, returnType="pos int, claim string"))
